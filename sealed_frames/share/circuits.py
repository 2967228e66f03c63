"""Circuits on shared words: comparison, equality, addition, division, selection, conversion (L213-273, L346-351)."""

from __future__ import annotations

import numpy as np

from ..plans.meter import lg
from .protocols import Protocol, Shared, U

ONES = (1 << 64) - 1


def fold_low(p: Protocol, x: Shared, ell: int) -> Shared:
    """Parity of the low ell bits, in bit 0: local."""
    for k in reversed(range(lg(ell))):
        x = p.xor(x, p.shift(x, -(1 << k)))
    return p.mask(x, 1)


def ones_from_top(p: Protocol, x: Shared, ell: int) -> Shared:
    """Every bit at or below the highest set bit, set: a prefix OR in log depth."""
    for k in range(lg(ell)):
        x = p.or_(x, p.shift(x, -(1 << k)))
    return x


def greater(p: Protocol, x: Shared, y: Shared, ell: int = 64, signed: bool = False) -> Shared:
    """x > y in bit 0: the first differing bit is isolated and x's bit there read by parity.

    Signed numbers compare as unsigned ones with both top bits flipped (E4).
    """
    if signed:
        top = 1 << (ell - 1)
        flip = lambda s: p.xor(s, p.public(np.full(len(s), top - (1 << 64) if top >> 63 else top), True))
        x, y = flip(x), flip(y)
    low = (1 << ell) - 1
    prefix = ones_from_top(p, p.mask(p.xor(x, y), low), ell)
    first = p.xor(prefix, p.shift(prefix, -1))
    return fold_low(p, p.and_(first, x), ell)


def not_equal(p: Protocol, x: Shared, y: Shared, ell: int = 64) -> Shared:
    d = p.mask(p.xor(x, y), (1 << ell) - 1)
    for k in reversed(range(lg(ell))):
        d = p.or_(d, p.shift(d, -(1 << k)))
    return p.mask(d, 1)


def equal(p: Protocol, x: Shared, y: Shared, ell: int = 64) -> Shared:
    return p.mask(p.not_(not_equal(p, x, y, ell)), 1)


def add(p: Protocol, x: Shared, y: Shared, ell: int = 64, kind: str = "prefix", carry: int = 0) -> Shared:
    """x + y (+ carry) on boolean shares, modulo 2^ell; ripple or parallel-prefix carries."""
    low = (1 << ell) - 1
    generate, propagate = p.and_(x, y), p.xor(x, y)
    if carry:
        first = p.mask(propagate, 1)
        generate = p.xor(generate, first)  # bit 0 also carries if it propagates the carry that comes in
    if kind == "ripple":
        carries = generate
        for i in range(1, ell):
            moved = p.and_(p.mask(propagate, 1 << i), p.shift(p.mask(carries, 1 << (i - 1)), 1), 1)
            carries = p.xor(carries, moved)
    else:
        carries, spread = generate, propagate
        for k in range(lg(ell)):
            carries = p.xor(carries, p.and_(spread, p.shift(carries, 1 << k)))
            below = p.xor(p.shift(spread, 1 << k), p.public(np.zeros(len(x), np.int64), True))
            spread = p.and_(spread, below)
    out = p.xor(propagate, p.shift(carries, 1))
    if carry:
        out = p.xor(out, p.public(np.ones(len(x), np.int64), True))
    return p.mask(out, low)


def negate(p: Protocol, x: Shared, ell: int = 64) -> Shared:
    zero = p.public(np.zeros(len(x), np.int64), True)
    return add(p, p.mask(p.not_(x), (1 << ell) - 1), zero, ell, carry=1)


def widen(p: Protocol, bit: Shared) -> Shared:
    """Bit 0 on every bit of the word: local, each term multiplies its bit by all ones."""
    return Shared((bit.terms & U(1)) * U(ONES), True)


def choose(p: Protocol, bit: Shared, x: Shared, y: Shared) -> Shared:
    """y where the bit is set, else x: one AND (L351)."""
    return p.xor(x, p.and_(widen(p, bit), p.xor(x, y)))


def choose_arithmetic(p: Protocol, bit: Shared, x: Shared, y: Shared) -> Shared:
    """The same on arithmetic shares: one multiplication; the bit is an arithmetic share of 0 or 1."""
    return p.add(x, p.mul(bit, p.sub(y, x)))


def divide(p: Protocol, x: Shared, y: Shared, ell: int = 32) -> Shared:
    """floor(x / y) of unsigned ell-bit numbers, private divisor: one conditional subtraction per bit (L346)."""
    wide = ell + 1
    minus_y = negate(p, y, wide)
    rest = p.public(np.zeros(len(x), np.int64), True)
    out = p.public(np.zeros(len(x), np.int64), True)
    for i in reversed(range(ell)):
        bit = p.mask(p.shift(x, -i), 1)
        rest = p.xor(p.mask(p.shift(rest, 1), (1 << wide) - 1), bit)
        tried = add(p, rest, minus_y, wide)
        fits = p.mask(p.not_(p.shift(tried, -ell)), 1)  # no borrow: top bit clear
        rest = choose(p, fits, rest, tried)
        out = p.xor(out, p.shift(fits, i))
    return out


def times_public(p: Protocol, x: Shared, factor: int, ell: int = 64) -> Shared:
    """x times a public number on boolean shares: shifted copies are added, an addition per set bit but the first;
    digits are 1, 0 and -1, so that runs of ones cost two."""
    out, i = None, 0
    while factor:
        if factor & 1:
            digit = 2 - (factor & 3)  # 1, or -1 before another one
            factor -= digit
            term = p.mask(p.shift(x, i), (1 << ell) - 1)
            if digit < 0:
                term = negate(p, term, ell)
            out = term if out is None else add(p, out, term, ell)
        factor >>= 1
        i += 1
    return p.public(np.zeros(len(x), np.int64), True) if out is None else out


def divide_public(p: Protocol, x: Shared, d: int, ell: int = 31) -> Shared:
    """floor(x / d) of unsigned ell-bit numbers by a public number: times a rounded-up reciprocal, whose
    excess stays below one for all of them, and a shift; a few additions instead of a step per bit (L743).

    ell is at most 31, so that the product fits 64 bits."""
    if not 0 < ell <= 31:
        raise ValueError("numbers of 1 to 31 bits")
    if d <= 0:
        raise ValueError("the divisor must be positive")
    shift = ell + max(1, (d - 1).bit_length())
    return p.mask(p.shift(times_public(p, x, -(-(1 << shift) // d), 64), -shift), (1 << ell) - 1)


def to_boolean(p: Protocol, x: Shared, ell: int = 64) -> Shared:
    """Arithmetic to boolean: the terms, each shared as bits, go through an adder."""
    parts = [p.share(t, True) for t in x.terms]
    out = parts[0]
    for part in parts[1:]:
        out = add(p, out, part, ell)
    return out


def bit_to_arithmetic(p: Protocol, bit: Shared) -> Shared:
    """Arithmetic shares of bit 0: its terms are bits a, b, which their holders share; a xor b is a + b - 2ab."""
    parts = [p.share(t & U(1), False) for t in bit.terms]
    out = parts[0]
    for other in parts[1:]:
        out = p.sub(p.add(out, other), p.scale(p.mul(out, other), 2))
    return out


def to_arithmetic(p: Protocol, bits: Shared, ell: int = 64) -> Shared:
    """Boolean to arithmetic: bits are converted, weighed and added."""
    total = p.public(np.zeros(len(bits), np.int64), False)
    for i in range(ell):
        total = p.add(total, p.scale(bit_to_arithmetic(p, p.shift(bits, -i)), 1 << i))
    return total
