"""Preparing multiplication triples: two OLE generators and boolean triples (L306-332, L1000-1066).

An OLE gives one party (x, z) and the other (y, w) with w = x*y + z; two of them make a triple without
further messages. The quadratic generator multiplies bit by bit; the other works modulo several small
primes and recombines, so that bits grow like ell log ell. Transfers are simulated by their function.
"""

from __future__ import annotations

import numpy as np

from .protocols import Random, U

#: Bits that one random transfer costs either generator, per chosen bit.
TRANSFER_BITS = 2


def _low(x: np.ndarray, ell: int) -> np.ndarray:
    return x & ((1 << ell) - 1 if x.dtype == object else U((1 << ell) - 1))


def _words(r: Random, n: int, ell: int) -> np.ndarray:
    """Random numbers of ell bits: words up to 64 bits, Python integers beyond."""
    if ell <= 64:
        return _low(r.words(n), ell)
    out = np.zeros(n, object)
    for at in range(0, ell, 64):
        out += r.words(n).astype(object) << at
    return _low(out, ell)


def ole_quadratic(n: int, ell: int, seed: int = 1):
    """((x, z), (y, w), bits sent): one transfer of an ell-bit word for each bit of x."""
    r = Random(seed)
    x, y = _words(r, n, ell), _words(r, n, ell)
    z, w = np.zeros_like(x), np.zeros_like(x)
    for i in range(ell):
        step = i if x.dtype == object else U(i)
        mask = _words(r, n, ell)  # the sender offers mask and mask + 2^i y; x's bit chooses
        w = w + np.where((x >> step) & (1 if x.dtype == object else U(1)) == 1, mask + (y << step), mask)
        z = z + mask
    return (x, _low(z, ell)), (y, _low(w, ell)), n * ell * (ell + TRANSFER_BITS)


def primes_above(count_bits: int) -> list[int]:
    """Primes from 5 on, as many as their product needs to exceed 2^count_bits."""
    out, product, k = [], 1, 5
    while product <= 1 << count_bits:
        if all(k % p for p in range(2, int(k**0.5) + 1)):
            out.append(k)
            product *= k
        k += 2
    return out


def prime_bits(p: int) -> int:
    """Bits sent for one evaluation modulo p."""
    return p.bit_length() * (p.bit_length() + TRANSFER_BITS)


def _residue(x: np.ndarray, p: int) -> np.ndarray:
    return (x % (p if x.dtype == object else U(p))).astype(np.int64)


def ole_crt(n: int, ell: int, seed: int = 1):
    """As ole_quadratic, by residues: w - z = x*y over the integers, recombined, then cut to ell bits.

    Modulo a prime of b bits the quadratic generator sends b words of b bits, each with its transfer. Numbers of
    up to 2 ell + 40 bits are recombined with Python integers."""
    r = Random(seed)
    x, y = _words(r, n, ell), _words(r, n, ell)
    primes = primes_above(2 * ell + 41)
    product = 1
    for p in primes:
        product *= p
    total = np.zeros(n, object)
    masks = np.zeros(n, object)
    bits = 0
    for p in primes:
        z = (r.words(n) % U(p)).astype(np.int64)
        w = (_residue(x, p) * _residue(y, p) + z) % p
        m = product // p
        weight = m * pow(m, -1, p)
        total = (total + w.astype(object) * weight) % product
        masks = (masks + z.astype(object) * weight) % product
        bits += n * prime_bits(p)
    # x*y < 2^(2 ell) is far below the product: a wrap shows as w < z and is taken back
    wrapped = np.array([int(a) < int(b) for a, b in zip(total, masks)])
    kind = U if ell <= 64 else object
    w = np.array([(int(a) + product * int(k)) % (1 << ell) for a, k in zip(total, wrapped)], dtype=kind)
    z = np.array([int(b) % (1 << ell) for b in masks], dtype=kind)
    return (x, z), (y, w), bits


def triples_from_ole(first, second, ell: int):
    """((a0, b0, c0), (a1, b1, c1)) with (a0+a1)(b0+b1) = c0+c1 mod 2^ell: local (L314-330)."""
    (x1, z1), (y1, w1) = first
    (x2, z2), (y2, w2) = second
    # party 0: x1, x2 as a0, b0; party 1: y2, y1 as a1, b1; cross products x1*y1 = w1 - z1, x2*y2 = w2 - z2
    c0 = _low(x1 * x2 - z1 - z2, ell)
    c1 = _low(y1 * y2 + w1 + w2, ell)
    return (x1, x2, c0), (y2, y1, c1)


def boolean_triples(n: int, ell: int, seed: int = 1):
    """The same over bits: cross products are xor shares; (two parties' terms, bits sent)."""
    r = Random(seed)
    a0, b0, a1, b1, m1, m2 = (_words(r, n, ell) for _ in range(6))
    c0 = (a0 & b0) ^ m1 ^ m2
    c1 = (a1 & b1) ^ (a0 & b1) ^ m1 ^ (a1 & b0) ^ m2
    return (a0, b0, c0), (a1, b1, c1), TRANSFER_BITS * n * ell


def ring(values: np.ndarray, ell: int) -> np.ndarray:
    """Signed 64-bit integers as numbers of ell bits."""
    return _low(values.astype(object) if ell > 64 else values.view(U), ell)


def product(first, second, x: np.ndarray, y: np.ndarray, ell: int, boolean: bool = False, seed: int = 1) -> np.ndarray:
    """x*y mod 2^ell (boolean: x & y) of shared factors, opened: a triple each masks both factors (L275-304)."""
    plus, minus, times = (np.bitwise_xor, np.bitwise_xor, np.bitwise_and) if boolean else (np.add, np.subtract, np.multiply)
    r = Random(seed)
    x0, y0 = _words(r, len(x), ell), _words(r, len(x), ell)
    x1, y1 = minus(x, x0), minus(y, y0)
    (a0, b0, c0), (a1, b1, c1) = first, second
    d = _low(plus(minus(x0, a0), minus(x1, a1)), ell)  # both differences are opened
    e = _low(plus(minus(y0, b0), minus(y1, b1)), ell)
    z0 = plus(plus(c0, times(d, e)), plus(times(d, b0), times(e, a0)))
    z1 = plus(c1, plus(times(d, b1), times(e, a1)))
    return _low(plus(z0, z1), ell)
