"""Oblivious permutations, sorting and scans on shared vectors (L334-341, L394-578, SURVEY 2.2-2.3).

Destinations: element i moves to place dest[i] (from 0). A shuffle applies one hidden permutation per
party; comparisons that are opened after it reveal nothing but the random order.
"""

from __future__ import annotations

import numpy as np

from ..plans.meter import lg
from .circuits import bit_to_arithmetic, choose, equal, greater
from .protocols import Protocol, Random, Shared, U

PAD_BITS = 32


def apply(dest: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Along the last axis."""
    out = np.empty_like(x)
    out[..., dest] = x
    return out


def invert(dest: np.ndarray) -> np.ndarray:
    return apply(dest, np.arange(len(dest)))


def compose(first: np.ndarray, then: np.ndarray) -> np.ndarray:
    """Both moves in one: dest of ``first`` followed by ``then``."""
    return then[first]


def random_permutation(n: int, seed: int) -> np.ndarray:
    """A party's hidden permutation: the ranks of pseudo-random words."""
    return invert(np.argsort(Random(seed).words(n), kind="stable"))


def sharded_permutation(p: Protocol, n: int, seed: int) -> list[np.ndarray]:
    """One permutation per party; together a permutation that none of them knows (L399)."""
    return [random_permutation(n, seed * 31 + party + 1) for party in range(p.n)]


def apply_sharded(p: Protocol, parts: list[np.ndarray], x: Shared, width: int = 64) -> Shared:
    """Each party in turn permutes and shares anew (L394-402)."""
    return apply_sharded_all(p, parts, [x], width)[0]


def apply_sharded_all(p: Protocol, parts: list[np.ndarray], xs: list[Shared], width: int = 64) -> list[Shared]:
    """The same for several vectors, which move in common rounds."""
    for dest in parts:
        p.meter.stage("permute", sum(map(len, xs)), width)
        moved = []
        for x in xs:
            terms, fresh = apply(dest, x.terms), p.share(np.zeros(len(x), np.int64), x.boolean).terms
            moved.append(Shared(terms ^ fresh if x.boolean else terms + fresh, x.boolean))
        xs = moved
    return xs


def invert_sharded(parts: list[np.ndarray]) -> list[np.ndarray]:
    """The parties' parts undone, last one first."""
    return [invert(d) for d in reversed(parts)]


def shuffle(p: Protocol, x: Shared, seed: int) -> Shared:
    return apply_sharded(p, sharded_permutation(p, len(x), seed), x)


def apply_elementwise(p: Protocol, dest: Shared, x: Shared, seed: int) -> Shared:
    """A permutation whose destinations are shared: shuffle both alike, open the destinations, move (L400)."""
    return apply_elementwise_all(p, dest, [x], seed)[0]


def apply_elementwise_all(p: Protocol, dest: Shared, xs: list[Shared], seed: int) -> list[Shared]:
    """One shuffle and one opening for all columns of a table."""
    parts = sharded_permutation(p, len(dest), seed)
    hidden, *moved = apply_sharded_all(p, parts, [dest, *xs])
    opened = p.open(hidden).astype(np.int64)
    return [Shared(apply(opened, x.terms), x.boolean) for x in moved]


def invert_elementwise(p: Protocol, dest: Shared, seed: int) -> Shared:
    """Values and places change roles under a common shuffle."""
    identity = p.public(np.arange(len(dest)), dest.boolean)
    return apply_elementwise(p, dest, identity, seed)


def compose_elementwise(p: Protocol, first: Shared, then: Shared, seed: int) -> Shared:
    """Shared destinations of ``first`` followed by ``then``: the first ones are shuffled and opened, say where to
    look in the second, and the outcome is shuffled back."""
    parts = sharded_permutation(p, len(first), seed)
    opened = p.open(apply_sharded(p, parts, first)).astype(np.int64)
    return apply_sharded(p, invert_sharded(parts), Shared(then.terms[:, opened], then.boolean))


def convert_elementwise(p: Protocol, dest: Shared, seed: int) -> Shared:
    """A shared permutation in the other kind of shares: shuffled it may be opened, is shared anew for
    nothing as a public vector, and shuffled back (S6)."""
    parts = sharded_permutation(p, len(dest), seed)
    opened = p.open(apply_sharded(p, parts, dest))
    return apply_sharded(p, invert_sharded(parts), p.public(opened.view(np.int64), not dest.boolean))


def permutation_correlation(n: int, seed: int):
    """(dest, b0) of one party and (a, b1) of the other with dest(a) = b0 + b1 (L334-341)."""
    r = Random(seed)
    dest, a, b1 = random_permutation(n, seed), r.words(n), r.words(n)
    return (dest, apply(dest, a) - b1), (a, b1)


def permute_with(correlation, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Shares of dest(x): the owner of x sends x - a once; the holder of dest moves it and adds its part."""
    (dest, b0), (a, b1) = correlation
    return apply(dest, x - a) + b0, b1


def bit_destinations(p: Protocol, bit: Shared) -> Shared:
    """Shared stable destinations by bit 0: two running sums of arithmetic shares, joined by one product (L470, L493)."""
    return _destinations(p, bit_to_arithmetic(p, bit))


def _destinations(p: Protocol, one: Shared) -> Shared:
    n = len(one)
    if not n:
        return one
    ones = Shared(np.cumsum(one.terms, axis=1, dtype=U), False)
    zeros = p.sub(p.public(np.arange(1, n + 1), False), ones)
    all_zeros = Shared(np.repeat(zeros.terms[:, -1:], n, axis=1), False)
    back = p.sub(p.add(all_zeros, ones), zeros)  # how much further an element with the bit set goes
    return p.add(p.sub(zeros, p.public(np.ones(n, np.int64), False)), p.mul(one, back))


def bitwise_sort(p: Protocol, key: Shared, bits: int, skip: int = 0, variant: str = "hybrid", seed: int = 7, held: int = 64) -> Shared:
    """Stable sort by ``bits`` bits of the key above the lowest ``skip``.

    hybrid: each bit's permutation is found on the vector as it is and applied to it. eager: the key is
    taken apart into a vector per bit first (``held`` bits, all that it has), and every pass moves them. composed:
    passes move one bit only, permutations are composed, and the vector moves once at the end.
    """
    n = len(key)
    seeds = range(seed, seed + bits + skip + 1)
    bit_of = lambda x, i: p.mask(p.shift(x, -i), 1)
    if not n or not bits:
        return key
    if variant == "hybrid":
        for i in range(skip, skip + bits):
            key = apply_elementwise(p, bit_destinations(p, bit_of(key, i)), key, seeds[i])
        return key
    if variant == "eager":
        columns = [bit_of(key, i) for i in range(held)]
        for i in range(skip, skip + bits):
            columns = apply_elementwise_all(p, bit_destinations(p, columns[i]), columns, seeds[i])
        out = columns[0]
        for i, c in enumerate(columns[1:], 1):
            out = p.xor(out, p.shift(c, i))
        return out
    if variant != "composed":
        raise ValueError(f"unknown variant {variant!r}")
    total = bit_destinations(p, bit_of(key, skip))
    for i in range(skip + 1, skip + bits):
        # the permutation so far, shuffled and opened, moves the bit; what the bit adds is shuffled back
        parts = sharded_permutation(p, n, seeds[i])
        hidden, bit = apply_sharded_all(p, parts, [total, bit_of(key, i)])
        opened = p.open(hidden).astype(np.int64)
        dest = bit_destinations(p, Shared(apply(opened, bit.terms), True))
        total = apply_sharded(p, invert_sharded(parts), Shared(dest.terms[:, opened], False))
    return apply_elementwise(p, total, key, seeds[skip + bits])


def pivot_sort(p: Protocol, key: Shared, ell: int = 64, seed: int = 7, signed: bool = False) -> tuple[Shared, int, int]:
    """Shuffle, then quicksort level by level: every element is compared with the pivot at or before it,
    outcomes are opened, segments split (L409-461). Keys must be distinct; (sorted key, levels,
    comparisons). Finished elements are compared no more."""
    n = len(key)
    now = shuffle(p, key, seed)
    pivot = np.zeros(n, bool)
    if n:
        pivot[0] = True
    levels = compared = 0
    placed = np.zeros(n, bool)  # elements that are their own finished segment
    while n and not placed.all():
        levels += 1
        at = np.maximum.accumulate(np.where(pivot, np.arange(n), 0))
        active = np.flatnonzero(at != np.arange(n))
        compared += len(active)
        less = np.zeros(n, bool)  # pivot > element
        less[active] = p.open(greater(p, Shared(now.terms[:, at[active]], True), Shared(now.terms[:, active], True), ell, signed), 1)
        dest, pivot, placed = split_segments(less, pivot, placed)
        now = Shared(apply(dest, now.terms), now.boolean)
    return now, levels, compared


def split_segments(less: np.ndarray, pivot: np.ndarray, placed: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Destinations of a level, next pivots (the pivot itself and the first of both sides), and what is done."""
    n = len(less)
    start = np.maximum.accumulate(np.where(pivot, np.arange(n), 0))
    stop = np.append(np.flatnonzero(pivot), n)[np.searchsorted(np.flatnonzero(pivot), start, "right")]
    small = np.cumsum(less)
    before = small - np.where(start > 0, small[start - 1], 0)  # smaller ones up to here, in the segment
    all_small = (small[stop - 1] - np.where(start > 0, small[start - 1], 0)).astype(np.int64)
    index = np.arange(n)
    is_pivot = index == start
    rank = np.where(less, before - 1, np.where(is_pivot, all_small, all_small + (index - start) - before))
    dest = start + rank
    new_pivot = np.zeros(n, bool)
    new_pivot[dest[is_pivot]] = True
    starts = np.flatnonzero(is_pivot)
    new_pivot[starts] = True
    after = starts + all_small[starts] + 1
    new_pivot[after[after < stop[starts]]] = True
    edges = np.append(np.flatnonzero(new_pivot), n)
    done = np.zeros(n, bool)
    single = edges[:-1][np.diff(edges) == 1]
    done[single] = True
    return dest, new_pivot, done


def network_pairs(n: int, kind: str):
    """Rounds of (lower, upper) places of a sorting network for n = 2^k; the smaller goes to lower."""
    if n & (n - 1):
        raise ValueError("a network needs a power of two")
    if kind == "bitonic":
        size = 2
        while size <= n:
            step = size // 2
            while step:
                i = np.arange(n)
                i = i[(i & step) == 0]
                up = (i & size) == 0
                yield np.where(up, i, i + step), np.where(up, i + step, i)
                step //= 2
            size *= 2
    elif kind == "odd_even":
        span = 1
        while span < n:
            step = span
            while step:
                i = np.arange(n - step)
                good = ((i - step % span) >= 0) & (((i - step % span) // step) % 2 == 0) & (i // (2 * span) == (i + step) // (2 * span))
                i = i[good]
                yield i, i + step
                step //= 2
            span *= 2
    elif kind == "pairwise":
        step = 1
        while step < n:
            i = np.arange(n)
            i = i[(i & step) == 0]
            yield i, i + step
            step *= 2
        step, span = n // 4, 1
        while step:
            far = span
            while far:
                i = np.arange(n - far * step)
                i = i[(i // step) % 2 == 1]
                yield i, i + far * step
                far //= 2
            step //= 2
            span = span * 2 + 1
    else:
        raise ValueError(f"unknown network {kind!r}")


def network_sort(p: Protocol, key: Shared, kind: str = "bitonic", ell: int = 64, signed: bool = False) -> tuple[Shared, int]:
    """Compare and exchange in rounds; (sorted key, compare-exchanges)."""
    terms, count = key.terms.copy(), 0
    for low, high in network_pairs(len(key), kind):
        if not len(low):
            continue
        a, b = Shared(terms[:, low], True), Shared(terms[:, high], True)
        swap = greater(p, a, b, ell, signed)
        terms[:, low], terms[:, high] = choose(p, swap, a, b).terms, choose(p, swap, b, a).terms
        count += len(low)
    return Shared(terms, True), count


def sort_vector(p: Protocol, key: Shared, order: str = "asc", base: str = "pivot", bits: int = 31, seed: int = 7) -> tuple[Shared, Shared]:
    """Stable sort of non-negative keys of up to ``bits`` bits: (sorted key, shared destinations).

    The index is put into the low bits, which makes keys distinct and comes back as the inverse of the
    sorting permutation. Descending order puts in negated indices and reverses (L495-546, E18)."""
    n = len(key)
    p.meter.local("sort", 1)
    p.meter.rows(n)
    pad = min(PAD_BITS, 64 - bits)
    if n > 1 << pad:
        raise ValueError("key and index need more than 64 bits")
    index = np.arange(n)
    low = index if order == "asc" else (1 << pad) - 1 - index
    padded = p.xor(p.shift(key, pad), p.public(low, True))
    if base == "pivot":
        out, _, _ = pivot_sort(p, padded, pad + bits, seed)
    elif base == "bitwise":
        # a stable sort by the key's bits needs no pass over the index
        source = padded if order == "asc" else Shared(padded.terms[:, ::-1], True)
        out = bitwise_sort(p, source, bits, pad, seed=seed)
    else:
        raise ValueError(f"unknown base sort {base!r}")
    if order == "desc":
        out = Shared(out.terms[:, ::-1], True)
    places = p.mask(out, (1 << pad) - 1)
    if order == "desc":  # converted, so that negating is an addition
        places = p.sub(p.public(np.full(n, (1 << pad) - 1), False), convert_elementwise(p, places, seed + 1))
    return p.shift(out, -pad), invert_elementwise(p, places, seed + 2)


def sort_table(p: Protocol, columns: dict[str, Shared], keys: list[tuple[str, str]], base: str = "auto", strategy: str = "compose", bits: int | dict[str, int] = 31, seed: int = 7) -> dict[str, Shared]:
    """Sort by several keys: vector sorts from the last key to the first, permutations composed, every column
    moved once (L552-578); ``per_key`` moves the whole table after every key. bits: of all keys, or by key."""
    now, total = dict(columns), None
    for step, (name, order) in enumerate(reversed(keys)):
        at = seed + 100 * step
        width = bits[name] if isinstance(bits, dict) else bits
        chosen = base if base != "auto" else "bitwise" if width <= 32 else "pivot"
        column = now[name] if total is None else apply_elementwise(p, total, columns[name], at)
        _, dest = sort_vector(p, column, order, chosen, width, at + 1)
        if strategy == "per_key":
            now = dict(zip(now, apply_elementwise_all(p, dest, list(now.values()), at + 5)))
        else:
            total = dest if total is None else compose_elementwise(p, total, dest, at + 6)
    if strategy == "compose" and total is not None:
        now = dict(zip(columns, apply_elementwise_all(p, total, list(columns.values()), seed + 99)))
    return now


def group_scan(p: Protocol, keys: Shared, value: Shared, key_bits: int = 64) -> Shared:
    """Inclusive sums within runs of equal shared keys, on arithmetic shares: neighbours are compared on
    shares, and partners at doubling distances added where no run begins between (L353-387)."""
    n = len(value)
    if n < 2:
        return value
    same = equal(p, Shared(keys.terms[:, 1:], True), Shared(keys.terms[:, :-1], True), key_bits)
    starts = np.concatenate([p.public(np.ones(1, np.int64), True).terms, p.mask(p.not_(same), 1).terms], axis=1)
    now, flag = value, Shared(starts, True)
    for k in range(lg(n)):
        d = 1 << k
        joined = bit_to_arithmetic(p, p.mask(p.not_(Shared(flag.terms[:, d:], True)), 1))
        more = p.mul(joined, Shared(now.terms[:, :-d], False))
        terms, spread = now.terms.copy(), flag.terms.copy()
        terms[:, d:] += more.terms
        spread[:, d:] = p.or_(Shared(flag.terms[:, d:], True), Shared(flag.terms[:, :-d], True), 1).terms
        now, flag = Shared(terms, False), Shared(spread, True)
    return now
