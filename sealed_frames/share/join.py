"""The fused join-aggregate on shares: stack, sort, compare neighbours, scan, trim (L594-701).

Keys, validity and columns are shares; nothing is opened on the way but outcomes of comparisons and
permutations behind a hidden shuffle. Public: the two sizes. Columns that are summed are arithmetic
shares, all others boolean ones.
"""

from __future__ import annotations

import numpy as np

from ..plans.meter import lg
from .circuits import bit_to_arithmetic, choose, equal, greater, widen
from .protocols import Protocol, Shared
from .sorting import apply_elementwise_all, bit_destinations, sort_table


def _stack(p: Protocol, a: Shared, b: Shared) -> Shared:
    return Shared(np.concatenate([a.terms, b.terms], axis=1), a.boolean)


def _zeros(p: Protocol, n: int, boolean: bool = True) -> Shared:
    return p.public(np.zeros(n, np.int64), boolean)


def _at(s: Shared, rows) -> Shared:
    return Shared(s.terms[:, rows], s.boolean)


def run_starts(p: Protocol, key: Shared, bits: int) -> Shared:
    """Bit 0 set where a row's key differs from the row's before."""
    n = len(key)
    first = p.public(np.ones(min(1, n), np.int64), True).terms
    same = equal(p, _at(key, slice(1, n)), _at(key, slice(0, max(0, n - 1))), bits)
    return Shared(np.concatenate([first, p.mask(p.not_(same), 1).terms], axis=1), True)


def run_ends(p: Protocol, starts: Shared) -> Shared:
    """Where runs end, from where they start."""
    last = p.public(np.ones(min(1, len(starts)), np.int64), True).terms
    return Shared(np.concatenate([starts.terms[:, 1:], last], axis=1), True)


def scan(p: Protocol, starts: Shared, columns: dict[str, tuple[str, Shared]], reverse: bool = False, bits: int = 63) -> dict[str, Shared]:
    """Segmented scan by doubling: ``starts`` has bit 0 set where a run begins; columns: name -> (function, values).

    copy takes the run's first value, or the bits of all rows so far, sum their sum (arithmetic shares), min
    and max the least and largest (unsigned, ``bits`` bits). The same flags serve all columns."""
    n = len(starts)
    flag = Shared(starts.terms[:, ::-1], True) if reverse else starts
    now = {k: Shared(s.terms[:, ::-1], s.boolean) if reverse else s for k, (_, s) in columns.items()}
    p.meter.rows(n)
    for k in range(lg(n)):
        d = 1 << k
        here, before = slice(d, n), slice(0, n - d)
        joined = p.mask(p.not_(_at(flag, here)), 1)  # no run begins between the partner and this row
        weight = bit_to_arithmetic(p, joined) if any(kind == "sum" for kind, _ in columns.values()) else None
        for name, (kind, _) in columns.items():
            old, partner = _at(now[name], here), _at(now[name], before)
            if kind == "sum":
                fresh = p.add(old, p.mul(weight, partner))
            elif kind == "or":
                fresh = p.or_(old, p.and_(widen(p, joined), partner))
            elif kind == "copy":
                fresh = choose(p, joined, old, partner)
            else:
                better = greater(p, old, partner, bits) if kind == "min" else greater(p, partner, old, bits)
                fresh = choose(p, p.and_(joined, better, 1), old, partner)
            terms = now[name].terms.copy()
            terms[:, here] = fresh.terms
            now[name] = Shared(terms, fresh.boolean)
        terms = flag.terms.copy()
        terms[:, here] = p.or_(_at(flag, here), _at(flag, before), 1).terms
        flag = Shared(terms, True)
    return {k: Shared(s.terms[:, ::-1], s.boolean) if reverse else s for k, s in now.items()}


def neutral(p: Protocol, kind: str, valid: Shared, value: Shared | None, bits: int = 63) -> Shared:
    """Values to aggregate: those of rows that are not valid change nothing."""
    if kind == "count":
        return bit_to_arithmetic(p, valid)
    if kind == "sum":
        return p.mul(bit_to_arithmetic(p, valid), value)
    none = p.public(np.full(len(value), (1 << bits) - 1 if kind == "min" else 0), True)
    return choose(p, valid, none, value)


def trim(p: Protocol, table: dict[str, Shared], rows: int, seed: int = 41) -> dict[str, Shared]:
    """Valid rows first, by a one-bit oblivious sort that keeps their order, then the first ``rows`` rows (L655)."""
    dest = bit_destinations(p, p.mask(p.not_(table["ok"]), 1))
    moved = apply_elementwise_all(p, dest, list(table.values()), seed)
    return {c: _at(s, slice(0, rows)) for c, s in zip(table, moved)}


def fused_join(
    p: Protocol, left: dict[str, Shared], right: dict[str, Shared], key: str, how: str = "inner", key_bits: int = 31, trim_rows: bool = False,
    aggs: dict[str, tuple[str, str]] | None = None, bits: int = 63, base: str = "pivot", seed: int = 7,
) -> dict[str, Shared]:
    """Both sides hold ``key``, ``ok`` (bit 0) and columns of their own; left keys are unique but for semi and anti.

    Returns n+m rows with ``ok``; left columns are copied down, SQL semantics for outer joins. aggs: out ->
    (sum, count, min or max, right column): the right rows of each left row are aggregated in the same pass
    (L687), and left rows stay as its carriers (inner: those that meet a row; left: all). trim_rows: cut to
    the rows that can be valid, which only joins with unique left keys bound by one side.
    """
    n, m = len(left["ok"]), len(right["ok"])
    if aggs and how not in ("inner", "left"):
        raise ValueError("right rows are aggregated in inner and left joins")
    mine = [c for c in left if c not in (key, "ok")]
    theirs = [c for c in right if c not in (key, "ok")]
    table = {key: _stack(p, left[key], right[key]), "ok": _stack(p, left["ok"], right["ok"])}
    table["origin"] = p.public(np.r_[np.zeros(n), np.ones(m)].astype(np.int64), True)  # 0: left
    for c in mine:
        table[c] = _stack(p, left[c], _zeros(p, m, left[c].boolean))
    for c in theirs:
        table[c] = _stack(p, _zeros(p, n, right[c].boolean), right[c])
    # one sort key: validity (valid rows first), key, origin
    order = p.xor(p.shift(table[key], 1), table["origin"])
    table["order"] = p.xor(order, p.shift(p.mask(p.not_(table["ok"]), 1), key_bits + 1))
    table = sort_table(p, table, [("order", "asc")], base, bits=key_bits + 2, seed=seed)
    starts = run_starts(p, p.shift(table["order"], -1), key_bits + 2)
    is_right = table["origin"]
    is_left = p.mask(p.not_(is_right), 1)
    valid_left, valid_right = p.and_(is_left, table["ok"], 1), p.and_(is_right, table["ok"], 1)
    if aggs or how in ("left", "full", "semi", "anti"):
        columns = {"__met": ("or", valid_right)}
        for out, (kind, column) in (aggs or {}).items():
            columns[out] = ("sum" if kind == "count" else kind, neutral(p, kind, valid_right, table.get(column), bits))
        up = scan(p, run_ends(p, starts), columns, reverse=True, bits=bits)
        met = up["__met"]
        alone = p.and_(valid_left, p.mask(p.not_(met), 1), 1)
    if aggs:
        ok = valid_left if how == "left" else p.mask(p.and_(valid_left, met, 1), 1)
        out = {key: table[key], "ok": ok} | {c: table[c] for c in mine} | {c: up[c] for c in aggs}
        return trim(p, out, n) if trim_rows else out
    down = scan(p, starts, {c: ("copy", table[c]) for c in mine} | {"hit": ("or", valid_left)})
    if how == "inner":
        ok = p.and_(valid_right, down["hit"], 1)
    elif how == "right":
        ok = valid_right
    elif how == "left":
        ok = p.or_(p.and_(valid_right, down["hit"], 1), alone, 1)
    elif how == "full":
        ok = p.or_(valid_right, alone, 1)
    elif how == "semi":
        ok = p.and_(valid_left, met, 1)
    elif how == "anti":
        ok = alone
    else:
        raise ValueError(f"unknown join type {how!r}")
    ok = p.mask(ok, 1)
    # a right row that no left row precedes got the columns of a right row, which are zero
    out = {key: table[key], "ok": ok, "origin": table["origin"], "hit": p.mask(down["hit"], 1)}
    copied = table if how in ("semi", "anti") else down  # nothing is copied where left keys may repeat
    out |= {c: copied[c] for c in mine} | {c: table[c] for c in theirs}
    if trim_rows and how in ("inner", "right", "semi", "anti"):
        return trim(p, out, m if how in ("inner", "right") else n)
    return out
