"""Tables of shares: the relational operators as one protocol run, from owners' columns to opened rows.

Every operator keeps public sizes: filters and joins clear validity bits, groups keep all their rows
with one valid carrier each, and only ``top`` and ``trim`` cut, to public numbers of rows. Rows come out
by ``reveal``: masked by validity, trimmed of nothing, shuffled, opened (L66, L348).
"""

from __future__ import annotations

import numpy as np

from .circuits import choose, greater, widen
from .join import fused_join, neutral, run_ends, run_starts, scan, trim
from .protocols import Protocol, Shared
from .sorting import apply_sharded_all, sharded_permutation, sort_table


class SharedTable:
    """Columns of shares and their validity. Boolean shares hold non-negative numbers; arithmetic ones are for sums."""

    def __init__(self, p: Protocol, columns: dict[str, Shared], ok: Shared, seed: int = 1):
        self.p, self.columns, self.ok, self.seed = p, columns, ok, seed
        p.meter.rows(len(ok))

    @classmethod
    def of(cls, p: Protocol, columns: dict[str, np.ndarray], sums: tuple[str, ...] = (), ok: np.ndarray | None = None) -> SharedTable:
        """Owners share their columns; those in ``sums`` as arithmetic shares."""
        n = len(next(iter(columns.values())))
        return cls(p, {c: p.share(x, c not in sums) for c, x in columns.items()}, p.share(np.ones(n, np.int64) if ok is None else ok, True))

    def __len__(self) -> int:
        return len(self.ok)

    def __getitem__(self, name: str) -> Shared:
        return self.columns[name]

    def _next(self, columns: dict[str, Shared], ok: Shared) -> SharedTable:
        return SharedTable(self.p, columns, ok, self.seed + 1000)

    # -- row by row ------------------------------------------------------------------------------

    def const(self, value: int) -> Shared:
        return self.p.public(np.full(len(self), value), True)

    def at_least(self, name: str, value: int, bits: int = 32) -> Shared:
        return self.p.mask(self.p.not_(greater(self.p, self.const(value), self[name], bits)), 1)

    def below(self, name: str, value: int, bits: int = 32) -> Shared:
        return greater(self.p, self.const(value), self[name], bits)

    def where(self, *conditions: Shared) -> SharedTable:
        """Rows where all bits hold stay valid."""
        ok = self.ok
        for bit in conditions:
            ok = self.p.and_(ok, bit, 1)
        return self._next(dict(self.columns), self.p.mask(ok, 1))

    def with_col(self, name: str, value: Shared) -> SharedTable:
        return self._next(self.columns | {name: value}, self.ok)

    def project(self, *names: str, **renamed: str) -> SharedTable:
        """Columns kept, and new=old pairs."""
        return self._next({c: self[c] for c in names} | {new: self[old] for new, old in renamed.items()}, self.ok)

    # -- sorts, groups, joins ------------------------------------------------------------------------

    def _ordered(self, key: Shared, bits: int, order: str = "asc", base: str = "pivot") -> dict[str, Shared]:
        """All columns and ``ok``, valid rows first, then by the key."""
        p = self.p
        late = p.mask(p.not_(self.ok), 1) if order == "asc" else self.ok
        table = self.columns | {"ok": self.ok, "__order": p.xor(key, p.shift(late, bits))}
        return sort_table(p, table, [("__order", order)], base, bits=bits + 1, seed=self.seed + 11)

    def group(self, key: str, aggs: dict[str, tuple[str, str | None]], bits: int = 31, value_bits: int = 63) -> SharedTable:
        """Per key one valid row, the last of its run, that carries the aggregates: sum, count, min, max (L353, R6)."""
        p, table = self.p, self._ordered(self[key], bits)
        starts = run_starts(p, table["__order"], bits + 1)
        columns = {out: ("sum" if kind == "count" else kind, neutral(p, kind, table["ok"], table.get(source), value_bits)) for out, (kind, source) in aggs.items()}
        done = scan(p, starts, columns, bits=value_bits)
        ok = p.and_(run_ends(p, starts), table["ok"], 1)
        return self._next({key: table[key]} | done, p.mask(ok, 1))

    def total(self, aggs: dict[str, tuple[str, str | None]]) -> dict[str, Shared]:
        """Sums and counts over all rows: additions of shares only, after one product with validity."""
        out = {}
        for name, (kind, source) in aggs.items():
            values = neutral(self.p, kind, self.ok, self.columns.get(source))
            out[name] = Shared(values.terms.sum(axis=1, dtype=np.uint64)[:, None], False)
        return out

    def join(self, right: SharedTable, key: str, how: str = "inner", aggs: dict[str, tuple[str, str]] | None = None, bits: int = 31, trim_rows: bool = False, value_bits: int = 63) -> SharedTable:
        out = fused_join(self.p, self.columns | {"ok": self.ok}, right.columns | {"ok": right.ok}, key, how, bits, trim_rows, aggs, value_bits, seed=self.seed + 17)
        ok = out.pop("ok")
        return self._next({c: s for c, s in out.items() if c not in ("origin", "hit")}, ok)

    def top(self, k: int, keys: list[tuple[str, str]], bits: int) -> SharedTable:
        """The first k valid rows by several keys, each asc or desc; k is public."""
        table = self.columns | {"ok": self.ok, "__late": self.p.mask(self.p.not_(self.ok), 1)}
        table = sort_table(self.p, table, [("__late", "asc"), *keys], "pivot", bits=bits, seed=self.seed + 13)
        cut = {c: Shared(s.terms[:, :k], s.boolean) for c, s in table.items() if c != "__late"}
        ok = cut.pop("ok")
        return self._next(cut, ok)

    def maximum(self, name: str, bits: int) -> Shared:
        """The largest value of the valid rows, by halving; one shared word (0 if no row is valid)."""
        p, now = self.p, neutral(self.p, "max", self.ok, self[name], bits)
        while len(now) > 1:
            half = (len(now) + 1) // 2
            a, b = Shared(now.terms[:, : len(now) - half], True), Shared(now.terms[:, half:], True)
            best = choose(p, greater(p, b, a, bits), a, b)
            now = Shared(np.concatenate([best.terms, now.terms[:, len(now) - half : half]], axis=1), True)
        return now if len(now) else p.public(np.zeros(1, np.int64), True)

    def trimmed(self, rows: int) -> SharedTable:
        out = trim(self.p, self.columns | {"ok": self.ok}, rows, self.seed + 23)
        ok = out.pop("ok")
        return self._next(out, ok)

    # -- out -------------------------------------------------------------------------------------------

    def reveal(self) -> dict[str, np.ndarray]:
        """Valid rows: columns of other rows are masked to zero, all rows are shuffled, then opened."""
        p = self.p
        every = widen(p, self.ok)
        weight = None
        masked = {}
        for c, s in self.columns.items():
            if s.boolean:
                masked[c] = p.and_(every, s)
            else:
                weight = neutral(p, "count", self.ok, None) if weight is None else weight
                masked[c] = p.mul(weight, s)
        moved = apply_sharded_all(p, sharded_permutation(p, len(self), self.seed + 29), [*masked.values(), self.ok])
        ok = (p.open(moved[-1], 1) & np.uint64(1)).astype(bool)
        opened = {c: p.open(s).view(np.int64)[ok] for c, s in zip(masked, moved)}
        p.verify()
        return opened
