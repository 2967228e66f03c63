"""Evaluates a join-aggregation query by the plan that its class calls for (L74-80).

one_to_many: fused joins, the unique side first. early_aggregation: reduction to one row per key and
table before tables meet. cartesian: comparison of all pairs, in blocks beyond a size.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce

from pyspark.sql import functions as F

from ..core.frame import SealedFrame
from ..operators.fused_join import cartesian_join
from .chain import chain_aggregate
from .classify import Query, classify


def _named(table: str, column: str) -> str:
    return f"{table}__{column}"


def _qualified(table: str, frame: SealedFrame) -> SealedFrame:
    return frame.rename(**{_named(table, c): c for c in frame.columns})


def _fused(tables: Mapping[str, SealedFrame], joins) -> tuple[SealedFrame, dict[str, str]]:
    """All tables joined along their edges; where a column is if its join kept the other side's name."""
    todo = {t: _qualified(t, f) for t, f in tables.items()}
    (first, whole), *_ = todo.items()
    met, alias = {first}, {}
    while len(met) < len(tables):
        found = {}
        for a, b in joins:
            for (t, x), (u, y) in ((a, b), (b, a)):
                if t in met and u not in met:
                    found.setdefault(u, {})[alias.get(_named(t, x), _named(t, x))] = _named(u, y)
        # a table whose key is unique, or else one that meets a unique key of what is joined so far
        new = next((u for u, on in found.items() if todo[u].is_unique(list(on.values()))), None)
        if new is not None:
            on = found[new]
            whole = todo[new].join(whole, {y: x for x, y in on.items()})
            alias = {k: on.get(v, v) for k, v in alias.items()} | {x: y for x, y in on.items()}
        else:
            new = next(u for u, on in found.items() if whole.is_unique(list(on)))
            whole = whole.join(todo[new], found[new])
            alias |= {y: x for x, y in found[new].items()}
        met.add(new)
    return whole, alias


def _quadratic(tables: Mapping[str, SealedFrame], joins) -> SealedFrame:
    done: list[str] = []

    def add(left: SealedFrame, table: str) -> SealedFrame:
        conditions = [F.col(_named(*a)) == F.col(_named(*b)) for a, b in joins if {a[0], b[0]} <= {*done, table} and table in (a[0], b[0])]
        done.append(table)
        return cartesian_join(left, _qualified(table, tables[table]), reduce(lambda p, q: p & q, conditions, F.lit(True)), beyond="blocks")

    first, *rest = tables
    done.append(first)
    return reduce(add, rest, _qualified(first, tables[first]))


def join_aggregate(tables: Mapping[str, SealedFrame], joins: Sequence[tuple[tuple[str, str], tuple[str, str]]], root: str, group_by: Sequence[str], sums: Mapping[str, tuple[str, str]] | None = None, count: str | None = None) -> tuple[SealedFrame, str]:
    """(aggregates by columns of ``root``, the class of the query); arguments as for ``chain_aggregate``."""
    unique = {t: [sorted(u) for u in f.public.unique] for t, f in tables.items()}
    kind = classify(Query({t: f.columns for t, f in tables.items()}, joins, [(root, c) for c in group_by], unique))
    if kind == "early_aggregation":
        return chain_aggregate(tables, joins, root, group_by, sums, count), kind
    whole, alias = _fused(tables, joins) if kind == "one_to_many" else (_quadratic(tables, joins), {})
    at = lambda t, c: alias.get(_named(t, c), _named(t, c))
    outputs = {o: ("sum", at(t, c)) for o, (t, c) in (sums or {}).items()} | ({count: ("count", "*")} if count else {})
    keys = [at(root, c) for c in group_by]
    out = whole.aggregate(keys, **outputs)
    return out.rename(**{c: k for c, k in zip(group_by, keys)}), kind
