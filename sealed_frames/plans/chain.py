"""Acyclic multi-way joins with sums, counts, averages, least and largest values, without forming joined rows
(L701, L711-732).

The join tree is rooted at the table that owns the grouping columns. Every other table is reduced, leaves
first, to one row per join key: how many joined rows stand below it (its multiplicity) and what each sum
amounts to there. A parent row multiplies its children's multiplicities; a sum from one child is
multiplied by those of the others; least and largest values pass as they are. Every exchange moves at most
one row per key and input.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import functions as F

from ..core.frame import SealedFrame
from .classify import Query, acyclic

MULT = "__mult"


def chain_aggregate(
    tables: Mapping[str, SealedFrame],
    joins: Sequence[tuple[tuple[str, str], tuple[str, str]]],
    root: str,
    group_by: Sequence[str],
    sums: Mapping[str, tuple[str, str]] | None = None,
    count: str | None = None,
    extremes: Mapping[str, tuple[str, str, str]] | None = None,
    averages: Mapping[str, tuple[str, str]] | None = None,
) -> SealedFrame:
    """joins: pairs of (table, column); sums: out -> (table, column); group_by: columns of ``root``.

    extremes: out -> (min or max, table, column); averages: out -> (table, column without nulls), truncated."""
    averages = {f"__a_{o}": x for o, x in (averages or {}).items()}
    sums, extremes = dict(sums or {}) | averages, dict(extremes or {})
    if not acyclic(Query({t: f.columns for t, f in tables.items()}, joins)):
        raise ValueError("a cyclic query needs the quadratic fallback")
    near: dict[str, dict[str, list[tuple[str, str]]]] = {t: {} for t in tables}
    for (a, x), (b, y) in joins:
        near[a].setdefault(b, []).append((x, y))
        near[b].setdefault(a, []).append((y, x))

    def joined(table: str, parent: str | None) -> tuple[SealedFrame, list[str], list[str]]:
        """The table with its subtree's multiplicity and sums beside every row; the sums and extremes it has."""
        frame = tables[table]
        have = [o for o, (t, _) in sums.items() if t == table]
        frame = frame.with_col(MULT, F.lit(1).cast("long"))
        for o in have:
            frame = frame.with_col(f"__s_{o}", F.col(sums[o][1]))
        far = [o for o, (_, t, _) in extremes.items() if t == table]
        for o in far:
            frame = frame.with_col(f"__x_{o}", F.col(extremes[o][2]))
        for child, pairs in near[table].items():
            if child == parent:
                continue
            below, theirs, beyond = joined(child, table)
            keys = [y for _, y in pairs]
            ends = {f"__x_{o}": (extremes[o][0], f"__x_{o}") for o in beyond}
            part = below.aggregate(keys, **{f"{MULT}_c": ("sum", MULT)}, **{f"__c_{o}": ("sum", f"__s_{o}") for o in theirs}, **ends)
            far += beyond
            renamed = {f"__k{i}": y for i, y in enumerate(keys)}
            part = part.rename(**renamed)
            frame = part.join(frame, {f"__k{i}": x for i, (x, _) in enumerate(pairs)})
            frame = frame.rename(**{x: f"__k{i}" for i, (x, _) in enumerate(pairs)})
            for o in have:
                frame = frame.with_col(f"__s_{o}", F.col(f"__s_{o}") * F.col(f"{MULT}_c"))
            for o in theirs:
                frame = frame.with_col(f"__s_{o}", F.col(f"__c_{o}") * F.col(MULT))
            frame = frame.with_col(MULT, F.col(MULT) * F.col(f"{MULT}_c"))
            have += theirs
            frame = frame.project(*[c for c in frame.columns if c != f"{MULT}_c" and not c.startswith("__c_")])
        return frame, have, far

    whole, have, far = joined(root, None)
    outputs = {o: ("sum", f"__s_{o}") for o in have} | {o: (extremes[o][0], f"__x_{o}") for o in far}
    rows = count or "__rows"
    if count or averages:
        outputs[rows] = ("sum", MULT)
    out = whole.aggregate(list(group_by), **outputs)
    for o in averages:
        out = out.with_col(o.removeprefix("__a_"), F.call_function("div", F.col(o), F.col(rows)))
    return out.project(*[c for c in out.columns if c not in averages and (count or c != rows)]) if averages else out
