"""Group scans: running aggregates within runs of equal keys, in three networks (L353-372).

``doubling`` combines partners at distance 1, 2, 4, ... (log depth), ``work_efficient`` sweeps up and down
(linear work), ``segmented`` is one running window frame. A partner of another group is no partner, so
all levels share one partitioning by key and one order: one exchange, one sort, however many levels.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: (combine earlier with later, window form)
FUNCTIONS = {
    "sum": (lambda a, b: a + b, F.sum),
    "min": (F.least, F.min),
    "max": (F.greatest, F.max),
    "copy": (lambda a, b: a, F.first),
    "concat": (F.concat, None),
}


def levels(rows: int) -> int:
    """Levels of a scan whose longest group may have ``rows`` rows: distances below rows."""
    return (rows - 1).bit_length() if rows > 1 else 0


def longest_group(df: DataFrame, keys: Sequence[str]) -> int:
    """Rows of the longest group: the largest of the counts per key, which are summed before they are exchanged."""
    return df.groupBy(*keys).count().agg(F.max("count")).first()[0] or 0


def group_scan(df: DataFrame, keys: Sequence[str], order: Sequence[str | Column], outputs: Sequence[tuple[str, str, str]], longest: int | None = None, variant: str = "segmented", reverse: bool = False) -> DataFrame:
    """outputs: (function, column, out). longest: public bound of a group's length; None: taken from the data.

    Networks have no more levels than the bound needs, so a longer group raises an error.
    """
    sequence = [F.desc(o) if isinstance(o, str) else o.desc() for o in order] if reverse else list(order)
    spec = Window.partitionBy(*keys).orderBy(*sequence)
    if variant == "segmented":
        frame = spec.rowsBetween(Window.unboundedPreceding, 0)
        return df.select("*", *[FUNCTIONS[f][1](c).over(frame).alias(o) for f, c, o in outputs])
    if longest is None:
        longest = longest_group(df, keys)
    over = F.raise_error(F.lit(f"a group has more than {longest} rows, the bound of this scan"))
    df = df.withColumn("__i", F.row_number().over(spec)).select("*", *[F.when(F.col("__i") > longest, over).otherwise(F.col(c)).alias(o) for _, c, o in outputs])
    if variant == "doubling":
        for k in range(levels(longest)):
            df = _level(df, spec, outputs, 1 << k, None)
        return df.drop("__i")
    if variant == "work_efficient":
        top = levels(longest)
        for k in range(top):
            df = _level(df, spec, outputs, 1 << k, F.col("__i") % (2 << k) == 0)
        for k in reversed(range(top)):
            df = _level(df, spec, outputs, 1 << k, (F.col("__i") % (2 << k) == 1 << k) & (F.col("__i") > 1 << k))
        return df.drop("__i")
    raise ValueError(f"unknown variant {variant!r}")


def _level(df: DataFrame, spec, outputs, distance: int, active: Column | None) -> DataFrame:
    """One synchronous step: every partner's value of the level before."""
    new = {}
    for f, _, o in outputs:
        partner = F.lag(o, distance).over(spec)
        there = F.lag(F.lit(1), distance).over(spec).isNotNull()
        new[o] = F.when(there if active is None else there & active, FUNCTIONS[f][0](partner, F.col(o))).otherwise(F.col(o))
    return df.withColumns(new)
