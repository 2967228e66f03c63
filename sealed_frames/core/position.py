"""Dense row positions without a window over the whole table.

Rows are range-partitioned and sorted (and checkpointed, since range bounds come from samples that a second
reading of the plan may draw otherwise); a count per partition gives each partition's offset; the
position is the offset plus the rank within the partition. Offsets are prefix sums over a tree, so that
neither they nor the join that brings them back meet in one task when there are many.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import checkpointed

POS = "__pos"
#: Children of a node of the tree of sums, which one task orders; offsets that may be broadcast.
FANOUT, MOST_BROADCAST = 1 << 14, 1 << 20


def prefix_sums(sums: DataFrame, key: str, value: str, rows: int, out: str = "__before", fanout: int = FANOUT) -> DataFrame:
    """(key, out): the sum of ``value`` over smaller keys. Keys are distinct numbers below ``rows``.

    Each group of ``fanout`` neighbouring keys is summed by a task; sums of groups take their turn as keys."""
    if key == "__g":
        sums, key = sums.withColumnRenamed("__g", "__k"), "__k"
        return prefix_sums(sums, key, value, rows, out, fanout).withColumnRenamed("__k", "__g")
    group = F.floor(F.col(key) / fanout).cast("long")
    before = F.coalesce(F.sum(value).over(Window.partitionBy("__g").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inner = sums.withColumn("__g", group).withColumn(out, before)
    if rows <= fanout:
        return inner.select(key, out)
    groups = -(-rows // fanout)
    above = sums.groupBy(group.alias("__g")).agg(F.sum(value).alias("__v"))
    above = prefix_sums(above, "__g", "__v", groups, "__b", fanout).select(F.col("__g").alias("__h"), F.col("__b").alias("__above"))
    met = inner.join(F.broadcast(above) if groups <= MOST_BROADCAST else above, F.col("__g") == F.col("__h"))
    return met.select(key, (F.col(out) + F.col("__above")).alias(out))


def beside(df: DataFrame, offsets: DataFrame, keys: list[str], rows: int) -> DataFrame:
    """Offsets beside the rows of their keys: broadcast if they are few, else a join that adaptive execution splits."""
    return df.join(F.broadcast(offsets) if rows <= MOST_BROADCAST else offsets, keys)


def with_positions(df: DataFrame, order: list[Column], blocks: int | None = None, name: str = POS) -> DataFrame:
    """Add ``name``: 0, 1, 2, ... along ``order``; ties are broken by chance unless the order is total."""
    dealt = df.repartitionByRange(blocks, *order) if blocks else df.repartitionByRange(*order)
    dealt = checkpointed(dealt.withColumn("__part", F.spark_partition_id().cast("long")))
    ranked = dealt.withColumn("__rank", F.row_number().over(Window.partitionBy("__part").orderBy(*order)) - 1)
    counts = dealt.groupBy("__part").agg(F.count("*").alias("__n"))
    parts = (counts.agg(F.max("__part")).first()[0] or 0) + 1
    placed = beside(ranked, prefix_sums(counts, "__part", "__n", parts), ["__part"], parts)
    return placed.withColumn(name, (F.col("__before") + F.col("__rank")).cast("long")).drop("__part", "__rank", "__before")


def running_sum(df: DataFrame, value: str, out: str, pos: str = POS, block_rows: int = 1 << 16, fanout: int = FANOUT) -> DataFrame:
    """Inclusive running sum along dense positions: per block, then offsets of blocks."""
    inner = df.withColumn("__block", F.floor(F.col(pos) / block_rows).cast("long"))
    inner = inner.withColumn(out, F.sum(value).over(Window.partitionBy("__block").orderBy(pos)))
    sums = checkpointed(inner.groupBy("__block").agg(F.sum(value).alias("__s")))
    blocks = sums.count()
    placed = beside(inner, prefix_sums(sums, "__block", "__s", blocks, fanout=fanout), ["__block"], blocks)
    return placed.withColumn(out, F.col(out) + F.col("__before")).drop("__block", "__before")
