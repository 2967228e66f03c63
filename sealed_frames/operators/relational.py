"""Surrounding relational operators that the paper's methods are used with."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: Sequence[str], ts: str, values: Sequence[str]) -> DataFrame:
    """For each left row the latest right row at or before it: one union, one ordered pass per key."""
    both = left.withColumn("__l", F.lit(True)).unionByName(right.select(*by, ts, F.struct(*values).alias("__v")).withColumn("__l", F.lit(False)), allowMissingColumns=True)
    upto = Window.partitionBy(*by).orderBy(F.col(ts), F.col("__l")).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("__v", F.last("__v", ignorenulls=True).over(upto)).where("__l")
    return found.select(*left.columns, *[F.col("__v")[v].alias(v) for v in values])


def band_join(left: DataFrame, right: DataFrame, left_on: str, right_on: str, width: int, by: Sequence[str] = ()) -> DataFrame:
    """Pairs with |left_on - right_on| <= width: an equi-join on buckets as wide as the band."""
    bucket = lambda c: F.floor(F.col(c) / width)
    near = left.withColumn("__b", F.explode(F.sequence(bucket(left_on) - 1, bucket(left_on) + 1)))
    met = near.join(right.withColumn("__b", bucket(right_on)), [*by, "__b"])
    return met.where(F.abs(F.col(left_on) - F.col(right_on)) <= width).drop("__b")


def overlap_join(left: DataFrame, right: DataFrame, left_span: tuple[str, str], right_span: tuple[str, str], bucket: int) -> DataFrame:
    """Pairs of closed integer intervals that meet: intervals are put into every bucket they touch and a pair
    counts in the bucket where the later one starts."""
    spread = lambda df, a, b: df.withColumn("__b", F.explode(F.sequence(F.floor(F.col(a) / bucket), F.floor(F.col(b) / bucket))))
    (a, b), (c, d) = left_span, right_span
    met = spread(left, a, b).join(spread(right, c, d), "__b").where((F.col(a) <= F.col(d)) & (F.col(c) <= F.col(b)))
    return met.where(F.floor(F.greatest(a, c) / bucket) == F.col("__b")).drop("__b")


def top_k_per(df: DataFrame, keys: Sequence[str], order: Sequence[Column], k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("rank", rank).where(F.col("rank") <= k)


def salted_aggregate(df: DataFrame, keys: Sequence[str], value: str, salts: int = 16) -> DataFrame:
    """Sums by key in two steps for keys whose partials alone are many: first by key and salt."""
    part = df.withColumn("__salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(*keys, "__salt").agg(F.sum(value).alias("__s"), F.count("*").alias("__n"))
    return part.groupBy(*keys).agg(F.sum("__s").alias("total"), F.sum("__n").alias("n"))


def salted_join(left: DataFrame, right: DataFrame, keys: Sequence[str], salts: int = 8) -> DataFrame:
    """An equi-join whose heavy right keys are split: the left side, unique by key, is repeated per salt."""
    copies = left.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return copies.join(right.withColumn("__salt", F.pmod(F.xxhash64(*right.columns), F.lit(salts)).cast("int")), [*keys, "__salt"]).drop("__salt")
