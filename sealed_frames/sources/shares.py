"""Owners' files: each party gets a folder with its term of every share."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def export_shares(df: DataFrame, keys: Sequence[str], columns: Sequence[str], path: str, parties: int, seed: int) -> None:
    """Boolean shares of integer columns: random terms for all parties but the last, who gets the rest."""
    for party in range(parties):
        out = []
        for c in columns:
            masks = [F.xxhash64(F.lit(seed), F.lit(c), F.lit(i), *keys) for i in range(parties - 1)]
            out.append((masks[party] if party < parties - 1 else reduce(lambda a, b: a.bitwiseXOR(b), masks, F.col(c))).alias(c))
        df.select(*keys, *out).write.parquet(f"{path}/party={party}")


def import_shares(spark: SparkSession, keys: Sequence[str], columns: Sequence[str], path: str, parties: int) -> DataFrame:
    """Open: the terms of a row meet by key in one aggregation."""
    every = spark.read.parquet(path)
    return every.groupBy(*keys).agg(*[F.bit_xor(c).alias(c) for c in columns])
