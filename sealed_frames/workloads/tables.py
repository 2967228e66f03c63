"""The given tables in integer normal form: money in cents, dates as dates, lines with revenue parts."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..core.frame import SealedFrame, seal
from ..functions.integers import cents, day_number, revenue

__all__ = ["PRELUDE", "day_number", "padded_table", "part_supply", "revenue", "table"]


def _day(name: str):
    return F.to_date(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> SealedFrame:
    """A sealed table with short column names; only columns that are used are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if name == "region":
        return seal(df.select("r_regionkey", "r_name"), [["r_regionkey"]])
    if name == "nation":
        return seal(df.select("n_nationkey", "n_name", "n_regionkey"), [["n_nationkey"]])
    if name == "customer":
        return seal(df.select("c_custkey", "c_name", "c_nationkey", cents("c_acctbal").alias("c_bal"), "c_mktsegment"), [["c_custkey"]])
    if name == "supplier":
        return seal(df.select("s_suppkey", "s_name", "s_nationkey", cents("s_acctbal").alias("s_bal")), [["s_suppkey"]])
    if name == "part":
        return seal(df.select("p_partkey", "p_name", "p_brand", "p_type", "p_size"), [["p_partkey"]])
    if name == "orders":
        return seal(df.select("o_orderkey", "o_custkey", "o_orderstatus", cents("o_totalprice").alias("o_total"), _day("o_orderdate").alias("o_date"), "o_orderpriority"), [["o_orderkey"]])
    if name == "lineitem":
        return seal(
            df.select(
                "l_orderkey", "l_partkey", "l_suppkey", F.col("l_quantity").cast("long").alias("qty"), cents("l_extendedprice").alias("price"), cents("l_discount").alias("disc"),
                cents("l_tax").alias("tax"), "l_returnflag", "l_linestatus", _day("l_shipdate").alias("ship"),
            )
        )
    if name == "events":
        return seal(df.select("event_id", "ts", "user_id", "event_type", cents("value").alias("val"), "props"), [["event_id"]])
    raise ValueError(f"unknown table {name!r}")


def padded_table(spark: SparkSession, sf_dir: str, name: str) -> SealedFrame:
    """The table in the padded tier: its size is public, and so is every size that follows from it."""
    f = table(spark, sf_dir, name)
    return replace(f, public=replace(f.public, rows=f.df.count(), tier="padded"))


def part_supply(lines: SealedFrame) -> SealedFrame:
    """Stand-in for the missing table of offers: per part and supplier the quantity and the least price."""
    return lines.aggregate(["l_partkey", "l_suppkey"], avail=("sum", "qty"), cost=("min", "price"))


#: The same normal form in DuckDB, put before every query's text.
PRELUDE = """
WITH L AS (SELECT l_orderkey, l_partkey, l_suppkey, CAST(l_quantity AS BIGINT) AS qty, CAST(round(l_extendedprice * 100) AS BIGINT) AS price,
  CAST(round(l_discount * 100) AS BIGINT) AS disc, CAST(round(l_tax * 100) AS BIGINT) AS tax, l_returnflag, l_linestatus, CAST(l_shipdate AS DATE) AS ship,
  CAST(round(l_extendedprice * 100) AS BIGINT) * (100 - CAST(round(l_discount * 100) AS BIGINT)) AS rev FROM lineitem),
O AS (SELECT o_orderkey, o_custkey, o_orderstatus, CAST(round(o_totalprice * 100) AS BIGINT) AS o_total, CAST(o_orderdate AS DATE) AS o_date, o_orderpriority FROM orders),
C AS (SELECT c_custkey, c_name, c_nationkey, CAST(round(c_acctbal * 100) AS BIGINT) AS c_bal, c_mktsegment FROM customer),
S AS (SELECT s_suppkey, s_name, s_nationkey, CAST(round(s_acctbal * 100) AS BIGINT) AS s_bal FROM supplier),
P AS (SELECT * FROM part), N AS (SELECT * FROM nation), R AS (SELECT * FROM region),
E AS (SELECT event_id, ts, user_id, event_type, CAST(round(value * 100) AS BIGINT) AS val, props FROM events),
PS AS (SELECT l_partkey, l_suppkey, sum(qty) AS avail, min(price) AS cost FROM L GROUP BY ALL)
"""
