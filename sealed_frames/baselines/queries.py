"""Baselines: the quadratic engine, the naive cascade, the leaking engine, the bounded and the size-revealing join."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators.fused_join import cartesian_join
from ..share import circuits as C
from ..share.protocols import PROTOCOLS
from ..workloads.micro import _importable
from ..workloads.tables import PRELUDE, revenue, table

QUERIES = {}
SQL = {}


def baseline(sql: str | None):
    def keep(fn):
        def run(spark, sf_dir):
            _importable(spark)
            return fn(spark, sf_dir)

        QUERIES[fn.__name__] = run
        if sql:
            SQL[fn.__name__] = PRELUDE + sql
        return fn

    return keep


@baseline("SELECT n_nationkey, count(*) AS n FROM N JOIN S ON n_nationkey = s_nationkey GROUP BY ALL")
def baseline_quadratic_shared(spark, sf_dir):
    """All pairs of two small tables compared on shares, in one task (L24, L555, L858)."""
    left = [int(r[0]) for r in table(spark, sf_dir, "nation").df.select("n_nationkey").collect()]

    def run(part: pd.DataFrame) -> pd.DataFrame:
        p = PROTOCOLS["3p"](1)
        a = np.repeat(np.array(left), len(part))
        b = np.tile(part["s_nationkey"].to_numpy(np.int64), len(left))
        hit = p.open(C.equal(p, p.share(a, True), p.share(b, True), 8), 1).astype(np.int64)
        counts = np.bincount(a, hit, max(left) + 1).astype(np.int64)
        return pd.DataFrame({"n_nationkey": np.flatnonzero(counts), "n": counts[counts > 0]})

    one = table(spark, sf_dir, "supplier").df.select(F.col("s_nationkey").cast("long").alias("s_nationkey")).withColumn("g", F.lit(0))
    return one.groupBy("g").applyInPandas(run, "n_nationkey int, n long")


@baseline("SELECT CAST(n_regionkey AS BIGINT) AS n_regionkey, count(*) AS n FROM N JOIN S ON n_nationkey = s_nationkey GROUP BY ALL")
def baseline_quadratic_engine(spark, sf_dir):
    """A join and a grouping as the quadratic engine runs them on shares: all pairs are compared, a bitonic network
    sorts all of them, padded to a power of two, and neighbours are scanned (L555, L858)."""
    from ..plans.meter import padded
    from ..share.blocks import seed_of
    from ..share.join import run_ends, run_starts, scan
    from ..share.protocols import Shared
    from ..share.sorting import apply_sharded_all, network_sort, sharded_permutation
    from ..workloads.shared import gathered, tables_of

    nations = table(spark, sf_dir, "nation").df.select("n_nationkey", "n_regionkey")
    sellers = table(spark, sf_dir, "supplier").df.select("s_nationkey")
    columns = {"n": nations.columns, "s": sellers.columns}

    def run(part: pd.DataFrame) -> pd.DataFrame:
        t = tables_of(part, columns)
        p = PROTOCOLS["3p"](seed_of(len(part)))
        keys, regions, theirs = (p.share(x, True) for x in (t["n"]["n_nationkey"], t["n"]["n_regionkey"], t["s"]["s_nationkey"]))
        n, m = len(keys), len(theirs)
        each = lambda s: Shared(np.repeat(s.terms, m, axis=1), True)
        hit = C.equal(p, each(keys), Shared(np.tile(theirs.terms, n), True), 8)
        none = p.public(np.full(n * m, 15), True)  # sorts behind all regions
        key = C.choose(p, hit, none, each(regions))
        size = padded(n * m)
        key = Shared(np.concatenate([key.terms, p.public(np.full(size - n * m, 15), True).terms], axis=1), True)
        key, _ = network_sort(p, key, "bitonic", 4)
        valid = C.greater(p, p.public(np.full(size, 15), True), key, 4)
        starts = run_starts(p, key, 4)
        counts = scan(p, starts, {"n": ("sum", C.bit_to_arithmetic(p, valid))})["n"]
        ok = p.and_(run_ends(p, starts), valid, 1)
        masked = [p.and_(C.widen(p, ok), key), p.mul(C.bit_to_arithmetic(p, ok), counts), ok]
        key, counts, ok = (p.open(s) for s in apply_sharded_all(p, sharded_permutation(p, size, 5), masked))
        keep = (ok & np.uint64(1)) == 1
        return pd.DataFrame({"n_regionkey": key[keep].astype(np.int64), "n": counts[keep].astype(np.int64)})

    return gathered({"n": nations, "s": sellers}).groupBy(F.lit(0).alias("g")).applyInPandas(run, "n_regionkey long, n long")


@baseline("SELECT count(*) AS n FROM N JOIN S ON n_nationkey = s_nationkey JOIN R ON r_regionkey = n_regionkey")
def baseline_cartesian_cascade(spark, sf_dir):
    """A chain of quadratic joins: the intermediate has the product of all sizes."""
    first = cartesian_join(table(spark, sf_dir, "nation"), table(spark, sf_dir, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"))
    second = cartesian_join(first, table(spark, sf_dir, "region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return second.aggregate([], n=("count", "*")).reveal()


@baseline("SELECT o_orderpriority, count(*) AS n, count(DISTINCT o_orderkey) AS left_rows_revealed, count(*) AS right_rows_revealed FROM O JOIN L ON o_orderkey = l_orderkey GROUP BY ALL")
def baseline_leaky(spark, sf_dir):
    """Which rows match is revealed, then everything goes on in the clear (L20, L861); with what the parties learn:
    how many rows of either side they know to have met."""
    met = table(spark, sf_dir, "orders").df.join(table(spark, sf_dir, "lineitem").df.drop("__ok"), F.col("o_orderkey") == F.col("l_orderkey"))
    return met.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.countDistinct("o_orderkey").alias("left_rows_revealed"), F.count("*").alias("right_rows_revealed"))


@baseline("""SELECT count(*) AS whole, CAST(sum(CASE WHEN k <= 3 THEN 1 ELSE 0 END) AS BIGINT) AS kept FROM (SELECT row_number() OVER (PARTITION BY o_orderkey ORDER BY price, qty, disc, l_partkey, l_suppkey) AS k FROM O JOIN L ON o_orderkey = l_orderkey)""")
def baseline_bounded_recall(spark, sf_dir):
    """A join that holds at most three rows per key: what it loses."""
    met = table(spark, sf_dir, "orders").df.join(table(spark, sf_dir, "lineitem").df.drop("__ok"), F.col("o_orderkey") == F.col("l_orderkey"))
    rank = F.row_number().over(Window.partitionBy("o_orderkey").orderBy("price", "qty", "disc", "l_partkey", "l_suppkey"))
    return met.withColumn("k", rank).agg(F.count("*").alias("whole"), F.sum(F.when(F.col("k") <= 3, 1).otherwise(0)).alias("kept"))


@baseline("SELECT event_type, count(*) AS n, count(*) AS revealed FROM E JOIN O ON user_id = o_custkey GROUP BY ALL")
def baseline_size_revealing(spark, sf_dir):
    """A join whose true size is opened before rows are expanded (L24-27)."""
    right = table(spark, sf_dir, "orders").aggregate(["o_custkey"], mult=("count", "*")).df.drop("__ok")
    met = table(spark, sf_dir, "events").df.join(right, F.col("user_id") == F.col("o_custkey"), "left")
    expanded = met.withColumn("copy", F.explode(F.array_repeat(F.lit(1), F.coalesce("mult", F.lit(0).cast("long")).cast("int"))))
    return expanded.groupBy("event_type").agg(F.count("*").alias("n"), F.count("*").alias("revealed"))


@baseline("SELECT l_suppkey, CAST(sum(rev) AS BIGINT) AS s FROM L GROUP BY ALL")
def baseline_plain_engine(spark, sf_dir):
    """The answer of a plain engine, for comparison of results (L800)."""
    df = table(spark, sf_dir, "lineitem").df
    return df.withColumn("rev", revenue()).groupBy("l_suppkey").agg(F.sum("rev").alias("s"))
