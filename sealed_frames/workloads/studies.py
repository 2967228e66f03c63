"""Costs and studies: what queries, operators, sorts and triples cost, from the queries themselves and from runs.

Rounds, bits, sorts and rows follow from public sizes and are the same in every run. Seconds are
those counts under the published networks plus computing at a rate that is measured when the study runs.
"""

from __future__ import annotations

import socket
import time

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from ..core.frame import OK
from ..core.position import with_positions
from ..plans import meter as M
from ..plans.oblivious import Plan, cost_of, scaled
from ..share import sorting as S
from ..share import triples as T
from ..share.blocks import seed_of
from ..share.protocols import PROTOCOLS, U
from . import prior, tpch
from .micro import _importable
from .tables import table

QUERIES = {}
SQL = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events")
NETWORKS = {"lan": M.LAN, "wan": M.WAN, "geo": M.GEO}
#: The decision-support queries, those of earlier engines, and those of two owners.
FUNCTIONS = {
    **{k: f for k, f in tpch.FUNCTIONS.items() if k != "tpch_q03_no_constraints"},
    **{k: f for k, f in prior.FUNCTIONS.items() if k.startswith(("prior_", "owner_"))},
}
KEYS = {"region": ["r_regionkey"], "nation": ["n_nationkey"], "customer": ["c_custkey"], "supplier": ["s_suppkey"], "part": ["p_partkey"], "orders": ["o_orderkey"], "events": ["event_id"], "lineitem": []}


def study(sql: str | None = None):
    def keep(fn):
        def run(spark, sf_dir):
            _importable(spark)
            return fn(spark, sf_dir)

        QUERIES[fn.__name__] = run
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return keep


def sizes_of(spark, sf_dir) -> dict[str, int]:
    return {t: table(spark, sf_dir, t).df.count() for t in TABLES}


def at_scale_one(sizes: dict[str, int]) -> dict[str, int]:
    """The same tables at the evaluated scale factor of one: 6 million lines."""
    return scaled(sizes, max(1, round(6_000_000 / max(1, sizes["lineitem"]))))


def columns_of(spark, sf_dir) -> dict[str, tuple[list[str], list[str]]]:
    return {t: ([c for c in table(spark, sf_dir, t).df.columns if c != OK], KEYS[t]) for t in TABLES}


def and_rate(seconds: float = 0.2) -> float:
    """64-bit ANDs a second that one core evaluates for one party of three, measured here."""
    p = PROTOCOLS["3p"](1)
    a = p.share(np.arange(1 << 16), True)
    began, done = time.time(), 0
    while time.time() - began < seconds:
        p.and_(a, a)
        done += 1 << 16
    return 3 * done / (time.time() - began)


def message_seconds(count: int = 4000) -> float:
    """What it takes to hand one word to the system's sockets and take it off again, measured here."""
    a, b = socket.socketpair()
    began = time.time()
    for _ in range(count):
        a.sendall(b"12345678")
        b.recv(8)
    took = (time.time() - began) / count
    a.close()
    b.close()
    return took


def window_bytes() -> int:
    """The largest receive window of one connection here."""
    try:
        with open("/proc/sys/net/ipv4/tcp_rmem") as f:
            return int(f.read().split()[2])
    except OSError:
        return 6 << 20


# -- queries -----------------------------------------------------------------------------------------------


def _query_costs(spark, sizes, columns):
    rate, rows = and_rate(), []
    for name, fn in FUNCTIONS.items():
        for protocol in PROTOCOLS:
            c = cost_of(fn, columns, sizes, Plan(protocol))
            compute = c.ands / 64 / rate / 16
            rows.append((name, protocol, c.sorts, c.joins, c.rounds, c.bits, c.peak_rows, *(net.seconds(c.rounds, c.bits, compute) for net in NETWORKS.values())))
    return spark.createDataFrame(rows, "query string, protocol string, sorts long, joins long, rounds long, bits long, peak_rows long, lan_s double, wan_s double, geo_s double")


@study()
def meter_queries(spark, sf_dir):
    """Every query under every protocol: sorts, joins, rounds, bits, largest table, seconds by network."""
    return _query_costs(spark, sizes_of(spark, sf_dir), columns_of(spark, sf_dir))


@study()
def meter_queries_scale_one(spark, sf_dir):
    """As meter_queries at the published scale, where sizes are public numbers and no table is needed."""
    return _query_costs(spark, at_scale_one(sizes_of(spark, sf_dir)), columns_of(spark, sf_dir))


@study()
def meter_quantiles(spark, sf_dir):
    """Median and largest time of the decision-support and of the other queries at the published scale, in minutes."""
    df = meter_queries_scale_one(spark, sf_dir).withColumn("workload", F.when(F.col("query").startswith("tpch"), "decision support").otherwise("other"))
    per = [(F.percentile(f"{n}_s", F.lit(0.5)) / 60).alias(f"{n}_median") for n in ("lan", "wan")] + [(F.max(f"{n}_s") / 60).alias(f"{n}_max") for n in ("lan", "wan")]
    return df.groupBy("workload", "protocol").agg(*per)


@study()
def meter_networks(spark, sf_dir):
    """Five queries from the fastest to the slowest in the geographic network, over the symmetric one, at the published scale."""
    df = meter_queries_scale_one(spark, sf_dir).where(F.col("query").isin("tpch_q06", "tpch_q11", "tpch_q12", "tpch_q08", "tpch_q21"))
    return df.withColumn("geo_over_wan", F.col("geo_s") / F.col("wan_s")).withColumn("wan_over_lan", F.col("wan_s") / F.col("lan_s"))


@study()
def meter_scaling(spark, sf_dir):
    """Each decision-support query on the given tables and at the published scale, and on ten times the rows: ratios (M5)."""
    sizes, columns, rate = sizes_of(spark, sf_dir), columns_of(spark, sf_dir), and_rate()
    rows = []
    for base, start in (("given", sizes), ("scale one", at_scale_one(sizes))):
        for name, fn in FUNCTIONS.items():
            if not name.startswith("tpch"):
                continue
            one, ten = (cost_of(fn, columns, s, Plan("2p")) for s in (start, scaled(start, 10)))
            t = [M.LAN.seconds(c.rounds, c.bits, c.ands / 64 / rate / 16) for c in (one, ten)]
            rows.append((base, name, one.peak_rows, ten.peak_rows, ten.bits / one.bits, ten.rounds / one.rounds, t[1] / t[0], M.scaling_ratio(max(2, one.peak_rows))))
    return spark.createDataFrame(rows, "base string, query string, rows long, rows_10 long, bits_ratio double, rounds_ratio double, seconds_ratio double, ideal double")


def ablation(sizes, columns, rate: float, message: float, window: int) -> list[tuple]:
    """(network, step, name, rounds, bits, messages, seconds, speedup) of the revenue-maximum query, step by step."""
    fn, out = FUNCTIONS["tpch_q15"], []

    def run(net, sort, join, batches, threads, connections):
        c = cost_of(fn, columns, sizes, Plan("3p", sort, join))
        messages = -(-c.ands // 64) if not batches else c.rounds * batches * threads
        rounds = c.rounds * max(1, batches)
        gbps = min(net.gbps, connections * window * 8 / (net.rtt_ms / 1e3) / 1e9)
        seconds = M.NetworkModel(net.rtt_ms, gbps).seconds(rounds, c.bits, c.ands / 64 / rate / threads + messages * message / threads)
        return rounds, c.bits, messages, seconds

    lan = [("baseline", "pairwise", "quadratic", 0, 1), ("pivot sort", "pivot", "quadratic", 0, 1), ("fused join", "pivot", "fused", 0, 1), ("batches", "pivot", "fused", 12, 1), ("threads", "pivot", "fused", 12, 16)]
    wan = [("baseline", 12, 1, 1), ("threads", 12, 16, 1), ("one batch", 1, 16, 1), ("connections", 1, 16, 16)]
    for network, net, steps in (("lan", M.LAN, [(n, s, j, b, t, 16) for n, s, j, b, t in lan]), ("wan", M.WAN, [(n, "pivot", "fused", b, t, c) for n, b, t, c in wan])):
        first = None
        for i, (name, *choice) in enumerate(steps):
            got = run(net, *choice)
            first = first or got[3]
            out.append((network, i, name, *got, first / got[3]))
    return out


@study()
def meter_ablation(spark, sf_dir):
    """The revenue-maximum query with one choice after the other turned on, in both networks."""
    rows = ablation(sizes_of(spark, sf_dir), columns_of(spark, sf_dir), and_rate(), message_seconds(), window_bytes())
    return spark.createDataFrame(rows, "network string, step int, name string, rounds long, bits long, messages long, seconds double, speedup double")


# -- operators, against SQL ----------------------------------------------------------------------------------

_LG = "CAST(ceil(log2({})) AS BIGINT)"


@study(f"""WITH t AS (SELECT (SELECT count(*) FROM orders) AS n, (SELECT count(*) FROM lineitem) AS m), k AS (SELECT *, {_LG.format('n + m')} AS lg, {_LG.format('least(n, m)')} AS lgn FROM t)
SELECT 'filter' AS operator, CAST(8 AS BIGINT) AS rounds, CAST(m * (7 * 64 + 1) AS BIGINT) AS ands FROM k
UNION ALL SELECT 'bitwise sort', 64 * 4, CAST((n + m) * 64 * 128 AS BIGINT) FROM k
UNION ALL SELECT 'bitonic sort', lg * (lg + 1) // 2 * 8, CAST((1 << lg) * lg * (lg + 1) // 4 * (7 * 64 + 128) AS BIGINT) FROM k
UNION ALL SELECT 'pairwise sort', lg * (lg + 1) // 2 * 8, CAST(((lg * lg - lg + 4) * (1 << lg) // 4 - 1) * (7 * 64 + 128) AS BIGINT) FROM k
UNION ALL SELECT 'scan', 6 + lg, CAST(((n + m) * lg - ((1 << lg) - 1)) * (63 + 64) AS BIGINT) FROM k
UNION ALL SELECT 'quadratic join', 7, CAST(n * m * 64 AS BIGINT) FROM k""")
def meter_operators(spark, sf_dir):
    """Rounds and ANDs of single operators on the orders and lines of the given tables."""
    n, m = (table(spark, sf_dir, t).df.count() for t in ("orders", "lineitem"))
    rows = [
        ("filter", *M.filter_cost(m)), ("bitwise sort", *M.bitwise_sort_cost(n + m)), ("bitonic sort", *M.network_sort_cost(n + m, "bitonic")), ("pairwise sort", *M.network_sort_cost(n + m, "pairwise")),
        ("scan", *M.scan_cost(n + m)), ("quadratic join", *M.quadratic_join_cost(n, m)),
    ]
    return spark.createDataFrame(rows, "operator string, rounds long, ands long")


@study(
    """SELECT l_returnflag, l_linestatus, k, CAST((1 << k) * k * (k + 1) // 4 AS BIGINT) AS bitonic, CAST((k * k - k + 4) * (1 << k) // 4 - 1 AS BIGINT) AS odd_even, CAST(k + 6 AS BIGINT) AS scan_rounds,
    CAST(7 AS BIGINT) AS compare_rounds, CAST(2 * (1 << k) AS BIGINT) AS filled FROM (SELECT l_returnflag, l_linestatus, CAST(ceil(log2(count(*))) AS BIGINT) AS k FROM lineitem GROUP BY ALL)"""
)
def meter_model(spark, sf_dir):
    """Formulas of the cost model, as integers, at the sizes of the groups of lines, filled up to powers of two."""
    rows = []
    for flag, status, size in table(spark, sf_dir, "lineitem").df.groupBy("l_returnflag", "l_linestatus").count().collect():
        n = M.padded(size)
        k = M.lg(n)
        rows.append((flag, status, k, M.network_size(n, "bitonic"), M.network_size(n, "odd_even"), k + M.equal_cost(64)[0], M.compare_cost(64)[0], M.padded(n + 1)))
    return spark.createDataFrame(rows, "l_returnflag string, l_linestatus string, k long, bitonic long, odd_even long, scan_rounds long, compare_rounds long, filled long")


# -- sorts, run ----------------------------------------------------------------------------------------------

#: Sorts by name: (run of (protocol, key, bits), needs distinct keys).
SORTS = {
    "pivot": lambda p, key, bits: S.pivot_sort(p, key, bits)[0],
    "hybrid": lambda p, key, bits: S.bitwise_sort(p, key, bits),
    "eager": lambda p, key, bits: S.bitwise_sort(p, key, bits, variant="eager"),
    "composed": lambda p, key, bits: S.bitwise_sort(p, key, bits, variant="composed"),
    "bitonic": lambda p, key, bits: S.network_sort(p, key, "bitonic", bits)[0],
    "pairwise": lambda p, key, bits: S.network_sort(p, key, "pairwise", bits)[0],
}


def run_sort(name: str, k: int, bits: int, protocol: str = "3p", ranks: np.ndarray | None = None) -> tuple[float, int, int, bool]:
    """(seconds, rounds, bits, sorted?) of one run on 2^k distinct keys of ``bits`` bits: given ranks, else random ones."""
    n, p = 1 << k, PROTOCOLS[protocol](seed_of(k, bits))
    keys = (np.random.default_rng(k).permutation(n) if ranks is None else ranks).astype(np.int64) << max(0, bits - k)
    key = p.share(keys, True)
    began = time.time()
    out = SORTS[name](p, key, bits)
    return time.time() - began, p.meter.rounds, p.meter.bits, bool((p.value(out) == np.sort(keys.view(U))).all())


def _runs(spark, work: list[tuple[str, int, int, str]]):
    def one(part: pd.DataFrame) -> pd.DataFrame:
        rows = [(n, int(k), int(b), p, *run_sort(n, int(k), int(b), p)) for n, k, b, p in zip(part["name"], part["k"], part["width"], part["protocol"])]
        return pd.DataFrame(rows, columns=["name", "k", "width", "protocol", "seconds", "rounds", "bits", "right"])

    df = spark.createDataFrame(work, "name string, k long, width long, protocol string")
    return df.repartition(max(2, len(work)), "name", "k", "width", "protocol").groupBy("name", "k", "width", "protocol").applyInPandas(one, "name string, k long, width long, protocol string, seconds double, rounds long, bits long, right boolean")


def _runs_on_suppliers(spark, sf_dir, work: list[tuple[str, int, int, str]]):
    """The same on all suppliers, 2^k a run: keys are ranks of their balances, the last run is filled up. Seconds
    are a run's mean, rounds and bits the largest, n counts the suppliers that were sorted."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        name, k, width, protocol = (part[c].iloc[0] for c in ("name", "k", "width", "protocol"))
        ranks = S.invert(np.lexsort((part["s_suppkey"], part["s_bal"])))
        ranks = np.concatenate([ranks, np.arange(len(ranks), 1 << int(k))])
        return pd.DataFrame([(name, k, width, protocol, *run_sort(name, int(k), int(width), protocol, ranks), len(part))], columns=["name", "k", "width", "protocol", "seconds", "rounds", "bits", "right", "n"])

    df = with_positions(table(spark, sf_dir, "supplier").df.select("s_suppkey", "s_bal"), [F.asc("s_suppkey")], 8)
    rows = df.count()
    runs = sum(-(-rows // (1 << k)) for _, k, _, _ in work)
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.lit(k).cast("long").alias("k"), F.lit(w).cast("long").alias("width"), F.lit(p).alias("protocol")) for n, k, w, p in work]))
    df = df.select("s_suppkey", "s_bal", "__pos", each.alias("w")).select("s_suppkey", "s_bal", "w.*", F.floor(F.col("__pos") / F.pow(F.lit(2), F.col("w.k"))).alias("run"))
    df = df.repartition(min(1 << 14, 2 * max(1, runs)), "name", "k", "width", "protocol", "run")
    ran = df.groupBy("name", "k", "width", "protocol", "run").applyInPandas(one, "name string, k long, width long, protocol string, seconds double, rounds long, bits long, right boolean, n long")
    return ran.groupBy("name", "k", "width", "protocol").agg(F.avg("seconds").alias("seconds"), F.max("rounds").alias("rounds"), F.max("bits").alias("bits"), F.min("right").alias("right"), F.sum("n").alias("n"))


@study()
def meter_sort_scaling(spark, sf_dir):
    """Every sort on 2^10 to 2^16 keys of 32 bits, run on all suppliers (M1, M3): seconds, rounds, bits, suppliers
    sorted. Larger sizes: ``sort_study``."""
    return _runs_on_suppliers(spark, sf_dir, [(n, k, 32, "3p") for k in (10, 12, 14, 16) for n in SORTS])


@study()
def meter_sort_protocols(spark, sf_dir):
    """Pivot and hybrid sort under the three protocols, run."""
    return _runs_on_suppliers(spark, sf_dir, [(n, 13, 64 if n == "hybrid" else 32, p) for n in ("pivot", "hybrid") for p in PROTOCOLS]).drop("n")


@study()
def meter_sort_widths(spark, sf_dir):
    """Bit by bit over 64 bits, 32 bits, and as many as dense ranks need (B7, M2), run on 2^12 to 2^15 keys."""
    return _runs_on_suppliers(spark, sf_dir, [("hybrid", k, w, "2p") for k in (12, 14, 15) for w in (k, 32, 63)]).drop("n")


def sort_study(spark, names: list[str], powers: list[int], bits: int = 32, protocol: str = "3p"):
    """The same at sizes of one's choice; a task holds a whole vector, some 2 GB for 2^22 keys."""
    _importable(spark)
    return _runs(spark, [(n, k, bits, protocol) for n in names for k in powers])


@study("""SELECT * FROM (VALUES ('hybrid', CAST(32 AS BIGINT), CAST(1024 AS BIGINT), CAST(7 * 32 AS BIGINT), true), ('composed', 32, 1024, 31 * 10 + 7, true)) t(name, width, n, rounds, right_)""")
def sort_rounds(spark, sf_dir):
    """Rounds of the two ways to sort by bits, from a run each: they depend on the width alone."""
    df = _runs_on_suppliers(spark, sf_dir, [(n, 10, 32, "3p") for n in ("hybrid", "composed")])
    return df.select("name", "width", F.pow(F.lit(2), F.col("k")).cast("long").alias("n"), "rounds", F.col("right").alias("right_"))


@study()
def meter_preprocess(spark, sf_dir):
    """Comparisons that a pivot sort makes against what is reserved for it: customers by balance, about n a run."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        n, size, seed = int(part["n"].iloc[0]), len(part), int(part["run"].iloc[0])
        p = PROTOCOLS["3p"](seed_of(n, seed))
        key = p.share(S.invert(np.lexsort((part["c_custkey"], part["c_bal"]))), True)
        _, levels, compared = S.pivot_sort(p, key, M.lg(size) + 1, seed + 1)
        return pd.DataFrame({"n": [n], "levels": [levels], "compared": [compared], "reserved": [M.preprocess_bound(size)]})

    df = table(spark, sf_dir, "customer").df.select("c_custkey", "c_bal")
    rows = df.count()
    each = F.explode(F.array(*[F.struct(F.lit(n).cast("long").alias("n"), F.lit(max(1, rows // n)).alias("runs")) for n in (256, 1024, 4096)]))
    df = df.select("*", each.alias("w")).select("c_custkey", "c_bal", "w.n", F.pmod(F.xxhash64("c_custkey"), F.col("w.runs")).alias("run"))
    done = df.groupBy("n", "run").applyInPandas(one, "n long, levels long, compared long, reserved long")
    return done.groupBy("n").agg(F.max("levels").alias("levels"), F.max("compared").alias("compared"), F.max("reserved").alias("reserved"))


@study("SELECT t.*, (SELECT count(*) FROM customer) AS n FROM (VALUES ('per_gate', CAST(20 AS BIGINT), CAST(20 + 20 * 10 AS BIGINT), true), ('batched', 20, 20 + 1, true)) t(checks, products, rounds, right_)")
def meter_four_party_checks(spark, sf_dir):
    """The four-party protocol with copies compared gate by gate, as first published, and in one batch at the end, as
    patched: the same products of all customers' balances, and ten comparisons a gate in rounds of their own against
    one (P8)."""

    def run(batches):
        for number, batch in enumerate(batches):
            if not batch.num_rows:
                continue
            given = batch.column(0).to_numpy().astype(np.int64)
            rows = []
            for checks in ("per_gate", "batched"):
                p = PROTOCOLS["4p"](seed_of(number, len(given)), check=checks)
                x, want = p.share(given, False), given.view(U)
                y = x
                for _ in range(20):
                    y, want = p.mul(y, x), want * given.view(U)
                if checks == "batched":
                    p.verify()
                rows.append((checks, 20, p.meter.rounds, bool((p.value(y) == want).all()), len(given)))
            yield pa.RecordBatch.from_pandas(pd.DataFrame(rows, columns=["checks", "products", "rounds", "right_", "n"]), preserve_index=False)

    ran = table(spark, sf_dir, "customer").df.select("c_bal").mapInArrow(run, "checks string, products long, rounds long, right_ boolean, n long")
    return ran.groupBy("checks", "products").agg(F.max("rounds").alias("rounds"), F.min("right_").alias("right_"), F.sum("n").alias("n"))


# -- triples -----------------------------------------------------------------------------------------------

ELLS = (8, 16, 32, 64, 128)


def make_triples(kind: str, n: int, ell: int, seed: int = 1):
    """(terms of one party, terms of the other, bits sent)."""
    if kind == "boolean":
        return T.boolean_triples(n, ell, seed)
    make = T.ole_quadratic if kind == "quadratic" else T.ole_crt
    (x, y, b), (u, v, c) = make(n, ell, 2 * seed), make(n, ell, 2 * seed + 1)
    return *T.triples_from_ole((x, y), (u, v), ell), b + c


def _triples(kind: str):
    """Per width: triples made, how many hold, and bits sent per triple."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        rows = []
        for seed, ell, n in zip(part["seed"], part["ell"], part["n"]):
            seed, ell, n = int(seed), int(ell), int(n)
            a, b, bits = make_triples(kind, n, ell, seed)
            m = (1 << ell) - 1 if ell > 64 else U((1 << ell) - 1)
            good = ((a[0] ^ b[0]) & (a[1] ^ b[1])) == (a[2] ^ b[2]) if kind == "boolean" else (((a[0] + b[0]) * (a[1] + b[1])) & m) == ((a[2] + b[2]) & m)
            rows.append((ell, n, int(good.sum()), bits // n))
        return pd.DataFrame(rows, columns=["ell", "made", "good", "bits"])

    def run(spark, sf_dir):
        work = spark.createDataFrame([(s, e, 250) for e in ELLS for s in range(1, 9)], "seed long, ell long, n long")
        made = work.repartition(8).groupBy("seed").applyInPandas(one, "ell long, made long, good long, bits long")
        return made.groupBy("ell").agg(F.sum("made").alias("made"), F.sum("good").alias("good"), F.max("bits").alias("bits"))

    run.__name__ = f"triple_{kind}"
    return run


def crt_bits(ell: int) -> int:
    return 2 * sum(map(T.prime_bits, T.primes_above(2 * ell + 41)))


for _k, _sent in (("quadratic", lambda e: 2 * e * (e + 2)), ("crt", crt_bits), ("boolean", lambda e: 2 * e)):
    study("SELECT * FROM (VALUES " + ", ".join(f"(CAST({e} AS BIGINT), CAST(2000 AS BIGINT), CAST(2000 AS BIGINT), CAST({_sent(e)} AS BIGINT))" for e in ELLS) + ") t(ell, made, good, bits)")(_triples(_k))


KINDS = ("quadratic", "crt", "boolean")
#: What ``meter_triples`` makes: (generator, width, triples of a batch), smaller batches where Python integers carry them.
BATCHES = [(k, e, b) for k in KINDS for e in ELLS for b in ((1 << 10, 1 << 12) if k == "crt" or e > 64 else (1 << 12, 1 << 15, 1 << 18))]


def use_triples(kind: str, ell: int, x: np.ndarray, y: np.ndarray, seed: int) -> tuple[float, int, bool]:
    """(seconds to make a triple for each pair of factors, bits sent for them, all products right?)."""
    began = time.time()
    a, b, bits = make_triples(kind, len(x), ell, seed)
    took = time.time() - began
    x, y, boolean = T.ring(x, ell), T.ring(y, ell), kind == "boolean"
    want = x & y if boolean else x * y & ((1 << ell) - 1 if ell > 64 else U((1 << ell) - 1))
    return took, bits, bool((T.product(a, b, x, y, ell, boolean, seed_of(seed)) == want).all())


def _triples_for_customers(spark, sf_dir, work: list[tuple[str, int, int]]):
    """Triples of every kind of ``work`` for all customers, a batch at a time: each multiplies a balance by a key on
    shares. The last batch is filled up with zeros, and nulls count as zeros: batches are of public size. Rates are
    those of making triples alone, over all batches."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        batch, run, size = int(part["batch"].iloc[0]), int(part["run"].iloc[0]), len(part)
        x, y = (np.pad(part[c].to_numpy(np.int64), (0, batch - size)) for c in ("c_bal", "c_custkey"))
        rows = [(k, e, b, *use_triples(k, e, x, y, seed_of(KINDS.index(k), e, b, run)), size) for k, e, b in work if b == batch]
        return pd.DataFrame(rows, columns=["kind", "ell", "batch", "seconds", "sent", "right", "used"])

    df = table(spark, sf_dir, "customer").df.select(*(F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in ("c_bal", "c_custkey")))
    tasks = min(1 << 14, max(len(work), df.count() >> 12))
    sizes = F.explode(F.array(*[F.lit(b).cast("long") for b in sorted({b for _, _, b in work})]))
    df = with_positions(df, [F.asc("c_custkey"), F.asc("c_bal")]).select("c_bal", "c_custkey", "__pos", sizes.alias("batch"))
    df = df.select("c_bal", "c_custkey", "batch", F.floor(F.col("__pos") / F.col("batch")).alias("run")).repartition(tasks, "batch", "run")
    ran = df.groupBy("batch", "run").applyInPandas(one, "kind string, ell long, batch long, seconds double, sent long, right boolean, used long")
    made, took, sent = F.count("*") * F.col("batch"), F.sum("seconds"), F.sum("sent")
    return ran.groupBy("kind", "ell", "batch").agg(
        (made / took).alias("per_second"), (made * F.col("ell") / took / 1e6).alias("mbps"), (sent / made).alias("bits"), (sent / made / F.col("ell")).alias("bits_per_bit"),
        F.sum("used").alias("products"), F.min("right").alias("right"),
    )


@study()
def meter_triples(spark, sf_dir):
    """By generator, width and batch: triples a second, megabits of triples a second, bits sent per triple and per bit (C8, M7),
    made for all customers and used."""
    return _triples_for_customers(spark, sf_dir, BATCHES)
