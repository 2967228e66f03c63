"""Gates, sorts, scans, permutations, triples and cost measures as queries; shared results are opened."""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..operators.group_scan import group_scan
from ..plans import meter as M
from ..share import circuits as C
from ..share import sorting as S
from ..share.blocks import on_shares, seed_of, sort_groups
from ..share.protocols import PROTOCOLS, U
from .tables import PRELUDE, table

QUERIES = {}
SQL = {}
ROOT = __file__.rsplit("/sealed_frames/", 1)[0]


def _importable(spark) -> None:
    env = spark.sparkContext.environment
    if ROOT not in (env.get("PYTHONPATH") or "").split(":"):
        env["PYTHONPATH"] = ":".join(x for x in (ROOT, env.get("PYTHONPATH")) if x)


#: Rows of a group that is one shared vector or table.
GROUP_ROWS = 1 << 13


def buckets(*frames) -> int:
    """Groups that tables are dealt to, so that one holds about ``GROUP_ROWS`` rows."""
    return max(1, -(-sum(df.count() for df in frames) // GROUP_ROWS))


def bucket(key: str, n: int):
    return F.pmod(F.xxhash64(key), F.lit(n))


def register(name: str, run, sql: str | None, prelude: bool = True) -> None:
    def guarded(spark, sf_dir):
        _importable(spark)
        return run(spark, sf_dir)

    QUERIES[name] = guarded
    if sql:
        SQL[name] = (PRELUDE if prelude else "") + sql


def _lines(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").df.select("l_orderkey", "l_suppkey", "price", "qty", "disc")


# -- gates -------------------------------------------------------------------------------------------

_GATES = {
    "compare": (["price", "limit"], lambda p, s: C.greater(p, s[0], s[1], 64, True), True, "CAST(price > limit_ AS BIGINT)"),
    "equal": (["qty", "disc"], lambda p, s: C.equal(p, s[0], s[1]), True, "CAST(qty = disc AS BIGINT)"),
    "add": (["price", "qty"], lambda p, s: C.add(p, s[0], s[1]), True, "price + qty"),
    "add_ripple": (["price", "qty"], lambda p, s: C.add(p, s[0], s[1], kind="ripple"), True, "price + qty"),
    "multiply": (["price", "disc"], lambda p, s: p.mul(s[0], s[1]), False, "price * disc"),
    "divide": (["price", "qty"], lambda p, s: C.divide(p, s[0], s[1], 32), True, "price // qty"),
    "divide_public": (["price"], lambda p, s: C.divide_public(p, s[0], 7), True, "price // 7"),
    "mux": (["price", "limit"], lambda p, s: C.choose(p, C.greater(p, s[0], s[1], 64, True), s[0], s[1]), True, "least(price, limit_)"),
    "or": (["price", "qty"], lambda p, s: p.or_(s[0], s[1]), True, "price | qty"),
    "to_boolean": (["price"], lambda p, s: C.to_boolean(p, s[0]), False, "price"),
    "to_arithmetic": (["price"], lambda p, s: C.to_arithmetic(p, s[0], 32), True, "price"),
}


def _gate(kind: str, protocol: str) -> None:
    columns, circuit, boolean, sql = _GATES[kind]

    def run(spark, sf_dir):
        df = _lines(spark, sf_dir).withColumn("limit", F.lit(2_500_000).cast("long") - F.col("qty") * 1000)
        opened = on_shares(df, columns, "y", circuit, protocol, boolean, keep=["l_suppkey"])
        return opened.groupBy("l_suppkey").agg(F.sum("y").alias("total"), F.max("y").alias("top"), F.count("*").alias("n"))

    register(
        f"gate_{kind}_{protocol}", run,
        f", X AS (SELECT *, 2500000 - qty * 1000 AS limit_ FROM L) SELECT l_suppkey, CAST(sum({sql}) AS BIGINT) AS total, CAST(max({sql}) AS BIGINT) AS top, count(*) AS n FROM X GROUP BY ALL",
    )


for _p in ("2p", "3p", "4p"):
    for _k in ("compare", "equal", "add", "multiply", "mux"):
        _gate(_k, _p)
for _k in ("add_ripple", "divide", "divide_public", "or", "to_boolean", "to_arithmetic"):
    _gate(_k, "3p")


# -- sorts: each supplier's prices as one shared vector -------------------------------------------------


def _network(kind):
    def sort(p, keys):
        size, bits = M.padded(max(len(keys), 1)), key_width(keys)
        filled = np.concatenate([keys, np.full(size - len(keys), 1 << bits)])
        return p.open(S.network_sort(p, p.share(filled, True), kind, bits + 1)[0]).astype(np.int64)[: len(keys)]

    return sort


def key_width(keys) -> int:
    """Bits of the keys: public, as a column's width is."""
    return max(1, int(keys.max(initial=0)).bit_length())


def _by_bits(variant):
    return lambda p, k: p.open(S.bitwise_sort(p, p.share(k, True), key_width(k), variant=variant)).astype(np.int64)


def _by_vector(order):
    return lambda p, k: p.open(S.sort_vector(p, p.share(k, True), order, "pivot", key_width(k))[0]).astype(np.int64)


def _by_rank(p, keys):
    """The owner hands in dense ranks of lg n bits in place of 64-bit keys, and keeps the list of keys."""
    values, ranks = np.unique(keys, return_inverse=True)
    return values[p.open(S.bitwise_sort(p, p.share(ranks, True), max(1, M.lg(len(keys))))).astype(np.int64)]


_SORTS = {
    "pivot": _by_vector("asc"), "bitwise": _by_bits("hybrid"), "eager": _by_bits("eager"), "composed": _by_bits("composed"), "bitonic": _network("bitonic"), "pairwise": _network("pairwise"),
    "odd_even": _network("odd_even"), "desc": _by_vector("desc"), "dense_rank": _by_rank,
    "wide": lambda p, k: p.open(S.bitwise_sort(p, p.share(k, True), 64)).astype(np.int64),
}
for _name, _sort in _SORTS.items():
    register(
        f"sort_{_name}", lambda spark, sf_dir, s=_sort: sort_groups(_lines(spark, sf_dir), "l_suppkey", "price", s),
        f"SELECT l_suppkey, row_number() OVER (PARTITION BY l_suppkey ORDER BY price{' DESC' * (_name == 'desc')}) - 1 AS place, price FROM L",
    )


def _by_suppliers(run, columns: tuple[str, ...]):
    """Lines in buckets of suppliers, who are public: ``run(p, ranks, width of the ranks, part)`` sorts a bucket as one
    shared vector, by the supplier's rank in the bucket first; (ranks, columns) opened, and places within suppliers."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        suppliers, ranks = np.unique(part["l_suppkey"].to_numpy(np.int64), return_inverse=True)
        p = PROTOCOLS["3p"](seed_of(int(part["b"].iloc[0]), len(part)))
        ranks, got = run(p, ranks.astype(np.int64), key_width(ranks), part)
        place = np.arange(len(part)) - np.searchsorted(ranks, ranks)
        return pd.DataFrame({"l_suppkey": suppliers[ranks], "place": place, **got})

    def query(spark, sf_dir):
        df = _lines(spark, sf_dir).select("l_suppkey", *columns)
        n = buckets(df)
        return df.withColumn("b", bucket("l_suppkey", n)).repartition(min(n, 2048), "b").groupBy("b").applyInPandas(one, "l_suppkey long, place long, " + ", ".join(f"{c} long" for c in columns))

    return query


def _sort_table_run(p, ranks, width, part):
    keys = {"supplier": ranks} | {c: part[c].to_numpy(np.int64) for c in ("disc", "qty", "price")}
    bits = {c: key_width(x) for c, x in keys.items()} | {"supplier": width}
    out = S.sort_table(p, {c: p.share(x, True) for c, x in keys.items()}, [("supplier", "asc"), ("disc", "desc"), ("qty", "asc"), ("price", "asc")], bits=bits)
    got = {c: p.open(s).astype(np.int64) for c, s in out.items()}
    return got.pop("supplier"), got


def _sort_eager_run(p, ranks, width, part):
    price = part["price"].to_numpy(np.int64)
    low = key_width(price)
    out = p.open(S.bitwise_sort(p, p.share(ranks << low | price, True), low + width, variant="eager", held=low + width)).astype(np.int64)
    return out >> low, {"price": out & (1 << low) - 1}


_sort_table = _by_suppliers(_sort_table_run, ("disc", "qty", "price"))


register("sort_eager", _by_suppliers(_sort_eager_run, ("price",)), SQL["sort_eager"], False)
register("sort_table", _sort_table, "SELECT l_suppkey, row_number() OVER (PARTITION BY l_suppkey ORDER BY disc DESC, qty, price) - 1 AS place, disc, qty, price FROM L")


def _sort_native(spark, sf_dir):
    """Whole-table order and dense positions without a window over the table."""
    from ..core.position import with_positions

    df = table(spark, sf_dir, "orders").df.select("o_orderkey", "o_total")
    return with_positions(df, [F.desc("o_total"), F.asc("o_orderkey")], 8).select("o_orderkey", F.col("__pos").alias("place"))


register("sort_positions", _sort_native, "SELECT o_orderkey, row_number() OVER (ORDER BY o_total DESC, o_orderkey) - 1 AS place FROM O")


def _running(spark, sf_dir):
    from ..core.position import running_sum, with_positions

    df = table(spark, sf_dir, "orders").df.select("o_orderkey", "o_total")
    return running_sum(with_positions(df, [F.asc("o_orderkey")], 8), "o_total", "upto", block_rows=1024).select("o_orderkey", "upto")


register("scan_running_sum", _running, "SELECT o_orderkey, CAST(sum(o_total) OVER (ORDER BY o_orderkey) AS BIGINT) AS upto FROM O")


# -- scans ---------------------------------------------------------------------------------------------


def _scan(variant: str):
    def run(spark, sf_dir):
        df = table(spark, sf_dir, "orders").df.select("o_custkey", "o_orderkey", "o_total")
        out = group_scan(df, ["o_custkey"], ["o_orderkey"], [("sum", "o_total", "s"), ("min", "o_total", "lo"), ("max", "o_total", "hi"), ("copy", "o_orderkey", "first")], variant=variant)
        return out.select("o_orderkey", "s", "lo", "hi", "first")

    return run


for _v in ("doubling", "work_efficient", "segmented"):
    register(
        f"scan_{_v}", _scan(_v),
        "SELECT o_orderkey, CAST(sum(o_total) OVER w AS BIGINT) AS s, min(o_total) OVER w AS lo, max(o_total) OVER w AS hi, first(o_orderkey) OVER w AS first FROM O WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)",
    )
register(
    "scan_reverse",
    lambda spark, sf_dir: group_scan(table(spark, sf_dir, "orders").df.select("o_custkey", "o_orderkey", "o_total"), ["o_custkey"], ["o_orderkey"], [("sum", "o_total", "s")], variant="doubling", reverse=True).select("o_orderkey", "s"),
    "SELECT o_orderkey, CAST(sum(o_total) OVER (PARTITION BY o_custkey ORDER BY o_orderkey DESC) AS BIGINT) AS s FROM O",
)


def _scan_shared(spark, sf_dir):
    def run(part: pd.DataFrame) -> pd.DataFrame:
        p = PROTOCOLS["2p"](seed_of(part["b"].iloc[0], len(part)))
        part = part.sort_values(["o_custkey", "o_orderkey"])
        out = S.group_scan(p, p.share(part["o_custkey"].to_numpy(np.int64), True), p.share(part["o_total"].to_numpy(np.int64), False))
        return pd.DataFrame({"o_orderkey": part["o_orderkey"], "s": p.open(out).view(np.int64)})

    df = table(spark, sf_dir, "orders").df.select("o_custkey", "o_orderkey", "o_total")
    return df.withColumn("b", bucket("o_custkey", buckets(df))).groupBy("b").applyInPandas(run, "o_orderkey long, s long")


register("scan_shared", _scan_shared, "SELECT o_orderkey, CAST(sum(o_total) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS BIGINT) AS s FROM O")


def _in_place(spark, sf_dir):
    from ..operators.aggregate import aggregate_in_place

    f = table(spark, sf_dir, "orders").project("o_custkey", "o_orderkey", "o_total")
    return aggregate_in_place(f, ["o_custkey"], {"s": ("sum", "o_total"), "n": ("count", "*")}, ["o_orderkey"]).reveal().select("o_custkey", "s", "n")


register("aggregate_in_place", _in_place, "SELECT o_custkey, CAST(sum(o_total) AS BIGINT) AS s, count(*) AS n FROM O GROUP BY ALL")


def _mark_first(spark, sf_dir):
    from ..operators.aggregate import mark_first

    return mark_first(table(spark, sf_dir, "lineitem").project("l_suppkey", "l_returnflag"), ["l_suppkey", "l_returnflag"]).reveal()


register("distinct_sorted", _mark_first, "SELECT DISTINCT l_suppkey, l_returnflag FROM L")


def _join_shared(how: str, protocol: str, aggs: dict | None = None, trim_rows: bool = False):
    """Orders and lines in buckets of the key; each bucket is joined (and aggregated) on shares, masked and opened."""
    from ..share.table import SharedTable

    def one(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        p = PROTOCOLS[protocol](seed_of((left if len(left) else right)["b"].iloc[0], len(left), len(right)))
        a = SharedTable.of(p, {"k": left["o_orderkey"].to_numpy(np.int64), "custkey": left["o_custkey"].to_numpy(np.int64)}, ok=left["ok"].to_numpy(np.int64))
        b = SharedTable.of(p, {"k": right["l_orderkey"].to_numpy(np.int64), "qty": right["qty"].to_numpy(np.int64)} | ({"w": right["qty"].to_numpy(np.int64)} if aggs else {}), ("w",), right["ok"].to_numpy(np.int64))
        got = a.join(b, "k", how, aggs, trim_rows=trim_rows).reveal()
        wanted = ["k", "custkey", *(aggs or ["qty"])]
        return pd.DataFrame({c: got.get(c, np.zeros(len(got["k"]), np.int64)) for c in wanted})

    def run(spark, sf_dir):
        left = table(spark, sf_dir, "orders").df.select("o_orderkey", "o_custkey", (F.col("o_orderstatus") != "P").cast("long").alias("ok"))
        right = table(spark, sf_dir, "lineitem").df.select("l_orderkey", "qty", (F.col("l_returnflag") == "R").cast("long").alias("ok"))
        n = buckets(left, right)
        deal = lambda df, k: df.withColumn("b", bucket(k, n)).groupBy("b")
        wanted = ["k", "custkey", *(aggs or ["qty"])]
        out = deal(left, "o_orderkey").cogroup(deal(right, "l_orderkey")).applyInPandas(one, ", ".join(f"{c} long" for c in wanted))
        if aggs:
            return out.withColumnRenamed("k", "o_orderkey")
        return out.groupBy("custkey").agg(F.count("*").alias("n"), F.sum("qty").alias("q"), F.sum("k").alias("ks"))

    return run


_SHARED_SIDES = "(SELECT * FROM O WHERE o_orderstatus <> 'P') a {} JOIN (SELECT * FROM L WHERE l_returnflag = 'R') b ON o_orderkey = l_orderkey"
for _how in ("inner", "left", "right", "full"):
    register(
        f"join_{_how}_share", _join_shared(_how, {"inner": "2p", "left": "3p", "right": "4p", "full": "3p"}[_how]),
        f"SELECT coalesce(o_custkey, 0) AS custkey, count(*) AS n, CAST(sum(coalesce(qty, 0)) AS BIGINT) AS q, CAST(sum(coalesce(o_orderkey, l_orderkey)) AS BIGINT) AS ks FROM {_SHARED_SIDES.format(_how.upper())} GROUP BY ALL",
    )
for _how in ("semi", "anti"):
    register(
        f"join_{_how}_share", _join_shared(_how, "3p"),
        f"SELECT o_custkey AS custkey, count(*) AS n, CAST(0 AS BIGINT) AS q, CAST(sum(o_orderkey) AS BIGINT) AS ks FROM O WHERE o_orderstatus <> 'P' AND o_orderkey {'NOT ' * (_how == 'anti')}IN (SELECT l_orderkey FROM L WHERE l_returnflag = 'R') GROUP BY ALL",
    )


_AGGS = {"s": ("sum", "w"), "n": ("count", "w"), "lo": ("min", "qty"), "hi": ("max", "qty")}
register(
    "join_inner_aggregate_share", _join_shared("inner", "3p", _AGGS, True),
    f"SELECT o_orderkey, o_custkey AS custkey, CAST(sum(qty) AS BIGINT) AS s, count(*) AS n, CAST(min(qty) AS BIGINT) AS lo, CAST(max(qty) AS BIGINT) AS hi FROM {_SHARED_SIDES.format('INNER')} GROUP BY ALL",
)
register(
    "join_left_aggregate_share", _join_shared("left", "2p", {"s": ("sum", "w"), "n": ("count", "w")}, True),
    f"SELECT o_orderkey, o_custkey AS custkey, CAST(coalesce(sum(qty), 0) AS BIGINT) AS s, count(l_orderkey) AS n FROM {_SHARED_SIDES.format('LEFT')} GROUP BY ALL",
)
register(
    "join_inner_trimmed_share", _join_shared("inner", "4p", trim_rows=True),
    f"SELECT o_custkey AS custkey, count(*) AS n, CAST(sum(qty) AS BIGINT) AS q, CAST(sum(o_orderkey) AS BIGINT) AS ks FROM {_SHARED_SIDES.format('INNER')} GROUP BY ALL",
)


def _group_shared(spark, sf_dir):
    """Grouping on shares: one carrier row per key, all rows stay until the end."""
    from ..share.table import SharedTable

    def run(part: pd.DataFrame) -> pd.DataFrame:
        p = PROTOCOLS["3p"](seed_of(part["b"].iloc[0], len(part)))
        t = SharedTable.of(p, {"k": part["o_custkey"].to_numpy(np.int64), "v": part["o_total"].to_numpy(np.int64), "w": part["o_total"].to_numpy(np.int64)}, ("w",), part["ok"].to_numpy(np.int64))
        got = t.group("k", {"s": ("sum", "w"), "n": ("count", None), "lo": ("min", "v"), "hi": ("max", "v")}, value_bits=40).reveal()
        return pd.DataFrame({"o_custkey": got["k"], **{c: got[c] for c in ("s", "n", "lo", "hi")}})

    df = table(spark, sf_dir, "orders").df.select("o_custkey", "o_total", (F.col("o_orderstatus") != "P").cast("long").alias("ok"))
    return df.withColumn("b", bucket("o_custkey", buckets(df))).groupBy("b").applyInPandas(run, "o_custkey long, s long, n long, lo long, hi long")


register("group_share", _group_shared, "SELECT o_custkey, CAST(sum(o_total) AS BIGINT) AS s, count(*) AS n, min(o_total) AS lo, max(o_total) AS hi FROM O WHERE o_orderstatus <> 'P' GROUP BY ALL")


def _radix(spark, sf_dir):
    from ..core.position import with_positions
    from ..operators.radix import radix_sort

    df = table(spark, sf_dir, "orders").df.select("o_orderkey", F.col("o_custkey").alias("k"))
    out = radix_sort(with_positions(df, [F.asc("o_orderkey")], 8), "k", digit_bits=9, block_rows=1 << 11)
    return out.select("o_orderkey", F.col("__pos").alias("place"))


register("sort_radix_digits", _radix, "SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderkey) - 1 AS place FROM O")


def _trimmed(spark, sf_dir):
    """The padded tier: public sizes at every step, the result cut to the right side's size."""
    from ..core.frame import seal

    o, lines = table(spark, sf_dir, "orders").df.drop("__ok"), table(spark, sf_dir, "lineitem").df.drop("__ok")
    left = seal(o.select("o_orderkey", "o_orderpriority", "o_orderstatus"), [["o_orderkey"]], o.count(), "padded").filter("o_orderstatus = 'F'")
    right = seal(lines.select(F.col("l_orderkey").alias("o_orderkey"), "qty"), rows=lines.count(), tier="padded").filter("qty > 10")
    joined = left.join(right, "o_orderkey", copy=["o_orderpriority"], strategy="stacked", trim="always")
    return joined.aggregate(["o_orderpriority"], n=("count", "*"), q=("sum", "qty")).reveal()


register("join_padded_trimmed", _trimmed, "SELECT o_orderpriority, count(*) AS n, CAST(sum(qty) AS BIGINT) AS q FROM O JOIN L ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F' AND qty > 10 GROUP BY ALL")


# -- permutations ----------------------------------------------------------------------------------------


def _permutation(kind: str):
    def one(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("o_orderkey")
        p = PROTOCOLS["3p"](seed_of(part["b"].iloc[0], len(part)))
        x = p.share(part["o_total"].to_numpy(np.int64), False)
        n = len(part)
        if kind == "shuffle":  # shuffled, and shuffled back
            parts = S.sharded_permutation(p, n, 4)
            out = p.open(S.apply_sharded(p, S.invert_sharded(parts), S.apply_sharded(p, parts, x)))
        elif kind == "elementwise":
            dest = p.share(S.random_permutation(n, 6), False)
            moved = S.apply_elementwise(p, dest, x, 5)
            out = p.open(S.apply_elementwise(p, S.invert_elementwise(p, dest, 8), moved, 9))
        elif kind == "compose":  # two shared permutations, composed on shares and undone
            a, b = (p.share(S.random_permutation(n, i), False) for i in (1, 2))
            moved = S.apply_elementwise(p, b, S.apply_elementwise(p, a, x, 3), 4)
            out = p.open(S.apply_elementwise(p, S.invert_elementwise(p, S.compose_elementwise(p, a, b, 5), 6), moved, 7))
        elif kind == "convert":  # boolean destinations, converted, moved by and undone
            dest = S.convert_elementwise(p, p.share(S.random_permutation(n, 6), True), 2)
            back = S.invert_elementwise(p, S.convert_elementwise(p, dest, 3), 4)
            out = p.open(S.apply_elementwise(p, back, S.apply_elementwise(p, dest, x, 5), 6))
        else:
            correlation = S.permutation_correlation(n, 3)
            s, t = S.permute_with(correlation, p.open(x))
            out = S.apply(S.invert(correlation[0][0]), s + t)
        return pd.DataFrame({"o_orderkey": part["o_orderkey"], "total": out.view(np.int64)})

    def run(spark, sf_dir):
        df = table(spark, sf_dir, "orders").df.select("o_orderkey", "o_total")
        return df.withColumn("b", bucket("o_orderkey", buckets(df))).groupBy("b").applyInPandas(one, "o_orderkey long, total long")

    return run


for _k in ("shuffle", "elementwise", "compose", "convert", "correlation"):
    register(f"perm_{_k}", _permutation(_k), "SELECT o_orderkey, o_total AS total FROM O")
