"""Queries of earlier engines and two-owner variants, rebuilt on the given tables.

Times are microseconds since the epoch; values are hundredths.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..core.frame import OK, SealedFrame
from ..operators.aggregate import combine, partials
from ..operators.fused_join import aggregate_join, cartesian_join
from .tables import PRELUDE, revenue, table

QUERIES = {}
SQL = {}
#: The functions themselves, for cost frames.
FUNCTIONS = {}


def query(sql: str):
    def keep(fn):
        FUNCTIONS[fn.__name__] = fn
        QUERIES[fn.__name__] = lambda spark, sf_dir: fn(lambda name: table(spark, sf_dir, name)).reveal()
        SQL[fn.__name__] = PRELUDE + sql
        return fn

    return keep


@query("SELECT DISTINCT a.user_id FROM E a JOIN E b ON a.user_id = b.user_id WHERE a.event_type = 'error' AND a.val > 4000 AND b.event_type = 'purchase' AND b.ts >= a.ts")
def prior_first_example(t):
    """Users with a large error and a purchase at that time or later: the earliest error decides."""
    errors = t("events").filter("event_type = 'error' and val > 4000").aggregate(["user_id"], since=("min", "ts"))
    bought = t("events").filter("event_type = 'purchase'").project("user_id", "ts")
    return errors.join(bought, "user_id", extra="ts >= since").distinct("user_id")


@query("""SELECT DISTINCT user_id FROM (SELECT user_id, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM E WHERE event_type = 'error')
  WHERE gap BETWEEN 86400000000 AND 2 * 86400000000""")
def prior_recurrence(t):
    """Users with two successive errors one to two days apart."""
    f = t("events").filter("event_type = 'error'").with_col("us", F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast(ts as timestamp_ntz))"))
    # neighbours among valid rows only, for tiers that keep the others
    gap = F.col("us") - F.lag("us").over(Window.partitionBy(OK, "user_id").orderBy("ts", "event_id"))
    return f.with_col("gap", gap).filter(F.col("gap").between(86_400_000_000, 2 * 86_400_000_000)).distinct("user_id")


@query("SELECT user_id, props, count(*) AS n FROM E GROUP BY ALL HAVING count(*) > 1")
def prior_reuse(t):
    """Pairs of user and properties that occur more than once."""
    return t("events").aggregate(["user_id", "props"], n=("count", "*")).filter("n > 1")


@query("SELECT user_id, CAST(max(val) - min(val) AS BIGINT) AS spread FROM E WHERE event_type = 'view' GROUP BY ALL HAVING max(val) - min(val) > 15000")
def prior_spread(t):
    f = t("events").filter("event_type = 'view'").aggregate(["user_id"], lo=("min", "val"), hi=("max", "val"))
    return f.with_col("spread", F.col("hi") - F.col("lo")).filter("spread > 15000").project("user_id", "spread")


@query("SELECT event_type, count(*) AS n FROM E WHERE user_id IN (SELECT c_custkey FROM C WHERE c_mktsegment = 'BUILDING') GROUP BY ALL ORDER BY n DESC, event_type LIMIT 10")
def prior_cohort(t):
    cohort = t("customer").filter("c_mktsegment = 'BUILDING'").project("c_custkey")
    f = t("events").project("user_id", "event_type").join(cohort, {"user_id": "c_custkey"}, "semi").aggregate(["event_type"], n=("count", "*"))
    return f.limit(10, "n desc", "event_type")


@query("SELECT event_type, count(*) AS n FROM E JOIN O ON user_id = o_custkey GROUP BY ALL")
def prior_count_dup(t):
    """A count over a join with duplicates on both sides, by multiplicities (L701)."""
    return aggregate_join(t("orders").project("o_custkey"), t("events").project("user_id", "event_type"), {"o_custkey": "user_id"}, ["event_type"], {}, count="n")


@query("SELECT CAST(sum((rev * 1000 // total) * (rev * 1000 // total)) AS BIGINT) AS concentration FROM (SELECT l_suppkey, sum(rev) AS rev, sum(sum(rev)) OVER () AS total FROM L GROUP BY l_suppkey)")
def prior_concentration(t):
    """Sum of squared market shares, in per mille."""
    sums = t("lineitem").with_col("rev", revenue()).aggregate(["l_suppkey"], r=("sum", "rev"))
    shares = sums.attach_scalar(sums.aggregate([], total=("sum", "r"))).with_col("share", F.expr("r * 1000 div total"))
    return shares.with_col("square", F.col("share") * F.col("share")).aggregate([], concentration=("sum", "square"))


@query("SELECT p_type, CAST(sum(price * (c_custkey % 10 + 1)) AS BIGINT) AS cost FROM C JOIN O ON c_custkey = o_custkey JOIN L ON o_orderkey = l_orderkey JOIN P ON l_partkey = p_partkey GROUP BY ALL")
def prior_class_cost(t):
    rates = t("customer").with_col("rate", F.col("c_custkey") % 10 + 1).project("c_custkey", "rate")
    orders = rates.join(t("orders").project("o_orderkey", "o_custkey"), {"c_custkey": "o_custkey"}).project("o_orderkey", "rate")
    lines = orders.join(t("lineitem").project("l_orderkey", "l_partkey", "price"), {"o_orderkey": "l_orderkey"})
    # the rate-weighted cost is summed by part before parts are joined
    sums = lines.with_col("w", F.col("price") * F.col("rate")).aggregate(["l_partkey"], w=("sum", "w"))
    return t("part").project("p_partkey", "p_type").join(sums, {"p_partkey": "l_partkey"}).aggregate(["p_type"], cost=("sum", "w"))


@query("SELECT count(*) AS n FROM C JOIN E a ON c_custkey = a.user_id JOIN E b ON c_custkey = b.user_id WHERE a.event_type = 'error' AND b.event_type = 'purchase'")
def prior_cascade(t):
    """A three-way count by the product of multiplicities; no joined row is formed."""
    a = t("events").filter("event_type = 'error'").aggregate(["user_id"], x=("count", "*"))
    b = t("events").filter("event_type = 'purchase'").aggregate(["user_id"], y=("count", "*"))
    met = t("customer").project("c_custkey").join(a.join(b, "user_id"), {"c_custkey": "user_id"})
    return met.with_col("xy", F.col("x") * F.col("y")).aggregate([], n=("sum", "xy")).with_col("n", F.coalesce("n", F.lit(0).cast("long")))


# -- two owners ----------------------------------------------------------------------------------


def owners(f: SealedFrame, key: str = "l_orderkey") -> tuple[SealedFrame, SealedFrame]:
    """The table as two owners hold it, split by parity of a key."""
    return f.filter(F.col(key) % 2 == 0), f.filter(F.col(key) % 2 == 1)


@query("SELECT CAST(sum(qty) AS BIGINT) AS s, count(*) AS n FROM L WHERE disc >= 5")
def owner_v1(t):
    """Filtered global sums: each owner aggregates, the partials are combined."""
    outputs = {"s": ("sum", "qty"), "n": ("count", "*")}
    a, b = (partials(o.filter("disc >= 5"), [], outputs) for o in owners(t("lineitem")))
    return combine(a.concat(b), [], {"s": "sum", "n": "count"})


@query("SELECT l_returnflag, CAST(sum(price) AS BIGINT) AS s, CAST(min(price) AS BIGINT) AS lo, CAST(max(price) AS BIGINT) AS hi, CAST(sum(qty) // count(*) AS BIGINT) AS mean FROM L WHERE qty > 10 GROUP BY ALL")
def owner_v2(t):
    outputs = {"s": ("sum", "price"), "lo": ("min", "price"), "hi": ("max", "price"), "mean": ("avg", "qty")}
    a, b = (partials(o.filter("qty > 10"), ["l_returnflag"], outputs) for o in owners(t("lineitem")))
    return combine(a.concat(b), ["l_returnflag"], {"s": "sum", "lo": "min", "hi": "max", "mean": "avg"})


@query("SELECT o_orderpriority, CAST(sum(qty) AS BIGINT) AS s FROM O JOIN L ON o_orderkey = l_orderkey WHERE l_linestatus = 'F' GROUP BY ALL")
def owner_v3(t):
    """One owner has orders, the other lines; lines are aggregated by order before they meet."""
    lines = t("lineitem").filter("l_linestatus = 'F'").aggregate(["l_orderkey"], q=("sum", "qty"))
    return lines.join(t("orders").project("o_orderkey", "o_orderpriority"), {"l_orderkey": "o_orderkey"}).aggregate(["o_orderpriority"], s=("sum", "q"))


@query("SELECT CAST(1000 * sum(CASE WHEN p_type = 'PROMO' THEN rev ELSE 0 END) // sum(rev) AS BIGINT) AS promo FROM L JOIN P ON l_partkey = p_partkey WHERE disc = 4")
def owner_v4(t):
    lines = t("lineitem").filter("disc = 4").with_col("rev", revenue()).aggregate(["l_partkey"], r=("sum", "rev"))
    met = t("part").project("p_partkey", "p_type").join(lines, {"p_partkey": "l_partkey"}).with_col("mine", F.when(F.col("p_type") == "PROMO", F.col("r")).otherwise(F.lit(0)))
    return met.aggregate([], a=("sum", "mine"), b=("sum", "r")).with_col("promo", F.expr("a * 1000 div b")).project("promo")


@query("SELECT o_custkey, CAST(sum(rev) AS BIGINT) AS revenue FROM O JOIN L ON o_orderkey = l_orderkey WHERE l_returnflag = 'R' GROUP BY ALL")
def owner_v5(t):
    """A join, then a grouping on another key."""
    lines = t("lineitem").filter("l_returnflag = 'R'").with_col("rev", revenue()).aggregate(["l_orderkey"], r=("sum", "rev"))
    return lines.join(t("orders").project("o_orderkey", "o_custkey"), {"l_orderkey": "o_orderkey"}).aggregate(["o_custkey"], revenue=("sum", "r"))


# -- join types, both passes -----------------------------------------------------------------------


def _join_query(how: str, strategy: str):
    def run(t):
        left = t("orders").filter("o_orderstatus = 'F'").project("o_orderkey", "o_orderpriority")
        right = t("lineitem").filter("l_returnflag = 'R'").project("l_orderkey", "qty")
        if how in ("semi", "anti"):
            f = left.join(right, {"o_orderkey": "l_orderkey"}, how, strategy=strategy)
            return f.aggregate(["o_orderpriority"], n=("count", "*"), k=("sum", "o_orderkey"))
        f = left.join(right, {"o_orderkey": "l_orderkey"}, how, strategy=strategy)
        return f.aggregate(["o_orderpriority"], n=("count", "*"), k=("sum", "o_orderkey"), q=("sum", "qty"))

    kind = {"inner": "JOIN", "left": "LEFT JOIN", "right": "RIGHT JOIN", "full": "FULL JOIN"}.get(how)
    a, b = "(SELECT * FROM O WHERE o_orderstatus = 'F')", "(SELECT * FROM L WHERE l_returnflag = 'R')"
    if kind:
        sql = f"SELECT o_orderpriority, count(*) AS n, CAST(sum(coalesce(o_orderkey, l_orderkey)) AS BIGINT) AS k, CAST(sum(qty) AS BIGINT) AS q FROM {a} {kind} {b} ON o_orderkey = l_orderkey GROUP BY ALL"
    else:
        sql = f"SELECT o_orderpriority, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS k FROM {a} WHERE o_orderkey {'NOT ' * (how == 'anti')}IN (SELECT l_orderkey FROM {b}) GROUP BY ALL"
    run.__name__ = f"join_{how}_{strategy}"
    query(sql)(run)


for _how in ("inner", "left", "right", "full", "semi", "anti"):
    for _strategy in ("stacked", "native"):
        _join_query(_how, _strategy)


@query("SELECT o_orderpriority, count(*) AS n FROM O JOIN L ON o_orderkey = l_orderkey WHERE ship >= o_date GROUP BY ALL")
def join_theta(t):
    """An equality and an inequality (L684)."""
    f = t("orders").project("o_orderkey", "o_orderpriority", "o_date").join(t("lineitem").project("l_orderkey", "ship"), {"o_orderkey": "l_orderkey"}, extra="ship >= o_date")
    return f.aggregate(["o_orderpriority"], n=("count", "*"))


@query("SELECT l_orderkey AS o_orderkey, CAST(sum(rev) AS BIGINT) AS s, count(*) AS n, CAST(max(qty) AS BIGINT) AS hi FROM O JOIN L ON o_orderkey = l_orderkey WHERE o_orderstatus = 'P' GROUP BY ALL")
def join_fused_aggregate(t):
    """Join and aggregation on one key in one clustered pass: one exchange (L594, L687)."""
    lines = t("lineitem").with_col("rev", revenue()).project("l_orderkey", "rev", "qty")
    return t("orders").filter("o_orderstatus = 'P'").project("o_orderkey").join(
        lines, {"o_orderkey": "l_orderkey"}, strategy="stacked", aggs={"s": ("sum", "rev"), "n": ("count", "*"), "hi": ("max", "qty")}
    )


@query("SELECT event_type, CAST(sum(val) AS BIGINT) AS v, CAST(sum(o_total) AS BIGINT) AS o, count(*) AS n FROM E JOIN O ON user_id = o_custkey GROUP BY ALL")
def join_m2m_sums(t):
    """Sums of both sides over a many-to-many join (L697-701)."""
    return aggregate_join(
        t("orders").project("o_custkey", "o_total"), t("events").project("user_id", "event_type", "val"), {"o_custkey": "user_id"}, ["event_type"], {"v": "val"}, {"o": "o_total"}, count="n"
    )


@query("SELECT count(*) AS n FROM N a JOIN N b ON a.n_regionkey = b.n_regionkey JOIN N c ON b.n_nationkey % 5 = c.n_nationkey % 5 AND c.n_regionkey = (a.n_regionkey + 1) % 5")
def join_cyclic_fallback(t):
    """A cyclic condition: the quadratic fallback, refused beyond a public size."""
    n = lambda p: t("nation").rename(**{f"{p}_k": "n_nationkey", f"{p}_r": "n_regionkey"}).project(f"{p}_k", f"{p}_r")
    ab = n("a").join(n("b").rename(a_r="b_r"), "a_r", strategy="native")
    f = cartesian_join(ab, n("c"), (F.col("b_k") % 5 == F.col("c_k") % 5) & (F.col("c_r") == (F.col("a_r") + 1) % 5))
    return f.aggregate([], n=("count", "*"))


@query("SELECT c_mktsegment, CAST(sum(val) AS BIGINT) AS v, CAST(sum(qty) AS BIGINT) AS q, CAST(sum(c_bal) AS BIGINT) AS b, count(*) AS n, CAST(min(val) AS BIGINT) AS lo, CAST(max(qty) AS BIGINT) AS hi, CAST(sum(qty) // count(*) AS BIGINT) AS mean FROM C JOIN E ON c_custkey = user_id JOIN O ON c_custkey = o_custkey JOIN L ON o_orderkey = l_orderkey GROUP BY ALL")
def join_chain_four_way(t):
    """Four tables, duplicates everywhere: sums of three of them and a count, by multiplicities."""
    from ..plans.chain import chain_aggregate

    tables = {
        "c": t("customer").project("c_custkey", "c_mktsegment", "c_bal"), "e": t("events").project("user_id", "val"), "o": t("orders").project("o_orderkey", "o_custkey"), "l": t("lineitem").project("l_orderkey", "qty"),
    }
    joins = [(("c", "c_custkey"), ("e", "user_id")), (("c", "c_custkey"), ("o", "o_custkey")), (("o", "o_orderkey"), ("l", "l_orderkey"))]
    return chain_aggregate(tables, joins, "c", ["c_mktsegment"], {"v": ("e", "val"), "q": ("l", "qty"), "b": ("c", "c_bal")}, "n", {"lo": ("min", "e", "val"), "hi": ("max", "l", "qty")}, {"mean": ("l", "qty")})


def _planned(kind: str):
    """Queries whose plan follows from their class."""
    from ..plans.choose import join_aggregate

    def run(t):
        c, o = t("customer").project("c_custkey", "c_mktsegment"), t("orders").project("o_orderkey", "o_custkey", "o_total")
        if kind == "one_to_many":
            tables = {"l": t("lineitem").project("l_orderkey", "qty"), "o": o, "c": c}
            joins = [(("c", "c_custkey"), ("o", "o_custkey")), (("o", "o_orderkey"), ("l", "l_orderkey"))]
            out, found = join_aggregate(tables, joins, "c", ["c_mktsegment"], {"q": ("l", "qty"), "v": ("o", "o_total")}, "n")
        elif kind == "early_aggregation":
            tables = {"e": t("events").project("user_id", "event_type"), "o": o}
            out, found = join_aggregate(tables, [(("e", "user_id"), ("o", "o_custkey"))], "e", ["event_type"], {"v": ("o", "o_total")}, "n")
        else:
            n = t("nation").with_col("m", F.col("n_nationkey") % 5).project("n_nationkey", "n_regionkey", "m")
            tables = {"a": n, "b": n, "c": n}
            joins = [(("a", "n_regionkey"), ("b", "n_regionkey")), (("b", "m"), ("c", "m")), (("c", "n_regionkey"), ("a", "m"))]
            out, found = join_aggregate(tables, joins, "a", ["n_regionkey"], {"s": ("c", "n_nationkey")}, "n")
        if found != kind:
            raise AssertionError(found)
        return out

    run.__name__ = f"join_planned_{kind}"
    return run


query("SELECT c_mktsegment, CAST(sum(qty) AS BIGINT) AS q, CAST(sum(o_total) AS BIGINT) AS v, count(*) AS n FROM C JOIN O ON c_custkey = o_custkey JOIN L ON o_orderkey = l_orderkey GROUP BY ALL")(_planned("one_to_many"))
query("SELECT event_type, CAST(sum(o_total) AS BIGINT) AS v, count(*) AS n FROM E JOIN O ON user_id = o_custkey GROUP BY ALL")(_planned("early_aggregation"))
query("SELECT a.n_regionkey, CAST(sum(c.n_nationkey) AS BIGINT) AS s, count(*) AS n FROM N a JOIN N b ON a.n_regionkey = b.n_regionkey JOIN N c ON b.n_nationkey % 5 = c.n_nationkey % 5 AND c.n_regionkey = a.n_nationkey % 5 GROUP BY ALL")(_planned("cartesian"))
