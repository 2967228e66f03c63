"""Queries of the surrounding surface: joins, aggregates, windows, functions, sources, streams."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..core.session import new_path
from ..operators import relational as R
from ..operators.fused_join import broadcast_limit, plan_bytes
from .tables import PRELUDE, day_number, table

QUERIES = {}
SQL = {}


def rel(sql: str | None):
    def keep(fn):
        QUERIES[fn.__name__] = lambda spark, sf_dir: fn(lambda n: table(spark, sf_dir, n).df.drop("__ok"), spark, sf_dir)
        if sql:
            SQL[fn.__name__] = PRELUDE + sql
        return fn

    return keep


def raw(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")




def _events(t):
    return t("events").withColumn("us", F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast(ts as timestamp_ntz))"))


@rel("SELECT a.event_id, coalesce((SELECT max(epoch_us(b.ts)) FROM E b WHERE b.event_type = 'error' AND b.user_id = a.user_id AND b.ts <= a.ts), -1) AS error_us FROM E a WHERE a.event_type = 'purchase'")
def rel_asof_join(t, spark, sf_dir):
    e = _events(t)
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "us")
    right = e.where("event_type = 'error'").select("user_id", "us", F.col("us").alias("error_us"))
    return R.asof_join(left, right, ["user_id"], "us", ["error_us"]).select("event_id", F.coalesce("error_us", F.lit(-1).cast("long")).alias("error_us"))


@rel("SELECT count(*) AS n FROM E a JOIN E b ON a.event_type = 'error' AND b.event_type = 'purchase' AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000")
def rel_band_join(t, spark, sf_dir):
    e = _events(t)
    a = e.where("event_type = 'error'").select(F.col("us").alias("ua"))
    b = e.where("event_type = 'purchase'").select(F.col("us").alias("ub"))
    return R.band_join(a, b, "ua", "ub", 600_000_000).agg(F.count("*").alias("n"))


@rel("SELECT count(*) AS n FROM (SELECT date_diff('day', DATE '1970-01-01', o_date) AS a, date_diff('day', DATE '1970-01-01', o_date) + 3 AS b FROM O WHERE o_orderstatus = 'P') x JOIN (SELECT date_diff('day', DATE '1970-01-01', o_date) AS c, date_diff('day', DATE '1970-01-01', o_date) + 1 AS d FROM O WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'F') y ON a <= d AND c <= b")
def rel_overlap_join(t, spark, sf_dir):
    o = t("orders").withColumn("day", day_number("o_date"))
    x = o.where("o_orderstatus = 'P'").select(F.col("day").alias("a"), (F.col("day") + 3).alias("b"))
    y = o.where("o_orderstatus = 'F' and o_orderpriority = '1-URGENT'").select(F.col("day").alias("c"), (F.col("day") + 1).alias("d"))
    return R.overlap_join(x, y, ("a", "b"), ("c", "d"), 7).agg(F.count("*").alias("n"))


def _hinted(hint: str):
    def run(t, spark, sf_dir):
        n = t("nation").hint(hint)
        return t("customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.sum("c_bal").alias("bal"))

    run.__name__ = f"rel_join_{hint}"
    rel("SELECT n_name, count(*) AS n, CAST(sum(c_bal) AS BIGINT) AS bal FROM C JOIN N ON c_nationkey = n_nationkey GROUP BY ALL")(run)


for _h in ("broadcast", "merge", "shuffle_hash", "shuffle_replicate_nl"):
    _hinted(_h)


@rel("SELECT l_returnflag, l_linestatus, grouping(l_returnflag) * 2 + grouping(l_linestatus) AS g, CAST(sum(qty) AS BIGINT) AS s FROM L GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def rel_rollup(t, spark, sf_dir):
    return t("lineitem").rollup("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("g"), F.sum("qty").alias("s"))


@rel("SELECT l_returnflag, l_linestatus, CAST(sum(qty) AS BIGINT) AS s FROM L GROUP BY CUBE (l_returnflag, l_linestatus)")
def rel_cube(t, spark, sf_dir):
    return t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.sum("qty").alias("s"))


@rel("SELECT l_returnflag, l_linestatus, count(*) AS n FROM L GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def rel_grouping_sets(t, spark, sf_dir):
    return t("lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@rel("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'view') AS view FROM E GROUP BY ALL")
def rel_pivot(t, spark, sf_dir):
    kinds = ["click", "error", "view"]
    return t("events").groupBy("user_id").pivot("event_type", kinds).count().select("user_id", *[F.coalesce(k, F.lit(0).cast("long")).alias(k) for k in kinds])


@rel("SELECT o_orderkey, 'total' AS kind, o_total AS v FROM O UNION ALL SELECT o_orderkey, 'customer', o_custkey FROM O")
def rel_unpivot(t, spark, sf_dir):
    o = t("orders").select("o_orderkey", F.col("o_total").alias("total"), F.col("o_custkey").alias("customer"))
    return o.unpivot("o_orderkey", ["total", "customer"], "kind", "v")


@rel("""SELECT o_orderkey, row_number() OVER w AS a, rank() OVER v AS b, dense_rank() OVER v AS c, ntile(3) OVER w AS d, coalesce(lag(o_total) OVER w, -1) AS e, coalesce(lead(o_total, 2) OVER w, -1) AS f, coalesce(nth_value(o_total, 2) OVER x, -1) AS g
  FROM O WINDOW w AS (PARTITION BY o_custkey ORDER BY o_date, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority), x AS (PARTITION BY o_custkey ORDER BY o_date, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def rel_ranking(t, spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_date", "o_orderkey")
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    x = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    big = lambda c: c.cast("long")
    none = lambda c: F.coalesce(c, F.lit(-1).cast("long"))
    return t("orders").select(
        "o_orderkey", big(F.row_number().over(w)).alias("a"), big(F.rank().over(v)).alias("b"), big(F.dense_rank().over(v)).alias("c"), big(F.ntile(3).over(w)).alias("d"),
        none(F.lag("o_total").over(w)).alias("e"), none(F.lead("o_total", 2).over(w)).alias("f"), none(F.nth_value("o_total", 2).over(x)).alias("g"),
    )


@rel("""SELECT event_id, CAST(sum(val) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS a,
  max(val) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS b,
  count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS c FROM E""")
def rel_frames(t, spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    r = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return _events(t).select("event_id", F.sum("val").over(w.rowsBetween(-2, 0)).alias("a"), F.max("val").over(w.rowsBetween(-1, 1)).alias("b"), F.count("*").over(r).alias("c"))


@rel("SELECT o_custkey, o_orderkey, o_total, rank FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_total DESC, o_orderkey) AS rank FROM O) WHERE rank <= 2")
def rel_top_k_per_group(t, spark, sf_dir):
    return R.top_k_per(t("orders").select("o_custkey", "o_orderkey", "o_total"), ["o_custkey"], [F.desc("o_total"), F.asc("o_orderkey")], 2).withColumn("rank", F.col("rank").cast("long"))


@rel("SELECT o_orderkey FROM O ORDER BY o_total DESC, o_orderkey LIMIT 20 OFFSET 10")
def rel_offset(t, spark, sf_dir):
    return t("orders").orderBy(F.desc("o_total"), "o_orderkey").offset(10).limit(20).select("o_orderkey")


@rel("(SELECT c_custkey AS k FROM C EXCEPT SELECT user_id FROM E) UNION ALL (SELECT c_custkey FROM C INTERSECT SELECT user_id FROM E WHERE event_type = 'error')")
def rel_set_ops(t, spark, sf_dir):
    c, e = t("customer").select(F.col("c_custkey").alias("k")), t("events")
    return c.subtract(e.select("user_id")).unionByName(c.intersect(e.where("event_type = 'error'").select(F.col("user_id").alias("k"))))


@rel("SELECT o_custkey, arg_max(o_orderkey, o_total) AS top, arg_min(o_orderkey, o_total) AS low, len(list(DISTINCT o_orderpriority)) AS kinds, bool_or(o_orderstatus = 'F') AS any_f, bool_and(o_orderstatus = 'F') AS all_f, count(*) FILTER (o_orderstatus = 'P') AS p FROM O GROUP BY ALL")
def rel_object_aggregates(t, spark, sf_dir):
    return t("orders").groupBy("o_custkey").agg(
        F.max_by("o_orderkey", "o_total").alias("top"), F.min_by("o_orderkey", "o_total").alias("low"), F.size(F.collect_set("o_orderpriority")).cast("long").alias("kinds"),
        F.bool_or(F.col("o_orderstatus") == "F").alias("any_f"), F.bool_and(F.col("o_orderstatus") == "F").alias("all_f"), F.count_if(F.col("o_orderstatus") == "P").alias("p"),
    )


@rel("SELECT l_returnflag, count(DISTINCT l_suppkey) AS s, count(DISTINCT l_partkey) AS p FROM L GROUP BY ALL")
def rel_count_distinct(t, spark, sf_dir):
    return t("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("s"), F.countDistinct("l_partkey").alias("p"))


@rel(None)
def rel_approximate(t, spark, sf_dir):
    return t("lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("price", 0.5).alias("median"), F.stddev("qty").alias("sd"), F.corr("qty", "price").alias("r"))


@rel("""SELECT p_partkey, upper(substr(p_name, 1, 3)) AS a, length(p_name) AS b, replace(p_type, 'O', '0') AS c, split_part(p_name, ' ', 2) AS d, levenshtein(p_name, p_type) AS e,
  regexp_extract(p_brand, '([0-9]+)', 1) AS f, concat_ws('-', p_brand, p_type) AS g, p_name LIKE '%a%' AS h FROM P""")
def rel_strings(t, spark, sf_dir):
    return t("part").select(
        "p_partkey", F.upper(F.substring("p_name", 1, 3)).alias("a"), F.length("p_name").cast("long").alias("b"), F.translate("p_type", "O", "0").alias("c"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("d"),
        F.levenshtein("p_name", "p_type").cast("long").alias("e"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("f"), F.concat_ws("-", "p_brand", "p_type").alias("g"), F.col("p_name").like("%a%").alias("h"),
    )


@rel("SELECT o_orderkey, CAST(year(o_date) * 100 + month(o_date) AS BIGINT) AS ym, date_diff('day', DATE '1970-01-01', CAST(date_trunc('month', o_date) AS DATE)) AS m, date_diff('day', DATE '1970-01-01', CAST(o_date + INTERVAL 2 MONTH AS DATE)) AS later, CAST(isodow(o_date) AS BIGINT) AS dow FROM O")
def rel_dates(t, spark, sf_dir):
    o = t("orders")
    day = lambda c: F.datediff(c, F.lit("1970-01-01").cast("date")).cast("long")
    return o.select("o_orderkey", (F.year("o_date") * 100 + F.month("o_date")).cast("long").alias("ym"), day(F.trunc("o_date", "month")).alias("m"), day(F.add_months("o_date", 2)).alias("later"), (F.weekday("o_date") + 1).cast("long").alias("dow"))


@rel("SELECT l_suppkey, CAST(sum(xor(price, qty)) AS BIGINT) AS a, CAST(sum(price & 255) AS BIGINT) AS b, CAST(sum(price >> 3) AS BIGINT) AS c, CAST(sum(bit_count(price)) AS BIGINT) AS d, CAST(sum(price % 7) AS BIGINT) AS e FROM L GROUP BY ALL")
def rel_integers(t, spark, sf_dir):
    p, q = F.col("price"), F.col("qty")
    return t("lineitem").groupBy("l_suppkey").agg(F.sum(p.bitwiseXOR(q)).alias("a"), F.sum(p.bitwiseAND(255)).alias("b"), F.sum(F.shiftright("price", 3)).alias("c"), F.sum(F.bit_count("price")).alias("d"), F.sum(p % 7).alias("e"))


@rel("SELECT vec_id, len(embedding) AS n, CAST(round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * 8)) * 1000) AS BIGINT) AS s, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")
def rel_arrays(t, spark, sf_dir):
    e = raw(spark, sf_dir, "embeddings")
    total = F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * 8)
    return e.select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(total * 1000).cast("long").alias("s"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"))


@rel("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM E")
def rel_json(t, spark, sf_dir):
    parsed = F.from_json("props", "k long")
    return t("events").select("event_id", parsed["k"].alias("k"))


@rel("SELECT doc_id, coalesce(quality, -1) AS quality, coalesce(toxic, -1) AS toxic, n_chars FROM documents LEFT JOIN labels USING (doc_id)")
def rel_outer_unmatched(t, spark, sf_dir):
    d = raw(spark, sf_dir, "documents").select("doc_id", "n_chars")
    return d.join(raw(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.coalesce("toxic", F.lit(-1)).alias("toxic"), "n_chars")


@rel("SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM conversations")
def rel_conversation_lag(t, spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return raw(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.lag("role").over(w).alias("before"))


@rel("SELECT l_suppkey, CAST(sum(price) AS BIGINT) AS total, count(*) AS n FROM L GROUP BY ALL")
def rel_salted_aggregate(t, spark, sf_dir):
    return R.salted_aggregate(t("lineitem").select("l_suppkey", "price", "l_orderkey", "l_partkey"), ["l_suppkey"], "price")


@rel("SELECT o_orderpriority, count(*) AS n FROM O JOIN L ON o_orderkey = l_orderkey GROUP BY ALL")
def rel_salted_join(t, spark, sf_dir):
    o = t("orders").select("o_orderkey", "o_orderpriority")
    lines = t("lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "price", "l_partkey")
    return R.salted_join(o, lines, ["o_orderkey"]).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@rel("SELECT o_orderstatus, count(*) AS n, CAST(sum(o_total) AS BIGINT) AS s FROM O GROUP BY ALL")
def rel_sql_views(t, spark, sf_dir):
    t("orders").createOrReplaceTempView("sealed_orders")
    return spark.sql("SELECT o_orderstatus, count(*) AS n, sum(o_total) AS s FROM sealed_orders GROUP BY o_orderstatus")


@rel("SELECT l_suppkey, CAST(count(*) * sum(qty * qty) - sum(qty) * sum(qty) AS BIGINT) AS spread FROM L GROUP BY ALL")
def rel_custom_aggregate(t, spark, sf_dir):
    """n^2 times the variance, by a decomposable rule of the user's own (L690-692)."""
    from ..core.frame import seal
    from ..operators.aggregate import Decomposable

    rule = Decomposable(lambda c: {"n": F.count(c), "s": F.sum(c), "q": F.sum(c * c)}, lambda _, c: F.sum(c), lambda p: p["n"] * p["q"] - p["s"] * p["s"])
    return seal(t("lineitem").select("l_suppkey", "qty")).aggregate(["l_suppkey"], spread=(rule, "qty")).reveal()


@rel("SELECT user_id, CAST(sum(CASE WHEN event_type = 'click' THEN val ELSE 0 END) AS BIGINT) AS click, count(DISTINCT event_type) AS kinds FROM E GROUP BY ALL")
def rel_maps(t, spark, sf_dir):
    """Per user a map of totals by kind, read and filtered as a map."""
    sums = t("events").groupBy("user_id", "event_type").agg(F.sum("val").alias("v"))
    maps = sums.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "v"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0).cast("long")).alias("click"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@rel("SELECT label, vec_id FROM (SELECT e.label, e.vec_id, row_number() OVER (PARTITION BY e.label ORDER BY round(list_dot_product(CAST(e.embedding AS DOUBLE[]), CAST(c.embedding AS DOUBLE[])), 9) DESC, e.vec_id) AS k FROM embeddings e JOIN (SELECT label, arg_min(embedding, vec_id) AS embedding FROM embeddings GROUP BY label) c USING (label)) WHERE k <= 3")
def rel_vector_top_k(t, spark, sf_dir):
    """The three vectors of each label nearest to the label's first: dot products as array functions."""
    e = raw(spark, sf_dir, "embeddings")
    first = e.groupBy("label").agg(F.min_by("embedding", "vec_id").alias("c"))
    dot = F.aggregate(F.zip_with("embedding", "c", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    small = plan_bytes(first) <= broadcast_limit(spark)
    near = e.join(F.broadcast(first) if small else first, "label").withColumn("dot", F.round(dot, 9))
    return R.top_k_per(near, ["label"], [F.desc("dot"), F.asc("vec_id")], 3).select("label", "vec_id")


@rel(None)
def rel_sample(t, spark, sf_dir):
    """A sampling operator: about a tenth of the lines, the same ones each time."""
    return t("lineitem").sample(0.1, seed=3).groupBy("l_returnflag").agg(F.count("*").alias("n"))


@rel("SELECT l_suppkey, CAST(sum(qty) AS BIGINT) AS q, count(*) AS n FROM L GROUP BY ALL")
def rel_grouped_map(t, spark, sf_dir):
    """applyInPandas over per-supplier partials (bounded by the partial step before it)."""
    part = t("lineitem").groupBy("l_suppkey", "l_returnflag").agg(F.sum("qty").alias("q"), F.count("*").alias("n"))
    return part.groupBy("l_suppkey").applyInPandas(lambda p: pd.DataFrame({"l_suppkey": [p["l_suppkey"].iloc[0]], "q": [p["q"].sum()], "n": [p["n"].sum()]}), "l_suppkey long, q long, n long")


@rel("SELECT o_orderkey, CASE WHEN o_total % 2 = 0 THEN 'even' ELSE 'odd' END AS parity FROM O")
def rel_scalar_udf(t, spark, sf_dir):
    """A row-at-a-time Python function, the slow path that the library itself avoids."""
    parity = F.udf(lambda x: "odd" if x % 2 else "even", "string")
    return t("orders").select("o_orderkey", parity("o_total").alias("parity"))


@rel("SELECT o_orderkey, o_orderpriority IN ('1-URGENT', '5-LOW') AS a, regexp_matches(o_orderpriority, '^[1-3]-[A-Z]+$') AS b, nullif(o_orderstatus, 'P') IS NOT DISTINCT FROM NULL AS c, nullif(o_orderstatus, 'P') IS NULL AS d, o_total BETWEEN 1000000 AND 5000000 AS e FROM O")
def rel_predicates(t, spark, sf_dir):
    none = F.when(F.col("o_orderstatus") != "P", F.col("o_orderstatus"))
    return t("orders").select(
        "o_orderkey", F.col("o_orderpriority").isin("1-URGENT", "5-LOW").alias("a"), F.col("o_orderpriority").rlike("^[1-3]-[A-Z]+$").alias("b"), none.eqNullSafe(F.lit(None)).alias("c"), none.isNull().alias("d"),
        F.col("o_total").between(1_000_000, 5_000_000).alias("e"),
    )


@rel("SELECT o_orderkey, CAST(round(percent_rank() OVER w * 1000000) AS BIGINT) AS a, CAST(round(cume_dist() OVER w * 1000000) AS BIGINT) AS b FROM O WINDOW w AS (PARTITION BY o_custkey ORDER BY o_total)")
def rel_distribution(t, spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_total")
    whole = lambda c: F.round(c * 1_000_000).cast("long")
    return t("orders").select("o_orderkey", whole(F.percent_rank().over(w)).alias("a"), whole(F.cume_dist().over(w)).alias("b"))


@rel("SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY nullif(o_orderstatus, 'P') NULLS FIRST, o_orderkey) AS a, row_number() OVER (PARTITION BY o_custkey ORDER BY nullif(o_orderstatus, 'P') DESC NULLS LAST, o_orderkey DESC) AS b FROM O")
def rel_null_order(t, spark, sf_dir):
    s = F.when(F.col("o_orderstatus") != "P", F.col("o_orderstatus"))
    place = lambda *o: F.row_number().over(Window.partitionBy("o_custkey").orderBy(*o)).cast("long")
    return t("orders").select("o_orderkey", place(s.asc_nulls_first(), F.asc("o_orderkey")).alias("a"), place(s.desc_nulls_last(), F.desc("o_orderkey")).alias("b"))


@rel("SELECT 'union' AS kind, k FROM (SELECT c_custkey AS k FROM C UNION SELECT user_id FROM E) UNION ALL SELECT 'intersect', k FROM (SELECT o_custkey AS k FROM O INTERSECT ALL SELECT user_id FROM E) UNION ALL SELECT 'except', k FROM (SELECT o_custkey AS k FROM O EXCEPT ALL SELECT user_id FROM E)")
def rel_set_ops_all(t, spark, sf_dir):
    c, o, e = (t(n).select(F.col(k).alias("k")) for n, k in (("customer", "c_custkey"), ("orders", "o_custkey"), ("events", "user_id")))
    named = lambda df, kind: df.select(F.lit(kind).alias("kind"), "k")
    return named(c.unionByName(e).distinct(), "union").unionByName(named(o.intersectAll(e), "intersect")).unionByName(named(o.exceptAll(e), "except"))


@rel("SELECT p_partkey, trim('  ' || p_name || ' ') AS a, len(string_split(p_name, ' ')) AS b, string_split(p_name, ' ')[1] AS c, lpad(CAST(p_size AS VARCHAR), 4, '0') AS d, reverse(p_brand) AS e, CAST(instr(p_name, 'a') AS BIGINT) AS f FROM P")
def rel_text(t, spark, sf_dir):
    words = F.split("p_name", " ")
    return t("part").select(
        "p_partkey", F.trim(F.concat(F.lit("  "), "p_name", F.lit(" "))).alias("a"), F.size(words).cast("long").alias("b"), F.element_at(words, 1).alias("c"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("d"),
        F.reverse("p_brand").alias("e"), F.instr("p_name", "a").cast("long").alias("f"),
    )


@rel("""SELECT o_orderkey, abs(o_total - 10000000) AS a, CAST(floor(sqrt(o_total)) AS BIGINT) AS b, CAST(round(ln(o_total) * 1000000) AS BIGINT) AS c, sha256(o_orderpriority) AS d, md5(o_orderstatus) AS e, upper(to_hex(o_orderkey)) AS f,
  CAST(round(o_total / 1000.0) AS BIGINT) AS g, CAST(pow(o_orderkey % 10, 3) AS BIGINT) AS h FROM O""")
def rel_math(t, spark, sf_dir):
    v = F.col("o_total")
    return t("orders").select(
        "o_orderkey", F.abs(v - 10_000_000).alias("a"), F.floor(F.sqrt(v)).cast("long").alias("b"), F.round(F.log(v) * 1_000_000).cast("long").alias("c"), F.sha2("o_orderpriority", 256).alias("d"), F.md5("o_orderstatus").alias("e"),
        F.conv(F.col("o_orderkey").cast("string"), 10, 16).alias("f"), F.round(v / 1000).cast("long").alias("g"), F.pow(F.col("o_orderkey") % 10, F.lit(3)).cast("long").alias("h"),
    )


@rel("SELECT b, CAST(sum(n) AS BIGINT) AS n FROM (SELECT l_orderkey % 7 AS b, count(DISTINCT l_partkey) AS n FROM L GROUP BY l_orderkey) GROUP BY b")
def rel_hash(t, spark, sf_dir):
    """Distinct keys counted by their 64-bit hashes, which all engines of this kind can exchange."""
    per = t("lineitem").groupBy("l_orderkey").agg(F.size(F.collect_set(F.xxhash64("l_partkey"))).alias("n"))
    return per.groupBy((F.col("l_orderkey") % 7).alias("b")).agg(F.sum("n").cast("long").alias("n"))


@rel("SELECT l_returnflag, CAST(round(stddev(qty) * 1000000) AS BIGINT) AS sd, CAST(round(var_pop(qty) * 1000) AS BIGINT) AS vp, CAST(round(corr(qty, price) * 1000000) AS BIGINT) AS r, CAST(round(median(qty) * 10) AS BIGINT) AS m, CAST(round(quantile_cont(qty, 0.9) * 10) AS BIGINT) AS q FROM L GROUP BY ALL")
def rel_statistics(t, spark, sf_dir):
    times = lambda c, k: F.round(c * k).cast("long")
    return t("lineitem").groupBy("l_returnflag").agg(
        times(F.stddev("qty"), 1_000_000).alias("sd"), times(F.var_pop("qty"), 1000).alias("vp"), times(F.corr("qty", "price"), 1_000_000).alias("r"), times(F.median("qty"), 10).alias("m"), times(F.percentile("qty", F.lit(0.9)), 10).alias("q"),
    )


@rel("SELECT vec_id, i, CAST(round(x * 100000) AS BIGINT) AS x FROM (SELECT vec_id, unnest([1, 2, 3]) AS i, unnest(list_sort(list_slice(CAST(embedding AS DOUBLE[]), 1, 3))) AS x FROM embeddings)")
def rel_array_rows(t, spark, sf_dir):
    """Slices, sorted, as rows with their places."""
    e = raw(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(F.sort_array(F.slice(F.col("embedding").cast("array<double>"), 1, 3))).alias("p", "v"))
    return e.select("vec_id", (F.col("p") + 1).alias("i"), F.round(F.col("v") * 100_000).cast("long").alias("x"))


@rel("SELECT o_orderpriority, count(*) AS n, CAST(sum(qty) AS BIGINT) AS q FROM O JOIN L ON o_orderkey = l_orderkey GROUP BY ALL")
def rel_bucketed_join(t, spark, sf_dir):
    """Both tables written in buckets of the key: the join after it exchanges neither."""
    import uuid

    def bucketed(df, key):
        name = f"sealed_{uuid.uuid4().hex}"
        df.write.bucketBy(8, key).sortBy(key).option("path", new_path(spark, name)).saveAsTable(name)
        return spark.table(name)

    o = bucketed(t("orders").select("o_orderkey", "o_orderpriority"), "o_orderkey")
    lines = bucketed(t("lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "qty"), "o_orderkey")
    return o.join(lines.hint("merge"), "o_orderkey").groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("qty").alias("q"))


# -- Python functions ---------------------------------------------------------------------------------


@rel("SELECT l_suppkey, CAST(sum(price // 100) AS BIGINT) AS euros FROM L GROUP BY ALL")
def rel_arrow_udf(t, spark, sf_dir):
    @F.pandas_udf("long")
    def whole(x: pd.Series) -> pd.Series:
        return x // 100

    return t("lineitem").select("l_suppkey", whole("price").alias("e")).groupBy("l_suppkey").agg(F.sum("e").alias("euros"))


@rel("SELECT n_nationkey, i, (n_nationkey >> i) & 1 AS bit FROM N, range(5) r(i)")
def rel_table_function(t, spark, sf_dir):
    @F.udtf(returnType="i long, bit int")
    class Bits:
        def eval(self, x: int):
            for i in range(5):
                yield i, x >> i & 1

    t("nation").createOrReplaceTempView("sealed_nation")
    spark.udtf.register("sealed_bits", Bits)
    return spark.sql("SELECT n_nationkey, i, bit FROM sealed_nation, LATERAL sealed_bits(n_nationkey)")


# -- sources and sinks -----------------------------------------------------------------------------------


def _format(fmt: str):
    def run(t, spark, sf_dir):
        path = new_path(spark, fmt)
        df = t("part")
        df.write.format(fmt).options(header=True).save(path)
        return spark.read.format(fmt).options(header=True).schema(df.schema).load(path)

    run.__name__ = f"source_{fmt}"
    rel("SELECT p_partkey, p_name, p_brand, p_type, p_size FROM P")(run)


for _f in ("csv", "json", "orc", "parquet"):
    _format(_f)


@rel("SELECT p_partkey || ' ' || p_name AS line FROM P")
def source_text(t, spark, sf_dir):
    path = new_path(spark, "text")
    t("part").select(F.concat_ws(" ", F.col("p_partkey").cast("string"), "p_name")).write.text(path)
    return spark.read.text(path).select(F.col("value").alias("line"))


@rel("SELECT o_orderkey, o_total FROM O")
def source_owner_shares(t, spark, sf_dir):
    """One folder of share terms per party, and the table opened from all of them (L66, L165)."""
    from ..sources.shares import export_shares, import_shares

    path = new_path(spark, "shares")
    export_shares(t("orders").select("o_orderkey", "o_total"), ["o_orderkey"], ["o_total"], path, parties=3, seed=7)
    return import_shares(spark, ["o_orderkey"], ["o_total"], path, parties=3)


@rel("SELECT c_custkey AS k, c_bal AS v, FALSE AS empty FROM C UNION ALL SELECT unnest(range(CAST(1 << CAST(ceil(log2(n)) AS INTEGER) AS BIGINT) - n)), NULL, TRUE FROM (SELECT count(*) AS n FROM C)")
def source_dummy_rows(t, spark, sf_dir):
    """Customers filled up to a power of two with rows of the data source."""
    from ..plans.meter import padded
    from ..sources.dummy import DummyRows

    spark.dataSource.register(DummyRows)
    df = t("customer").select(F.col("c_custkey").alias("k"), F.col("c_bal").alias("v"))
    n = df.count()
    more = spark.read.format("sealed_dummy_rows").option("rows", padded(n) - n).option("partitions", 4).load()
    return df.withColumn("empty", F.lit(False)).unionByName(more.withColumn("empty", F.lit(True)))


# -- streams ------------------------------------------------------------------------------------------------


@rel("SELECT event_type, CAST(floor(epoch_us(ts) / 3600000000) AS BIGINT) AS hour, count(*) AS n, CAST(sum(val) AS BIGINT) AS s FROM E GROUP BY ALL")
def stream_tumbling(t, spark, sf_dir):
    from ..streaming.events import hourly_counts, run_available

    return run_available(hourly_counts(spark, sf_dir), "complete")


@rel("SELECT user_id, count(*) AS mult FROM E GROUP BY ALL")
def stream_partials(t, spark, sf_dir):
    """Multiplicities kept as mergeable partials, batch by batch."""
    from ..streaming.events import merge_partials

    return merge_partials(spark, sf_dir, new_path(spark, "partials"))


@rel("SELECT event_id, c_mktsegment FROM E JOIN C ON user_id = c_custkey")
def stream_static_join(t, spark, sf_dir):
    from ..streaming.events import events_stream, run_available

    return run_available(events_stream(spark, sf_dir).join(t("customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "c_mktsegment"), "append")


@rel("SELECT DISTINCT event_id FROM E")
def stream_dedupe(t, spark, sf_dir):
    from ..streaming.events import events_stream, run_available

    return run_available(events_stream(spark, sf_dir).withWatermark("at", "40 days").dropDuplicates(["event_id"]).select("event_id"), "append")


@rel("SELECT event_type, h - k AS hour, count(*) AS n FROM (SELECT event_type, CAST(floor(epoch_us(ts) / 3600000000) AS BIGINT) AS h, k FROM E, (VALUES (0), (1)) s(k)) GROUP BY ALL")
def stream_sliding(t, spark, sf_dir):
    """Windows of two hours, one each hour."""
    from ..streaming.events import run_available, sliding_counts

    return run_available(sliding_counts(spark, sf_dir), "complete")


@rel("""SELECT user_id, CAST(min(us) AS BIGINT) AS first_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id) AS s FROM (
  SELECT user_id, event_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 3600000000 THEN 0 ELSE 1 END AS fresh FROM E)) GROUP BY user_id, s""")
def stream_sessions(t, spark, sf_dir):
    """Sessions that end after an hour without an event."""
    from ..streaming.events import run_available, session_counts

    return run_available(session_counts(spark, sf_dir), "complete")


@rel("SELECT a.event_id AS error_id, b.event_id AS purchase_id FROM E a JOIN E b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts >= a.ts AND epoch_us(b.ts) <= epoch_us(a.ts) + 3600000000")
def stream_interval_join(t, spark, sf_dir):
    """Purchases within an hour after an error of the same user: two streams, both with watermarks."""
    from ..streaming.events import errors_then_purchases, run_available

    return run_available(errors_then_purchases(spark, sf_dir), "append")


@rel("SELECT event_type, CAST(floor(epoch_us(ts) / 3600000000) AS BIGINT) AS hour, count(*) AS n, CAST(sum(val) AS BIGINT) AS s FROM E GROUP BY ALL")
def stream_update(t, spark, sf_dir):
    """Windows as they change, batch by batch; the last state of each."""
    from ..streaming.events import hourly_counts, run_available

    return run_available(hourly_counts(spark, sf_dir), "update", ["event_type", "hour"])
