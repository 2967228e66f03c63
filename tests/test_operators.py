import random

import pytest
from pyspark.sql import functions as F

from sealed_frames.core.frame import OK, SealedFrame, seal
from sealed_frames.core.position import beside, prefix_sums, running_sum, with_positions
from sealed_frames.operators import relational as R
from sealed_frames.operators.aggregate import combine, mark_first, partials
from sealed_frames.operators.fused_join import aggregate_join, cartesian_join, fused_join, should_trim
from sealed_frames.operators.group_scan import group_scan, levels
from sealed_frames.operators.radix import radix_sort
from sealed_frames.plans.chain import chain_aggregate
from sealed_frames.plans.classify import Query, acyclic, classify
from sealed_frames.plans.digest import trace_digest
from sealed_frames.workloads import micro


def frame(spark, rows, schema, unique=(), tier="clear"):
    """rows end in their validity."""
    return SealedFrame(spark.createDataFrame(rows, f"{schema}, {OK} boolean"), seal(spark.range(1), unique, len(rows), tier).public)


def plain_join(left, right, how):
    """left: (k, a, ok), right: (k, b, ok); SQL semantics on valid rows."""
    l, r = [x for x in left if x[2]], [x for x in right if x[2]]
    out = []
    for k, a, _ in l:
        hits = [b for j, b, _ in r if j == k and k is not None]
        if how == "semi" and hits or how == "anti" and not hits:
            out.append((k, a))
        elif how in ("inner", "left", "right", "full"):
            out += [(k, a, b) for b in hits]
            if how in ("left", "full") and not hits:
                out.append((k, a, None))
    if how in ("right", "full"):
        out += [(k, None, b) for k, b, _ in r if k is None or not any(j == k for j, _, _ in l)]
    return sorted(out, key=str)


@pytest.mark.parametrize("how", ["inner", "left", "right", "full", "semi", "anti"])
def test_joins_against_brute_force(spark, how):
    for seed in range(3):
        rng = random.Random(seed)
        unique = how not in ("semi", "anti")
        keys = rng.sample([0, 1, 2, 3, 4, 5], 4) + [None] if unique else [rng.choice([0, 1, 2, 3, None]) for _ in range(6)]
        left = [(k, i, rng.random() < 0.8) for i, k in enumerate(keys)]
        right = [(rng.choice([0, 1, 2, 3, 7, None]), 10 + i, rng.random() < 0.8) for i in range(9)]
        want = plain_join(left, right, how)
        for strategy in ("stacked", "native"):
            for tier in ("clear", "padded"):
                l, r = frame(spark, left, "k long, a long", [["k"]], tier), frame(spark, right, "k long, b long", tier=tier)
                out = l.join(r, "k", how, strategy=strategy)
                got = [tuple(x) for x in out.reveal().select(*(["k", "a"] if how in ("semi", "anti") else ["k", "a", "b"])).collect()]
                assert sorted(got, key=str) == want, (seed, strategy, tier)
                if strategy == "stacked" and tier == "padded":
                    assert out.df.count() == (len(left) if how in ("semi", "anti") else len(left) + len(right))


def test_carrier_mode_keeps_matched_left_rows(spark):
    l, r = frame(spark, [(1, 5, True), (2, 6, True)], "k long, a long", [["k"]]), frame(spark, [(1, 7, True), (3, 8, True)], "k long, b long")
    got = fused_join(l, r, "k", "full", strategy="stacked", outer_mode="carrier").reveal()
    assert sorted(map(tuple, got.select("k", "a", "b").collect()), key=str) == sorted([(1, 5, None), (1, 5, 7), (2, 6, None), (3, None, 8)], key=str)


def test_stacked_join_needs_unique_keys(spark):
    f = frame(spark, [(1, 5, True)], "k long, a long")
    with pytest.raises(ValueError, match="unique"):
        fused_join(f, frame(spark, [(1, 5, True)], "k long, b long"), "k", strategy="stacked")
    with pytest.raises(ValueError, match="both sides"):
        fused_join(f, frame(spark, [(1, 5, True)], "k long, a long"), "k")


def test_join_and_aggregation_share_one_exchange(spark, tiny):
    orders = seal(spark.read.parquet(f"{tiny}/orders.parquet").select("o_orderkey"), [["o_orderkey"]])
    lines = seal(spark.read.parquet(f"{tiny}/lineitem.parquet").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey"))
    plan = fused_join(orders, lines, "o_orderkey", strategy="stacked", aggs={"n": ("count", "*")}).df._jdf.queryExecution().toString()
    physical = plan[plan.index("== Physical Plan ==") :]
    assert physical.count("Exchange hashpartitioning") == 1


def test_many_to_many_sums(spark):
    rng = random.Random(2)
    left = [(rng.randrange(4), rng.randrange(9), True) for _ in range(12)]
    right = [(rng.randrange(5), rng.randrange(9), True) for _ in range(14)]
    met = [(j % 2, a, b) for k, a, _ in left for j, b, _ in right if j == k]
    r = frame(spark, right, "k long, b long").with_col("g", F.col("k") % 2)
    got = aggregate_join(frame(spark, left, "k long, a long"), r, "k", ["g"], {"sb": "b"}, {"sa": "a"}, "n").reveal().collect()
    assert {(x.g, x.sb, x.sa, x.n) for x in got} == {(g, sum(b for h, _, b in met if h == g), sum(a for h, a, _ in met if h == g), sum(h == g for h, _, _ in met)) for g in {h for h, _, _ in met}}


def test_quadratic_fallback_is_guarded(spark):
    f, g = frame(spark, [(i, i, True) for i in range(5)], "x long, y long"), frame(spark, [(i, i, i != 2) for i in range(5)], "u long, v long")
    assert sorted(map(tuple, cartesian_join(f, g, F.col("x") < F.col("u")).reveal().select("x", "u").collect())) == [(x, u) for x in range(5) for u in range(5) if x < u and u != 2]
    with pytest.raises(ValueError):
        cartesian_join(f, g, F.lit(True), most_rows=24)


@pytest.mark.parametrize("variant", ["doubling", "work_efficient", "segmented"])
def test_scans(spark, variant):
    rng = random.Random(1)
    for n in (1, 2, 3, 4, 5, 8, 9):
        rows = [(0, i, rng.randrange(9), chr(97 + i)) for i in range(n)] + [(g, i, 1, "z") for g in (1, 2) for i in range(3)]
        outputs = [("sum", "v", "s"), ("max", "v", "m"), ("copy", "c", "f")] + ([("concat", "c", "t")] if variant != "segmented" else [])
        got = group_scan(spark.createDataFrame(rows, "g long, i long, v long, c string"), ["g"], ["i"], outputs, 9, variant).where("g = 0").orderBy("i").collect()
        v = [r[2] for r in rows[:n]]
        assert [r.s for r in got] == [sum(v[: i + 1]) for i in range(n)] and [r.m for r in got] == [max(v[: i + 1]) for i in range(n)] and all(r.f == "a" for r in got)
        if variant != "segmented":
            assert [r.t for r in got] == ["abcdefghi"[: i + 1] for i in range(n)]
    assert [levels(n) for n in (0, 1, 2, 3, 4, 5, 8, 9)] == [0, 0, 1, 2, 2, 3, 3, 4]


@pytest.mark.parametrize("name", ["scan_doubling", "scan_work_efficient", "scan_reverse"])
def test_scan_queries_cover_long_groups(spark, tmp_path, name):
    """One customer holds 300 orders, more than any in the given tables."""
    given = spark.read.parquet("/root/testdata/sf0.001/orders.parquet")
    hot = F.when(F.col("o_orderkey") <= F.lit(1200), F.lit(1)).otherwise(F.col("o_custkey"))
    given.withColumn("o_custkey", hot.cast(given.schema["o_custkey"].dataType)).write.parquet(f"{tmp_path}/orders.parquet")
    got = {r.o_orderkey: r.s for r in micro.QUERIES[name](spark, str(tmp_path)).collect()}
    rows = sorted(micro.table(spark, str(tmp_path), "orders").df.select("o_custkey", "o_orderkey", "o_total").collect(), key=lambda r: r.o_orderkey, reverse=name == "scan_reverse")
    sums, want = {}, {}
    for r in rows:
        want[r.o_orderkey] = sums[r.o_custkey] = sums.get(r.o_custkey, 0) + r.o_total
    assert sum(r.o_custkey == 1 for r in rows) >= 300 and got == want


@pytest.mark.parametrize("variant", ["doubling", "work_efficient"])
def test_scans_refuse_groups_beyond_their_bound(spark, variant):
    df = spark.range(65).select(F.lit(0).alias("g"), F.col("id").alias("i"), F.lit(1).alias("v"))
    with pytest.raises(Exception, match="more than 64 rows"):
        group_scan(df, ["g"], ["i"], [("sum", "v", "s")], 64, variant).collect()
    assert group_scan(df.where("i < 64"), ["g"], ["i"], [("sum", "v", "s")], 64, variant).agg(F.max("s")).first()[0] == 64


def test_positions_and_running_sums(spark):
    df = spark.range(1000).select((F.col("id") * 37 % 1000).alias("x"))
    placed = with_positions(df, [F.desc("x")], 7)
    assert [tuple(r) for r in placed.orderBy("x").select("x", "__pos").collect()] == [(i, 999 - i) for i in range(1000)]
    sums = running_sum(with_positions(df, [F.asc("x")], 5), "x", "s", block_rows=64).orderBy("x").collect()
    assert [r.s for r in sums] == [i * (i + 1) // 2 for i in range(1000)]


@pytest.mark.parametrize("fanout", [3, 10, 1 << 14])
def test_prefix_sums_over_a_tree(spark, fanout):
    rows = [(i, i % 7 + 1) for i in range(0, 200, 3)]
    got = prefix_sums(spark.createDataFrame(rows, "k long, v long"), "k", "v", 200, "b", fanout)
    assert {r.k: r.b for r in got.collect()} == {k: sum(v for j, v in rows if j < k) for k, _ in rows}
    met = beside(spark.createDataFrame(rows, "k long, v long"), got, ["k"], 1 << 40)
    assert met.count() == len(rows)


def test_radix_query_sorts_keys_of_more_than_17_bits(spark, tmp_path):
    given = spark.read.parquet("/root/testdata/sf0.001/orders.parquet")
    moved = F.col("o_custkey") + F.when(F.col("o_orderkey") % 2 == 0, 131_072).otherwise(0)
    given.withColumn("o_custkey", moved.cast(given.schema["o_custkey"].dataType)).write.parquet(f"{tmp_path}/orders.parquet")
    rows = sorted((r.o_custkey, r.o_orderkey) for r in spark.read.parquet(f"{tmp_path}/orders.parquet").collect())
    got = {r.o_orderkey: r.place for r in micro.QUERIES["sort_radix_digits"](spark, str(tmp_path)).collect()}
    assert got == {o: i for i, (_, o) in enumerate(rows)}
    with pytest.raises(ValueError, match="17 bits"):
        radix_sort(with_positions(spark.range(131_072, 131_075), [F.asc("id")], 2), "id", 17)


def test_filters_and_padding_keep_the_public_size(spark):
    f = frame(spark, [(i, i, True) for i in range(6)], "x long, y long", tier="padded").filter("x > 3").filter(F.col("y") < 5)
    assert f.df.count() == 6 and [r.x for r in f.reveal().collect()] == [4]
    p = f.pad_to(10)
    assert p.df.count() == 10 and p.public.rows == 10 and p.reveal().count() == 1
    with pytest.raises(ValueError):
        p.pad_to(3)
    a = f.assign_if(F.col("x") > 4, "y", F.lit(0).cast("long"))
    assert [r.y for r in a.df.orderBy("x").collect()] == [0, 1, 2, 3, 4, 0]


def test_plans_do_not_depend_on_the_data(spark):
    """Equal sizes, other contents: the same trace and the same plan (L263)."""
    plans = []
    for shift in (0, 50):
        f = frame(spark, [(i, i + shift, True) for i in range(8)], "x long, y long", [["x"]], "padded").filter("y > 20")
        g = f.join(frame(spark, [(i % 3, i, True) for i in range(8)], "x long, z long", tier="padded"), "x", strategy="stacked")
        plans.append((g.public.trace, g.df.count(), trace_digest(g)))
    assert plans[0] == plans[1]


def test_padded_groups_keep_all_rows(spark):
    """Aggregates of the padded tier: public sizes, one carrier per group, and a plan that the data do not change."""
    shown = []
    for shift in (0, 70):
        rows = [(i % 4, (i * 7 + shift) % 50, i % 3 != 0) for i in range(24)]
        f = frame(spark, rows, "g long, v long", tier="padded")
        out = f.aggregate(["g"], s=("sum", "v"), n=("count", "*"), lo=("min", "v"), mean=("avg", "v"))
        joined = frame(spark, [(i, i, True) for i in range(4)], "g long, a long", [["g"]], "padded").join(out, "g")
        assert out.df.count() == 24 and joined.df.count() >= 24
        want = {g: [v for h, v, ok in rows if h == g and ok] for g in range(4)}
        assert {r.g: (r.s, r.n, r.lo, r.mean) for r in out.reveal().collect()} == {g: (sum(v), len(v), min(v), sum(v) // len(v)) for g, v in want.items()}
        assert sorted((r.g, r.a, r.s) for r in joined.reveal().collect()) == [(g, g, sum(want[g])) for g in range(4)]
        shown.append((trace_digest(joined), joined.df.count()))
    assert shown[0] == shown[1]


def test_quadratic_fallback_beyond_its_bound(spark):
    a = frame(spark, [(i, True) for i in range(30)], "x long")
    b = frame(spark, [(i, i % 2 == 0) for i in range(30)], "y long")
    with pytest.raises(ValueError):
        cartesian_join(a, b, F.col("x") < F.col("y"), 100)
    got = cartesian_join(a, b, F.col("x") < F.col("y"), 100, beyond="blocks").reveal()
    assert got.count() == sum(i < j for i in range(30) for j in range(0, 30, 2))


def test_late_events_are_dropped(spark, tmp_path):
    """Files of one batch each: an event behind the watermark of the batches before is dropped, a less late one counts."""
    import os
    from datetime import datetime, timedelta

    from sealed_frames.streaming.events import hourly_counts, run_available

    given = spark.read.parquet("/root/testdata/sf0.001/events.parquet").schema
    start = datetime(2024, 1, 1)
    # late rows are judged by the watermark of the batch before last: the fourth batch comes ten hours late, the fifth one
    hours = [[0, 1], [10], [11], [1], [10], [20]]
    for i, batch in enumerate(hours):
        rows = [{"event_id": 10 * i + j, "ts": start + timedelta(hours=h, minutes=5), "user_id": 1, "event_type": "view", "value": 1.0, "props": None} for j, h in enumerate(batch)]
        path = f"{tmp_path}/part{i}"
        spark.createDataFrame([tuple(r.get(f.name) for f in given) for r in rows], given).coalesce(1).write.parquet(path)
        name = next(f for f in os.listdir(path) if f.endswith(".parquet"))
        os.rename(f"{path}/{name}", f"{tmp_path}/e{i}.parquet")
        os.utime(f"{tmp_path}/e{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))
    first = int(start.timestamp()) // 3600
    for late in ("2 hours", "40 days"):
        df = hourly_counts(spark, str(tmp_path), late, files="e*.parquet", per_batch=1)
        got = {r.hour - first: r.n for r in run_available(df, "update", ["event_type", "hour"]).collect()}
        assert got == {0: 1, 1: 1 if late == "2 hours" else 2, 10: 2, 11: 1, 20: 1}


def test_partials_combine(spark):
    f = frame(spark, [(i % 3, i, i != 4) for i in range(20)], "g long, v long")
    outputs = {"s": ("sum", "v"), "n": ("count", "*"), "lo": ("min", "v"), "hi": ("max", "v"), "mean": ("avg", "v")}
    halves = [partials(f.filter(F.col("v") % 2 == k), ["g"], outputs) for k in (0, 1)]
    both = combine(halves[0].concat(halves[1]), ["g"], {k: fn for k, (fn, _) in outputs.items()})
    assert sorted(map(tuple, both.reveal().collect())) == sorted(map(tuple, f.aggregate(["g"], **outputs).reveal().collect()))
    assert mark_first(f, ["g"]).reveal().count() == 3 and f.distinct("g").reveal().count() == 3


def test_trimming_keeps_valid_rows_and_the_public_size(spark):
    left = frame(spark, [(i, i * 10, i % 3 != 0) for i in range(40)], "k long, a long", [["k"]], "padded")
    right = frame(spark, [(i % 50, i, i % 4 != 0) for i in range(90)], "k long, b long", tier="padded")
    whole = left.join(right, "k", strategy="stacked", trim="never")
    cut = left.join(right, "k", strategy="stacked", trim="always")
    assert whole.df.count() == 130 and cut.df.count() == 90 == cut.public.rows
    assert sorted(map(tuple, cut.reveal().collect())) == sorted(map(tuple, whole.reveal().collect()))
    assert cut.reveal().count() == sum(i % 4 != 0 and i % 50 < 40 and i % 50 % 3 != 0 for i in range(90))


def test_right_rows_are_aggregated_before_they_are_exchanged(spark):
    keep = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        left = frame(spark, [(i, i + 5, i != 3) for i in range(10)], "k long, a long", [["k"]])
        right = frame(spark, [(0 if i % 2 else i % 12, i, i % 7 != 0) for i in range(400)], "k long, b long")
        aggs = {"s": ("sum", "b"), "n": ("count", "*"), "lo": ("min", "b"), "hi": ("max", "b")}
        early = left.join(right, "k", aggs=aggs)
        late = left.join(right, "k", strategy="stacked", aggs=aggs)
        assert early.public.trace.count("aggregate") == 2 and late.public.trace.count("aggregate") == 1
        got = [sorted((r.k, r.s, r.n, r.lo, r.hi) for r in f.reveal().collect()) for f in (early, late)]
        assert got[0] == got[1] and [r[0] for r in got[0]] == [0, 2, 4, 6, 8]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", keep)


def test_trim_rule():
    assert [should_trim(n, m) for n, m in ((1500, 15_000), (15_000, 60_000), (25, 100), (1_500_000, 6_000_000))] == [False, True, False, True]


def test_classifier():
    tables = {"c": ["ck"], "o": ["ok", "ock"], "l": ["lk"]}
    joins = [(("c", "ck"), ("o", "ock")), (("o", "ok"), ("l", "lk"))]
    assert classify(Query(tables, joins, unique={"c": [["ck"]], "o": [["ok"]]})) == "one_to_many"
    assert classify(Query(tables, joins, [("o", "ok")])) == "early_aggregation"
    assert classify(Query(tables, joins, [("o", "ok"), ("c", "ck")])) == "cartesian"
    triangle = Query({"a": ["x", "z"], "b": ["x", "y"], "c": ["y", "z"]}, [(("a", "x"), ("b", "x")), (("b", "y"), ("c", "y")), (("c", "z"), ("a", "z"))])
    assert not acyclic(triangle) and classify(triangle) == "cartesian"


def test_interval_and_band_joins(spark):
    rng = random.Random(6)
    a = [(i, s := rng.randrange(100), s + rng.randrange(12)) for i in range(40)]
    b = [(i, s := rng.randrange(100), s + rng.randrange(12)) for i in range(40)]
    x, y = spark.createDataFrame(a, "i long, s long, e long"), spark.createDataFrame(b, "j long, t long, f long")
    got = {(r.i, r.j) for r in R.overlap_join(x, y, ("s", "e"), ("t", "f"), 5).collect()}
    assert got == {(i, j) for i, s, e in a for j, t, f in b if s <= f and t <= e} and R.overlap_join(x, y, ("s", "e"), ("t", "f"), 5).count() == len(got)
    near = R.band_join(x, y, "s", "t", 3).collect()
    assert sorted((r.i, r.j) for r in near) == sorted((i, j) for i, s, _ in a for j, t, _ in b if abs(s - t) <= 3)


def test_chains_against_brute_force(spark):
    rng = random.Random(8)
    a = [(rng.randrange(3), rng.randrange(3), rng.randrange(5)) for _ in range(9)]
    b = [(rng.randrange(3), rng.randrange(4), rng.randrange(5)) for _ in range(10)]
    c = [(rng.randrange(4), rng.randrange(5)) for _ in range(8)]
    d = [(rng.randrange(3), rng.randrange(5)) for _ in range(7)]
    met = [(p, q, r, s) for p in a for q in b for r in c for s in d if p[0] == q[0] and q[1] == r[0] and p[1] == s[0]]
    tables = {"a": seal(spark.createDataFrame(a, "x long, w long, g long")), "b": seal(spark.createDataFrame(b, "x long, y long, vb long")), "c": seal(spark.createDataFrame(c, "y long, vc long")), "d": seal(spark.createDataFrame(d, "w long, vd long"))}
    joins = [(("a", "x"), ("b", "x")), (("b", "y"), ("c", "y")), (("a", "w"), ("d", "w"))]
    got = chain_aggregate(tables, joins, "a", ["g"], {"sb": ("b", "vb"), "sc": ("c", "vc"), "sd": ("d", "vd")}, "n", {"lo": ("min", "c", "vc"), "hi": ("max", "d", "vd")}, {"mean": ("b", "vb")}).reveal().collect()
    want = {}
    for p, q, r, s in met:
        sb, sc, sd, n, lo, hi = want.get(p[2], (0, 0, 0, 0, 99, 0))
        want[p[2]] = (sb + q[2], sc + r[1], sd + s[1], n + 1, min(lo, r[1]), max(hi, s[1]))
    assert {r.g: (r.sb, r.sc, r.sd, r.n, r.lo, r.hi) for r in got} == want and all(r["mean"] == r.sb // r.n for r in got)
    with pytest.raises(ValueError):
        chain_aggregate(tables, [*joins, (("c", "vc"), ("d", "vd"))], "a", ["g"], count="n")
