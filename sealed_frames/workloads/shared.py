"""Whole queries on shares: every filter, sort, group and join runs under a protocol, only the answer is opened.

Owners deal their tables by a hash of the join or group key, so that a run, one simulation of all parties,
holds about ``RUN_ROWS`` rows; runs go side by side. What they hand on stays shared: partial results, cut to
public numbers of rows, meet in a last run that opens the answer. Rows that need another key are shuffled and
dealt anew by a bucket that their owner shared with them; it is opened for all of them, valid or not, so that
nothing but the sizes of dealings becomes public. Owners share integers: days, cents, and positions in
public lists of names.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable
from dataclasses import dataclass
from math import isqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.integers import revenue
from ..plans.meter import Meter
from ..share import circuits as C
from ..share.blocks import seed_of
from ..share.join import fused_join, trim
from ..share.protocols import PROTOCOLS, Protocol, Shared
from ..share.sorting import apply_sharded_all, sharded_permutation
from ..share.table import SharedTable
from .tables import PRELUDE, day_number, table

QUERIES = {}
SQL = {}
#: Rows of all tables that a run is dealt.
RUN_ROWS = 1 << 13
#: Rows of all tables of a run that is not dealt (``tables_of``).
MOST_ROWS = 1 << 22
#: Public lists of names; a column is shared as the position in its list, from 1.
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
STATUS = ("F", "O", "P")



@dataclass(frozen=True)
class PlanOnShares:
    """``part(p, tables)`` of every run gives named partial results, ``last(p, partials)`` opens the answer of all."""

    inputs: Callable
    #: table -> column it is dealt by, None: row by row, "*": every run gets all of it
    by: dict[str, str | None]
    part: Callable
    last: Callable
    schema: str
    #: (tables, step, columns): a dealing before, whose rows come as the shared table "moved"
    first: tuple[dict[str, str | None], Callable, tuple[str, ...]] | None = None
    #: partials are added up row by row before the last run
    add: bool = False


PLANS: dict[str, PlanOnShares] = {}


def day(text: str) -> int:
    return int(np.datetime64(text, "D").astype(int))


def position(column: str, names: tuple[str, ...]):
    return F.array_position(F.array(*map(F.lit, names)), F.col(column))


def gathered(frames: dict[str, DataFrame]) -> DataFrame:
    """Rows of all tables as (table, integers)."""
    out = None
    for name, df in frames.items():
        part = df.select(F.lit(name).alias("t"), F.array(*[F.col(c).cast("long") for c in df.columns]).alias("v"))
        out = part if out is None else out.unionByName(part)
    return out


def tables_of(part: pd.DataFrame, columns: dict[str, list[str]]) -> dict[str, dict[str, np.ndarray]]:
    if len(part) > MOST_ROWS:
        raise ValueError(f"{len(part)} rows: a run on shares holds {MOST_ROWS}; use the clear tier")
    out = {}
    for name, names in columns.items():
        rows = part.loc[part["t"] == name, "v"]
        grid = np.stack(rows.to_list()) if len(rows) else np.zeros((0, len(names)))
        out[name] = dict(zip(names, grid.astype(np.int64).T.copy() if len(rows) else np.zeros((len(names), 0), np.int64)))
    return out


def _dealt(frames: dict[str, DataFrame], by: dict[str, str | None], n: int) -> DataFrame:
    """Rows of all tables as (run, table, integers), each in its run."""
    width = max(len(df.columns) for df in frames.values())
    out = None
    for at, (name, df) in enumerate(frames.items()):
        key = by[name]
        if key == "*":
            run = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
        else:
            run = F.pmod(F.monotonically_increasing_id() if key is None else F.xxhash64(key), F.lit(n))
        columns = [F.col(c).cast("long") for c in df.columns] + [F.lit(0).cast("long")] * (width - len(df.columns))
        part = df.select(run.alias("run"), F.lit(at).alias("t"), *(c.alias(f"c{i}") for i, c in enumerate(columns)))
        out = part if out is None else out.unionByName(part)
    return out.repartition(min(n, 2048), "run")


def _columns(part: pd.DataFrame, columns: dict[str, list[str]]) -> dict[str, dict[str, np.ndarray]]:
    table = part["t"].to_numpy()
    return {name: {c: part[f"c{i}"].to_numpy()[table == at].astype(np.int64) for i, c in enumerate(names)} for at, (name, names) in enumerate(columns.items())}


def _run_count(frames: dict[str, DataFrame], by: dict[str, str | None]) -> int:
    counts = {k: df.count() for k, df in frames.items()}
    copied = sum(c for k, c in counts.items() if by[k] == "*")
    return max(1, -(-(sum(counts.values()) - copied) // max(RUN_ROWS, 2 * copied)))


_METER = ("sorts", "rounds", "bits", "peak_rows")


def _costs(p: Protocol) -> list[int]:
    return [p.meter.gates["sort"], p.meter.rounds, p.meter.bits, p.meter.peak_rows]


def _side_by_side(costs: list[list[int]]) -> list[int]:
    """Runs at the same time: bits add up, sorts and rounds are those of the longest."""
    grid = np.array(costs or [[0] * 4])
    return [int(grid[:, 0].max()), int(grid[:, 1].max()), int(grid[:, 2].sum()), int(grid[:, 3].max())]


def _one_after_another(a: list[int], b: list[int]) -> list[int]:
    return [a[0] + b[0], a[1] + b[1], a[2] + b[2], max(a[3], b[3])]


def _packed(t: SharedTable) -> dict:
    return {c: (s.terms, s.boolean) for c, s in (t.columns | {"ok": t.ok}).items()}


def _joined(p: Protocol, parts: list[dict]) -> SharedTable:
    """Partials under each other."""
    columns = {c: Shared(np.concatenate([x[c][0] for x in parts], axis=1), parts[0][c][1]) for c in parts[0]}
    ok = columns.pop("ok")
    return SharedTable(p, columns, ok)


def _added(parts: list[dict]) -> dict:
    """Partials with the same rows in the same order: arithmetic shares add up, the others are taken once."""
    return {c: (x if boolean else np.sum([y[c][0] for y in parts], axis=0, dtype=np.uint64), boolean) for c, (x, boolean) in parts[0].items()}


def _moved(step: Callable, columns: dict[str, list[str]], names: tuple[str, ...], protocols: tuple[str, ...], terms: int):
    """A run of the dealing before, under one protocol after the other: rows of shares, filled up to ``terms`` terms,
    the opened run they go to, and on the first row the costs."""

    def under(protocol: str, number: int, part: pd.DataFrame, given: dict) -> pd.DataFrame:
        p = PROTOCOLS[protocol](seed_of(number, len(part), 1), Meter(protocol))
        table, run = step(p, given)
        p.verify()
        out = {"run": run, "protocol": protocol}
        for c in names:
            s = table.ok if c == "ok" else table[c]
            out |= {f"{c}_{i}": x.view(np.int64) for i, x in enumerate(s.terms)} | {f"{c}_{i}": 0 for i in range(p.n, terms)}
        out = pd.DataFrame(out)
        for c, x in zip(_METER, _costs(p)):
            out[c] = np.where(np.arange(len(out)) == 0, x, 0)
        return out

    def one(part: pd.DataFrame) -> pd.DataFrame:
        number, given = int(part["run"].iloc[0]), _columns(part, columns)
        return pd.concat([under(protocol, number, part, given) for protocol in protocols], ignore_index=True)

    return one


def execute(spark, sf_dir: str, name: str, protocols: tuple[str, ...] = ("3p",), metered: bool = False) -> DataFrame:
    """The answer under every protocol, or what its runs cost. Tables are dealt once: a run goes through all protocols."""
    from .micro import _importable

    _importable(spark)
    plan = PLANS[name]
    frames = plan.inputs(lambda t: table(spark, sf_dir, t).df.drop("__ok"))
    part, last, add = plan.part, plan.last, plan.add
    terms = max(PROTOCOLS[protocol](1).n for protocol in protocols)
    fields = [f.split()[0] for f in plan.schema.split(", ")]
    before, names = None, ()
    if plan.first:
        by, step, names = plan.first
        early = {k: frames.pop(k) for k in by}
        rows = {**{k: df for k, df in frames.items()}, **{k: df for k, df in early.items() if k == "orders"}}
        n = _run_count(rows, dict.fromkeys(rows, "k"))
        early["orders"] = early["orders"].withColumn("to", F.pmod(F.xxhash64("k"), F.lit(n)))
        schema = "run long, protocol string, " + ", ".join(f"{c} long" for c in [*(f"{c}_{i}" for c in names for i in range(terms)), *_METER])
        before = _dealt(early, by, _run_count(early, by)).groupBy("run").applyInPandas(_moved(step, {k: v.columns for k, v in early.items()}, names, protocols, terms), schema)
    else:
        n = _run_count(frames, plan.by)
    columns = {k: v.columns for k, v in frames.items()}

    def under(protocol: str, run: int, rows: pd.DataFrame, given: dict, moved: pd.DataFrame | None) -> bytes:
        p = PROTOCOLS[protocol](seed_of(run, len(rows), 2), Meter(protocol))
        earlier = [0] * 4
        if moved is not None:
            moved = moved[moved["protocol"] == protocol]
            shares = {c: Shared(np.stack([moved[f"{c}_{i}"].to_numpy().astype(np.int64).view(np.uint64) for i in range(p.n)]), True) for c in names}
            given = given | {"moved": SharedTable(p, shares, shares.pop("ok"))}
            earlier = _side_by_side(moved[list(_METER)].to_numpy().tolist())
        out = {k: _packed(t) for k, t in part(p, given).items()}
        p.verify()
        return pickle.dumps((out, _costs(p), earlier))

    def partial(rows: pd.DataFrame, moved: pd.DataFrame | None = None) -> pd.DataFrame:
        run, given = int((rows if len(rows) else moved)["run"].iloc[0]), _columns(rows, columns)
        return pd.DataFrame({"protocol": protocols, "run": run, "body": [under(protocol, run, rows, given, moved) for protocol in protocols]})

    def opened(parts: pd.DataFrame) -> tuple:
        got = [pickle.loads(x) for x in parts["body"]]
        tables = {k: [x[0][k] for x in got] for k in got[0][0]}
        return tables, _side_by_side([x[1] for x in got]), _side_by_side([x[2] for x in got])

    def some(parts: pd.DataFrame) -> pd.DataFrame:
        tables, costs, earlier = opened(parts)
        return pd.DataFrame({"protocol": parts["protocol"].iloc[:1], "run": [0], "body": [pickle.dumps(({k: _added(v) for k, v in tables.items()}, costs, earlier))]})

    def final(parts: pd.DataFrame) -> pd.DataFrame:
        protocol = parts["protocol"].iloc[0]
        tables, costs, earlier = opened(parts)
        p = PROTOCOLS[protocol](seed_of(len(parts), len(name), 3), Meter(protocol))
        answer = pd.DataFrame(last(p, {k: _joined(p, [_added(v)] if add else v) for k, v in tables.items()}))
        if not metered:
            return answer[fields]
        total = _one_after_another(_one_after_another(earlier, costs), _costs(p))
        return pd.DataFrame({"query": [name], "protocol": [protocol]} | {c: [x] for c, x in zip(_METER, total)})

    dealt, schema = _dealt(frames, plan.by, n), "protocol string, run long, body binary"
    if before is None:
        done = dealt.groupBy("run").applyInPandas(lambda rows: partial(rows), schema)
    else:
        done = dealt.groupBy("run").cogroup(before.groupBy("run")).applyInPandas(lambda rows, moved: partial(rows, moved), schema)
    if add and n > 4:
        done = done.groupBy("protocol", F.pmod("run", F.lit(isqrt(n))).alias("some")).applyInPandas(some, schema)
    schema = "query string, protocol string, sorts long, rounds long, bits long, peak_rows long" if metered else plan.schema
    return done.groupBy("protocol").applyInPandas(final, schema)


def shared_query(sql: str, schema: str):
    """Registers a plan: (name, inputs, dealing, part, last, more of ``PlanOnShares``)."""

    def keep(plan):
        name, inputs, by, part, last, *more = plan
        PLANS[name] = PlanOnShares(inputs, by, part, last, schema, **(more[0] if more else {}))
        QUERIES[name] = lambda spark, sf_dir: execute(spark, sf_dir, name)
        SQL[name] = PRELUDE + sql
        return plan

    return keep


def _single(p: Protocol, **columns: Shared) -> SharedTable:
    """A table of one row."""
    return SharedTable(p, columns, p.public(np.ones(1, np.int64), True))


def _bit(p: Protocol, t: SharedTable, name: str, value: int, bits: int = 4) -> Shared:
    return C.equal(p, t[name], t.const(value), bits)


def _named(values: np.ndarray, names: tuple[str, ...]) -> list[str]:
    return [names[v - 1] for v in values]


def _q6(p, t):
    lines = SharedTable.of(p, t["lines"], ("price", "disc_a"))
    lines = lines.where(lines.at_least("ship", day("1997-01-01")), lines.below("ship", day("1998-01-01")), lines.at_least("disc", 5, 8), lines.below("disc", 8, 8), lines.below("qty", 24, 8))
    lines = lines.with_col("part", p.mul(lines["price"], lines["disc_a"]))
    return {"sum": _single(p, s=lines.total({"s": ("sum", "part")})["s"])}


def _q6_last(p, t):
    return {"revenue": p.open(t["sum"].total({"s": ("sum", "s")})["s"]).view(np.int64)}


shared_query("SELECT CAST(coalesce(sum(price * disc), 0) AS BIGINT) AS revenue FROM L WHERE ship >= DATE '1997-01-01' AND ship < DATE '1998-01-01' AND disc BETWEEN 5 AND 7 AND qty < 24", "revenue long")((
    "tpch_q06_share", lambda t: {"lines": t("lineitem").select(day_number("ship").alias("ship"), "disc", F.col("disc").alias("disc_a"), "qty", "price")}, {"lines": None}, _q6, _q6_last,
))


def _q4(p, t):
    orders = SharedTable.of(p, t["orders"])
    orders = orders.where(orders.at_least("date", day("1997-07-01")), orders.below("date", day("1997-10-01"))).project("k", "priority")
    late = SharedTable.of(p, t["lines"])
    late = late.where(_bit(p, late, "returned", 1)).project("k")
    counts = orders.join(late, "k", "semi", trim_rows=True).group("priority", {"n": ("count", None)}, 3)
    return {"counts": counts.trimmed(8)}  # three bits


def _q4_last(p, t):
    out = t["counts"].group("priority", {"n": ("sum", "n")}, 3).reveal()
    return {"o_orderpriority": _named(out["priority"], PRIORITIES), "n": out["n"]}


shared_query("SELECT o_orderpriority, count(*) AS n FROM O WHERE o_date >= DATE '1997-07-01' AND o_date < DATE '1997-10-01' AND EXISTS (SELECT 1 FROM L WHERE l_orderkey = o_orderkey AND l_returnflag = 'R') GROUP BY ALL", "o_orderpriority string, n long")((
    "tpch_q04_share",
    lambda t: {
        "orders": t("orders").select(F.col("o_orderkey").alias("k"), day_number("o_date").alias("date"), position("o_orderpriority", PRIORITIES).alias("priority")),
        "lines": t("lineitem").select(F.col("l_orderkey").alias("k"), (F.col("l_returnflag") == "R").cast("int").alias("returned")),
    },
    {"orders": "k", "lines": "k"}, _q4, _q4_last,
))


def _q12(p, t):
    orders = SharedTable.of(p, t["orders"])
    lines = SharedTable.of(p, t["lines"])
    lines = lines.where(lines.at_least("ship", day("1997-01-01")), lines.below("ship", day("1998-01-01"))).project("k", "status")
    met = orders.join(lines, "k", trim_rows=True)
    high = C.bit_to_arithmetic(p, met.below("priority", 3, 4))
    met = met.with_col("h", high).with_col("l", p.sub(p.public(np.ones(len(met), np.int64), False), high))
    return {"counts": met.group("status", {"high": ("sum", "h"), "low": ("sum", "l")}, 3).trimmed(8)}


def _q12_last(p, t):
    out = t["counts"].group("status", {"high": ("sum", "high"), "low": ("sum", "low")}, 3).reveal()
    return {"l_linestatus": _named(out["status"], STATUS), "high": out["high"], "low": out["low"]}


shared_query("""SELECT l_linestatus, CAST(sum(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END) AS BIGINT) AS high, CAST(sum(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 0 ELSE 1 END) AS BIGINT) AS low
  FROM O JOIN L ON o_orderkey = l_orderkey WHERE ship >= DATE '1997-01-01' AND ship < DATE '1998-01-01' GROUP BY ALL""", "l_linestatus string, high long, low long")((
    "tpch_q12_share",
    lambda t: {
        "orders": t("orders").select(F.col("o_orderkey").alias("k"), position("o_orderpriority", PRIORITIES).alias("priority")),
        "lines": t("lineitem").select(F.col("l_orderkey").alias("k"), day_number("ship").alias("ship"), position("l_linestatus", STATUS).alias("status")),
    },
    {"orders": "k", "lines": "k"}, _q12, _q12_last,
))


def _q13(p, t):
    customers = SharedTable.of(p, t["customers"])
    orders = SharedTable.of(p, t["orders"])
    orders = orders.where(_bit(p, orders, "status", 1), _bit(p, orders, "priority", 1)).project("k")
    per = customers.join(orders, "k", "left", {"n": ("count", "k")}, trim_rows=True)
    per = per.with_col("n_orders", C.to_boolean(p, per["n"], 20)).project("n_orders")
    # d different numbers of orders take d (d - 1) / 2 orders at least
    return {"counts": per.group("n_orders", {"n_customers": ("count", None)}, 20).trimmed(isqrt(2 * len(orders)) + 2)}


def _q13_last(p, t):
    return t["counts"].group("n_orders", {"n_customers": ("sum", "n_customers")}, 20).reveal()


shared_query("SELECT n_orders, count(*) AS n_customers FROM (SELECT c_custkey, count(o_orderkey) AS n_orders FROM C LEFT JOIN O ON c_custkey = o_custkey AND o_orderstatus = 'F' AND o_orderpriority = '1-URGENT' GROUP BY ALL) GROUP BY ALL", "n_orders long, n_customers long")((
    "tpch_q13_share",
    lambda t: {
        "customers": t("customer").select(F.col("c_custkey").alias("k")),
        "orders": t("orders").select(F.col("o_custkey").alias("k"), position("o_orderstatus", STATUS).alias("status"), position("o_orderpriority", PRIORITIES).alias("priority")),
    },
    {"customers": "k", "orders": "k"}, _q13, _q13_last,
))


def _q3_first(p, t):
    """Orders with the bit whether they count, all of them, shuffled, and the runs they go to."""
    customers = SharedTable.of(p, t["customers"])
    customers = customers.where(_bit(p, customers, "building", 1)).project("c")
    orders = SharedTable.of(p, t["orders"])
    orders = orders.where(orders.below("date", day("1998-03-15")))
    met = fused_join(p, orders.columns | {"ok": orders.ok}, customers.columns | {"ok": customers.ok}, "c", "semi")
    kept = {c: met[c] for c in ("k", "date", "priority", "to")} | {"met": met["ok"], "ok": p.mask(p.not_(met["origin"]), 1)}
    kept = trim(p, kept, len(orders))
    names = ("k", "date", "priority", "met", "to")
    moved = dict(zip(names, apply_sharded_all(p, sharded_permutation(p, len(orders), 71), [kept[c] for c in names])))
    run = p.open(moved.pop("to")).view(np.int64)
    ok = moved.pop("met")
    return SharedTable(p, moved, ok), run


def _q3(p, t):
    lines = SharedTable.of(p, t["lines"], ("rev",))
    lines = lines.where(lines.at_least("ship", day("1998-03-15") + 1)).project("k", "rev")
    sums = t["moved"].project("k", "date", "priority").join(lines, "k", aggs={"r": ("sum", "rev")}, trim_rows=True)
    sums = sums.with_col("revenue", C.to_boolean(p, sums["r"], 40))
    return {"best": sums.project("k", "date", "priority", "revenue").top(10, [("revenue", "desc"), ("k", "asc")], 40)}


def _q3_last(p, t):
    out = t["best"].top(10, [("revenue", "desc"), ("k", "asc")], 40).reveal()
    return {"l_orderkey": out["k"], "o_day": out["date"], "o_orderpriority": _named(out["priority"], PRIORITIES), "revenue": out["revenue"]}


shared_query("""SELECT l_orderkey, CAST(date_diff('day', DATE '1970-01-01', o_date) AS BIGINT) AS o_day, o_orderpriority, CAST(sum(rev) AS BIGINT) AS revenue FROM C JOIN O ON c_custkey = o_custkey JOIN L ON l_orderkey = o_orderkey
  WHERE c_mktsegment = 'BUILDING' AND o_date < DATE '1998-03-15' AND ship > DATE '1998-03-15' GROUP BY ALL ORDER BY revenue DESC, l_orderkey LIMIT 10""", "l_orderkey long, o_day long, o_orderpriority string, revenue long")((
    "tpch_q03_share",
    lambda t: {
        "customers": t("customer").select(F.col("c_custkey").alias("c"), (F.col("c_mktsegment") == "BUILDING").cast("int").alias("building")),
        "orders": t("orders").select(F.col("o_orderkey").alias("k"), F.col("o_custkey").alias("c"), day_number("o_date").alias("date"), position("o_orderpriority", PRIORITIES).alias("priority")),
        "lines": t("lineitem").select(F.col("l_orderkey").alias("k"), day_number("ship").alias("ship"), revenue().alias("rev")),
    },
    {"lines": "k"}, _q3, _q3_last, {"first": ({"customers": "c", "orders": "c"}, _q3_first, ("k", "date", "priority", "ok"))},
))


def _q15(p, t):
    lines = SharedTable.of(p, t["lines"], ("rev",))
    lines = lines.where(lines.at_least("ship", day("1997-01-01")), lines.below("ship", day("1997-04-01"))).project("k", "rev")
    sums = lines.group("k", {"r": ("sum", "rev")})
    sums = sums.with_col("total", C.to_boolean(p, sums["r"], 48)).project("k", "total")
    suppliers = SharedTable.of(p, t["suppliers"])
    return {"best": _single(p, total=sums.maximum("total", 48)), "totals": suppliers.join(sums, "k", trim_rows=True).trimmed(len(suppliers))}


def _q15_last(p, t):
    best, totals = t["best"].maximum("total", 48), t["totals"]
    out = totals.where(C.equal(p, totals["total"], Shared(np.repeat(best.terms, len(totals), axis=1), True), 48)).reveal()
    return {"s_suppkey": out["k"], "total": out["total"]}


shared_query("SELECT s_suppkey, CAST(total AS BIGINT) AS total FROM (SELECT * FROM (SELECT l_suppkey, sum(rev) AS total FROM L WHERE ship >= DATE '1997-01-01' AND ship < DATE '1997-04-01' GROUP BY ALL) QUALIFY total = max(total) OVER ()) JOIN S ON l_suppkey = s_suppkey", "s_suppkey long, total long")((
    "tpch_q15_share",
    lambda t: {
        "lines": t("lineitem").select(F.col("l_suppkey").alias("k"), day_number("ship").alias("ship"), revenue().alias("rev")),
        "suppliers": t("supplier").select(F.col("s_suppkey").alias("k")),
    },
    {"lines": "k", "suppliers": "k"}, _q15, _q15_last,
))


def _q21(p, t):
    lines = SharedTable.of(p, t["lines"])
    late, most = _bit(p, lines, "returned", 1), (1 << 30) - 1
    lines = lines.with_col("lo", C.choose(p, late, lines.const(most), lines["s"])).with_col("hi", C.choose(p, late, lines.const(0), lines["s"])).with_col("late", C.bit_to_arithmetic(p, late))
    spans = lines.group("k", {"a": ("min", "s"), "b": ("max", "s"), "c": ("min", "lo"), "d": ("max", "hi"), "n": ("sum", "late")}, value_bits=30)
    spans = spans.where(C.not_equal(p, spans["a"], spans["b"], 30), C.equal(p, spans["c"], spans["d"], 30)).project("k", "c", "n")
    orders = SharedTable.of(p, t["orders"])
    orders = orders.where(_bit(p, orders, "status", 1)).project("k")
    waits = spans.join(orders, "k", "semi", trim_rows=True).trimmed(len(orders)).project("n", s="c")
    suppliers = SharedTable.of(p, t["suppliers"])
    # every run's rows are those of all suppliers, by key
    return {"waits": suppliers.join(waits, "s", "left", {"w": ("sum", "n")}, trim_rows=True)}


def _q21_last(p, t):
    waits = t["waits"]
    waits = waits.with_col("waiting", C.to_boolean(p, waits["w"], 30)).project("s", "waiting")
    out = waits.where(C.not_equal(p, waits["waiting"], waits.const(0), 30)).top(100, [("waiting", "desc"), ("s", "asc")], 31).reveal()
    return {"s_suppkey": out["s"], "waiting": out["waiting"]}


shared_query("""SELECT s_suppkey, count(*) AS waiting FROM L l1 JOIN O ON l1.l_orderkey = o_orderkey JOIN S ON l1.l_suppkey = s_suppkey WHERE o_orderstatus = 'F' AND l1.l_returnflag = 'R'
  AND EXISTS (SELECT 1 FROM L l2 WHERE l2.l_orderkey = l1.l_orderkey AND l2.l_suppkey <> l1.l_suppkey)
  AND NOT EXISTS (SELECT 1 FROM L l3 WHERE l3.l_orderkey = l1.l_orderkey AND l3.l_suppkey <> l1.l_suppkey AND l3.l_returnflag = 'R')
  GROUP BY ALL ORDER BY waiting DESC, s_suppkey LIMIT 100""", "s_suppkey long, waiting long")((
    "tpch_q21_share",
    lambda t: {
        "lines": t("lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_suppkey").alias("s"), (F.col("l_returnflag") == "R").cast("int").alias("returned")),
        "orders": t("orders").select(F.col("o_orderkey").alias("k"), position("o_orderstatus", STATUS).alias("status")),
        "suppliers": t("supplier").select(F.col("s_suppkey").alias("s")),
    },
    {"lines": "k", "orders": "k", "suppliers": "*"}, _q21, _q21_last, {"add": True},
))


def _metered(spark, sf_dir):
    """What runs of the queries above cost, by protocol: sorts and rounds of the longest runs of every step, bits of
    all runs, and the largest table."""
    out = None
    for name in PLANS:
        done = execute(spark, sf_dir, name, tuple(PROTOCOLS), metered=True)
        out = done if out is None else out.unionByName(done)
    return out


QUERIES["meter_shared_queries"] = _metered
