"""Join fused with decomposable aggregation (L594-701), in all its types.

``stacked``: both tables are stacked, clustered by key with left rows first, and one ordered pass per
group copies left columns down, sets validity and can aggregate: one exchange on the join key, which a
following aggregation on a prefix-compatible key reuses. It needs unique left keys for types that copy.
``native``: Catalyst's joins (broadcast, shuffled hash or sort-merge; adaptive execution splits skew),
after early aggregation. ``auto`` takes native if a side can be broadcast, or if nothing is aggregated
on the key; the stacked pass otherwise.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.frame import OK, Public, SealedFrame

LEFT = "__left"
TYPES = ("inner", "left", "right", "full", "semi", "anti")


def _pairs(on) -> list[tuple[str, str]]:
    if isinstance(on, str):
        return [(on, on)]
    if isinstance(on, Mapping):
        return list(on.items())
    return [(k, k) if isinstance(k, str) else tuple(k) for k in on]


def plan_bytes(df: DataFrame) -> int:
    """The optimizer's size estimate; no job runs."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def broadcast_limit(spark: SparkSession) -> int:
    """The session's broadcast threshold in bytes; 0 if broadcasts are off."""
    text = spark.conf.get("spark.sql.autoBroadcastJoinThreshold").strip().lower()
    number = text.rstrip("bkmgt")
    return max(0, int(number) << {"k": 10, "m": 20, "g": 30, "t": 40}.get(text[len(number) : len(number) + 1], 0)) if int(number) > 0 else 0


def fused_join(
    left: SealedFrame,
    right: SealedFrame,
    on,
    how: str = "inner",
    copy: Sequence[str] | None = None,
    aggs: Mapping[str, tuple] | None = None,
    agg_keys: Sequence[str] | None = None,
    extra: Column | str | None = None,
    strategy: str = "auto",
    outer_mode: str = "sql",
    trim: str = "auto",
) -> SealedFrame:
    """Join on equal keys (left name: right name); keys keep the left names; null keys meet nothing.

    how: inner, left, right and full need unique left keys in the stacked pass; semi and anti keep left
    rows and take duplicates on both sides. copy: left columns wanted (default: all). extra: a further
    condition, applied to joined rows of an inner join (L684). aggs: aggregates of the joined rows by
    ``agg_keys`` (default: the join keys). outer_mode "carrier" leaves matched left rows of left and full
    joins in place as rows of their own (L670-680). auto aggregates right rows early where that is the same. trim: in the padded tier, cut to the size of the
    right side where the public rule says so.
    """
    if how not in TYPES:
        raise ValueError(f"unknown join type {how!r}")
    pairs = _pairs(on)
    keys = [a for a, _ in pairs]
    right = right if all(a == b for a, b in pairs) else SealedFrame(right.df.withColumnsRenamed({b: a for a, b in pairs if a != b}), right.public)
    wanted = [c for c in (left.columns if copy is None else copy) if c not in keys]
    clash = set(wanted) & set(right.columns) if how not in ("semi", "anti") else set()
    if clash:
        raise ValueError(f"columns on both sides: {sorted(clash)}")
    if strategy == "auto":
        by_key = aggs is not None and set(agg_keys or keys) >= set(keys) and (how in ("semi", "anti") or left.is_unique(keys))
        small = by_key and min(plan_bytes(left.df), plan_bytes(right.df)) <= broadcast_limit(left.df.sparkSession)
        strategy = "stacked" if by_key and not small else "native"
        if left.public.tier == "padded" and (how in ("semi", "anti") or left.is_unique(keys)):
            strategy = "stacked"  # native joins drop rows
        if strategy == "stacked" and aggs and _early(left, right, keys, how, aggs, extra):
            # partial sums of the right side are formed before rows are exchanged: a heavy key is a row per task
            by = [*keys, *[c for c in agg_keys or () if c in right.columns and c not in keys]]
            right = right.aggregate(by, **aggs)
            aggs = {o: (fn if fn in ("min", "max") else "sum", o) for o, (fn, _) in aggs.items()}
    if strategy == "native":
        df = _native(left, right, keys, wanted, how)
    elif strategy == "stacked":
        if how not in ("semi", "anti") and not left.is_unique(keys):
            raise ValueError("the stacked pass needs unique left keys; aggregate one side first or use native")
        df = _stacked(left, right, keys, wanted, how, outer_mode)
    else:
        raise ValueError(f"unknown strategy {strategy!r}")
    if extra is not None:
        if how != "inner":
            raise ValueError("further conditions need an inner join")
        df = df.where(F.expr(extra) if isinstance(extra, str) else extra)
    n, m = left.public.rows, right.public.rows
    bound = n if how in ("semi", "anti") else (None if None in (n, m) else n + m if how in ("left", "full", "right") else m)
    unique = left.public.unique if how in ("semi", "anti") else right.public.unique if left.is_unique(keys) and how == "inner" else ()
    out = SealedFrame(df, Public(bound, unique, (*left.public.trace, *right.public.trace, f"join {how}"), left.public.tier))
    if out.public.tier == "padded" and how == "inner" and None not in (n, m) and left.is_unique(keys):
        from .trim import maybe_trim

        out = maybe_trim(out, n, m, trim)
    return out.aggregate(list(agg_keys or keys), **aggs) if aggs else out


def _early(left: SealedFrame, right: SealedFrame, keys: list[str], how: str, aggs: Mapping[str, tuple], extra) -> bool:
    """Whether right rows may be aggregated before an inner join with unique left keys."""
    own = lambda c: isinstance(c, str) and (c == "*" or c in right.columns)
    simple = all(fn in ("sum", "count", "min", "max") and own(c) for fn, c in aggs.values())
    return how == "inner" and extra is None and simple and left.public.tier == "clear" and left.is_unique(keys) and not set(aggs) & {*left.columns, *right.columns}


def _native(left: SealedFrame, right: SealedFrame, keys: list[str], wanted: list[str], how: str) -> DataFrame:
    a, b = left.df.where(OK).drop(OK), right.df.where(OK).drop(OK)
    if how in ("semi", "anti"):
        return a.join(b.select(*keys), keys, f"left_{how}").withColumn(OK, F.lit(True))
    return a.select(*keys, *wanted).join(b, keys, {"left": "left", "right": "right", "full": "full", "inner": "inner"}[how]).withColumn(OK, F.lit(True))


def stack(left: SealedFrame, right: SealedFrame, keys: list[str], wanted: list[str]) -> DataFrame:
    """Both sides one above the other: merged keys and validity, an origin flag, nulls elsewhere (L614)."""
    mine = left.df.select(*keys, OK, F.lit(True).alias(LEFT), *wanted)
    theirs = right.df.select(*keys, OK, F.lit(False).alias(LEFT), *[c for c in right.columns if c not in keys])
    return mine.unionByName(theirs, allowMissingColumns=True)


def _stacked(left: SealedFrame, right: SealedFrame, keys: list[str], wanted: list[str], how: str, outer_mode: str) -> DataFrame:
    usable = F.lit(True)
    for k in keys:
        usable = usable & F.col(k).isNotNull()
    if how in ("semi", "anti"):
        both = stack(left, SealedFrame(right.df.select(*keys, OK), right.public), keys, [c for c in left.columns if c not in keys])
        first = Window.partitionBy(*keys).orderBy(F.asc(LEFT)).rowsBetween(Window.unboundedPreceding, 0)  # right rows come first
        found = F.coalesce(F.max(~F.col(LEFT) & F.col(OK) & usable).over(first), F.lit(False))
        df = both.withColumn(OK, F.col(OK) & (found if how == "semi" else ~found)).where(LEFT)
        return df.select(*left.columns, OK)
    both = stack(left, right, keys, wanted)
    down = Window.partitionBy(*keys).orderBy(F.desc(LEFT)).rowsBetween(Window.unboundedPreceding, 0)
    mine = F.when(F.col(LEFT) & F.col(OK) & usable, F.struct(F.lit(True).alias("__hit"), *wanted))
    df = both.withColumn("__copied", F.first(mine, ignorenulls=True).over(down))
    matched = F.col("__copied").isNotNull()
    if how == "inner":
        valid = ~F.col(LEFT) & F.col(OK) & matched
    elif how == "right":
        valid = ~F.col(LEFT) & F.col(OK)
    else:
        if outer_mode == "sql":
            whole = Window.partitionBy(*keys)
            alone = ~F.coalesce(F.max(~F.col(LEFT) & F.col(OK) & usable).over(whole), F.lit(False))
        else:
            alone = F.lit(True)
        keep_right = matched if how == "left" else F.lit(True)
        valid = F.col(OK) & F.when(F.col(LEFT), alone).otherwise(keep_right)
    rest = [c for c in right.columns if c not in keys]
    own = [F.when(F.col(LEFT), F.col(c)).otherwise(F.col("__copied")[c]).alias(c) for c in wanted]
    df = df.withColumn(OK, valid)
    if left.public.tier == "clear":
        df = df.where(OK)
    return df.select(*keys, *own, *rest, OK)


def aggregate_join(left: SealedFrame, right: SealedFrame, on, agg_keys: Sequence[str], sums: Mapping[str, str], left_sums: Mapping[str, str] | None = None, count: str | None = None) -> SealedFrame:
    """Many-to-many: sums over joined rows without forming them (L694-701).

    The side that does not own ``agg_keys`` (left) is aggregated by the join key to a multiplicity and to
    partial sums; the other joins it as a unique table. sums: out=right column; left_sums: out=left column.
    """
    pairs = _pairs(on)
    keys = [a for a, _ in pairs]
    part = left.aggregate(keys, __mult=("count", "*"), **{f"__l_{o}": ("sum", c) for o, c in (left_sums or {}).items()})
    joined = part.join(right, on)
    outputs = {o: ("sum", F.col(c) * F.col("__mult")) for o, c in sums.items()}
    outputs |= {o: ("sum", f"__l_{o}") for o in left_sums or {}}
    if count:
        outputs[count] = ("sum", "__mult")
    return joined.aggregate(list(agg_keys), **outputs)


def cartesian_join(left: SealedFrame, right: SealedFrame, condition: Column, most_rows: int = 10_000_000, beyond: str = "refuse") -> SealedFrame:
    """The quadratic fallback for cyclic queries (L80): beyond ``most_rows`` pairs refused, or, with
    beyond="blocks", compared block by block of the two sides, where only pairs that meet the condition become rows."""
    n = left.public.rows if left.public.rows is not None else left.df.count()
    m = right.public.rows if right.public.rows is not None else right.df.count()
    if n * m > most_rows:
        if beyond != "blocks":
            raise ValueError(f"{n} x {m} rows are more than {most_rows}")
        right_side = right.df.withColumnRenamed(OK, "__ok2").hint("shuffle_replicate_nl")
        met = left.df.join(right_side, F.col(OK) & F.col("__ok2") & condition).drop("__ok2")
        return SealedFrame(met, Public(n * m, (), (*left.public.trace, *right.public.trace, "cartesian in blocks"), left.public.tier))
    df = left.df.crossJoin(right.df.withColumnRenamed(OK, "__ok2")).withColumn(OK, F.col(OK) & F.col("__ok2") & condition).drop("__ok2")
    return SealedFrame(df, Public(n * m, (), (*left.public.trace, *right.public.trace, "cartesian"), left.public.tier))


def should_trim(n: int, m: int, ell: int = 64) -> bool:
    """Whether sorting by validity to cut n+m rows to m pays (L655-656)."""
    from math import log2

    return 9 * m < n * log2(max(n, 2)) * log2(max(ell, 2))
