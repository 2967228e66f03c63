"""Group-by aggregation and distinct, as partial and combining steps (L35-38, L353-357, L690-692)."""

from __future__ import annotations

from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, Window
from pyspark.sql import functions as F

from ..core.frame import OK, Public, SealedFrame


@dataclass(frozen=True)
class Decomposable:
    """An aggregate that splits: ``pre`` makes partials of rows, ``post`` combines partials, ``final`` ends.

    pre: row column -> {part: aggregate column}; post: part name -> aggregate over that part;
    final: {part: column} -> column. Combining must be associative (L692).
    """

    pre: Callable[[Column], dict[str, Column]]
    post: Callable[[str, Column], Column]
    final: Callable[[dict[str, Column]], Column]


def _sum_all(_: str, c: Column) -> Column:
    return F.sum(c)


SUM = Decomposable(lambda c: {"s": F.sum(c)}, _sum_all, lambda p: p["s"])
COUNT = Decomposable(lambda c: {"n": F.count(c)}, _sum_all, lambda p: p["n"])
MIN = Decomposable(lambda c: {"m": F.min(c)}, lambda _, c: F.min(c), lambda p: p["m"])
MAX = Decomposable(lambda c: {"m": F.max(c)}, lambda _, c: F.max(c), lambda p: p["m"])
#: Truncated average of non-negative integers.
AVG = Decomposable(lambda c: {"s": F.sum(c), "n": F.count(c)}, _sum_all, lambda p: F.call_function("div", p["s"], p["n"]))
#: n * sum of squares - square of the sum, over n squared: the population variance's parts.
VARIANCE = Decomposable(
    lambda c: {"n": F.count(c), "s": F.sum(c), "q": F.sum(c * c)}, _sum_all, lambda p: (p["n"] * p["q"] - p["s"] * p["s"]) / (p["n"] * p["n"])
)
BUILT_IN = {"sum": SUM, "count": COUNT, "min": MIN, "max": MAX, "avg": AVG, "variance": VARIANCE}


def aggregate(frame: SealedFrame, keys: Sequence[str], outputs: Mapping[str, tuple]) -> SealedFrame:
    """out=(function, column): map-side partials, one exchange on the keys, combining.

    Without keys one row comes out. A function is a name or a Decomposable; column "*" counts rows. In the
    padded tier every row stays, and the first one of each group of valid rows carries its aggregates (L353).
    """
    pre, final = [c.alias(name) for name, c in _columns(outputs)], []
    for out, (fn, _) in outputs.items():
        rule = BUILT_IN[fn] if isinstance(fn, str) else fn
        final.append(rule.final({p: F.col(f"__{out}_{p}") for p in rule.pre(F.lit(1))}).alias(out))
    if keys and frame.public.tier == "padded":
        whole = Window.partitionBy(OK, *keys)
        parts = [_over(c, whole) for c in _columns(outputs)]
        first = F.row_number().over(whole.orderBy(*keys)) == 1
        df = frame.df.select(*keys, *parts, (F.col(OK) & first).alias(OK)).select(*keys, *final, OK)
    else:
        grouped = frame.df.where(OK).groupBy(*keys).agg(*pre)
        df = grouped.select(*keys, *final, F.lit(True).alias(OK))
    unique = (frozenset(keys),)
    rows = 1 if not keys else frame.public.rows
    return SealedFrame(df, Public(rows, unique, (*frame.public.trace, "aggregate"), frame.public.tier))


def _columns(outputs: Mapping[str, tuple]) -> list[tuple[str, Column]]:
    """Partial aggregates of all outputs, by name."""
    out = []
    for name, (fn, source) in outputs.items():
        rule = BUILT_IN[fn] if isinstance(fn, str) else fn
        value = source if not isinstance(source, str) else F.lit(1) if source == "*" else F.col(source)
        out += [(f"__{name}_{part}", c) for part, c in rule.pre(value).items()]
    return out


def _over(part: tuple[str, Column], window) -> Column:
    return part[1].over(window).alias(part[0])


def partials(frame: SealedFrame, keys: Sequence[str], outputs: Mapping[str, tuple]) -> SealedFrame:
    """Only the partial step: columns out__part, to be combined later by ``combine``."""
    if not isinstance(frame, SealedFrame):
        return frame.partials(keys, outputs)
    pre = [c.alias(f"{out}__{p}") for out, (fn, source) in outputs.items() for p, c in BUILT_IN[fn].pre(F.lit(1) if source == "*" else F.col(source)).items()]
    df = frame.df.where(OK).groupBy(*keys).agg(*pre).withColumn(OK, F.lit(True))
    return SealedFrame(df, Public(frame.public.rows, (frozenset(keys),), (*frame.public.trace, "partials"), frame.public.tier))


def combine(frame: SealedFrame, keys: Sequence[str], outputs: Mapping[str, str]) -> SealedFrame:
    """Combine partials of several frames (stacked) and finish: out=function name."""
    if not isinstance(frame, SealedFrame):
        return frame.combine(keys, outputs)
    post, final = [], []
    for out, fn in outputs.items():
        rule = BUILT_IN[fn]
        names = [c.split("__")[1] for c in frame.df.columns if c.startswith(f"{out}__")]
        post += [rule.post(p, F.col(f"{out}__{p}")).alias(f"__{out}_{p}") for p in names]
        final.append(rule.final({p: F.col(f"__{out}_{p}") for p in names}).alias(out))
    df = frame.df.where(OK).groupBy(*keys).agg(*post).select(*keys, *final, F.lit(True).alias(OK))
    return SealedFrame(df, Public(frame.public.rows, (frozenset(keys),), (*frame.public.trace, "combine"), frame.public.tier))


def aggregate_in_place(frame: SealedFrame, keys: Sequence[str], outputs: Mapping[str, tuple], order: Sequence[str]) -> SealedFrame:
    """The size-preserving form: every row stays, the last valid row of a group carries the totals (L353, E13)."""
    running = Window.partitionBy(OK, *keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    df = frame.df
    for out, (fn, source) in outputs.items():
        value = F.lit(1) if source == "*" else F.col(source)
        df = df.withColumn(out, getattr(F, fn)(value).over(running))
    last = F.lead(F.lit(1)).over(Window.partitionBy(OK, *keys).orderBy(*order)).isNull()
    return SealedFrame(df.withColumn(OK, F.col(OK) & last), frame.public.after("aggregate_in_place"))


def distinct(frame: SealedFrame, keys: Sequence[str]) -> SealedFrame:
    """Distinct keys. Clear: hash aggregation; padded: the first row of each run stays valid (L350)."""
    if frame.public.tier == "clear":
        df = frame.df.where(OK).select(*keys).distinct().withColumn(OK, F.lit(True))
        return SealedFrame(df, Public(frame.public.rows, (frozenset(keys),), (*frame.public.trace, "distinct"), "clear"))
    return mark_first(frame, keys).project(*keys)


def mark_first(frame: SealedFrame, keys: Sequence[str]) -> SealedFrame:
    """One valid row per valid key; no row leaves."""
    rank = F.row_number().over(Window.partitionBy(OK, *keys).orderBy(*keys))
    return SealedFrame(frame.df.withColumn("__rank", rank).withColumn(OK, F.col(OK) & (F.col("__rank") == 1)).drop("__rank"), frame.public.after("mark_first"))
