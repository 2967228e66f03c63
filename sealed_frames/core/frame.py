"""Sealed frames: a DataFrame with a validity column, and what is public about it.

Rows that a filter or a join rules out stay in the frame with a false validity (L348-350); only
``reveal`` drops them. ``public`` holds what everybody may know: an upper bound of the row count, unique
keys, and the operations so far. In the clear tier Catalyst may use validity to prune early; the padded
tier keeps every intermediate at its public size.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OK = "__ok"


@dataclass(frozen=True)
class Public:
    rows: int | None = None
    unique: tuple[frozenset[str], ...] = ()
    trace: tuple[str, ...] = ()
    tier: str = "clear"

    def after(self, step: str, **changes) -> Public:
        return replace(self, trace=(*self.trace, step), **changes)


@dataclass(frozen=True)
class SealedFrame:
    df: DataFrame
    public: Public = field(default_factory=Public)

    @property
    def columns(self) -> list[str]:
        return [c for c in self.df.columns if c != OK]

    def is_unique(self, keys: Sequence[str]) -> bool:
        return any(u <= set(keys) for u in self.public.unique)

    # -- row-wise operators: narrow, no exchange -------------------------------------------------

    def filter(self, condition: Column | str) -> SealedFrame:
        """Rule out rows where the condition is not true; the row count stays (L14, L350)."""
        condition = F.expr(condition) if isinstance(condition, str) else condition
        if self.public.tier == "clear":
            return replace(self, df=self.df.where(condition), public=self.public.after("filter"))
        kept = F.col(OK) & F.coalesce(condition, F.lit(False))
        return replace(self, df=self.df.withColumn(OK, kept), public=self.public.after("filter"))

    def with_col(self, name: str, value: Column | str) -> SealedFrame:
        value = F.expr(value) if isinstance(value, str) else value
        return replace(self, df=self.df.withColumn(name, value), public=self.public.after("with_col"))

    def assign_if(self, condition: Column, name: str, value: Column) -> SealedFrame:
        """Branch-free assignment: the column is rewritten on every row (L263-273)."""
        return self.with_col(name, F.when(F.coalesce(condition, F.lit(False)), value).otherwise(F.col(name)))

    def project(self, *columns: str | Column) -> SealedFrame:
        return replace(self, df=self.df.select(*columns, OK), public=self.public.after("project"))

    def rename(self, **names: str) -> SealedFrame:
        """new=old pairs."""
        old = {o: n for n, o in names.items()}
        unique = tuple(frozenset(old.get(c, c) for c in u) for u in self.public.unique)
        return replace(self, df=self.df.withColumnsRenamed(old), public=replace(self.public, unique=unique))

    def pad_to(self, rows: int) -> SealedFrame:
        """Owners fill up to a public size with rows that are not valid (L348)."""
        have = self.public.rows if self.public.rows is not None else self.df.count()
        if rows < have:
            raise ValueError("a frame can't be padded below its public size")
        blank = self.df.sparkSession.range(rows - have).select(*[F.lit(None).cast(f.dataType).alias(f.name) for f in self.df.schema if f.name != OK], F.lit(False).alias(OK))
        return replace(self, df=self.df.unionByName(blank), public=self.public.after("pad", rows=rows))

    # -- operators of their own modules ----------------------------------------------------------

    def aggregate(self, keys: Sequence[str], **outputs) -> SealedFrame:
        from ..operators.aggregate import aggregate

        return aggregate(self, keys, outputs)

    def distinct(self, *keys: str) -> SealedFrame:
        from ..operators.aggregate import distinct

        return distinct(self, keys)

    def join(self, right: SealedFrame, on, how: str = "inner", **options) -> SealedFrame:
        from ..operators.fused_join import fused_join

        return fused_join(self, right, on, how, **options)

    def attach_scalar(self, one: SealedFrame) -> SealedFrame:
        """Put the single row of a global aggregate beside every row: a broadcast of one row."""
        row = F.broadcast(one.df.where(OK).drop(OK).limit(1))
        return replace(self, df=self.df.crossJoin(row), public=self.public.after("attach_scalar"))

    def sort(self, *order: str | Column) -> SealedFrame:
        """Valid rows first, then by the keys; 'name desc' or 'name' (L106, L555)."""
        return replace(self, df=self.df.orderBy(F.desc(OK), *[_direction(o) for o in order]), public=self.public.after("sort"))

    def limit(self, k: int, *order: str | Column) -> SealedFrame:
        """The first k rows of the order: a top-k per task, then of those (L107)."""
        return replace(self, df=self.df.orderBy(F.desc(OK), *[_direction(o) for o in order]).limit(k), public=self.public.after("limit", rows=k))

    def concat(self, other: SealedFrame) -> SealedFrame:
        """Rows of both, columns either lacks filled with nulls (L614)."""
        rows = None if None in (self.public.rows, other.public.rows) else self.public.rows + other.public.rows
        return replace(self, df=self.df.unionByName(other.df, allowMissingColumns=True), public=Public(rows, (), (*self.public.trace, *other.public.trace, "concat"), self.public.tier))

    def reveal(self) -> DataFrame:
        """What the analyst gets: valid rows, without the validity (L66, L348)."""
        return self.df.where(OK).drop(OK)


def _direction(order: str | Column) -> Column:
    if isinstance(order, Column):
        return order
    name, _, way = order.partition(" ")
    return F.desc(name) if way == "desc" else F.asc(name)


def seal(df: DataFrame, unique: Sequence[Sequence[str]] = (), rows: int | None = None, tier: str = "clear") -> SealedFrame:
    """Every row valid; unique: keys the analyst knows to be unique."""
    return SealedFrame(df.withColumn(OK, F.lit(True)), Public(rows, tuple(frozenset(u) for u in unique), ("seal",), tier))
