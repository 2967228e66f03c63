"""Cutting a padded join result back to the size of its right side (L651-657)."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..core.frame import OK, SealedFrame
from ..core.position import beside, prefix_sums
from ..core.session import checkpointed
from .fused_join import should_trim


def maybe_trim(frame: SealedFrame, n: int, m: int, when: str = "auto", ell: int = 64) -> SealedFrame:
    """All valid rows and as many others as make m rows: exact where at most m rows can be valid (inner joins
    with unique left keys). when: always, never, or auto, the rule on the public sizes.

    The others are taken by their number among all partitions' rows that are not valid; no task holds them all."""
    if when == "never" or (when == "auto" and not should_trim(n, m, ell)):
        return frame
    dealt = checkpointed(frame.df.withColumn("__part", F.spark_partition_id().cast("long")))
    counts = dealt.groupBy("__part").agg(F.count_if(~F.col(OK)).alias("__n"), F.count_if(OK).alias("__v"))
    parts = (counts.agg(F.max("__part")).first()[0] or 0) + 1
    valid = F.broadcast(counts.agg(F.coalesce(F.sum("__v"), F.lit(0)).alias("__all")))  # one row: the plan does not show it
    rank = F.row_number().over(Window.partitionBy("__part", OK).orderBy(F.lit(0)))
    placed = beside(dealt.withColumn("__r", rank), prefix_sums(counts, "__part", "__n", parts), ["__part"], parts)
    kept = placed.crossJoin(valid).where(F.col(OK) | (F.col("__before") + F.col("__r") <= m - F.col("__all")))
    return replace(frame, df=kept.select(*frame.df.columns), public=frame.public.after("trim", rows=m))
