"""Mix sources to target weights: hash-threshold histograms instead of sorting.

Every document has a fixed 60-bit place (leading bits of the MD5 of its id). For each source the
sizes are summed by bucket of leading place bits; the bucket in which the source's budget runs out is
found from running sums over its buckets, and only that bucket is summed again by its next bits,
until a single place is left. Documents before the place are taken once more, those behind are not:
a comparison per row. Budgets nest: a larger budget takes a superset. Rows of one doc_id share a
place and go together.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..core.position import POS, running_sum, with_positions
from . import kernels as K
from .runtime import settle, ship, small_side

#: Place bits that each round of histograms resolves; together all 60.
ROUNDS = (12, 16, 16, 16)
#: Sources that may be broadcast; beyond, documents meet their source in a shuffled join.
BROADCAST_SOURCES = 100_000


def _sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, body, offsets in K.slices(batch, "text"):
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array(K.count_words(body, offsets))],
                names=["doc_id", "source", "size"],
            )


def place_of(doc_id: str):
    """The leading 60 bits of the MD5 of the id's text (of the empty text for null)."""
    text = F.coalesce(F.col(doc_id).cast("long").cast("string"), F.lit("")).cast("binary")
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def sized(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size, place) of every row; size: words of the text."""
    ship(docs.sparkSession)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text"))
    found = picked.mapInArrow(_sizes, "doc_id long, source string, size long")
    return found.withColumn("place", place_of("doc_id"))


def targets(sums: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most: int = 3, few: int = BROADCAST_SOURCES) -> DataFrame:
    """(source, source_size, target) from (source, source_size), one row per source, in a written table.

    Sources in code point order, null last, weigh ``weights`` in turn. Every target is the smaller of
    ``most`` times the source's size and weight times one common level; the level at which targets add
    up to all sizes is the largest of those found with the 0, 1, 2, ... most easily filled sources full.
    Up to ``few`` sources are ordered in one task; more by ranges, with running sums over blocks.
    """
    by_name, by_fill = [F.col("source").asc_nulls_last()], [(F.col("cap") / F.col("w")).asc(), F.col("source").asc_nulls_last()]
    small = sums.count() <= few
    ranked = sums.withColumn("rank", F.row_number().over(Window.orderBy(*by_name)) - 1) if small else with_positions(sums, by_name, name="rank")
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("rank") % len(weights) + 1).cast("int"))
    ranked = ranked.withColumn("w", w).withColumn("cap", F.col("source_size") * most)
    if small:
        upto = Window.orderBy(*by_fill).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        ranked = ranked.withColumn("caps", F.sum("cap").over(upto)).withColumn("ws", F.sum("w").over(upto))
    else:
        ranked = with_positions(ranked, by_fill)
        ranked = running_sum(running_sum(ranked, "cap", "caps"), "w", "ws").drop(POS)
    ranked = settle(ranked, "ranked")
    whole = ranked.agg(F.sum("source_size").alias("size"), F.sum("w").alias("w")).first()
    if whole["w"] is None:
        return ranked.select("source", "source_size", F.lit(0.0).alias("target"))
    level = (F.lit(whole["size"]) - F.col("caps") + F.col("cap")).cast("double") / (F.lit(whole["w"]) - F.col("ws") + F.col("w"))
    top = ranked.agg(F.max(level)).first()[0]
    return ranked.select("source", "source_size", F.least(F.col("cap").cast("double"), F.lit(float(top)) * F.col("w")).alias("target"))


def thresholds(rows: DataFrame, budgets: DataFrame) -> DataFrame:
    """(source, edge, inclusive): documents placed before ``edge`` fit the source's budget, those at it
    if ``inclusive`` (then the sum is nearer to the budget than without). rows: (source, size, place) in a
    written table; budgets: (source, budget). A source whose budget takes all rows has no row here."""
    state = budgets.select("source", "budget", F.lit(0).cast("long").alias("path"), F.lit(0).cast("long").alias("before"))
    done = 0
    for bits in ROUNDS:
        done += bits
        at = state.select(F.col("source").alias("s"), "budget", "path", "before")
        inside = rows.join(small_side(at, BROADCAST_SOURCES), F.col("source").eqNullSafe(F.col("s")) & (F.shiftright("place", 60 - done + bits) == F.col("path")))
        bucket = F.shiftright("place", 60 - done).alias("path")
        sums = inside.groupBy("source", "budget", "before", bucket).agg(F.sum("size").alias("here"))
        upto = Window.partitionBy("source").orderBy("path")
        run = sums.withColumn("end", F.col("before") + F.sum("here").over(upto)).where(F.col("end") > F.col("budget"))
        state = settle(
            run.groupBy("source", "budget").agg(F.min(F.struct("path", "end", "here")).alias("x"))
            .select("source", "budget", F.col("x.path").alias("path"), (F.col("x.end") - F.col("x.here")).alias("before"), F.col("x.here").alias("here")),
            "edges",
        )
    return state.select(
        "source", F.col("path").alias("edge"), ((2 * F.col("before") + F.col("here")).cast("double") <= 2 * F.col("budget")).alias("inclusive")
    )


def plan(rows: DataFrame, weights: tuple[float, ...], most: int) -> DataFrame:
    """Per source (s): source_size, target, whole passes, and the threshold of the rest."""
    sums = settle(rows.groupBy("source").agg(F.sum("size").alias("source_size")), "sources")
    aims = targets(sums, weights, most)
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    aims = settle(aims.withColumn("passes", passes).withColumn("budget", F.col("target") - (F.col("passes") * F.col("source_size")).cast("double")), "aims")
    edges = thresholds(rows, aims.select("source", "budget"))
    known = aims.join(edges.withColumnRenamed("source", "es"), F.col("source").eqNullSafe(F.col("es")), "left")
    return settle(known.select(F.col("source").alias("s"), "source_size", "target", "passes", "edge", "inclusive"), "known")


def _times(place, prefix: str = ""):
    """How often the mix takes a document that meets its source's plan."""
    edge, inclusive, passes = (F.col(prefix + c) for c in ("edge", "inclusive", "passes"))
    once = edge.isNull() | (place < edge) | ((place == edge) & inclusive)
    return passes + F.when(once, 1).otherwise(0)


def mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most: int = 3) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken) of every row of ``docs`` (doc_id, source, text).

    A source's budget is split into whole passes over it and a rest; ``taken`` is the document's size
    times the passes, once more if its place is before the rest's threshold. Null texts have size 0;
    null is a source like others; a source of size 0 has target 0. Further columns are ignored.
    """
    rows = settle(sized(docs), "sized")
    known = plan(rows, weights, most)
    met = rows.join(small_side(known, BROADCAST_SOURCES), F.col("source").eqNullSafe(F.col("s")))
    return met.select("doc_id", "source", "size", "source_size", "target", (F.col("size") * _times(F.col("place"))).alias("taken"))


def mixed_documents(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most: int = 3) -> DataFrame:
    """The mixture itself: each row of ``docs`` as often as its words are taken, all columns as they were.

    Documents meet only their source's plan, so texts are not moved. A row without words is never taken.
    """
    known = small_side(plan(settle(sized(docs), "sized"), weights, most), BROADCAST_SOURCES)
    known = known.select(*[F.col(c).alias(f"mix plan {c}") for c in known.columns])
    met = docs.where(F.col("text").rlike(r"[^\x20\x09-\x0D]")).join(known, F.col("source").cast("string").eqNullSafe(F.col("mix plan s")))
    met = met.withColumn("mix times", _times(place_of("doc_id"), "mix plan ").cast("int")).where("`mix times` > 0")
    return met.withColumn("mix copy", F.explode(F.sequence(F.lit(1), F.col("mix times")))).select(*docs.columns)
