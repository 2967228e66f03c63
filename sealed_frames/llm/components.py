"""Connected components of an edge table, as a DataFrame loop.

Alternates two contractions: every vertex hands its larger neighbours to its smallest neighbour,
then its smaller neighbours to the smallest of them. Both keep the components, and the edge set
becomes a forest of stars after O(log^2 n) rounds in theory, a handful in practice. A round costs a
partially aggregated minimum per vertex and one equi-join, so a vertex with very many neighbours is
split by adaptive execution; each round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import settle


def _stars(edges: DataFrame, larger: bool) -> DataFrame:
    """One contraction of edges (u > v): by larger or by smaller neighbours."""
    if larger:
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges.select("u", "v")
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    linked = both.join(least, "u")
    moved = linked.where("v > u" if larger else "v <> m").select(F.col("v").alias("a"), F.col("m").alias("b"))
    if not larger:
        moved = moved.unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return (
        moved.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    )


def connected(edges: DataFrame) -> DataFrame:
    """(id, component) of every vertex that is not its component's smallest; edges: (u, v) long.

    Self loops and repeated edges are harmless; an empty edge table gives an empty result.
    """
    now = settle(
        edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges"
    )
    print_of = lambda e: tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    seen = print_of(now)
    while seen[0]:  # every round that changes anything hands some vertex a smaller neighbour
        now = settle(_stars(_stars(now, True), False), "stars")
        fresh = print_of(now)
        if fresh == seen:
            break
        seen = fresh
    return now.select(F.col("u").alias("id"), F.col("v").alias("component"))
