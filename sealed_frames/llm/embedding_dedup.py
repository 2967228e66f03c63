"""Embedding near-duplicates: all pairs above a cosine threshold by dual traversal of cover trees.

Vectors are scaled to length one, where cosine c is distance sqrt(2 - 2c). Equal vectors are one class.
Classes are dealt to cells by their nearest of a bounded sample of centres, cells are cut into blocks
of bounded size, and each block is a cover tree (nested levels, radii halving). Pairs of cells, then of
blocks, are skipped if their covering balls are further apart than the threshold; the trees of the
others are walked together. A pair of nodes further apart than the threshold allows is dropped, one
wholly within it is counted as a whole, leaves are compared vector by vector: screened in single
precision, decided in double wherever the screen is within its error. A node whose points would need
more than ``FAN`` children (no structure at that scale) stays a leaf. Per pair of blocks, links are
returned as a count per class and a spanning set of links, so that a group of copies costs rows in
proportion to its size.
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected
from .runtime import get_arrays, new_path, put_arrays, settle, ship

#: Vectors of a block; centres, at most, that vectors are dealt by; vectors of a node that is not divided;
#: children of a node, at most.
BLOCK, CENTRES, LEAF, FAN = 8192, 2048, 96, 48
#: Rows of the products that leaves are compared by; pairs of blocks of a task, at most, but for small inputs.
TILE, PAIRS = 2048, 64
#: Above the error of a single-precision product of unit vectors of up to some thousand components.
SCREEN = 2e-4
#: Slack of every pruning bound: bounds decide only where rounding can't matter.
SLACK = 1e-9


@dataclass
class Node:
    """Points first..stop (in tree order) lie within ``reach`` of ``centre``, and ``reach`` within the level's
    ``radius``; levels below have half of it, a quarter, ..."""

    centre: int
    radius: float
    reach: float
    first: int
    stop: int
    children: list[Node]


class CoverTree:
    """A cover tree of unit vectors; ``order`` gives the rows of the input in tree order.

    A node of level radius r has children centred at points of it that are pairwise at least r/2 apart
    and within r/2 of all its points; the first child keeps its parent's centre (nesting).
    """

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.points, self.leaf = points, leaf
        self.single = points.astype(np.float32)
        self.order: list[int] = []
        every = np.arange(len(points))
        away = self._from(0, every) if len(points) else np.zeros(0)
        self.root = self._grow(every, away, 0, float(away.max(initial=0.0)))
        self.order = np.array(self.order, np.int64)

    def _from(self, centre: int, rows: np.ndarray) -> np.ndarray:
        d = self.points[rows] - self.points[centre]
        return np.sqrt(np.einsum("ij,ij->i", d, d))

    def _grow(self, rows: np.ndarray, away: np.ndarray, centre: int, radius: float) -> Node:
        first = len(self.order)
        reach = float(away.max(initial=0.0))
        node = Node(centre, radius, reach, first, first + len(rows), [])
        if len(rows) <= self.leaf or reach <= 1e-12:
            self.order.extend(rows.tolist())
            return node
        half = radius / 2
        while half >= reach:  # levels that hold the one centre are passed over
            half /= 2
        near, best = away.copy(), np.zeros(len(rows), np.int64)
        centres = [centre]
        while near.max() > half:
            if len(centres) == FAN:
                self.order.extend(rows.tolist())
                return node
            far = int(np.argmax(near))
            d = self._from(int(rows[far]), rows)
            closer = d < near
            near[closer], best[closer] = d[closer], len(centres)
            centres.append(int(rows[far]))
        for k, c in enumerate(centres):
            mine = best == k
            node.children.append(self._grow(rows[mine], near[mine], c, half))
        return node


def close_pairs(a: CoverTree, b: CoverTree | None, cosine: float):
    """Walk two trees (or one against itself): yields (rows of a, rows of b, linked matrix or None, mirror).

    None: every pair of the two row sets is linked. Against itself each unordered pair of nodes is
    visited once, with mirror set where its links hold in the other direction too; a node with itself
    comes whole.
    """
    limit = np.sqrt(2 - 2 * cosine)
    other = b or a

    def rows(tree: CoverTree, node: Node) -> np.ndarray:
        return tree.order[node.first : node.stop]

    stack = [(a.root, other.root)]
    while stack:
        x, y = stack.pop()
        same = b is None and x is y
        if not same:
            d = float(np.linalg.norm(a.points[x.centre] - other.points[y.centre]))
            if d > x.reach + y.reach + limit + SLACK:
                continue
            if d + x.reach + y.reach < limit - SLACK:
                yield rows(a, x), rows(other, y), None, b is None
                continue
        elif 2 * x.reach < limit - SLACK:
            yield rows(a, x), rows(other, y), None, False
            continue
        if not x.children and not y.children:
            every = rows(other, y)
            for s in np.split(every, range(TILE, len(every), TILE)):
                for r in np.split(rows(a, x), range(TILE, x.stop - x.first, TILE)):
                    linked = _linked(a, r, other, s, cosine)
                    if linked is not None:
                        yield r, s, linked, b is None and not same
        elif same:
            n = len(x.children)
            stack += [(x.children[i], x.children[j]) for i in range(n) for j in range(i, n)]
        elif y.children and (not x.children or y.reach > x.reach):
            stack += [(x, c) for c in y.children]
        else:
            stack += [(c, y) for c in x.children]


def _linked(a: CoverTree, r: np.ndarray, b: CoverTree, s: np.ndarray, cosine: float) -> np.ndarray | None:
    """Matrix of links between rows of two trees; None if there is none."""
    rough = a.single[r] @ b.single[s].T
    if not (rough >= cosine - SCREEN).any():
        return None
    linked = rough >= cosine
    i, j = np.nonzero(np.abs(rough - cosine) <= SCREEN)
    linked[i, j] = np.einsum("ij,ij->i", a.points[r[i]], b.points[s[j]]) >= cosine
    return linked if linked.any() else None


def _spanning(x: np.ndarray, y: np.ndarray, linked: np.ndarray | None) -> list[tuple[int, int]]:
    """Links that connect what a matrix of links connects."""
    if linked is None:
        return [(int(x[0]), int(j)) for j in y] + [(int(i), int(y[0])) for i in x[1:]]
    out, free, todo = [], np.ones(len(y), bool), set(np.flatnonzero(linked.any(axis=1)).tolist())
    while todo:
        wave = [todo.pop()]
        while wave:
            i = wave.pop()
            fresh = np.flatnonzero(linked[i] & free)
            free[fresh] = False
            for j in fresh.tolist():
                out.append((int(x[i]), int(y[j])))
                for k in np.flatnonzero(linked[:, j]).tolist():
                    if k in todo:
                        todo.discard(k)
                        wave.append(k)
                        out.append((int(x[k]), int(y[j])))
    return out


def block_links(tree: CoverTree, ids, weight, others=None, cosine: float = 0.95):
    """(links per row of the tree, links per row of the others or None, spanning links as id pairs);
    others: (tree, ids, weight)."""
    pair = None if others is None else others[0]
    own = np.zeros(len(ids), np.int64)
    theirs = None if others is None else np.zeros(len(others[1]), np.int64)
    right_ids, right_weight = (ids, weight) if others is None else others[1:]
    edges: list[tuple[int, int]] = []
    for x, y, linked, mirror in close_pairs(tree, pair, cosine):
        whole = linked is None
        own[x] += right_weight[y].sum() if whole else linked @ right_weight[y]
        if others is not None:
            theirs[y] += weight[x].sum() if whole else weight[x] @ linked
        elif mirror:
            own[y] += weight[x].sum() if whole else weight[x] @ linked
        edges += [(int(ids[i]), int(right_ids[j])) for i, j in _spanning(x, y, linked)]
    return own, theirs, edges


def usable_unit(raw: list) -> np.ndarray | None:
    """The vector scaled to length one; None if null, empty, zero or with null or non-finite components."""
    if raw is None or not len(raw) or any(x is None for x in raw):
        return None
    v = np.asarray(raw, np.float64)
    if not np.isfinite(v).all():
        return None
    top = np.abs(v).max()
    if top == 0:
        return None
    v = v / top
    return v / np.sqrt(v @ v)


def unit_rows(column: pa.Array) -> tuple[np.ndarray, list[np.ndarray]]:
    """(row numbers, unit vectors) of the usable vectors of a list column."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    size = np.diff(column.offsets.to_numpy())
    plain = not column.null_count and column.flatten().null_count == 0 and len(size) and (size == size[0]).all() and size[0]
    if not plain:
        found = [(i, u) for i, raw in enumerate(column.to_pylist()) if (u := usable_unit(raw)) is not None]
        return np.array([i for i, _ in found], np.int64), [u for _, u in found]
    v = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, int(size[0]))
    top = np.abs(v).max(axis=1)
    good = np.flatnonzero(np.isfinite(v).all(axis=1) & (top > 0))
    v = v[good] / top[good, None]
    return good, list(v / np.sqrt(np.einsum("ij,ij->i", v, v))[:, None])


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, batch.num_rows, 4096):
            part = batch.slice(i, 4096)
            rows, units = unit_rows(part.column(1))
            ids = part.column(0).take(pa.array(rows))
            yield pa.RecordBatch.from_arrays([ids, pa.array([len(u) for u in units], pa.int32()), pa.array([u.tobytes() for u in units], pa.binary())], names=["vec_id", "dims", "unit"])


def _deal(batches: Iterator[pa.RecordBatch], centres: dict[int, np.ndarray]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        dims = batch.column(batch.schema.get_field_index("dims")).to_numpy()
        cell, away = np.zeros(len(dims), np.int32), np.zeros(len(dims))
        raw = batch.column(batch.schema.get_field_index("unit"))
        for d in np.unique(dims):
            rows = np.flatnonzero(dims == d)
            v = np.frombuffer(b"".join(raw.take(pa.array(rows)).to_pylist()), np.float64).reshape(-1, d)
            cell[rows] = np.argmax(v @ centres[int(d)].T, axis=1)
            away[rows] = np.sqrt(((v - centres[int(d)][cell[rows]]) ** 2).sum(axis=1))
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell), pa.array(away)], names=[*batch.schema.names, "cell", "away"])


def _near_cells(cells: list[tuple[int, int, float]], tops: dict[int, np.ndarray], limit: float) -> list[tuple[int, int, int]]:
    """(dims, cell, cell not before it) of cells whose balls come within the threshold."""
    out = []
    for dims, centres in tops.items():
        reach = np.full(len(centres), -np.inf)
        for d, cell, r in cells:
            if d == dims:
                reach[cell] = r
        for i in np.flatnonzero(np.isfinite(reach)).tolist():
            gap = np.sqrt(((centres[i:] - centres[i]) ** 2).sum(axis=1))
            out += [(dims, i, i + j) for j in np.flatnonzero(gap <= reach[i] + reach[i:] + limit + SLACK).tolist()]
    return out


def _pack(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    """A file per block with ids, weights and vectors; a row with its number, cell and covering ball."""
    for batch in batches:
        out = []
        for r in range(batch.num_rows):
            dims = batch.column(batch.schema.get_field_index("dims"))[r].as_py()
            part = batch.column(batch.schema.get_field_index("part"))[r].values
            v = np.frombuffer(b"".join(part.field("unit").to_pylist()), np.float64).reshape(-1, dims)
            centre = v.mean(axis=0)
            reach = float(np.sqrt(((v - centre) ** 2).sum(axis=1).max()))
            ids, weight = part.field("id").to_numpy(), part.field("weight").to_numpy()
            cell = batch.column(batch.schema.get_field_index("cell"))[r].as_py()
            number = int(ids.min())
            put_arrays(f"{folder}/block-{number}.bin", {"ids": ids, "weights": weight.astype(np.int64), "units": v.ravel()})
            out.append((number, dims, cell, centre.tolist(), reach))
        kinds = [pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.float64()), pa.float64()]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=["block", "dims", "cell", "centre", "reach"])


class _Blocks:
    """Blocks with their trees; those used last stay."""

    def __init__(self, folder: str, most: int = 6):
        self.folder, self.most, self.held = folder, most, OrderedDict()

    def __getitem__(self, number: int):
        if (got := self.held.get(number)) is None:
            raw = get_arrays(f"{self.folder}/block-{number}.bin")
            got = CoverTree(raw["units"].reshape(len(raw["ids"]), -1)), raw["ids"], raw["weights"]
            self.held[number] = got
            if len(self.held) > self.most:
                self.held.popitem(last=False)
        self.held.move_to_end(number)
        return got


def _walk(batches: Iterator[pa.RecordBatch], folder: str, cosine: float) -> Iterator[pa.RecordBatch]:
    """Count rows (u, n) and link rows (u, v) of each pair of blocks."""
    blocks = _Blocks(folder)
    for batch in batches:
        for left, right in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            a = blocks[left]
            b = None if left == right else blocks[right]
            own, theirs, edges = block_links(*a, b, cosine)
            ids, n = a[1], own
            if b is not None:
                ids, n = np.concatenate([ids, b[1]]), np.concatenate([own, theirs])
            some = n > 0
            edges = np.array([e for e in edges if e[0] != e[1]], np.int64).reshape(-1, 2)
            u = np.concatenate([ids[some], edges[:, 0]])
            v = pa.array(np.concatenate([np.zeros(some.sum(), np.int64), edges[:, 1]]), mask=np.arange(len(u)) < some.sum())
            yield pa.RecordBatch.from_arrays([pa.array(u), v, pa.array(np.concatenate([n[some], np.zeros(len(edges), np.int64)]))], names=["u", "v", "n"])


def close_vectors(vectors: DataFrame, cosine: float = 0.95, block: int = BLOCK, centres: int = CENTRES) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row of ``vectors`` (vec_id, embedding).

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing, as do
    vectors of different lengths. Rows with a null vec_id count as links of others, have a null component
    and are kept; repeated rows count as vectors of their own, rows of one vec_id with different vectors share
    their links. Only the sample of centres
    is bounded; it decides how vectors are dealt, never what is linked.
    """
    spark = vectors.sparkSession
    ship(spark)
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    units = settle(rows.mapInArrow(_units, "vec_id long, dims int, unit binary"), "units")
    named = units.groupBy("dims", "unit").agg(F.min("vec_id").alias("id"), F.count("*").alias("weight"))
    # a class without an id is named by a number beyond all ids
    classes = settle(named.withColumn("id", F.coalesce("id", F.lit(1 << 62) + F.pmod(F.xxhash64("unit"), F.lit(1 << 62)))), "classes")
    k = int(min(centres, max(1, -(-classes.count() // block))))
    sample: dict[int, list[np.ndarray]] = {}
    for r in classes.select("dims", "unit").orderBy(F.xxhash64("unit")).limit(k).collect():
        sample.setdefault(r["dims"], []).append(np.frombuffer(r["unit"], np.float64))
    for r in classes.select("dims").distinct().collect():
        sample.setdefault(r["dims"], [np.zeros(r["dims"])])
    tops = {d: np.stack(v) for d, v in sample.items()}
    celled = settle(classes.mapInArrow(lambda it: _deal(it, tops), "dims int, unit binary, id long, weight long, cell int, away double"), "cells")
    cells = celled.groupBy("dims", "cell").agg(F.count("*").alias("k"), F.max("away").alias("reach")).collect()
    limit = float(np.sqrt(2 - 2 * cosine))
    parts = spark.createDataFrame([(r["dims"], r["cell"], -(-r["k"] // block)) for r in cells], "dims int, cell int, parts int")
    dealt = celled.join(F.broadcast(parts), ["dims", "cell"])
    dealt = dealt.withColumn("part_no", F.pmod(F.xxhash64("unit"), F.col("parts")).cast("int"))
    grouped = dealt.groupBy("dims", "cell", "part_no").agg(F.collect_list(F.struct("id", "weight", "unit")).alias("part"))
    folder = new_path(spark, "blocks")
    packed = settle(
        grouped.select("dims", "cell", "part").mapInArrow(
            lambda it: _pack(it, folder), "block long, dims int, cell int, centre array<double>, reach double"
        ),
        "blocks",
    )
    # the few cells are paired on the driver; blocks meet through the pairs of cells that are left
    near = spark.createDataFrame(_near_cells([(r["dims"], r["cell"], r["reach"]) for r in cells], tops, limit), "dims_a int, cell_a int, cell_b int")
    balls = packed.select("block", "dims", "cell", "centre", "reach")
    a, b = (balls.select(*[F.col(c).alias(c + s) for c in balls.columns]) for s in ("_a", "_b"))
    gap = F.sqrt(F.aggregate(F.zip_with("centre_a", "centre_b", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, x: s + x))
    pairs = a.join(near, ["dims_a", "cell_a"]).join(b, [F.col("dims_a") == F.col("dims_b"), near["cell_b"] == b["cell_b"]])
    pairs = pairs.where((F.col("cell_a") < b["cell_b"]) | (F.col("block_a") <= F.col("block_b")))
    pairs = pairs.where(gap <= F.col("reach_a") + F.col("reach_b") + limit + SLACK)
    todo = settle(pairs.select("block_a", "block_b"), "pairs")
    # pairs of numbers travel, blocks are read where they are compared; neighbouring pairs share a block
    tasks = int(min(todo.count(), max(4 * spark.sparkContext.defaultParallelism, todo.count() // PAIRS)))
    met = todo.repartitionByRange(max(1, tasks), "block_a", "block_b").sortWithinPartitions("block_a", "block_b")
    found = settle(met.mapInArrow(lambda it: _walk(it, folder, cosine), "u long, v long, n long"), "found")
    counts = found.where("v is null").groupBy(F.col("u").alias("id")).agg(F.sum("n").alias("near"))
    labels = connected(found.where("v is not null").select("u", "v"))
    known = settle(
        classes.join(counts, "id", "left").join(labels, "id", "left")
        .select("dims", "unit", (F.coalesce("near", F.lit(1)) - 1).alias("n_links"), F.coalesce("component", "id").alias("component")),
        "known",
    )
    placed = units.join(known, ["dims", "unit"]).select("vec_id", "n_links", "component")
    rest = rows.mapInArrow(_unusable, "vec_id long").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component"))
    every = placed.unionByName(rest)
    own = F.when(F.col("vec_id").isNotNull(), F.col("component"))
    return every.select("vec_id", "n_links", own.alias("component_id"), F.coalesce(F.col("vec_id") == own, F.lit(True)).alias("kept"))


def _unusable(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rest = np.ones(batch.num_rows, bool)
        rest[unit_rows(batch.column(1))[0]] = False
        yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(rest))], names=["vec_id"])
