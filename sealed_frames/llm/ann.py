"""Approximate nearest neighbours by inner product: score-aware 4-bit quantisation, exact reranking.

Vectors are cut into pieces of two components, each coded by one of 16 codewords. What matters to large
inner products is the part of a vector's residual that is parallel to the vector, so the loss weighs
it ``eta`` times; since that part is a sum over all pieces, codes are chosen by rounds of descent
over pieces, and codewords by weighted least squares. A query turns into a table of 16 products per
piece; tables of neighbouring pieces are added to tables of a byte, and scanning a vector is one
lookup per byte. Equal vectors of a chunk are one class, looked up and scored once.

The classes of a chunk that look best are scored on the original vectors; the k-th of these scores is a
threshold. A rough score is off by no more than the query's norm times the residual's, so every class whose
rough score comes within that of the threshold is scored too, and what is left out can't be among the k
best. Classes are then spread to their rows by smallest ids. Codes decide on the work only, not on the result.

Codewords are fitted on a bounded sample; every vector is indexed. Queries are written in blocks of
bounded size to the shared folder; a task reads its part of the index once and takes the blocks one
after the other. The driver sees neither queries nor vectors but the sample.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .embedding_dedup import usable_unit
from .runtime import get_arrays, new_path, put_arrays, settle, ship

#: Vectors that codewords are fitted on; queries of a block; vectors of a chunk; classes of a chunk that set its threshold.
SAMPLE, QUERIES, CHUNK, RERANK = 10_000, 4096, 4096, 192
#: Numbers of gathered vectors that are held at a time; chunks that a task holds at a time.
GATHERED, PARTS = 1 << 21, 16
PIECE = 2


def parallel_weight(dims: int, threshold: float = 0.2) -> float:
    """Weight of the parallel residual for scores above ``threshold`` times the norms."""
    return max(1.0, (dims - 1) * threshold**2 / (1 - threshold**2))


class Quantiser:
    """codewords: pieces x 16 x PIECE."""

    def __init__(self, dims: int, codewords: np.ndarray, eta: float):
        self.dims, self.codewords, self.eta = dims, codewords, eta

    @property
    def pieces(self) -> int:
        return len(self.codewords)

    def cut(self, x: np.ndarray) -> np.ndarray:
        """rows x pieces x PIECE, filled up with zeros."""
        full = np.zeros((len(x), self.pieces * PIECE))
        full[:, : self.dims] = x
        return full.reshape(len(x), self.pieces, PIECE)

    def codes(self, x: np.ndarray, rounds: int = 2, start: np.ndarray | None = None) -> np.ndarray:
        """Codes (rows x pieces) of small loss: plain nearest codewords first, then descent by piece."""
        cut = self.cut(x)
        direction = cut / np.maximum(np.sqrt(np.einsum("ijk,ijk->i", cut, cut)), 1e-300)[:, None, None]
        if start is None:
            out = np.stack([((cut[:, m, None] - self.codewords[m]) ** 2).sum(axis=2).argmin(axis=1) for m in range(self.pieces)], axis=1)
        else:
            out = start.copy()
        rest = np.stack([((cut[:, m] - self.codewords[m][out[:, m]]) * direction[:, m]).sum(axis=1) for m in range(self.pieces)], axis=1)
        total = rest.sum(axis=1)
        for _ in range(rounds):
            for m in range(self.pieces):
                left = cut[:, m, None] - self.codewords[m]
                along = np.einsum("ijk,ik->ij", left, direction[:, m])
                others = total - rest[:, m]
                loss = (left**2).sum(axis=2) + (self.eta - 1) * (others[:, None] + along) ** 2
                out[:, m] = loss.argmin(axis=1)
                rest[:, m] = along[np.arange(len(x)), out[:, m]]
                total = others + rest[:, m]
        return out

    def slack(self, x: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Per vector, what a rough score of a query of norm 1 may be off by: the residual's norm, and roundings of single precision."""
        rest = self.cut(x) - self.codewords[np.arange(self.pieces), codes] if len(x) else np.zeros((0, 1, 1))
        off, norm = np.sqrt((rest**2).sum(axis=(1, 2))), np.sqrt((x**2).sum(axis=1))
        return off * (1 + 1e-9) + (self.pieces + 16) * 2.0**-23 * (norm + 2 * off)

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """queries x pairs of pieces x 256: products with both codewords of a byte."""
        cut = self.cut(queries)
        one = np.einsum("qmk,mck->qmc", cut, self.codewords)
        if one.shape[1] % 2:
            one = np.concatenate([one, np.zeros((len(one), 1, 16))], axis=1)
        low, high = one[:, ::2], one[:, 1::2]
        return (high[:, :, :, None] + low[:, :, None, :]).reshape(len(one), -1, 256).astype(np.float32)


def pack(codes: np.ndarray) -> np.ndarray:
    """Two codes per byte, the first in the low half."""
    if codes.shape[1] % 2:
        codes = np.concatenate([codes, np.zeros((len(codes), 1), codes.dtype)], axis=1)
    return (codes[:, ::2] | codes[:, 1::2] << 4).astype(np.uint8)


def fit(sample: np.ndarray, rounds: int = 8, threshold: float = 0.2) -> Quantiser:
    """Codewords by alternating codes and least squares; deterministic."""
    dims = sample.shape[1]
    pieces = -(-dims // PIECE)
    q = Quantiser(dims, np.zeros((pieces, 16, PIECE)), parallel_weight(dims, threshold))
    cut = q.cut(sample)
    rng = np.random.default_rng(5)
    pick = rng.permutation(len(sample))[np.arange(16) % len(sample)]
    q.codewords[:] = cut[pick].transpose(1, 0, 2)
    direction = cut / np.maximum(np.sqrt(np.einsum("ijk,ijk->i", cut, cut)), 1e-300)[:, None, None]
    eta, q.eta = q.eta, 1.0
    codes = None
    for step in range(rounds):
        if step == rounds // 2:
            q.eta = eta  # plain codewords are the start of score-aware ones
        codes = q.codes(sample, 1, codes if step > rounds // 2 else None)
        rest = np.stack([((cut[:, m] - q.codewords[m][codes[:, m]]) * direction[:, m]).sum(axis=1) for m in range(pieces)], axis=1)
        for m in range(pieces):
            others = rest.sum(axis=1) - rest[:, m]
            u, x, c = direction[:, m], cut[:, m], codes[:, m]
            lhs = np.zeros((16, PIECE, PIECE))
            rhs = np.zeros((16, PIECE))
            np.add.at(lhs, c, np.eye(PIECE) + (q.eta - 1) * u[:, :, None] * u[:, None, :])
            np.add.at(rhs, c, x + (q.eta - 1) * u * (others + (x * u).sum(axis=1))[:, None])
            used = np.bincount(c, minlength=16) > 0
            q.codewords[m][used] = np.linalg.solve(lhs[used], rhs[used][:, :, None])[:, :, 0]
            rest[:, m] = ((x - q.codewords[m][c]) * u).sum(axis=1)
    return q


def usable_rows(column: pa.Array, dims: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(row numbers, vectors) of vectors that take part: of length ``dims``, finite, not zero."""
    size = np.diff(column.offsets.to_numpy())
    plain = not column.null_count and column.flatten().null_count == 0 and len(size) and dims and (size == dims).all()
    if plain:
        v = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dims)
        good = np.flatnonzero(np.isfinite(v).all(axis=1) & (v != 0).any(axis=1))
        return good, v[good]
    found = [(i, raw) for i, raw in enumerate(column.to_pylist()) if usable_unit(raw) is not None and dims in (None, len(raw))]
    return np.array([i for i, _ in found], np.int64), np.array([raw for _, raw in found], np.float64).reshape(len(found), dims or 0)


def _index(batches: Iterator[pa.RecordBatch], q: Quantiser) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, batch.num_rows, CHUNK):
            part = batch.slice(i, CHUNK)
            rows, v = usable_rows(part.column(1), q.dims)
            codes = q.codes(v) if len(v) else np.zeros((0, 1), np.int64)
            yield pa.RecordBatch.from_arrays(
                [part.column(0).take(pa.array(rows)), pa.array([c.tobytes() for c in pack(codes)], pa.binary()), pa.array([x.tobytes() for x in v], pa.binary()), pa.array(q.slack(v, codes))],
                names=["vec_id", "code", "vector", "slack"],
            )


def exact_scores(v: np.ndarray, queries: np.ndarray, row: np.ndarray, col: np.ndarray) -> np.ndarray:
    """Inner products of pairs (query row, vector col), each summed in the same order whatever pairs are with it."""
    out = np.empty(len(row))
    step = max(1, GATHERED // v.shape[1])
    for i in range(0, len(row), step):
        out[i : i + step] = np.einsum("nd,nd->n", v[col[i : i + step]], queries[row[i : i + step]])
    return out


def _classes(vectors: list[bytes], ids: np.ndarray):
    """(first row, size, start) of each class of equal vectors, rows ordered by class and id, largest number of rows with an id."""
    number: dict[bytes, int] = {}
    of = np.array([number.setdefault(x, len(number)) for x in vectors], np.int64)
    order = np.lexsort((ids, of))
    size = np.bincount(of)
    start = np.cumsum(size) - size
    return of, size, start, order, int(np.unique(ids, return_counts=True)[1].max())


class _Top:
    """The k best rows of each query so far, ties to smaller ids; missing entries have score -inf."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.scores, self.ids = np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)

    def add(self, first: int, row: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        """Candidates of the queries ``first`` + row."""
        touched = np.unique(row)
        old = self.scores[first + touched]
        row = np.concatenate([row, np.repeat(touched, self.k)])
        ids = np.concatenate([ids, self.ids[first + touched].ravel()])
        scores = np.concatenate([scores, old.ravel()])
        order = np.lexsort((ids, -scores, row))
        row, ids, scores = row[order], ids[order], scores[order]
        begin = np.searchsorted(row, row, "left")
        place = np.arange(len(row)) - begin
        best = place < self.k
        self.scores[first + row[best], place[best]], self.ids[first + row[best], place[best]] = scores[best], ids[best]


class _Part:
    """A chunk of the index as a scan uses it."""

    def __init__(self, part: pa.RecordBatch):
        self.ids = part.column(0).to_numpy()
        vectors = part.column(2).to_pylist()
        self.of, self.size, self.start, self.order, self.repeats = _classes(vectors, self.ids)
        lead = self.order[self.start]
        self.codes = np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint8).reshape(len(self.ids), -1)[lead].T.copy()
        self.vectors = np.frombuffer(b"".join(vectors), np.float64).reshape(len(self.ids), -1)[lead]
        self.slack = part.column(3).to_numpy()[lead]
        self.by_id = np.argsort(self.ids, kind="stable")
        self.sorted_ids = self.ids[self.by_id]

    def search(self, top: _Top, first: int, asked: np.ndarray, queries: np.ndarray, tables: np.ndarray, k: int, rerank: int) -> None:
        """Enter what the chunk has for the queries from ``first`` on."""
        size = self.size
        rough = tables[:, 0].take(self.codes[0], axis=1)
        for byte in range(1, len(self.codes)):
            rough += tables[:, byte].take(self.codes[byte], axis=1)
        open_ = np.ones(rough.shape, bool)
        # a class without rows but the query's own is no candidate
        lo, hi = np.searchsorted(self.sorted_ids, asked, "left"), np.searchsorted(self.sorted_ids, asked, "right")
        own = np.repeat(np.arange(len(asked)), hi - lo)
        pairs, count = np.unique(own * len(size) + self.of[self.by_id[K.spread(lo, hi - lo)]], return_counts=True)
        pairs = pairs[count == size[pairs % len(size)]]
        open_[pairs // len(size), pairs % len(size)] = False
        rough[~open_] = -np.inf
        # first the classes that look best
        keep = min(max(rerank, k), len(size))
        near = np.argpartition(rough, len(size) - keep, axis=1)[:, len(size) - keep :]
        row, col = np.repeat(np.arange(len(asked)), keep), near.ravel()
        exact = np.where(open_[row, col], exact_scores(self.vectors, queries, row, col), -np.inf)
        threshold = top.scores[first : first + len(asked), k - 1].copy()
        if keep >= k:
            threshold = np.maximum(threshold, np.partition(exact.reshape(near.shape), keep - k, axis=1)[:, keep - k])
        # then all that may reach the threshold
        open_[row, col] = False
        norms = np.sqrt((queries**2).sum(axis=1))
        open_ &= ~(rough + norms[:, None] * self.slack < threshold[:, None])
        more_row, more_col = np.nonzero(open_)
        if len(more_row):
            row, col = np.concatenate([row, more_row]), np.concatenate([col, more_col])
            exact = np.concatenate([exact, exact_scores(self.vectors, queries, more_row, more_col)])
        good = (exact >= threshold[row]) & np.isfinite(exact)
        row, col, exact = row[good], col[good], exact[good]
        members = np.minimum(size[col], k + self.repeats)
        at = self.order[K.spread(self.start[col], members)]
        row, exact = np.repeat(row, members), np.repeat(exact, members)
        other = self.ids[at] != asked[row]
        top.add(first, row[other], self.ids[at][other], exact[other])


def _scan(batches: Iterator[pa.RecordBatch], q: Quantiser, folder: str, blocks: int, k: int, rerank: int) -> Iterator[pa.RecordBatch]:
    """The k best of this part of the index for every query; ``PARTS`` chunks are held at a time."""
    held: list[_Part] = []

    def answers():
        for b in range(blocks):
            block = get_arrays(f"{folder}/queries-{b}.bin")
            query_ids, queries = block["ids"], block["vectors"].reshape(len(block["ids"]), q.dims)
            top = _Top(len(query_ids), k)
            for a in range(0, len(query_ids), 256):
                rows = slice(a, a + 256)
                tables = q.tables(queries[rows])
                for part in held:
                    part.search(top, a, query_ids[rows], queries[rows], tables, k, rerank)
            row, col = np.nonzero(np.isfinite(top.scores))
            for i in range(0, len(row), 1 << 16):
                r, c = row[i : i + (1 << 16)], col[i : i + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array(query_ids[r]), pa.array(top.ids[r, c]), pa.array(top.scores[r, c])], names=["query_id", "vec_id", "score"])

    for batch in batches:
        for i in range(0, batch.num_rows, CHUNK):
            held.append(_Part(batch.slice(i, CHUNK)))
            if len(held) == PARTS:
                yield from answers()
                held.clear()
    if held:
        yield from answers()


def _write_queries(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    """A file for each row (block, vec_ids, vectors)."""
    for batch in batches:
        numbers = batch.column(0).to_pylist()
        for r, number in enumerate(numbers):
            part = batch.column(1)[r].values
            put_arrays(f"{folder}/queries-{number}.bin", {"ids": part.field("vec_id").to_numpy(), "vectors": np.frombuffer(b"".join(part.field("vector").to_pylist()), np.float64)})
        yield pa.RecordBatch.from_arrays([pa.array(numbers, pa.int64())], names=["block"])


def neighbours(vectors: DataFrame, every: int = 20, k: int = 20, sample: int = SAMPLE, rerank: int = RERANK) -> DataFrame:
    """(query_id, rank, vec_id, score): for each vec_id divisible by ``every``, the ``k`` rows of largest inner
    product, ties to smaller vec_id; score in double precision on the original vectors.

    Vectors that are null, zero, hold null or non-finite components, or are not of the commonest length,
    take no part, as do rows with a null vec_id. Rows with the query's own vec_id are no candidates; of
    repeated query ids one row (the smallest vector) is the query. Other repeated rows are candidates each.
    """
    spark = vectors.sparkSession
    ship(spark)
    rows = vectors.where("vec_id is not null").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    schema = "query_id long, rank int, vec_id long, score double"
    lengths = rows.where("size(embedding) > 0").groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    if not lengths:
        return spark.createDataFrame([], schema)
    dims = lengths[0]["d"]
    picked = rows.where(F.size("embedding") == dims).orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).select("embedding").toArrow()
    fitting = usable_rows(picked["embedding"].combine_chunks(), dims)[1]
    if not len(fitting):
        return spark.createDataFrame([], schema)
    q = fit(fitting)
    index = settle(rows.mapInArrow(lambda it: _index(it, q), "vec_id long, code binary, vector binary, slack double"), "index")
    total = index.count()
    scans = index.coalesce(max(1, -(-total // CHUNK)))
    asked = index.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("vector").alias("vector"))
    blocks = max(1, -(-index.where(F.col("vec_id") % every == 0).count() // QUERIES))
    folder = new_path(spark, "queries")
    dealt = asked.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("block")).agg(F.collect_list(F.struct("vec_id", "vector")).alias("part"))
    written = {r["block"] for r in settle(dealt.mapInArrow(lambda it: _write_queries(it, folder), "block long"), "written").collect()}
    if not written:
        return spark.createDataFrame([], schema)
    for b in set(range(blocks)) - written:  # a block that no query fell to
        put_arrays(f"{folder}/queries-{b}.bin", {"ids": np.zeros(0, np.int64), "vectors": np.zeros(0)})
    found = scans.mapInArrow(lambda it: _scan(it, q, folder, blocks, k, rerank), "query_id long, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
