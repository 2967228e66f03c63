"""Toxicity: a factorization machine over hashed terms.

Terms of a text are its distinct lower-cased words and their 4-, 5- and 6-byte prefixes, each hashed
to 32 bits. The model adds, to a weight per term, the inner product of two terms' factors for each
pair of terms present, so that a pair (an insult beside a group mention) can weigh what neither term
does alone. Every term of at least ``LEAST_ROWS`` fitted rows has a weight and factors, whether or not it
tells the classes apart by itself; rarer ones weigh nothing. Those that do take longer steps in the fit.

Fitted by rounds over blocks of rows on at most ``SAMPLE_ROWS`` labelled rows (those first by a hash of doc_id); scoring is one
narrow pass over all texts with the small model in the task's closure.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .runtime import ship

#: Labelled rows that the model is fitted on, at most.
SAMPLE_ROWS = 10_000
#: Rows that a term must be in to be active; rows of a step of the fit; text bytes scored at a time.
LEAST_ROWS, BLOCK_ROWS, SLICE = 4, 500, 1 << 20
#: Terms a row, telling little by themselves, up to which their steps have full length; beyond, they move a row together.
FEW = 20
PREFIXES = (4, 5, 6)
_U = np.uint64


def terms(body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, 32-bit term) of every word and prefix, with repeats."""
    hashes, counts, start, end = K.words(body, offsets)
    row = np.repeat(np.arange(len(counts)), counts)
    kinds, rows = [hashes], [row]
    for k in PREFIXES:
        long = np.flatnonzero(end - start > k)
        at = K.spread(start[long], np.full(len(long), k))
        kinds.append(K.words(body[at], np.arange(0, k * len(long) + 1, k))[0] + _U(k))
        rows.append(row[long])
    return np.concatenate(rows), (K.mix(np.concatenate(kinds)) >> _U(32)).astype(np.uint32)


def distinct_terms(body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    row, term = terms(body, offsets)
    both = np.unique((row.astype(_U) << _U(32)) | term)
    return (both >> _U(32)).astype(np.int64), both.astype(np.uint32)


@dataclass
class FactorizationMachine:
    """bias + sum of weights + sum over pairs of <factor, factor>, through a logistic."""

    active: np.ndarray  # sorted 32-bit terms
    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def margins(self, row: np.ndarray, index: np.ndarray, rows: int) -> np.ndarray:
        """row ascending; index into active, distinct within a row."""
        counts = np.bincount(row, minlength=rows)
        w, v = self.weight[index], self.factor[index]
        total = K.segment_sums(v, counts)
        return self.bias + K.segment_sums(w, counts) + 0.5 * (total**2 - K.segment_sums(v**2, counts)).sum(axis=1)

    def find(self, term: np.ndarray) -> np.ndarray:
        """Positions of terms in active; -1: not there."""
        if not len(self.active):
            return np.full(len(term), -1)
        at = np.minimum(np.searchsorted(self.active, term), len(self.active) - 1)
        return np.where(self.active[at] == term, at, -1)


def choose_terms(term: np.ndarray, least_rows: int = LEAST_ROWS) -> np.ndarray:
    """Terms in at least ``least_rows`` rows; terms are distinct within a row."""
    distinct, rows = np.unique(term, return_counts=True)
    return distinct[rows >= least_rows]


def _parts(n: int):
    """Slices of a long vector, so that what is made from it stays small."""
    return (slice(i, i + (1 << 20)) for i in range(0, n, 1 << 20))


def telling(row: np.ndarray, index: np.ndarray, label: np.ndarray, size: int) -> np.ndarray:
    """Which of the ``size`` active terms have shares that differ between the classes by 4 standard errors."""
    here, hits = np.zeros(size), np.zeros(size)
    for part in _parts(len(index)):
        here += np.bincount(index[part], minlength=size)
        hits += np.bincount(index[part], weights=label[row[part]], minlength=size)
    n, p = len(label), label.mean()
    z = (hits - here * p) / np.sqrt(np.maximum(here * p * (1 - p) * (1 - here / n) + 1e-9, 1e-9) + 0.25)
    return np.abs(z) >= 4


def fit(row: np.ndarray, term: np.ndarray, label: np.ndarray, factors: int = 8, steps: int = 200, rate: float = 0.05, decay: float = 2e-4) -> FactorizationMachine:
    """Adam on the mean logistic loss of blocks of rows; row ascending, terms distinct within a row."""
    label = np.asarray(label, float)
    n = len(label)
    if not n or label.min() == label.max():
        return FactorizationMachine(np.zeros(0, np.uint32), 4.0 if n and label[0] else -4.0, np.zeros(0), np.zeros((0, factors)))
    model = FactorizationMachine(choose_terms(term), 0.0, np.zeros(0), np.zeros((0, factors)))
    index = np.empty(len(term), np.int32)
    for part in _parts(len(term)):
        index[part] = model.find(term[part])
    row, index = row[index >= 0], index[index >= 0]
    size = len(model.active)
    rng = np.random.default_rng(7)
    p = label.mean()
    counts = np.bincount(row, minlength=n)
    # terms that tell little by themselves come by hundreds a row and take shorter steps from smaller factors
    alone = telling(row, index, label, size)
    pace = np.where(alone, 1.0, 1 / max(1.0, (~alone[index]).sum() / n / FEW))
    state = [np.array([np.log(p / (1 - p))]), np.zeros(size), rng.normal(0, 0.05, (size, factors)) * np.sqrt(pace)[:, None]]
    rates = [rate, rate * pace, rate * pace[:, None]]
    first, second = [np.zeros_like(x) for x in state], [np.zeros_like(x) for x in state]
    start = np.cumsum(counts) - counts
    blocks = max(1, -(-n // BLOCK_ROWS))
    for step in range(1, steps + 1):
        if (step - 1) % blocks == 0:
            deal = rng.permutation(n)
        rows = deal[(step - 1) % blocks :: blocks]
        here_counts = counts[rows]
        at_index = index[K.spread(start[rows], here_counts)]
        bias, w, v = state
        at = v[at_index]
        total = K.segment_sums(at, here_counts)
        margin = bias[0] + K.segment_sums(w[at_index], here_counts) + 0.5 * (total**2 - K.segment_sums(at**2, here_counts)).sum(axis=1)
        error = (1 / (1 + np.exp(-np.clip(margin, -35, 35))) - label[rows]) / len(rows)
        here = np.repeat(error, here_counts)
        pull = here[:, None] * (np.repeat(total, here_counts, axis=0) - at)
        gradient = [
            np.array([error.sum()]),
            np.bincount(at_index, weights=here, minlength=size) + decay * w / max(size, 1),
            np.stack([np.bincount(at_index, weights=pull[:, f], minlength=size) for f in range(factors)], axis=1) + decay * v / max(size, 1) if size else np.zeros((0, factors)),
        ]
        for i, g in enumerate(gradient):
            first[i] = 0.9 * first[i] + 0.1 * g
            second[i] = 0.999 * second[i] + 0.001 * g * g
            state[i] = state[i] - rates[i] * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
    return FactorizationMachine(model.active, float(state[0][0]), state[1], state[2])


def _sample_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, body, offsets in K.slices(batch, "text"):
            row, term = distinct_terms(body, offsets)
            ends = np.searchsorted(row, np.arange(j - i + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.ListArray.from_arrays(pa.array(ends), pa.array(term.view(np.int32)))],
                names=["doc_id", "toxic", "terms"],
            )


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> FactorizationMachine:
    """Fit on labelled rows of ``docs``; labels: (doc_id, toxic 0/1). Null ids or labels are passed over,
    of repeated labels the largest counts. Without rows of both classes the model is a constant."""
    ship(docs.sparkSession)
    ids = (
        labels.where("doc_id is not null and toxic is not null")
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(sample_rows)
    )
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    picked = texts.join(F.broadcast(ids), "doc_id").select("doc_id", "toxic", "text")
    found = picked.mapInArrow(_sample_terms, "doc_id long, toxic int, terms array<int>").toArrow().combine_chunks()
    order = np.argsort(found["doc_id"].to_numpy(), kind="stable")
    found = found.take(pa.array(order))
    label = found["toxic"].to_numpy().astype(float)
    lists = found["terms"].combine_chunks()
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) and lists.num_chunks else lists
    if not len(label):
        return fit(np.zeros(0, np.int64), np.zeros(0, np.uint32), label)
    counts, term = np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy().view(np.uint32)
    del found
    K.give_back()
    return fit(np.repeat(np.arange(len(label), dtype=np.int32), counts), term, label)


def _score(batches: Iterator[pa.RecordBatch], model: FactorizationMachine) -> Iterator[pa.RecordBatch]:
    maybe = np.zeros(1 << 20, bool)
    maybe[model.active >> np.uint32(12)] = True
    for batch in batches:
        for i, j, body, offsets in K.slices(batch, "text", SLICE):
            row, term = terms(body, offsets)
            near = np.flatnonzero(maybe[term >> np.uint32(12)])
            row, index = row[near], model.find(term[near])
            row, index = row[index >= 0], index[index >= 0]
            both = np.unique(row * np.int64(max(1, len(model.active))) + index)
            margin = model.margins(both // max(1, len(model.active)), both % max(1, len(model.active)), j - i)
            scores = 1 / (1 + np.exp(-np.clip(margin, -35, 35)))
            rest = [batch.column(c).slice(i, j - i) for c in range(batch.num_columns) if batch.schema.names[c] != "text"]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(scores)], names=[*(c for c in batch.schema.names if c != "text"), "score"])


def score(docs: DataFrame, model: FactorizationMachine) -> DataFrame:
    """(doc_id, score) of every row; null and empty texts score as texts without active terms."""
    ship(docs.sparkSession)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(lambda it: _score(it, model), "doc_id long, score double")


def fold(column="doc_id", folds: int = 5):
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % folds == 0, F.lit(False))


def held_out_scores(docs: DataFrame, labels: DataFrame, folds: int = 5) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of ``docs``; labels of held-out rows are never read.

    Rows with a null doc_id are scored and not held out; repeated rows are scored each.
    """
    model = train(docs, labels.where(~fold("doc_id", folds)))
    return score(docs, model).select(
        "doc_id", fold("doc_id", folds).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted")
    )


def drop_toxic(docs: DataFrame, model: FactorizationMachine, threshold: float = 0.5) -> DataFrame:
    """The rows that score below ``threshold``, all columns as they were; a narrow pass."""
    ship(docs.sparkSession)
    schema = docs.schema
    names = docs.columns

    def keep(batches):
        for batch in batches:
            text = pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index("text"))], names=["text"])
            at = 0
            for out in _score([text], model):
                stay = pa.array(out.column(0).to_numpy() < threshold)
                yield batch.slice(at, out.num_rows).filter(stay).select(names)
                at += out.num_rows

    return docs.mapInArrow(keep, schema)
