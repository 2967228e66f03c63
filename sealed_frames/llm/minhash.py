"""Near-duplicate documents: tensored MinHash banding, exact confirmation, components.

A document's set holds its distinct word shingles (64-bit hashes). ``groups`` collections of
``rows`` minhashes each are computed; every *pair* of collections is one table key, so
groups*rows minhashes serve groups*(groups-1)/2 tables of 2*rows rows. Two sets of Jaccard
similarity j miss all tables only if fewer than two collections agree; at j = 0.8 and the defaults
(16 collections of 3) that happens with probability 0.00018, falling fast above.

Nothing is ever paired within a bucket: members are confirmed against the bucket's smallest
member and components are formed. Only documents of *other* components of the same bucket are then
compared with the rest, in blocks whose intersections are matrix products, so that no link between
buckets' members is lost and a group of copies costs rows in proportion to its size. Equal sets are
one class from the start.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .components import connected
from .runtime import settle, ship, small_side

#: Ids that may be broadcast to pick candidates' texts; beyond it the texts are joined by a shuffle.
BROADCAST_IDS = 1_000_000
#: Documents whose keys a task makes: a document has a key per table.
KEYED = 16_384
#: Sets and set members of a block that is compared with another, about.
BLOCK_SETS, BLOCK_VALUES = 192, 100_000
_U = np.uint64


def shingle_sets(body: np.ndarray, offsets: np.ndarray, words: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; a text of fewer words gives one for the whole
    sequence, a text without words gives none."""
    hashes, counts, _, _ = K.words(body, offsets)
    ends = np.cumsum(counts)
    n = len(hashes)
    rolled = np.zeros(max(0, n - words + 1), _U)
    for i in range(words):
        rolled = K.mix(rolled * _U(0x9FB21C651E98DF25) + hashes[i : n - words + 1 + i]) if len(rolled) else rolled
    out = []
    for a, b in zip((ends - counts).tolist(), ends.tolist()):
        if b - a >= words:
            out.append(np.unique(rolled[a : b - words + 1]))
        elif b > a:
            whole = np.full(1, _U(b - a) * _U(0xD6E8FEB86659FD93), _U)
            for h in hashes[a:b]:
                whole = K.mix(whole + h)
            out.append(whole)
        else:
            out.append(np.zeros(0, _U))
    return out


def _factors(n: int) -> tuple[np.ndarray, np.ndarray]:
    seeds = K.mix(np.arange(1, 2 * n + 1, dtype=_U) * _U(0x9E3779B97F4A7C15))
    return seeds[:n] | _U(1), seeds[n:]


def collections_of(values: np.ndarray, a: np.ndarray, b: np.ndarray, groups: int) -> np.ndarray:
    """One hash per collection of minhashes of a set."""
    least = np.full(len(a), ~_U(0), _U)
    for i in range(0, len(values), 2048):
        np.minimum(least, (values[i : i + 2048, None] * a + b).min(axis=0), out=least)
    folded = np.arange(groups, dtype=_U)
    for column in least.reshape(groups, -1).T:
        folded = K.mix(folded * _U(0x9FB21C651E98DF25) + column)
    return folded


def _features(batches: Iterator[pa.RecordBatch], words: int, groups: int, rows: int) -> Iterator[pa.RecordBatch]:
    a, b = _factors(groups * rows)
    for batch in batches:
        ids = batch.column(0)
        for i, j, body, offsets in K.slices(batch, "text"):
            sets = shingle_sets(body, offsets, words)
            prints = np.frombuffer(b"".join(blake2b(s.tobytes(), digest_size=16).digest() for s in sets), np.int64)
            keys = np.concatenate([collections_of(s, a, b, groups) for s in sets]).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [
                    ids.slice(i, j - i),
                    pa.array(np.fromiter(map(len, sets), np.int64, len(sets))),
                    pa.array(prints[::2]),
                    pa.array(prints[1::2]),
                    pa.ListArray.from_arrays(pa.array(np.arange(0, len(keys) + 1, groups, dtype=np.int32)), pa.array(keys)),
                ],
                names=["doc_id", "n_shingles", "fp1", "fp2", "parts"],
            )


def _keys(batches: Iterator[pa.RecordBatch], groups: int) -> Iterator[pa.RecordBatch]:
    left, right = map(np.array, zip(*combinations(range(groups), 2)))
    for batch in batches:
        for i in range(0, batch.num_rows, 4000):
            part = batch.slice(i, 4000)
            ids = part.column(0).to_numpy()
            at = part.column(1).flatten().to_numpy().view(_U).reshape(-1, groups)
            keys = K.mix(at[:, left] * _U(0x9FB21C651E98DF25) + at[:, right]).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [pa.array(keys.ravel()), pa.array(np.repeat(ids, len(left)))], names=["bucket", "id"]
            )


def _sets(batches: Iterator[pa.RecordBatch], words: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, body, offsets in K.slices(batch, "text"):
            sets = shingle_sets(body, offsets, words)
            ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets).view(np.int64)))],
                names=["id", "members"],
            )


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) whose full sets reach the threshold."""
    held = pairs.join(sets.select(F.col("id").alias("u"), F.col("members").alias("mu")), "u")
    held = held.join(sets.select(F.col("id").alias("v"), F.col("members").alias("mv")), "v")
    shared = F.size(F.array_intersect("mu", "mv"))
    return (
        held.select("u", "v", shared.alias("both"), (F.size("mu") + F.size("mv")).alias("sum"))
        .where(F.col("both") * 100 >= (F.col("sum") - F.col("both")) * percent)
        .select("u", "v")
    )


def _candidate_sets(docs: DataFrame, pairs: DataFrame, words: int) -> DataFrame:
    ids = settle(pairs.select(F.col("u").alias("id")).unionByName(pairs.select(F.col("v").alias("id"))).distinct(), "ids")
    texts = docs.select(F.col("doc_id").alias("id"), "text").join(small_side(ids, BROADCAST_IDS), "id", "left_semi")
    found = texts.mapInArrow(lambda it: _sets(it, words), "id long, members array<long>")
    # rows of one id: the text of the longest, then of the largest set, as one value per id
    best = F.max(F.struct(F.size("members").alias("n"), F.col("members")))
    return settle(found.groupBy("id").agg(best.alias("best")).select("id", "best.members"), "sets")


def shared_counts(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of two blocks of sorted sets: products of 0/1 matrices over the values
    that both blocks hold."""
    values = [np.concatenate(x) if x else np.zeros(0, np.int64) for x in (left, right)]
    rows = [np.repeat(np.arange(len(x)), [len(s) for s in x]) for x in (left, right)]
    both = np.intersect1d(*values)
    out = np.zeros((len(left), len(right)), np.float32)
    if not len(both):
        return out.astype(np.int64)
    at = [np.searchsorted(both, v) for v in values]
    good = [(i < len(both)) & (both[np.minimum(i, len(both) - 1)] == v) for i, v in zip(at, values)]
    for c in range(0, len(both), 4096):
        parts = []
        for x, i, g, r in zip((left, right), at, good, rows):
            here = g & (i >= c) & (i < c + 4096)
            grid = np.zeros((len(x), min(4096, len(both) - c)), np.float32)
            grid[r[here], i[here] - c] = 1
            parts.append(grid)
        out += parts[0] @ parts[1].T
    return out.astype(np.int64)


def _forest(linked: np.ndarray, ids: list[int], others: list[int], joined: bool) -> list[tuple[int, int]]:
    """Links that connect what ``linked`` connects; ``joined``: the others are one component anyway."""
    if joined:
        return [(ids[i], others[int(np.argmax(linked[i]))]) for i in np.flatnonzero(linked.any(axis=1))]
    left = np.ones(len(others), bool)  # columns that no row of an earlier walk has reached
    todo = set(np.flatnonzero(linked.any(axis=1)).tolist())
    out = []
    while todo:
        wave = [todo.pop()]
        while wave:
            i = wave.pop()
            fresh = np.flatnonzero(linked[i] & left)
            left[fresh] = False
            for j in fresh.tolist():
                out.append((ids[i], others[j]))
                for k in np.flatnonzero(linked[:, j]).tolist():
                    if k in todo:
                        todo.discard(k)
                        wave.append(k)
                        out.append((ids[k], others[j]))
    return out


def _compare(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found: list[tuple[int, int]] = []
        for r in range(batch.num_rows):
            ids, others, sets = [], [], []
            for name, into in (("a", ids), ("b", others)):
                block = batch.column(batch.schema.get_field_index(name))[r].values
                into += block.field("id").to_pylist()
                lists = block.field("members")
                sets.append([lists[k].values.to_numpy() for k in range(len(lists))])
            both = shared_counts(*sets)
            sizes = np.add.outer([len(s) for s in sets[0]], [len(s) for s in sets[1]])
            linked = both * 100 >= (sizes - both) * percent
            linked &= np.not_equal.outer(ids, others)
            found += _forest(linked, ids, others, bool(batch.column(batch.schema.get_field_index("joined"))[r].as_py()))
        if found:
            u, v = map(np.array, zip(*found))
            yield pa.RecordBatch.from_arrays([pa.array(np.maximum(u, v)), pa.array(np.minimum(u, v))], names=["u", "v"])


def _links_across(members: DataFrame, labels: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between members of one bucket that the first components leave apart.

    In every such bucket one component has most members. Documents of other components that share a
    bucket with it are compared, in blocks of bounded size, with its members in such buckets and with
    each other: exactly, on full sets. Only links that connect are returned.
    """
    placed = members.join(labels, "id", "left").select("bucket", "id", F.coalesce("component", "id").alias("comp"))
    counts = placed.groupBy("bucket", "comp").agg(F.count("*").alias("k"))
    split = counts.groupBy("bucket").agg(F.max(F.struct("k", "comp")).alias("top"), F.count("*").alias("parts")).where("parts > 1")
    apart = placed.join(split.select("bucket", F.col("top.comp").alias("main")), "bucket")
    sided = settle(apart.select("main", "id", (F.col("comp") == F.col("main")).alias("own")).distinct(), "apart")
    held = sided.join(sets, "id")
    size = F.size("members")
    room = sided.join(sets.select("id", size.alias("n")), "id").groupBy("main", "own").agg(F.count("*").alias("k"), F.sum("n").alias("n"))
    room = room.select("main", "own", F.ceil(F.greatest(F.col("k") / BLOCK_SETS, F.col("n") / BLOCK_VALUES)).cast("long").alias("blocks"))
    room = small_side(settle(room, "room"), BROADCAST_IDS)
    dealt = held.join(room, ["main", "own"]).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
    dealt = dealt.repartition("main", "own", "block")  # else a large component's blocks would meet in one task
    blocks = settle(dealt.groupBy("main", "own", "block").agg(F.collect_list(F.struct("id", "members")).alias("part")), "blocks")
    x = blocks.where("not own").select("main", F.col("block").alias("i"), F.col("part").alias("a"))
    y = blocks.select("main", F.col("own").alias("joined"), F.col("block").alias("j"), F.col("part").alias("b"))
    pairs = x.join(y, "main").where("joined or i <= j").select("a", "b", "joined")
    return pairs.mapInArrow(lambda it: _compare(it, percent), "u long, v long").distinct()


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, groups: int = 16, rows: int = 3) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row of ``docs`` (doc_id, text).

    Null and empty texts, and texts of white space, have an empty set and link with nothing. Rows with
    a null doc_id keep a null component and are kept. Repeated rows of one doc_id are one document
    and come back as often as they came; if their texts differ, that with the largest set is compared. Further columns of ``docs`` are ignored.
    """
    spark = docs.sparkSession
    ship(spark)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marks = settle(
        docs.mapInArrow(
            lambda it: _features(it, words, groups, rows),
            "doc_id long, n_shingles long, fp1 long, fp2 long, parts array<long>",
        ),
        "marks",
    )
    usable = marks.where("n_shingles > 0 and doc_id is not null")
    classes = settle(usable.groupBy("fp1", "fp2").agg(F.min("doc_id").alias("id"), F.first("n_shingles").alias("n")), "classes")
    heads = classes.select("fp1", "fp2", F.col("id").alias("doc_id")).join(
        usable.select("fp1", "fp2", "doc_id", "parts"), ["fp1", "fp2", "doc_id"]
    )
    # a document becomes a row per table here: as many tasks as those rows need, not as the documents do
    tasks = max(2 * spark.sparkContext.defaultParallelism, -(-classes.count() // KEYED))
    keyed = heads.select("doc_id", "parts").repartition(tasks, "doc_id").mapInArrow(lambda it: _keys(it, groups), "bucket long, id long")
    shared = keyed.groupBy("bucket").agg(F.min("id").alias("lead"), F.max("id").alias("last")).where("lead <> last")
    members = settle(keyed.join(shared.select("bucket", "lead"), "bucket"), "members")

    first = settle(members.where("id <> lead").select(F.col("id").alias("u"), F.col("lead").alias("v")).distinct(), "pairs")
    sets = _candidate_sets(docs, first, words)
    links = settle(_confirm(first, sets, percent), "links")
    labels = connected(links)

    more = settle(_links_across(members, labels, sets, percent), "links")
    if not more.isEmpty():
        labels = connected(labels.select(F.col("id").alias("u"), F.col("component").alias("v")).unionByName(more))

    roots = settle(
        classes.join(labels, "id", "left").select("fp1", "fp2", F.coalesce("component", "id").alias("component_id")), "roots"
    )
    out = marks.drop("parts").join(roots, ["fp1", "fp2"], "left")
    own = F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    return out.select(
        "doc_id",
        "n_shingles",
        F.when(F.col("doc_id").isNotNull(), own).alias("component_id"),
        F.coalesce(F.col("doc_id") == own, F.lit(True)).alias("kept"),
    )


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The documents that stay: one row of each near-duplicate component, all columns as they were.

    Rows with a null doc_id stay. Of repeated rows of one kept doc_id one stays; only such rows are
    shuffled with their texts.
    """
    found = settle(near_duplicates(docs, **options), "found").where("doc_id is not null")
    gone = settle(found.where("not kept").select("doc_id").distinct(), "gone")
    again = settle(found.where("kept").groupBy("doc_id").count().where("count > 1").select("doc_id"), "again")
    left = docs.join(small_side(gone, BROADCAST_IDS), "doc_id", "left_anti").select(*docs.columns)
    if again.isEmpty():
        return left
    again = small_side(again, BROADCAST_IDS)
    once = left.join(again, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id"])
    return left.join(again, "doc_id", "left_anti").select(*docs.columns).unionByName(once)
