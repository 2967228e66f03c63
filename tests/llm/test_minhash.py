import random

import numpy as np

from sealed_frames.llm import kernels as K
from sealed_frames.llm import minhash


def brute(texts, words=2, percent=80):
    """Components by comparing all pairs of word shingle sets."""
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {}
    for i, t in texts:
        w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", (t or "").translate(lower)) if x]
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                a_, b_ = find(a), find(b)
                root[max(a_, b_)] = min(a_, b_)
    return {i: (len(sets[i]), find(i)) for i in ids}


def group(seed, n, length=150):
    rng = random.Random(seed)
    base = [f"w{rng.randrange(400)}" for _ in range(length)]
    out = []
    for i in range(n):
        words = list(base)
        for _ in range(rng.randrange(22)):
            words[rng.randrange(length)] = f"x{rng.randrange(10**6)}"
        out.append((i, " ".join(words)))
    return out


def result(spark, rows, **options):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df, words=2, **options).collect()}


def test_group_of_near_copies_matches_all_pairs(spark):
    rows = group(3, 220)
    want = brute(rows)
    got = result(spark, rows)
    assert {i: x[:2] for i, x in got.items()} == want
    assert len({c for _, c in want.values()}) > 5


def test_edge_rows(spark):
    rows = [(1, None), (2, ""), (3, " \t\n"), (4, "One"), (5, "one"), (6, "a b"), (7, "A\x0bB"), (8, "É b"), (9, "é b"), (10, "x " * 50_000)]
    got = result(spark, rows)
    assert got[1] == (0, 1, True) and got[2] == (0, 2, True) and got[3] == (0, 3, True)
    assert got[4] == (1, 4, True) and got[5] == (1, 4, False)
    assert got[6] == (1, 6, True) and got[7] == (1, 6, False)
    assert got[8][1] == 8 and got[9][1] == 9 and got[10][0] == 1


def test_empty_null_ids_repeats_and_clashing_columns(spark):
    assert minhash.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    df = spark.createDataFrame([(None, "a b c d e f", 1, 2), (1, "a b c d e f", 1, 2), (1, "a b c d e f", 1, 2), (2, "a b c d e f", 0, 0)], "doc_id long, text string, component_id int, kept int")
    got = sorted((r.doc_id or -1, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect())
    assert got == [(-1, None, True), (1, 1, True), (1, 1, True), (2, 1, False)]
    left = minhash.keep_one(df)
    assert left.columns == df.columns
    assert sorted((r.doc_id or -1) for r in left.collect()) == [-1, 1]


def test_one_id_with_different_texts(spark):
    """The row with the largest set stands for the id, in whatever order rows come."""
    rows = [(1, "a b c d e f g h"), (1, "x y"), (2, "a b c d e f g h i"), (3, "x y"), (5, "a b c d e f g h")]
    for turn in range(3):
        df = spark.createDataFrame(rows[turn:] + rows[:turn], "doc_id long, text string").repartition(3)
        got = sorted((r.doc_id, r.n_shingles, r.component_id) for r in minhash.near_duplicates(df, words=2).collect())
        assert got == [(1, 1, 1), (1, 7, 1), (2, 8, 1), (3, 1, 1), (5, 7, 1)]


def test_shared_counts():
    rng = np.random.default_rng(0)
    sets = [np.unique(rng.integers(0, 9000, n)) for n in (0, 1, 50, 6000, 300)]
    got = minhash.shared_counts(sets, sets[::-1])
    assert got.tolist() == [[len(np.intersect1d(a, b)) for b in sets[::-1]] for a in sets]


def test_word_hashes_do_not_depend_on_place():
    body = "Alpha beta\talpha".encode()
    hashes, counts, start, end = K.words(np.frombuffer(body, np.uint8), np.array([0, 5, 5, len(body)]))
    assert counts.tolist() == [1, 0, 2] and hashes[0] == hashes[2] != hashes[1]
    assert [body[a:b] for a, b in zip(start, end)] == [b"Alpha", b"beta", b"alpha"]
