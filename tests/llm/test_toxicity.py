import random

import numpy as np

from sealed_frames.llm import toxicity as T

DOCS = "doc_id long, text string, score string, row int"


def test_margins_are_sums_over_all_pairs():
    """Against the plain sum over single terms and pairs of terms."""
    rng = np.random.default_rng(3)
    model = T.FactorizationMachine(np.arange(30, dtype=np.uint32), 0.3, rng.normal(size=30), rng.normal(size=(30, 5)))
    rows = [sorted(rng.choice(30, rng.integers(0, 12), replace=False).tolist()) for _ in range(40)]
    row, index = np.repeat(np.arange(40), [len(r) for r in rows]), np.array([i for r in rows for i in r], np.int64)
    want = [0.3 + sum(model.weight[i] for i in r) + sum(model.factor[i] @ model.factor[j] for n, i in enumerate(r) for j in r[n + 1 :]) for r in rows]
    assert np.allclose(model.margins(row, index, 40), want)


def test_pairs_weigh_what_single_terms_do_not(spark):
    """insult and group appear equally in both classes of 4,000 texts; only together (or neither) are they toxic."""
    rng = random.Random(1)
    filler = ["".join(rng.choice("bcdfgklmnprst") + rng.choice("aeiou") for _ in range(3)) for _ in range(60)]
    rows, labels = [], []
    for i in range(4000):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        words = [rng.choice(filler) for _ in range(6)] + ["zoteff"] * a + ["quablin"] * b
        rng.shuffle(words)
        rows.append((i, " ".join(words)))
        labels.append((i, int(a == b)))
    docs, known = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = T.held_out_scores(docs, known).join(known, "doc_id").where("held_out").toPandas()
    assert len(got) > 600 and (got.predicted == got.toxic).mean() > 0.95


def test_pairs_count_with_the_choice_of_terms_as_it_is():
    """No term tells the classes apart by itself, and all the same every one has factors."""
    rng = random.Random(2)
    draws = [(rng.random() < 0.5, rng.random() < 0.5) for _ in range(1200)]
    row, term = np.repeat(np.arange(1200), 2), np.array([sorted({1 if a else 2, 3 if b else 4}) for a, b in draws], np.uint32).ravel()
    label = np.array([float(a == b) for a, b in draws])
    model = T.fit(row, term, label, steps=600)
    assert model.active.tolist() == [1, 2, 3, 4]
    assert ((model.margins(row, model.find(term), 1200) > 0) == (label == 1)).mean() > 0.99


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = T.held_out_scores(docs, labels).join(labels, "doc_id").where("held_out").toPandas()
    assert len(got) > 500 and (got.predicted == got.toxic).mean() > 0.95
    assert got[got.toxic == 0].predicted.mean() < 0.02


def test_edge_rows(spark):
    docs = spark.createDataFrame([(None, "you idiot", "x", 1), (1, None, "x", 1), (2, "", "x", 1), (3, "fine " * 40_000, None, None), (3, "fine", None, None)], DOCS)
    labels = spark.createDataFrame([(1, None), (None, 1), (2, 0), (3, 0)], "doc_id long, toxic int")
    got = T.held_out_scores(docs, labels).collect()
    assert len(got) == 5 and all(0 <= r.score <= 1 for r in got) and [r.held_out for r in got if r.doc_id is None] == [False]
    kept = T.drop_toxic(docs, T.train(docs, labels))
    assert kept.columns == docs.columns and kept.count() == 5


def test_empty_tables(spark):
    docs, labels = spark.createDataFrame([], "doc_id long, text string"), spark.createDataFrame([], "doc_id long, toxic int")
    assert T.held_out_scores(docs, labels).count() == 0
