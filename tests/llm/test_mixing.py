import random

from sealed_frames.llm import mixing as M

COLUMNS = "doc_id long, source string, text string, size int, place string, s int"


def plain_targets(sizes, weights=(5, 2, 1), most=3):
    """Share by weight, cut at the cap, reshare the excess, until none is above."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    full, total = set(), sum(sizes.values())
    while True:
        left = total - sum(most * sizes[s] for s in full)
        share = sum(w[s] for s in order if s not in full)
        target = {s: most * sizes[s] if s in full else left * w[s] / share for s in order}
        over = {s for s in order if s not in full and target[s] > most * sizes[s]}
        if not over:
            return target
        full |= over


def test_targets_and_nearness(spark):
    rng = random.Random(4)
    rows = [(i, rng.choice(["b", "a", None, "é", "tiny"]) if i % 50 else "tiny2", "w " * rng.randrange(60), 1, "p", 1) for i in range(1500)]
    docs = spark.createDataFrame(rows, COLUMNS)
    got = M.mix(docs).collect()
    assert len(got) == len(rows)
    sizes, taken, target = {}, {}, {}
    for r in got:
        sizes[r.source] = sizes.get(r.source, 0) + r.size
        taken[r.source] = taken.get(r.source, 0) + r.taken
        target[r.source] = r.target
        assert r.taken <= 3 * r.size and r.taken >= 0
    want = plain_targets(sizes)
    for s in sizes:
        assert abs(target[s] - want[s]) < 1e-6 and abs(taken[s] - want[s]) <= 30
    assert sorted((r.doc_id, r.taken) for r in M.mix(docs).collect()) == sorted((r.doc_id, r.taken) for r in got)
    mixed = M.mixed_documents(docs)
    assert mixed.columns == docs.columns
    words = {}
    for r in mixed.collect():
        words[r.source] = words.get(r.source, 0) + len(r.text.split())
    assert words == {s: t for s, t in taken.items() if t}


def test_targets_of_many_sources(spark):
    """The same targets by ranges and running sums as in one task."""
    rng = random.Random(7)
    sizes = {f"s{i:03}é"[: rng.randrange(3, 6)] + str(i): rng.choice([0, 1, 5, 40, 900]) for i in range(120)} | {None: 33}
    sums = M.settle(spark.createDataFrame(list(sizes.items()), "source string, source_size long"), "sums")
    want = plain_targets(sizes)
    for few in (0, 1000):
        got = {r.source: r.target for r in M.targets(sums, few=few).collect()}
        assert got.keys() == want.keys() and all(abs(got[s] - want[s]) < 1e-6 for s in want)
        assert M.targets(M.settle(sums.limit(0), "none"), few=few).count() == 0


def test_budgets_nest(spark):
    docs = spark.createDataFrame([(i, "s", "w w w") for i in range(400)], "doc_id long, source string, text string")
    rows = M.settle(M.sized(docs), "t")
    kept = []
    for budget in (90.0, 300.0, 900.0):
        edge = M.thresholds(rows, spark.createDataFrame([("s", budget)], "source string, budget double")).first()
        kept.append({r.doc_id for r in rows.collect() if r.place < edge.edge or (r.place == edge.edge and edge.inclusive)})
        assert abs(3 * len(kept[-1]) - budget) <= 3
    assert kept[0] < kept[1] < kept[2]


def test_edge_rows(spark):
    docs = spark.createDataFrame([(None, None, None, 1, "p", 1), (1, "a", "", 1, "p", 1), (2, "a", " \t", 1, "p", 1), (3, "b", "x " * 90_000, 1, "p", 1), (3, "b", "x", 1, "p", 1), (4, None, "y", 1, "p", 1)], COLUMNS)
    got = {(r.doc_id, r.size): r.taken for r in M.mix(docs).collect()}
    assert len(got) == 6 and got[None, 0] == 0 and got[1, 0] == 0
    assert M.mix(docs.limit(0)).count() == 0
    assert M.mixed_documents(docs.where("doc_id < 3")).count() == 0
