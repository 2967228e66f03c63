import numpy as np

from sealed_frames.llm import ann
from sealed_frames.llm import embedding_dedup as D

SCHEMA = "vec_id long, embedding array<float>, score string, unit int, id int"


def frame(spark, rows):
    return spark.createDataFrame([(i, None if v is None else [None if x is None else float(x) for x in v], "c", 1, 1) for i, v in rows], SCHEMA)


def clusters(seed, n=600, dims=24):
    rng = np.random.default_rng(seed)
    centres = rng.normal(size=(25, dims))
    x = centres[rng.integers(0, 25, n)] + rng.normal(size=(n, dims)) * rng.choice([0.02, 0.12, 0.2, 0.5], (n, 1))
    x[50:90] = x[50]
    return np.float32(x)


def plain_links(ids, x, cosine):
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1)[:, None]
    near = u @ u.T >= cosine
    label = np.array(ids)
    while True:
        new = np.array([label[row].min() for row in near])
        if (new == label).all():
            return near.sum(1) - 1, label
        label = new


def test_cover_tree_is_one():
    x = clusters(1).astype(float)
    tree = D.CoverTree(x, leaf=5)
    assert sorted(tree.order.tolist()) == list(range(len(x)))
    stack = [tree.root]
    while stack:
        node = stack.pop()
        rows = tree.order[node.first : node.stop]
        assert np.linalg.norm(x[rows] - x[node.centre], axis=1).max(initial=0) <= node.reach + 1e-9
        if node.children:
            assert node.children[0].centre == node.centre and sum(c.stop - c.first for c in node.children) == len(rows)
            assert all(c.reach <= c.radius <= node.radius / 2 for c in node.children)
            heads = x[[c.centre for c in node.children]]
            apart = np.linalg.norm(heads[:, None] - heads[None], axis=2)[~np.eye(len(heads), dtype=bool)]
            assert apart.min(initial=np.inf) > node.children[0].radius - 1e-9
        stack += node.children


def test_links_match_all_pairs(spark):
    x = clusters(2)
    want_n, want_c = plain_links(range(len(x)), x, 0.95)
    for block, centres in ((2048, 2048), (64, 8)):
        got = {r.vec_id: r for r in D.close_vectors(frame(spark, enumerate(x.tolist())), 0.95, block, centres).collect()}
        assert [got[i].n_links for i in range(len(x))] == want_n.tolist()
        assert [got[i].component_id for i in range(len(x))] == want_c.tolist()
        assert all(r.kept == (r.component_id == r.vec_id) for r in got.values())


def test_links_edge_rows(spark):
    rows = [(1, [1, 0]), (2, [2, 0]), (3, None), (4, [0, 0]), (5, [1, None]), (6, [float("nan"), 1]), (7, [float("inf"), 1]), (8, []), (9, [1, 0, 0]), (None, [1, 0]), (2, [2, 0]), (10, [-1, 0])]
    got = sorted(((r.vec_id or -1), r.n_links, r.component_id, r.kept) for r in D.close_vectors(frame(spark, rows)).collect())
    assert [g for g in got if g[0] in (3, 4, 5, 6, 7, 8, 9, 10)] == [(i, 0, i, True) for i in (3, 4, 5, 6, 7, 8, 9, 10)]
    assert (1, 3, 1, True) in got and got.count((2, 3, 1, False)) == 2 and (-1, 3, None, True) in got
    assert D.close_vectors(frame(spark, []).limit(0)).count() == 0


def test_neighbours_recall_and_scores(spark):
    rng = np.random.default_rng(3)
    x = np.float32(rng.normal(size=(3000, 32)) * rng.lognormal(0, 0.3, (3000, 1)))
    ids = np.arange(3000)
    got = ann.neighbours(frame(spark, zip(ids.tolist(), x.tolist()))).toPandas()
    hits = 0
    for q, g in got.groupby("query_id"):
        s = x.astype(float) @ x[q].astype(float)
        s[q] = -np.inf
        best = np.lexsort((ids, -s))[:20]
        g = g.sort_values("rank")
        hits += len(set(best) & set(g.vec_id))
        assert g["rank"].tolist() == list(range(1, 21)) and np.allclose(g.score, s[g.vec_id], rtol=1e-12)
        assert (np.lexsort((g.vec_id, -g.score)) == np.arange(20)).all()
    assert got.query_id.nunique() == 150 and hits / (150 * 20) >= 0.95


def test_neighbours_among_50_000(spark):
    rng = np.random.default_rng(12)
    x = np.float32(rng.normal(size=(50_000, 24)) + rng.normal(size=(40, 24))[rng.integers(0, 40, 50_000)]).astype(float)
    ids = rng.permutation(50_000)
    df = spark.createDataFrame(__import__("pandas").DataFrame({"vec_id": ids, "embedding": x.tolist()}), "vec_id long, embedding array<double>").repartition(6)
    got = ann.neighbours(df, every=250).toPandas()
    assert got.query_id.nunique() == 200
    hits = 0
    for q, g in got.groupby("query_id"):
        s = x @ x[ids == q][0]
        s[ids == q] = -np.inf
        hits += len(set(ids[np.argsort(-s)[:20]]) & set(g.vec_id))
    assert hits >= 0.999 * 200 * 20


def test_neighbours_among_copies(spark):
    """A third of the rows are copies, another third near copies: ids are exact all the same, ties to smaller ids."""
    rng = np.random.default_rng(9)
    x = rng.normal(size=(3600, 32))
    kind = rng.permutation(3600) % 3
    x[kind == 1] = x[kind == 1][0]
    x[kind == 2] = x[kind == 2][0] + rng.normal(size=((kind == 2).sum(), 32)) * 1e-3
    x = np.float32(x).astype(float)
    ids = rng.permutation(3600)
    got = ann.neighbours(frame(spark, zip(ids.tolist(), x.tolist()))).toPandas()
    assert got.query_id.nunique() == 180
    for q, g in got.groupby("query_id"):
        s = np.einsum("nd,nd->n", x, np.repeat(x[ids == q], 3600, 0))
        s[ids == q] = -np.inf
        assert g.sort_values("rank").vec_id.tolist() == ids[np.lexsort((ids, -s))[:20]].tolist()


def test_parallel_residuals_shrink():
    """The score-aware codes leave smaller parallel residuals than plain ones, at a larger plain error."""
    rng = np.random.default_rng(4)
    x = rng.normal(size=(2000, 16))
    aware = ann.fit(x, threshold=0.5)
    plain = ann.Quantiser(16, ann.fit(x, threshold=0.0).codewords, 1.0)

    def residuals(q):
        codes = q.codes(x)
        r = (q.cut(x) - np.stack([q.codewords[m][codes[:, m]] for m in range(q.pieces)], 1)).reshape(len(x), -1)
        u = x / np.linalg.norm(x, axis=1)[:, None]
        return ((r * u).sum(1) ** 2).mean(), (r**2).sum(1).mean()

    (a_par, a_all), (p_par, p_all) = residuals(aware), residuals(plain)
    assert a_par < 0.5 * p_par and a_all > p_all


def test_neighbours_edge_rows(spark):
    same = [(i, [1, 2, 3]) for i in range(0, 60, 3)]
    rows = [*same, (20, [1, 2, 3]), (40, None), (80, [0, 0, 0]), (100, [1, None, 1]), (120, [float("nan"), 0, 0]), (140, [1, 1]), (None, [9, 9, 9])]
    got = ann.neighbours(frame(spark, rows)).toPandas()
    assert set(got.query_id) == {0, 20} and got[got.query_id == 20].sort_values("rank").vec_id.tolist() == [i for i, _ in same]
    assert ann.neighbours(frame(spark, []).limit(0)).count() == 0
    assert ann.neighbours(frame(spark, [(20, [1, 1])])).count() == 0
