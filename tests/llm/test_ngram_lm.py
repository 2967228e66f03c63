import collections
import math
import re
import zlib

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from sealed_frames.llm import ngram_lm as L


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 1 << 40), max_size=300), st.integers(0, 1 << 40))
def test_elias_fano(values, other):
    x = np.sort(np.array(values, np.int64))
    e = L.EliasFano.of(L.EliasFano.pack(x))
    assert e.get(np.arange(len(x))).tolist() == x.tolist()
    ask = np.array([*values, other, 0, 1 << 41], np.int64)
    found = e.find(ask, np.zeros(len(ask), np.int64), np.full(len(ask), len(x)))
    for v, i in zip(ask.tolist(), found.tolist()):
        assert (i >= 0) == (v in values) and (i < 0 or x[i] == v)


class Plain:
    """The same model without levels, shards and quantiser, on all rows."""

    def __init__(self, rows, least=1, discount=0.6):
        self.one, self.two, self.three, self.context = (collections.Counter() for _ in range(4))
        for _, text in rows:
            w = ["<s>", *text.split(), "</s>"]
            self.one.update(w[1:])
            self.context.update(w)
            self.two.update(zip(w, w[1:]))
            self.three.update(zip(w, w[1:], w[2:]))
        self.d = discount

    def p(self, before, w):
        before = ["<s>", *before][-2:]
        p = (self.one[w] + 0.1) / (sum(self.one.values()) + 0.1 * (len(self.one) + 1))
        for table, owner, context in ((self.two, before[-1:], self.context[before[-1]]), (self.three, before, self.two[tuple(before)])):
            if len(owner) == len(next(iter(table))) - 1 and context:
                follows = [c for k, c in table.items() if k[:-1] == tuple(owner)]
                left = 1 - sum(c - self.d for c in follows) / context if follows else 1
                n = table[(*owner, w)]
                p = (max(n - self.d, 0) / context if n else 0) + left * p
        return p


def plain_probabilities(rows, before, words):
    m = Plain(rows)
    return [m.p(before, w if w != "never" else "\0") for w in words]


def plain_probabilities_of_end(rows, before, words):
    m = Plain(rows)
    return [m.p([*before, w], "</s>") for w in words]


def plain_log(rows, before):
    m = Plain(rows)
    return sum(math.log10(m.p(before[:i], w)) for i, w in enumerate(before))


def plain(rows, least, discount, folds=10):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    tokens = [(i, re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low))) for i, t in rows]
    one, two, three, context = (collections.Counter() for _ in range(4))
    for i, w in tokens:
        if i is None or zlib.crc32(str(i).encode()) % folds:
            w = ["<s>", *w, "</s>"]
            one.update(w[1:])
            context.update(w)
            two.update(zip(w, w[1:]))
            three.update(zip(w, w[1:], w[2:]))
    n, v = sum(one.values()), len(one)
    two = {k: c for k, c in two.items() if c >= least}
    three = {k: c for k, c in three.items() if c >= least}
    left1, left2 = collections.Counter(), collections.Counter()
    for (a, _), c in two.items():
        left1[a] += (c - discount) / context[a]
    for k, c in three.items():
        left2[k[:2]] += (c - discount) / two[k[:2]]
    out = []
    for i, w in tokens:
        w = ["<s>", *w, "</s>"]
        base = score = 0.0
        for j in range(1, len(w)):
            p = (one[w[j]] + 0.1) / (n + 0.1 * (v + 1))
            base += math.log10(p)
            k = (w[j - 1], w[j])
            p = ((two[k] - discount) / context[w[j - 1]] if k in two else 0) + (1 - left1[w[j - 1]]) * p
            k = tuple(w[j - 2 : j + 1])
            if j > 1 and k[:2] in two:
                p = ((three[k] - discount) / two[k[:2]] if k in three else 0) + (1 - left2[k[:2]]) * p
            score += math.log10(p)
        out.append((i, len(w) - 1, sum(one[t] > 0 for t in w[1:]), n, base, score))
    return out


def check(spark, rows, least, **sizes):
    df = spark.createDataFrame([(*r, "clash", 0.0) for r in rows], "doc_id long, text string, n_tokens string, score double")
    got = sorted(L.held_out_scores(df, least=least, **sizes).collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.n_tokens))
    want = sorted(plain(rows, least, 0.6), key=lambda r: (r[0] is not None, r[0] or 0, r[1]))
    assert len(got) == len(want)
    for g, w in zip(got, want):
        assert (g.doc_id, g.n_tokens, g.n_known, g.train_tokens) == w[:4]
        assert abs(g.base_score - w[4]) < 1e-9 * max(1, abs(w[4]))
        assert abs(g.score - w[5]) < 0.02 * w[1] + 0.02  # the quantiser's error, per token


def test_matches_a_plain_model(spark, tiny):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()]
    check(spark, rows, 3)


def test_default_leaves_no_pair_or_triple_out(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    want = {r[0]: r for r in plain([(r.doc_id, r.text) for r in docs.collect()], 1, 0.6)}
    got = L.held_out_scores(docs).collect()
    assert len(got) == len(want)
    assert all(abs(g.score - want[g.doc_id][5]) < 0.02 * g.n_tokens + 0.02 for g in got)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 300), min_size=1, max_size=400), min_size=1, max_size=4), st.integers(0, 1 << 60))
def test_counts_survive_their_blocks(parts, low):
    parts = [np.array(p, np.uint64) + np.uint64(low) for p in parts]
    want = collections.Counter(int(k) for p in parts for k in np.repeat(p, np.where(p % np.uint64(7) == 0, 300, 1)))
    blocks = [L.encode_counts(*L._runs(np.repeat(p, np.where(p % np.uint64(7) == 0, 300, 1))), low) for p in parts]
    keys, counts = L.merge_counts(blocks, low)
    assert dict(zip(keys.tolist(), counts.tolist())) == dict(want) and (np.diff(keys) > 0).all()


def test_many_shards_and_words_cut_into_several(spark, tiny):
    """Shards of 3,000 words and of 500 tokens: words and pairs that occur more often have several."""
    sizes = {"shard_words": 3000, "shard_tokens": 500}
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{tiny}/documents.parquet").limit(60).collect()]
    rows += [(1000 + i, "so it goes and so it goes " * 200 + f"on and so it goes {i}") for i in range(12)]
    check(spark, rows, 1, **sizes)
    check(spark, rows, 2, **sizes)
    layout = L.train(spark.createDataFrame(rows, "doc_id long, text string").select("text"), **sizes)
    assert len(layout.pairs.cut_owner) > 3 and len(layout.triples.cut_owner) > 3


def test_edge_rows(spark):
    rows = [(None, "a b a b a b"), (1, None), (2, ""), (3, "\t \n"), (4, "A b " * 20_000), (4, "a b"), (4, "a b"), (5, "É é")]
    check(spark, rows, 2)


def test_empty_table(spark):
    assert L.held_out_scores(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_probabilities_add_up(spark):
    """After one and after two words: the probabilities of all words, the end and an unknown word sum to one, but for the quantiser."""
    rows = [(i, "x y z x y w") for i in range(30)] + [(100 + i, "x z y") for i in range(30)]
    layout = L.train(spark.createDataFrame(rows, "doc_id long, text string").select("text"))

    def logs(texts):
        asked = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
        return [r.score for r in sorted(L.score(asked, layout).collect(), key=lambda r: r.doc_id)]

    words = ["x", "y", "z", "w", "never"]
    # a text's end is a token: P(end | a b) is that of "a b" over what "a b" has without it
    for context in ("", "x", "x y", "z x", "never y"):
        # log10 P(context w end) - log10 P(end | ... w) = log10 P(context w); the end's share is found from the base model's plain form
        one = plain_probabilities(rows, context.split(), [*words, "</s>"])
        assert abs(sum(one) - 1) < 1e-9
        got = logs([" ".join([context, w]).strip() for w in words] + [context])
        ends = plain_probabilities_of_end(rows, context.split(), words)
        head = plain_log(rows, context.split())
        mine = [10 ** (g - head) / e for g, e in zip(got, ends)] + [10 ** (got[-1] - head)]
        assert abs(sum(mine) - 1) < 0.06
