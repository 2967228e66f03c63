import hashlib
import random

import numpy as np
import pytest
import sentencepiece

from sealed_frames.llm import sentencepiece_codec as C
from sealed_frames.llm.entry import piece_file


@pytest.fixture(scope="module")
def pair():
    return C.load_pieces(piece_file()), sentencepiece.SentencePieceProcessor(model_file=piece_file())


def test_encodes_as_the_library(pair):
    ours, theirs = pair
    rng = random.Random(2)
    letters = list("abehlort ,.'-0159\n\t  éßöñ▁日本😀\x00Ⅳ") + ["the", "ing", " of", "tion"]
    texts = ["", " ", "▁", "a" * 5000, " " * 5000 + "x", "\n" * 99, "ab" * 3000, *("".join(rng.choices(letters, k=rng.randrange(60))) for _ in range(6000))]
    for t in texts:
        assert ours.encode(t, True) == theirs.encode(t, add_bos=True, add_eos=True), t[:80]
        assert ours.decode(ours.encode(t, True)) == theirs.decode(theirs.encode(t)), t[:80]


def test_decodes_any_ids(pair):
    ours, theirs = pair
    rng = random.Random(3)
    some = [0, 1, 2, 29871, 259, 3 + 0xE2, 3 + 0x96, 3 + 0x81, 3 + 0xF0, 3 + 0xC3, 3 + 0xA9]
    for _ in range(4000):
        ids = [rng.choice([*some, rng.randrange(32000)]) for _ in range(rng.randrange(9))]
        assert ours.decode(ids) == theirs.decode(ids), ids


def test_one_last_token_per_prefix(pair):
    ours, theirs = pair
    text = "▁unbelievability's"
    last = ours.prefix_tokens(text)
    for n in range(1, len(text) + 1):
        assert theirs.encode(text[1:n])[-1] == last[n - 1] if n > 1 else True


def test_table_with_edge_rows(spark, pair):
    _, theirs = pair
    texts = [None, "", " ", "▁ ▁", "a\u0301 x", "word " * 30_000, "dup", "dup"]
    rows = [(i if i != 6 else None, t, "clash", 1) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string, ids string, n_tokens int")
    got = C.encode_decode(df, piece_file(), with_ids=True).collect()
    assert len(got) == len(texts)
    for r in got:
        text = texts[6 if r.doc_id is None else r.doc_id] or ""
        ids = theirs.encode(text, add_bos=True, add_eos=True)
        assert r.ids == ids and r.n_tokens == len(ids) and r.decoded == theirs.decode(ids)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(theirs.decode(ids).encode()).hexdigest()
    assert C.encode_decode(df.limit(0), piece_file()).count() == 0


def test_documents(spark, pair, tiny):
    _, theirs = pair
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    got = {r.doc_id: r for r in C.encode_decode(docs, piece_file()).collect()}
    for r in docs.collect():
        ids = theirs.encode(r.text or "", add_bos=True, add_eos=True)
        assert got[r.doc_id].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()


def test_little_is_held_at_once(spark, pair, monkeypatch):
    """Batches are bounded by their bytes, remembered fragments and pairs by number; ids stay the library's."""
    import pyarrow as pa

    spark.conf.unset("spark.sql.execution.arrow.maxBytesPerBatch")
    docs = spark.range(2000).selectExpr("id AS doc_id", "repeat('some words and more ', 500) AS text").coalesce(1)
    assert C.encode_decode(docs, piece_file()).select("ids_sha256").distinct().count() == 1
    sizes = docs.mapInArrow(lambda it: (pa.RecordBatch.from_arrays([pa.array([b.nbytes])], names=["n"]) for b in it), "n long").collect()
    assert len(sizes) > 4 and max(r.n for r in sizes) < 5 << 20
    monkeypatch.setattr(C, "REMEMBERED", 7)
    monkeypatch.setattr(C, "REMEMBERED_PAIRS", 5)
    ours, theirs = C.load_pieces(piece_file()), pair[1]
    for i in range(60):
        assert ours.encode(t := f"word{i * 7919} unbelievable{i}", True) == theirs.encode(t, add_bos=True, add_eos=True)
    assert len(ours.memo) <= 7 and len(ours.beside) <= 5
