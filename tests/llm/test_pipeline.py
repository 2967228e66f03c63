import collections
import hashlib

import numpy as np
import sentencepiece

import corpus_pipeline
from sealed_frames.llm import mixing, toxicity
from sealed_frames.llm.entry import piece_file
from tests.llm.test_minhash import brute


def test_stages_against_plain_versions(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    labels = spark.read.parquet(f"{tiny}/labels.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    model = toxicity.train(docs, labels.where(~toxicity.fold("doc_id")))
    fine = {r.doc_id for r in toxicity.score(docs, model).collect() if r.score < 0.5}
    first = corpus_pipeline.drop_toxic(spark, docs, tiny)
    assert {r.doc_id for r in first.collect()} == fine and first.columns == docs.columns
    second = corpus_pipeline.drop_near_duplicates(spark, first, tiny)
    found = brute([(i, rows[i].text) for i in fine], words=5)
    assert sorted(r.doc_id for r in second.collect()) == sorted(i for i, (_, c) in found.items() if c == i)
    third = corpus_pipeline.mix_sources(spark, second, tiny)
    times = {r.doc_id: r.taken // r.size for r in mixing.mix(second).collect() if r.taken}
    assert collections.Counter(r.doc_id for r in third.collect()) == times and third.columns == docs.columns
    sp = sentencepiece.SentencePieceProcessor(model_file=piece_file())
    last = corpus_pipeline.run(spark, tiny).collect()
    assert collections.Counter(r.doc_id for r in last) == times
    for r in last:
        ids = sp.encode(rows[r.doc_id].text or "", add_bos=True, add_eos=True)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest() and r.n_tokens == len(ids)


def test_contract():
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "mixing", "sentencepiece"]


def test_empty_documents_and_no_labels(spark, tiny, tmp_path):
    docs, labels = spark.read.parquet(f"{tiny}/documents.parquet"), spark.read.parquet(f"{tiny}/labels.parquet")
    for name, d, k in (("none", docs.limit(0), labels), ("unlabelled", docs.limit(30), labels.limit(0))):
        d.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        k.write.parquet(f"{tmp_path}/{name}/labels.parquet")
        got = corpus_pipeline.run(spark, f"{tmp_path}/{name}")
        assert got.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        assert (got.count() > 0) == (name != "none")
