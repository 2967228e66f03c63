"""Corpus preparation: four stages over ``documents``, each on all that the one before it kept.

Every stage is a function (spark, docs, sf_dir) -> DataFrame; its result is written as Parquet and read
again as the next stage's input. All but the last return the columns they got.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sealed_frames.llm import minhash, mixing, sentencepiece_codec, toxicity
from sealed_frames.llm.entry import piece_file
from sealed_frames.llm.runtime import read, settle

#: The classifier and the choice of one copy can't be expressed in SQL; the tests hold run() against
#: a plain version of each stage.
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted on the labelled rows outside the held-out fold, accepts."""
    labels = read(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.where(~toxicity.fold("doc_id")))
    return toxicity.drop_toxic(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that with the smallest doc_id, of each near-duplicate group (five words, 0.8)."""
    return minhash.keep_one(docs, words=5, percent=80)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture by source weights: a document comes as often as the mix takes it."""
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Number of tokens and digests of ids and decoded text of each row of the mixture."""
    return sentencepiece_codec.encode_decode(docs, piece_file())


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("mixing", mix_sources),
    ("sentencepiece", encode),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn, from ``documents`` on."""
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = settle(stage(spark, docs, sf_dir), name)
    return docs
