"""Corpus pipeline: reject toxic documents, keep one of each near-duplicate group, redact secrets, mix sources, encode.

Each stage takes (spark, docs, sf_dir), works on all documents its predecessor kept and returns a frame; ``run``
writes it as Parquet into the shared folder and reads it back as the next stage's documents. All stages but the last
return the columns of ``documents``. The mixing stage repeats a document as often as the mix takes it and leaves the
rows in the order of the shards, shuffled within each. The last stage returns one row per document of the mix with its ids and digests.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from privq.llm import bpe, mixing, ngram_join, secrets, toxicity
from privq.llm.common import give_back, give_back_driver, give_back_executors, small_batches, table
from privq.sources.scratch import materialize


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def rested(stage: Stage) -> Stage:
    """``stage``, begun with a driver and executors that don't hold what the stages before freed."""

    @functools.wraps(stage)
    def begin(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        give_back_driver(spark)
        give_back_executors(spark)
        return stage(spark, docs, sf_dir)

    return begin


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    give_back()  # what the training took of the driver
    return toxicity.drop_toxic(docs, model)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return ngram_join.keep_one_of_each(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redact(docs, secrets.default_trees(spark))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    with small_batches(spark):  # each of an executor's tasks holds a batch of whole texts on both sides
        return materialize(bpe.encode_and_decode(docs, bpe.default_tokenizer(), keep_ids=True), "pipeline-ids")


STAGES = [(name, rested(stage)) for name, stage in (("toxicity", reject_toxic), ("ngram_jaccard_join", one_of_each_group), ("secret_scan", redact_secrets), ("mixing", mix_sources), ("bpe", encode))]

#: Neither the field's scores nor the encoder can be written in SQL; tests compare with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
