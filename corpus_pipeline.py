"""From raw documents to shards: five operators, each over what the last kept."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from levcut.llm import decontaminate, mixing, quality, shards, similar, simhash
from levcut.llm.common import checkpoint_folder, drop_folder, drop_stored, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.accept(docs.select(*COLUMNS), table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs = docs.select(*COLUMNS)
    return simhash.keep_one(docs, similar.cluster(docs))


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.emit(mixing.plan(docs.select(*COLUMNS)), COLUMNS)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shards.assign(docs)


STAGES = [
    ("quality", keep_quality),
    ("near_copies", drop_near_copies),
    ("benchmark", drop_benchmark),
    ("mixing", mix_sources),
    ("sharding", shard),
]

#: SQL can't express the classifier or the fingerprints.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written and read again.

    The written tables stand in the shared checkpoint folder of the session. When a
    stage is written, the table that it has read and its own helping tables go; the
    last table stays, as the result reads it.
    """
    base = f"{checkpoint_folder(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{name}")
        drop_stored(spark)
        if before:
            drop_folder(spark, before)
        before = f"{base}/{name}"
        docs = spark.read.parquet(before)
    return docs
