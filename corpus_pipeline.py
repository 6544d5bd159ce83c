"""A corpus pipeline in five stages over the documents table; each stage returns the table's columns, the last its shards.

Language ID (rows that it rejects go), near-duplicate groups (one row of each stays), benchmark decontamination (rows with a
passage go), mixing to target weights (rows are repeated or left out), sharding (shuffled rows get shard and slot).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.llm import decontaminate, language_id, mixing, near_dedup, sharding
from rgsketch.llm.common import materialize

SHARDS = 8


def known_languages(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.keep_known(docs)


def one_of_each_group(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.keep_one(docs)


def without_benchmark(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixed(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_rows(docs)


def sharded(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sharding.shard(docs, SHARDS).select("rec.*", "shard", "slot")


STAGES = [("language ID", known_languages), ("near-dedup", one_of_each_group), ("decontamination", without_benchmark), ("mixing", mixed), ("sharding", sharded)]

#: SQL can't express the classifier, the embedding or the shuffle; tests compare stages with brute force.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs)
    return docs
