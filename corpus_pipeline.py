"""From raw documents to sharded training data: five stages, each a function of (spark, docs, sf_dir)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from langspan.llm import decontamination, mixing, quality, sharding, similarity_join
from langspan.llm.common import durable, table

#: Sources weigh their size to this power; none loses a document, small ones are read up to three times.
TEMPER = 0.8


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of low quality and toxic ones go."""
    return quality.drop_poor(docs, table(spark, sf_dir, "labels"), *quality.document_sites())


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that link at 0.8 on five-word shingles, directly or over others, the one with the smallest id stays."""
    return similarity_join.one_of_each(docs, similarity_join.Rule(words=5, num=80, den=100))


def keep_unleaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontamination.drop_leaking(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are brought to tempered weights; a document read again is a row of its own."""
    return mixing.mix(docs, weight=mixing.tempered_weight(TEMPER), share=None)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row gets a shard and a slot in it."""
    return sharding.assign_shards(docs)


STAGES = [
    ("quality", keep_good),
    ("near_duplicates", keep_one_of_each),
    ("decontamination", keep_unleaked),
    ("mixing", mix_sources),
    ("sharding", shard),
]

#: A trained classifier and its cuts are not SQL; tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = durable(docs)
    return docs
