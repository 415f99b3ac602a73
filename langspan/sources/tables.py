"""The given tables with declared schemas, and the sources and sinks that users of the methods need."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


#: Tables of texts, whose rows cost far more to work on than to move.
TEXTS = ("documents", "pages")
#: A table of texts is dealt out in parts of at least so many bytes, and not at all beyond so many bytes a core.
PART_BYTES, DEALT_BYTES = 1 << 20, 32 << 20


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as Parquet with its declared schema; tables without one bring their own."""
    reader = spark.read.schema(SCHEMAS[name]) if name in SCHEMAS else spark.read
    table = reader.parquet(f"{sf_dir}/{name}.parquet")
    return dealt(table) if name in TEXTS else table


def dealt(table: DataFrame) -> DataFrame:
    """The same rows over all cores, where the files are small for the cluster: a file of one row group, which no two tasks can
    share, would leave all cores but one idle. Larger tables have row groups enough and are left as they lie, so that the
    shuffle stays below DEALT_BYTES a core; their size is that of the listed files."""
    size = int(str(table._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    cores = table.sparkSession.sparkContext.defaultParallelism
    parts = min(cores, size // PART_BYTES)
    return table.repartition(parts) if parts > 1 and size <= cores * DEALT_BYTES else table


def read_manifest(spark: SparkSession, path: str) -> DataFrame:
    """A JSON-lines manifest of utterances."""
    return spark.read.schema("utt_id bigint, lang string, source string, text string, n_samples int").json(path)


def write_manifest(utterances: DataFrame, path: str) -> None:
    utterances.select("utt_id", "lang", "source", "text", "n_samples").write.mode("overwrite").json(path)


def list_audio(spark: SparkSession, folder: str) -> DataFrame:
    """Audio files by path, size and time, their bytes left unread until asked for."""
    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(folder).select("path", F.col("length").alias("n_bytes"), "modificationTime", "content")


def write_sharded(samples: DataFrame, path: str, shard_size: int) -> None:
    """Parquet by ``shard`` = sample_id div shard_size, so that a lost shard can be made again alone."""
    samples.withColumn("shard", F.expr(f"sample_id div {int(shard_size)}")).repartition("shard").sortWithinPartitions("sample_id").write.mode("overwrite").partitionBy("shard").parquet(path)
