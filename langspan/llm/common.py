"""Small shared pieces: table access, stable hashes, names that do not clash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.session import durable

__all__ = ["WORD", "durable", "hash48", "inner_names", "table", "without", "word_count"]

#: Word pattern of the contracts: everything but space and tab..carriage return.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hash48(text: Column) -> Column:
    """First 48 bits of MD5 as a BIGINT: the same integer in any SQL engine that has MD5."""
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("bigint")


def word_count(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("bigint")


def without(df: DataFrame, *names: str) -> DataFrame:
    """Columns that would clash with an operator's own are dropped: the operator's win."""
    lower = {x.lower() for x in names}
    return df.select([F.col(f"`{c}`") for c in df.columns if c.lower() not in lower])


def inner_names(df: DataFrame, *names: str) -> list[str]:
    """Names for an operator's inner columns that no column of ``df`` has, so that it drops none of the caller's."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out
