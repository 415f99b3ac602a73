"""Every query of the library by name, with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from langspan.queries import corpus, languages, measures, studies, switched, waves

_MODULES = (corpus, languages, waves, switched, measures, studies)

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {k: f for m in _MODULES for k, f in m.QUERIES.items()}
ORACLES: dict[str, str] = {k: s for m in _MODULES for k, s in m.ORACLES.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language identification accuracy on pages, from token ids of a partitioned vocabulary trained on documents."""
    return languages.lid_pages(spark, sf_dir)
