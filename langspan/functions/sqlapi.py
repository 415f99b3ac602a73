"""The methods in SQL: scalar functions that Catalyst inlines, and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from langspan.operators.vocab import RangeVocab


def register(spark: SparkSession, vocab: RangeVocab) -> None:
    """``lang_of(id)``, ``shift_id(lang, local_id)``, and the table functions ``spans(ids)`` and ``sample_ids(first, n)``."""
    case = vocab.sql_case("id")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lang_of(id INT) RETURNS STRING RETURN {case}")
    offsets = " ".join(f"WHEN '{lang}' THEN {offset}" for lang, offset, _ in vocab.entries)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION shift_id(lang STRING, local_id INT) RETURNS INT RETURN local_id + CASE lang {offsets} END")
    entries = vocab.entries

    class Spans:
        def eval(self, ids: list):  # noqa: ANN201
            name = lambda t: next((lang for lang, o, s in entries if t is not None and o <= t < o + s), None)
            first, before, number = 0, None, 0
            for k, t in enumerate([*(ids or []), None]):
                lang = name(t) if k < len(ids or []) else None
                if lang != before:
                    if before is not None:
                        number += 1
                        yield number, before, first, k - 1
                    first, before = k, lang

    class SampleIds:
        def eval(self, first: int, n: int):  # noqa: ANN201
            for k in range(n):
                yield (first + k,)

    spark.udtf.register("spans", udtf(Spans, returnType="span int, lang string, first_pos int, last_pos int"))
    spark.udtf.register("sample_ids", udtf(SampleIds, returnType="sample_id bigint"))
