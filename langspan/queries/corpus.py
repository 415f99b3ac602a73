"""Corpus preparation and profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.functions.binding import let
from langspan.operators import metrics
from langspan.queries.base import PAGE_TEXT_SQL, docs, page_texts, utts
from langspan.sources.tables import read

SHORTEST = 2 * T.SAMPLE_RATE  # two seconds


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    segs = T.segments(docs(spark, sf_dir))
    return segs.groupBy("lang").agg(F.count(F.lit(1)).alias("n_segments"), F.sum(F.length("raw")).alias("n_chars"), F.sum(T.hash48(F.col("raw")) % T.MODULUS).alias("checksum"))


def clean_utterances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.cleaned(T.segments(docs(spark, sf_dir))).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).alias("n_chars"))


def split_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return utts(spark, sf_dir).groupBy("lang", "split").agg(F.count(F.lit(1)).alias("n"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return utts(spark, sf_dir).groupBy("lang").agg(F.count(F.lit(1)).alias("n_all"), F.countDistinct("text").alias("n_distinct"))


def leakage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and benchmark passages that share all of a passage's eight-word shingles, by equi-joins."""
    grams = lambda text: let(T.words(text), lambda ws: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(ws) - 7, F.lit(1))), lambda i: F.array_join(F.slice(ws, i, F.lit(8)), " "))))
    items = read(spark, sf_dir, "benchmark").select("item_id", grams(F.col("text")).alias("g")).select("item_id", F.size("g").alias("need"), F.explode("g").alias("gram"))
    each = docs(spark, sf_dir).select("doc_id", F.explode(grams(F.col("text"))).alias("gram"))
    hits = each.join(items, "gram").groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("n"), F.max("need").alias("need")).filter("n >= need")
    return hits.agg(F.countDistinct("doc_id").alias("n_docs"), F.countDistinct("item_id").alias("n_items"))


def corpus_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.corpus_profile(utts(spark, sf_dir))


def _grouped(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    pool = utts(spark, sf_dir)
    grouped = pool.rollup("lang", "source") if how == "rollup" else pool.cube("lang", "source")
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).alias("n_chars"), F.grouping_id().cast("bigint").alias("grouping_id"))


def profile_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grouped(spark, sf_dir, "rollup")


def profile_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grouped(spark, sf_dir, "cube")


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conv_id, turn, start, end, text of interactions of two seconds or more, on a clock of ten samples a letter."""
    order = Window.partitionBy("conv_id").orderBy("turn")
    timed = read(spark, sf_dir, "conversations").withColumn("n", F.length("text") * T.SAMPLES_PER_CHAR)
    timed = timed.withColumn("end", F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return timed.filter(F.col("n") >= SHORTEST).select("conv_id", "turn", (F.col("end") - F.col("n")).alias("start"), "end", "text", F.col("n").alias("n_samples"))


def conv_interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interactions(spark, sf_dir).select("conv_id", "turn", "start", "end")


def conv_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.corpus_profile(interactions(spark, sf_dir), by=())


def pages_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.page_blocks(read(spark, sf_dir, "pages")).select("page_id", "tag", F.length("text").cast("bigint").alias("n_chars"))


def pages_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_texts(spark, sf_dir).select("page_id", "page_lang", F.size(T.words(F.col("text"))).cast("bigint").alias("n_words"), F.md5(T.normalise(F.col("text"))).alias("text_md5"))


def pages_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = page_texts(spark, sf_dir).select("page_lang", T.normalise(F.col("text")).alias("text"))
    return metrics.corpus_profile(pages.withColumn("n_samples", F.length("text") * T.SAMPLES_PER_CHAR), by=("page_lang",))


def top_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    from langspan.operators.vocab import ranked, word_counts

    return ranked(word_counts(docs(spark, sf_dir)), ["lang"], "piece", 10).select("lang", F.col("piece").alias("w"), "n")


QUERIES = {f.__name__: f for f in (segments, clean_utterances, split_counts, dedup, leakage, corpus_profile, profile_rollup, profile_cube, conv_interactions, conv_profile, pages_blocks, pages_clean, pages_profile, top_words)}


def _profile_sql(relation: str, by: str) -> str:
    keys, comma, join = (by, by + ", ", f"s.{by} IS NOT DISTINCT FROM c.{by}") if by else ("", "", "true")
    group = f"GROUP BY {by}" if by else ""
    select = f"s.{by}, " if by else ""
    return f"""
s AS (SELECT {comma}count(*) AS n_utts, sum(n_samples)::bigint AS n_samples FROM {relation} {group}),
c AS (SELECT {comma}count(DISTINCT ch) AS n FROM (SELECT {comma}unnest(string_split(text, '')) AS ch FROM {relation}) WHERE ch <> '' AND ch <> ' ' {group})
SELECT {select}n_utts, s.n_samples, round(s.n_samples / 150.0 / 3600, 6) AS hours, coalesce(c.n, 0)::bigint AS n_unique_chars FROM s LEFT JOIN c ON {join}"""


_TURNS = """t AS (SELECT conv_id, turn, text, length(text) * 10 AS n, sum(length(text) * 10) OVER (PARTITION BY conv_id ORDER BY turn)::bigint AS e FROM conversations),
i AS (SELECT conv_id, turn, e - n AS start, e AS "end", text, n AS n_samples FROM t WHERE n >= 300)"""
_GRAMS = "list_distinct(list_transform(range(1, greatest(len(ws) - 7, 1) + 1), lambda i: array_to_string(ws[i:i + 7], ' ')))"

ORACLES = {
    "segments": f"WITH {T.SEGMENTS_SQL} SELECT lang, count(*) AS n_segments, sum(length(raw))::bigint AS n_chars, sum({T.hash48_sql('raw')} % {T.MODULUS})::bigint AS checksum FROM seg GROUP BY lang",
    "clean_utterances": f"WITH {T.CLEAN_SQL} SELECT lang, count(*) AS n, sum(length(text))::bigint AS n_chars FROM clean GROUP BY lang",
    "split_counts": f"WITH {T.UTTERANCES_SQL} SELECT lang, split, count(*) AS n FROM utt GROUP BY lang, split",
    "dedup": f"WITH {T.UTTERANCES_SQL} SELECT lang, count(*) AS n_all, count(DISTINCT text) AS n_distinct FROM utt GROUP BY lang",
    "leakage": f"""WITH bw AS (SELECT item_id, {T.WORDS_SQL.format('text')} AS ws FROM benchmark), b AS (SELECT item_id, len(g) AS need, unnest(g) AS gram FROM (SELECT item_id, {_GRAMS} AS g FROM bw)),
dw AS (SELECT doc_id, {T.WORDS_SQL.format('text')} AS ws FROM documents), d AS (SELECT doc_id, unnest({_GRAMS}) AS gram FROM dw),
h AS (SELECT doc_id, item_id FROM d JOIN b USING (gram) GROUP BY doc_id, item_id HAVING count(*) >= max(need))
SELECT count(DISTINCT doc_id) AS n_docs, count(DISTINCT item_id) AS n_items FROM h""",
    "corpus_profile": f"WITH {T.UTTERANCES_SQL}, {_profile_sql('utt', 'lang')}",
    "profile_rollup": f"WITH {T.UTTERANCES_SQL} SELECT lang, source, count(*) AS n, sum(length(text))::bigint AS n_chars, grouping(lang, source)::bigint AS grouping_id FROM utt GROUP BY ROLLUP (lang, source)",
    "profile_cube": f"WITH {T.UTTERANCES_SQL} SELECT lang, source, count(*) AS n, sum(length(text))::bigint AS n_chars, grouping(lang, source)::bigint AS grouping_id FROM utt GROUP BY CUBE (lang, source)",
    "conv_interactions": f'WITH {_TURNS} SELECT conv_id, turn, start, "end" FROM i',
    "conv_profile": f"WITH {_TURNS}, {_profile_sql('i', '')}",
    "pages_blocks": f"WITH {T.PAGES_SQL} SELECT page_id, tag, length(text)::bigint AS n_chars FROM blocks",
    "pages_clean": f"WITH {PAGE_TEXT_SQL} SELECT page_id, page_lang, len({T.WORDS_SQL.format('text')})::bigint AS n_words, md5(array_to_string({T.WORDS_SQL.format('text')}, ' ')) AS text_md5 FROM pt",
    "pages_profile": f"WITH {PAGE_TEXT_SQL}, pn AS (SELECT page_lang, array_to_string({T.WORDS_SQL.format('text')}, ' ') AS text FROM pt), pp AS (SELECT *, length(text) * 10 AS n_samples FROM pn), {_profile_sql('pp', 'page_lang')}",
    "top_words": f"WITH wc AS (SELECT lang, w, count(*) AS n FROM (SELECT lang, unnest({T.WORDS_SQL.format('text')}) AS w FROM documents) GROUP BY ALL) SELECT lang, w, n FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, w) AS k FROM wc) WHERE k <= 10",
}
