"""What the queries share: the vocabulary of the four languages, common relations, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators import lid, vocab
from langspan.sources.tables import read

#: The worked ranges (0-1023 and 1024-2047) come first; two more languages follow.
VOCAB = vocab.RangeVocab.allocate([("en", 1024), ("es", 1024), ("de", 1024), ("fr", 1024)])
OFFSET_SQL = "CASE {0} " + " ".join(f"WHEN '{lang}' THEN {o}" for lang, o, _ in VOCAB.entries) + " END"


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents")


def utts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.utterances(docs(spark, sf_dir))


def tokenizers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.train_word(docs(spark, sf_dir))


def doc_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.tokens_long(docs(spark, sf_dir), tokenizers(spark, sf_dir), VOCAB, "doc_id")


def greedy(spark: SparkSession, sf_dir: str, texts: DataFrame, key: str) -> DataFrame:
    return lid.greedy_tokens(texts, lid.best_language(tokenizers(spark, sf_dir), VOCAB), VOCAB, key)


def page_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, page_lang, text: all blocks of a page in order, a naturally switched text."""
    blocks = T.page_blocks(read(spark, sf_dir, "pages"))
    ordered = F.sort_array(F.collect_list(F.struct("block", "text")))
    return blocks.groupBy("page_id", "page_lang").agg(F.array_join(F.transform(ordered, lambda b: b["text"]), " ").alias("text"))


COUNTS_SQL = f"""wc AS (SELECT lang, w AS piece, count(*) AS n FROM (SELECT lang, unnest({T.WORDS_SQL.format('text')}) AS w FROM documents) GROUP BY ALL)"""
VOCAB_SQL = COUNTS_SQL + """,
vocab AS (SELECT lang, k::int AS local_id, piece, n FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, piece) AS k FROM wc) WHERE k <= 1023)"""
TOKENS_SQL = VOCAB_SQL + f""",
dw AS (SELECT doc_id, lang, {T.WORDS_SQL.format('text')} AS ws FROM documents),
dwp AS (SELECT doc_id, lang, i AS pos, ws[i + 1] AS piece FROM (SELECT *, unnest(range(len(ws))) AS i FROM dw)),
tok AS (SELECT d.doc_id, d.lang, d.pos, coalesce(v.local_id, 0) + {OFFSET_SQL.format('d.lang')} AS token_id, v.piece FROM dwp d LEFT JOIN vocab v ON v.lang = d.lang AND v.piece = d.piece)"""
BEST_SQL = VOCAB_SQL + f""",
rated AS (SELECT v.*, n / sum(n) OVER (PARTITION BY lang) AS share, {OFFSET_SQL.format('lang')} AS o FROM vocab v),
best AS (SELECT piece, lang, local_id + o AS token_id, share FROM (SELECT *, row_number() OVER (PARTITION BY piece ORDER BY round(share, 12) DESC, o) AS k FROM rated) WHERE k = 1)"""
PAGE_TEXT_SQL = T.PAGES_SQL + """,
pt AS (SELECT page_id, page_lang, string_agg(text, ' ' ORDER BY block) AS text FROM blocks GROUP BY page_id, page_lang)"""


def greedy_sql(relation: str, key: str, text: str = "text") -> str:
    """CTEs ending in ``g`` (key, pos, lang, token_id, score)."""
    return BEST_SQL + f""",
gw AS (SELECT {key}, {T.WORDS_SQL.format(text)} AS ws FROM {relation}),
gp AS (SELECT {key}, i AS pos, ws[i + 1] AS piece FROM (SELECT *, unnest(range(len(ws))) AS i FROM gw)),
g AS (SELECT gp.{key}, gp.pos, b.lang, b.token_id, b.share AS score FROM gp LEFT JOIN best b ON b.piece = gp.piece)"""


def votes_sql(key: str, value: str = "count(lang)") -> str:
    """A CTE ``v`` (key, pred_lang, n_votes) from ``g``."""
    return f"""
vs AS (SELECT {key}, lang, {value} AS n FROM g GROUP BY {key}, lang),
v AS (SELECT {key}, lang AS pred_lang, n AS n_votes FROM (SELECT *, row_number() OVER (PARTITION BY {key} ORDER BY (lang IS NOT NULL) DESC, round(n, 6) DESC, {OFFSET_SQL.format('lang')}) AS k FROM vs) WHERE k = 1)"""
