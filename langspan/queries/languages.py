"""Vocabularies, encoding, language identification, tags."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators import lid, metrics, vocab
from langspan.queries.base import OFFSET_SQL, PAGE_TEXT_SQL, TOKENS_SQL, VOCAB, VOCAB_SQL, doc_tokens, docs, greedy, greedy_sql, page_texts, tokenizers, utts, votes_sql
from langspan.session import durable
from langspan.sources.tables import read


def word_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenizers(spark, sf_dir)


def pooled_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.train_pooled(docs(spark, sf_dir))


def char_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.train_char(docs(spark, sf_dir))


def vocab_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.union_vocab(tokenizers(spark, sf_dir)).filter("n_langs > 1").select("piece", F.col("n_langs").cast("bigint").alias("n_langs"))


def range_alloc(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = tokenizers(spark, sf_dir).groupBy("lang").agg((F.count(F.lit(1)) + 1).alias("size"))
    return vocab.ranges_by_size(sizes, "lang", "size")


def encode_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = F.col("token_ids")
    encoded = vocab.encode(docs(spark, sf_dir), durable(tokenizers(spark, sf_dir)), VOCAB, "doc_id")
    unknown = F.filter(ids, lambda t: F.array_contains(F.array(*(F.lit(o) for _, o, _ in VOCAB.entries)), t))
    total = F.aggregate(ids, F.lit(0).cast("bigint"), lambda s, t: s + t)
    return encoded.select(
        "doc_id", "lang", F.size(ids).cast("bigint").alias("n_tokens"), F.size(unknown).cast("bigint").alias("n_unk"), total.alias("id_sum"), F.get(ids, F.lit(0)).alias("first_id"), F.element_at(ids, -1).alias("last_id")
    )


def decode_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = durable(tokenizers(spark, sf_dir))
    encoded = vocab.encode(docs(spark, sf_dir), known, VOCAB, "doc_id")
    return vocab.decode(encoded, known, VOCAB, "doc_id").select("doc_id", F.md5("text").alias("text_md5"))


def lang_of_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return doc_tokens(spark, sf_dir).groupBy(VOCAB.lang_of(F.col("token_id")).alias("lang")).agg(F.count(F.lit(1)).alias("n_tokens"))


def range_join_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by a range join with the table of ranges: a cross-check, not the way to do it."""
    ranges = VOCAB.to_df(spark).select(F.col("lang").alias("_lang"), "offset", "size")
    joined = doc_tokens(spark, sf_dir).join(F.broadcast(ranges), (F.col("token_id") >= F.col("offset")) & (F.col("token_id") < F.col("offset") + F.col("size")))
    return joined.groupBy(F.col("_lang").alias("lang")).agg(F.count(F.lit(1)).alias("n_tokens"))


def utterance_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lid.utterance_lid(greedy(spark, sf_dir, docs(spark, sf_dir), "doc_id"), VOCAB, "doc_id")


def utterance_lid_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = lid.utterance_lid(greedy(spark, sf_dir, docs(spark, sf_dir), "doc_id"), VOCAB, "doc_id", how="score")
    return found.select("doc_id", "pred_lang", F.round("n_votes", 6).alias("n_votes"))


def _page_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return greedy(spark, sf_dir, page_texts(spark, sf_dir), "page_id").withColumnRenamed("page_id", "utt_id")


def language_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lid.language_spans(_page_tokens(spark, sf_dir), VOCAB, "utt_id")


def switch_kind(spark: SparkSession, sf_dir: str) -> DataFrame:
    each = page_texts(spark, sf_dir).select(F.col("page_id").alias("utt_id"), F.posexplode(T.sentences(F.col("text"))).alias("s", "raw")).withColumn("n", F.size(T.words(F.col("raw"))))
    order = Window.partitionBy("utt_id").orderBy("s").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ends = each.select("utt_id", (F.sum("n").over(order) - 1).alias("pos"))
    return lid.switch_kind(language_spans(spark, sf_dir), ends, "utt_id")


def route_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, n_spans, n_words, score: spans sent to their language's unigram model."""
    models = tokenizers(spark, sf_dir)
    totals = models.groupBy(F.col("lang").alias("_of")).agg(F.sum("n").alias("_n"))
    models = models.join(F.broadcast(totals), F.col("lang") == F.col("_of")).select("lang", "piece", F.log(F.col("n") / F.col("_n")).alias("logp"))
    tokens = _page_tokens(spark, sf_dir).withColumn("lang", VOCAB.lang_of(F.col("token_id"))).filter("lang IS NOT NULL")
    order = Window.partitionBy("utt_id").orderBy("pos")
    numbered = tokens.withColumn("_new", F.when(F.lag("lang").over(order) == F.col("lang"), 0).otherwise(1)).withColumn("span", F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    scored = lid.route_spans(numbered.select("utt_id", "span", "lang", "piece"), models, -20.0)
    return scored.groupBy("lang").agg(F.count(F.lit(1)).alias("n_spans"), F.sum("n").alias("n_words"), F.round(F.sum("score"), 3).alias("score"))


def _known(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _page_tokens(spark, sf_dir).filter("token_id IS NOT NULL").select("utt_id", "pos", "token_id")


def _tag_counts(tagged: DataFrame) -> DataFrame:
    tag = vocab.is_tag(F.col("token_id"), VOCAB).cast("int")
    return tagged.groupBy("utt_id").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(tag).alias("n_tags"))


def tags_start(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tag_counts(vocab.inject_tags(_known(spark, sf_dir), VOCAB, "utt_id", "start"))


def tags_span(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tag_counts(vocab.inject_tags(_known(spark, sf_dir), VOCAB, "utt_id", "span"))


def lid_from_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vocab.lid_from_tags(vocab.inject_tags(_known(spark, sf_dir), VOCAB, "utt_id", "start"), VOCAB, "utt_id")


def _articles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.page_blocks(read(spark, sf_dir, "pages")).filter("tag = 'article'").select("page_id", "page_lang", "text")


def _judged(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _articles(spark, sf_dir)
    found = lid.utterance_lid(greedy(spark, sf_dir, pages, "page_id"), VOCAB, "page_id").select(F.col("page_id").alias("_id"), "pred_lang")
    return pages.select("page_id", "page_lang").join(found, F.col("page_id") == F.col("_id"), "left")


def lid_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.lid_accuracy(_judged(spark, sf_dir), "page_lang", "pred_lang")


def lid_pages_short(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy on the first one, three and five words of the title: n_words, lang, n, correct, accuracy."""
    pages = read(spark, sf_dir, "pages").select("page_id", T.page_language(F.col("html")).alias("page_lang"), T.words(T.title(F.col("html"))).alias("w"))
    cut = pages.withColumn("n_words", F.explode(F.array(F.lit(1), F.lit(3), F.lit(5)))).withColumn("key", F.col("page_id") * 10 + F.col("n_words")).withColumn("text", F.array_join(F.slice("w", F.lit(1), F.col("n_words")), " "))
    found = lid.utterance_lid(greedy(spark, sf_dir, cut, "key"), VOCAB, "key").select(F.col("key").alias("_key"), "pred_lang")
    judged = cut.select("key", "n_words", "page_lang").join(found, F.col("key") == F.col("_key"), "left")
    right = F.sum(F.coalesce((F.col("page_lang") == F.col("pred_lang")).cast("int"), F.lit(0)))
    out = judged.groupBy("n_words", F.col("page_lang").alias("lang")).agg(F.count(F.lit(1)).alias("n"), right.alias("correct"))
    return out.withColumn("accuracy", F.round(100 * F.col("correct") / F.col("n"), 6))


def lid_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.confusion(_judged(spark, sf_dir), "page_lang", "pred_lang")


def lid_micro_macro(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.lid_micro_macro(_judged(spark, sf_dir), "page_lang", "pred_lang")


def word_vote_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lid.word_vote_lid(_articles(spark, sf_dir), lid.train_word_vote(docs(spark, sf_dir)), "page_id").select("page_id", "pred")


def stickiness(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = language_spans(spark, sf_dir).groupBy("utt_id").agg(F.countDistinct("lang").alias("n_langs"))
    pages = page_texts(spark, sf_dir).select("page_id", "page_lang").join(spans, F.col("page_id") == F.col("utt_id"))
    return metrics.stickiness(pages, "page_lang").withColumnRenamed("page_lang", "grp")


def oov_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of the test split that the train split's vocabulary lacks."""
    pool = utts(spark, sf_dir)
    known = vocab.train_word(pool.filter("split = 'train'")).select("lang", "piece")
    each = pool.filter("split = 'test'").select("lang", F.explode(T.words(F.col("text"))).alias("piece"))
    missing = each.join(F.broadcast(known), ["lang", "piece"], "left_anti").groupBy(F.col("lang").alias("_l")).agg(F.count(F.lit(1)).alias("n_oov"))
    return each.groupBy("lang").agg(F.count(F.lit(1)).alias("n_tokens")).join(missing, F.col("lang") == F.col("_l"), "left").select("lang", "n_tokens", F.coalesce("n_oov", F.lit(0)).alias("n_oov"))


def fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.fertility(doc_tokens(spark, sf_dir), [o for _, o, _ in VOCAB.entries])


def near_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """English and Spanish words of the vocabulary at most one edit apart, by equi-join on their deletes: word, cand, dist."""
    known = tokenizers(spark, sf_dir)
    cuts = F.concat(F.array("piece"), F.transform(F.sequence(F.lit(1), F.length("piece")), lambda i: F.concat(F.substr("piece", F.lit(1), i - 1), F.substr("piece", i + 1, F.length("piece")))))
    keyed = known.select("lang", "piece", F.explode(F.array_distinct(cuts)).alias("cut"))
    a, b = keyed.filter("lang = 'en'").select("cut", F.col("piece").alias("word")), keyed.filter("lang = 'es'").select("cut", F.col("piece").alias("cand"))
    return a.join(b, "cut").select("word", "cand").distinct().withColumn("dist", F.levenshtein("word", "cand").cast("bigint")).filter("dist <= 1")


QUERIES = {
    f.__name__: f
    for f in (
        word_vocab, pooled_vocab, char_vocab, vocab_overlap, range_alloc, encode_words, decode_words, lang_of_tokens, range_join_lid, utterance_lid, utterance_lid_score, language_spans, switch_kind, route_spans,
        tags_start, tags_span, lid_from_tags, lid_pages, lid_pages_short, lid_confusion, lid_micro_macro, word_vote_lid, stickiness, oov_words, fertility, near_words,
    )
}

_SPANS = """
kn AS (SELECT *, CASE WHEN lag(lang) OVER (PARTITION BY page_id ORDER BY pos) = lang THEN 0 ELSE 1 END AS fresh FROM g WHERE lang IS NOT NULL),
nu AS (SELECT *, sum(fresh) OVER (PARTITION BY page_id ORDER BY pos)::bigint AS span FROM kn),
sp AS (SELECT page_id AS utt_id, span, lang, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS n FROM nu GROUP BY page_id, span, lang)"""
_PAGES = f"WITH {PAGE_TEXT_SQL}, {greedy_sql('pt', 'page_id')}"
_ARTICLES = f"WITH {T.PAGES_SQL}, art AS (SELECT page_id, page_lang, text FROM blocks WHERE tag = 'article'), {greedy_sql('art', 'page_id')}, {votes_sql('page_id')}, j AS (SELECT art.page_id, page_lang, pred_lang FROM art LEFT JOIN v USING (page_id))"
_TOK_LANG = VOCAB.sql_case("token_id")

ORACLES = {
    "word_vocab": f"WITH {VOCAB_SQL} SELECT lang, local_id, piece, n FROM vocab",
    "pooled_vocab": f"WITH wc AS (SELECT w AS piece, count(*) AS n FROM (SELECT unnest({T.WORDS_SQL.format('text')}) AS w FROM documents) GROUP BY ALL) SELECT k::int AS local_id, piece, n FROM (SELECT *, row_number() OVER (ORDER BY n DESC, piece) AS k FROM wc) WHERE k <= 2047",
    "char_vocab": f"WITH wc AS (SELECT lang, c AS piece, count(*) AS n FROM (SELECT lang, unnest(string_split(array_to_string({T.WORDS_SQL.format('text')}, ''), '')) AS c FROM documents) WHERE c <> '' GROUP BY ALL) SELECT lang, k::int AS local_id, piece, n FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, piece) AS k FROM wc) WHERE k <= 63",
    "vocab_overlap": f"WITH {VOCAB_SQL} SELECT piece, count(DISTINCT lang) AS n_langs FROM vocab GROUP BY piece HAVING count(DISTINCT lang) > 1",
    "range_alloc": f"WITH {VOCAB_SQL}, s AS (SELECT lang, count(*) + 1 AS size FROM vocab GROUP BY lang) SELECT lang, coalesce(sum(size) OVER (ORDER BY lang ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::bigint AS \"offset\", size FROM s",
    "encode_words": f"WITH {TOKENS_SQL} SELECT doc_id, lang, count(*) AS n_tokens, count(*) FILTER (token_id = {OFFSET_SQL.format('lang')}) AS n_unk, sum(token_id)::bigint AS id_sum, arg_min(token_id, pos) AS first_id, arg_max(token_id, pos) AS last_id FROM tok GROUP BY doc_id, lang",
    "decode_words": f"WITH {TOKENS_SQL} SELECT doc_id, md5(string_agg(coalesce(piece, '<unk>'), ' ' ORDER BY pos)) AS text_md5 FROM tok GROUP BY doc_id",
    "lang_of_tokens": f"WITH {TOKENS_SQL} SELECT {_TOK_LANG} AS lang, count(*) AS n_tokens FROM tok GROUP BY 1",
    "range_join_lid": f"WITH {TOKENS_SQL} SELECT {_TOK_LANG} AS lang, count(*) AS n_tokens FROM tok GROUP BY 1",
    "utterance_lid": f"WITH {greedy_sql('documents', 'doc_id')}, {votes_sql('doc_id')} SELECT doc_id, pred_lang, n_votes FROM v",
    "utterance_lid_score": f"WITH {greedy_sql('documents', 'doc_id')}, {votes_sql('doc_id', 'sum(score)')} SELECT doc_id, pred_lang, round(n_votes, 6) AS n_votes FROM v",
    "language_spans": f"{_PAGES}, {_SPANS} SELECT utt_id, span, lang, first_pos, last_pos, n FROM sp",
    "switch_kind": rf"""{_PAGES}, {_SPANS},
ss AS (SELECT page_id, string_split_regex(regexp_replace(text, '([.!?])\s+', '\1' || chr(10), 'g'), '\n+') AS s FROM pt),
se AS (SELECT page_id, i, len({T.WORDS_SQL.format('s[i + 1]')}) AS n FROM (SELECT *, unnest(range(len(s))) AS i FROM ss)),
en AS (SELECT DISTINCT page_id AS utt_id, sum(n) OVER (PARTITION BY page_id ORDER BY i)::bigint - 1 AS pos FROM se),
sw AS (SELECT utt_id, last_pos AS pos FROM (SELECT *, lead(lang) OVER (PARTITION BY utt_id ORDER BY span) AS nx FROM sp) WHERE nx IS NOT NULL)
SELECT CASE WHEN en.pos IS NULL THEN 'intra' ELSE 'inter' END AS kind, count(*) AS n FROM sw LEFT JOIN en ON en.utt_id = sw.utt_id AND en.pos = sw.pos GROUP BY 1""",
    "route_spans": f"""{_PAGES}, {_SPANS},
lp AS (SELECT lang, piece, ln(n / sum(n) OVER (PARTITION BY lang)) AS logp FROM vocab),
wd AS (SELECT nu.page_id, nu.span, nu.lang, coalesce(lp.logp, -20.0) AS logp FROM nu JOIN gp ON gp.page_id = nu.page_id AND gp.pos = nu.pos LEFT JOIN lp ON lp.lang = nu.lang AND lp.piece = gp.piece),
sc AS (SELECT page_id, span, lang, sum(logp) AS score, count(*) AS n FROM wd GROUP BY ALL)
SELECT lang, count(*) AS n_spans, sum(n)::bigint AS n_words, round(sum(score), 3) AS score FROM sc GROUP BY lang""",
    "tags_start": f"{_PAGES} SELECT page_id AS utt_id, count(*) + 1 AS n_tokens, 1::bigint AS n_tags FROM g WHERE lang IS NOT NULL GROUP BY page_id",
    "tags_span": f"{_PAGES}, {_SPANS} SELECT utt_id, sum(n)::bigint + 2 * count(*) AS n_tokens, 2 * count(*) AS n_tags FROM sp GROUP BY utt_id",
    "lid_from_tags": f"{_PAGES} SELECT page_id AS utt_id, arg_min(lang, pos) AS lang FROM g WHERE lang IS NOT NULL GROUP BY page_id",
    "lid_pages": f"{_ARTICLES} SELECT page_lang AS lang, count(*) AS n, count(*) FILTER (page_lang = pred_lang) AS correct, round(100.0 * count(*) FILTER (page_lang = pred_lang) / count(*), 6) AS accuracy FROM j GROUP BY page_lang",
    "lid_pages_short": f"""WITH ti AS (SELECT page_id, regexp_extract(html, '<html lang="([a-z]+)"', 1) AS page_lang, trim(regexp_replace(regexp_replace(regexp_replace(regexp_extract(html, '(?s)<title>(.*?)</title>', 1), '<[^>]*>', ' ', 'g'), '&[A-Za-z#0-9]+;', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g')) AS t FROM pages),
ct AS (SELECT page_id * 10 + n_words AS key, n_words, page_lang, array_to_string(({T.WORDS_SQL.format('t')})[1:n_words], ' ') AS text FROM ti, (VALUES (1), (3), (5)) x(n_words)), {greedy_sql('ct', 'key')}, {votes_sql('key')}
SELECT n_words, page_lang AS lang, count(*) AS n, count(*) FILTER (page_lang = pred_lang) AS correct, round(100.0 * count(*) FILTER (page_lang = pred_lang) / count(*), 6) AS accuracy FROM ct LEFT JOIN v USING (key) GROUP BY n_words, page_lang""",
    "lid_confusion": f"{_ARTICLES} SELECT page_lang AS truth, pred_lang AS pred, count(*) AS n FROM j GROUP BY page_lang, pred_lang",
    "lid_micro_macro": f"{_ARTICLES}, a AS (SELECT page_lang, count(*) AS n, count(*) FILTER (page_lang = pred_lang) AS c FROM j GROUP BY page_lang) SELECT round(100.0 * sum(c) / sum(n), 6) AS micro, round(avg(round(100.0 * c / n, 6)), 6) AS macro FROM a",
    "word_vote_lid": f"""WITH {T.PAGES_SQL}, wc AS (SELECT lang, w AS piece, count(*) AS n FROM (SELECT lang, unnest({T.WORDS_SQL.format('text')}) AS w FROM documents) GROUP BY ALL),
m AS (SELECT lang, piece, n FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, piece) AS k FROM wc) WHERE k <= 20000), t AS (SELECT lang, sum(n) AS n, count(*) AS v FROM m GROUP BY lang),
w AS (SELECT page_id, unnest({T.WORDS_SQL.format('text')}) AS piece FROM blocks WHERE tag = 'article'), z AS (SELECT page_id, count(*) AS n FROM w GROUP BY page_id),
gains AS (SELECT w.page_id, m.lang, sum(ln(m.n + 1)) AS gain FROM w JOIN m USING (piece) GROUP BY ALL),
s AS (SELECT gains.page_id, gains.lang, gain - z.n * ln(t.n + t.v + 1) AS score FROM gains JOIN z USING (page_id) JOIN t USING (lang))
SELECT page_id, lang AS pred FROM (SELECT *, row_number() OVER (PARTITION BY page_id ORDER BY round(score, 6) DESC, lang DESC) AS k FROM s) WHERE k = 1""",
    "stickiness": f"{_PAGES}, {_SPANS}, l AS (SELECT utt_id, count(DISTINCT lang) AS n_langs FROM sp GROUP BY utt_id) SELECT page_lang AS grp, count(*) AS n, count(*) FILTER (n_langs <= 1) AS n_single FROM pt JOIN l ON l.utt_id = pt.page_id GROUP BY page_lang",
    "oov_words": f"""WITH {T.UTTERANCES_SQL}, wc AS (SELECT lang, w AS piece, count(*) AS n FROM (SELECT lang, unnest({T.WORDS_SQL.format('text')}) AS w FROM utt WHERE split = 'train') GROUP BY ALL),
k AS (SELECT lang, piece FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, piece) AS k FROM wc) WHERE k <= 1023), t AS (SELECT lang, unnest({T.WORDS_SQL.format('text')}) AS piece FROM utt WHERE split = 'test')
SELECT t.lang, count(*) AS n_tokens, count(*) FILTER (k.piece IS NULL) AS n_oov FROM t LEFT JOIN k ON k.lang = t.lang AND k.piece = t.piece GROUP BY t.lang""",
    "fertility": f"WITH {TOKENS_SQL} SELECT lang, count(*) AS n_tokens, count(*) FILTER (token_id = {OFFSET_SQL.format('lang')}) AS n_unk, round(count(*) FILTER (token_id = {OFFSET_SQL.format('lang')}) / count(*), 6) AS unk_rate FROM tok GROUP BY lang",
    "near_words": f"""WITH {VOCAB_SQL}, s AS (SELECT lang, piece, {T.one_byte_sql('piece')} AS b FROM vocab),
d AS (SELECT x.piece AS word, y.piece AS cand, levenshtein(x.b, y.b) AS dist FROM s x, s y WHERE x.lang = 'en' AND y.lang = 'es')
SELECT word, cand, dist FROM d WHERE dist <= 1""",
}
