"""Generated samples as token sequences: encoding by segments, languages of tokens, boundaries between languages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators import lid, metrics, unigram, vocab
from langspan.plans import synth
from langspan.queries.base import BEST_SQL, OFFSET_SQL, VOCAB, VOCAB_SQL, tokenizers, utts
from langspan.queries.waves import PLAN, SWEEP, TEST, TRAIN, _planned, _planned_samples
from langspan.session import durable


def _texts(spark: SparkSession, sf_dir: str, *splits: str) -> DataFrame:
    """Utterances of the plan's languages, cleaned once: plans read their lengths, samples their texts."""
    mine = utts(spark, sf_dir).filter(F.col("split").isin(*splits) & F.col("lang").isin([lang for lang, _, _ in PLAN.shares]))
    return durable(mine.select("utt_id", "lang", "text", "n_samples", "split"))


def _segments(spark: SparkSession, sf_dir: str, split: str = "train", share: float = SWEEP, texts: DataFrame | None = None) -> DataFrame:
    """sample_id, slot, lang, text of generated samples. ``texts``: ``_texts``, if made before."""
    pool = (_texts(spark, sf_dir, split) if texts is None else texts).filter(F.col("split") == split)
    lengths = durable(pool.select("lang", "utt_id", "n_samples"))
    drawn = synth.slots(_planned_samples(spark, lengths, PLAN, share)).select("sample_id", "slot", "lang", F.col("utt_id").alias("_utt"))
    return drawn.join(pool.dropDuplicates(["utt_id"]).select("utt_id", "text"), F.col("_utt") == F.col("utt_id")).select("sample_id", "slot", "lang", "text")


def _words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, pos, lang (the segment's), piece of every word."""
    each = _segments(spark, sf_dir).select("sample_id", "slot", "lang", F.posexplode(T.words(F.col("text"))).alias("at", "piece"))
    order = Window.partitionBy("sample_id").orderBy("slot", "at")
    return each.select("sample_id", (F.row_number().over(order) - 1).alias("pos"), "lang", "piece")


def _guessed(words: DataFrame, spark: SparkSession, sf_dir: str) -> DataFrame:
    """``words`` with ``guess``, the language in which each is most frequent, as if no segment were known."""
    best = lid.best_language(tokenizers(spark, sf_dir), VOCAB).select(F.col("piece").alias("_piece"), F.col("lang").alias("guess"))
    return words.join(F.broadcast(best), F.col("piece") == F.col("_piece"), "left").drop("_piece")


def encode_switched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, n_tokens, id_sum, first_id, last_id: every segment by its own language's tokenizer, in order."""
    segments = F.sort_array(F.collect_list(F.struct("slot", "lang", "text"))).alias("segments")
    samples = _segments(spark, sf_dir).groupBy("sample_id").agg(segments)
    ids = F.col("token_ids")
    encoded = vocab.encode_segments(samples, tokenizers(spark, sf_dir), VOCAB)
    total = F.aggregate(ids, F.lit(0).cast("bigint"), lambda s, x: s + x)
    return encoded.select("sample_id", F.size(ids).cast("bigint").alias("n_tokens"), total.alias("id_sum"), F.get(ids, F.lit(0)).alias("first_id"), F.element_at(ids, -1).alias("last_id"))


def token_lid_switched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, n, correct, accuracy over the tokens of generated samples."""
    return metrics.lid_accuracy(_guessed(_words(spark, sf_dir), spark, sf_dir), "lang", "guess")


def switched_boundaries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """precision, recall, f1 of the places where generated samples change their language."""
    words = durable(_guessed(_words(spark, sf_dir), spark, sf_dir))
    return metrics.boundary_f1(lid.runs(words, F.col("guess"), "sample_id"), lid.runs(words, F.col("lang"), "sample_id"), "sample_id")


def straddling_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """tokenizer, n_pieces, n_across, n_tokens, n_switches, n_straddled of held-out generated samples.

    ``agg_switched``: one tokenizer over generated samples, its pieces free to cross words; ``agg_apart``: the same over the same
    segments, each by itself, so that no pair of words crosses a switch; ``con``: a tokenizer for each language, every
    segment by its own. ``n_across`` pieces hold letters of two words; ``n_straddled`` switches lie inside a piece. No SQL
    twin: trained by iteration.
    """
    texts = _texts(spark, sf_dir, "train", "test")
    segments = durable(_segments(spark, sf_dir, share=TRAIN, texts=texts))
    held = F.sort_array(F.collect_list(F.struct("slot", "lang", "text"))).alias("segments")
    tests = unigram.dealt_rows(durable(_segments(spark, sf_dir, "test", TEST, texts).groupBy("sample_id").agg(held)))
    whole = segments.groupBy("sample_id").agg(held).select(F.array_join(F.transform("segments", lambda s: s["text"]), " ").alias("text"))
    both = {"size": 2 * vocab.BLOCK, "seed_size": 4000, "across": True}
    all_of = F.lit("all").alias("lang")
    trained = {
        "agg_switched": (unigram.train_unigram(whole.select(all_of, "text"), **both), "all"),
        "agg_apart": (unigram.train_unigram(segments.select(all_of, "text"), **both), "all"),
        "con": (unigram.train_unigram(segments), None),
    }
    out = None
    for name, (pieces, pooled) in trained.items():
        told = unigram.encode_switched(tests, pieces, pooled).agg(*(F.coalesce(F.sum(c), F.lit(0)).cast("bigint").alias(c) for c in ("n_tokens", "n_switches", "n_straddled")))
        size = pieces.agg(F.count(F.lit(1)).alias("n_pieces"), F.count(F.when(F.instr("piece", unigram.MARK) > 1, 1).when(F.col("piece").rlike(f"{unigram.MARK}.+{unigram.MARK}"), 1)).alias("n_across"))
        one = size.crossJoin(told).select(F.lit(name).alias("tokenizer"), "*")
        out = one if out is None else out.union(one)
    return out


QUERIES = {f.__name__: f for f in (encode_switched, token_lid_switched, switched_boundaries, straddling_pieces)}

_WORDS = f"""{_planned(PLAN, SWEEP)},
sw AS (SELECT p.sample_id, p.slot, p.lang AS truth, {T.WORDS_SQL.format('u.text')} AS ws FROM plan p JOIN pool u ON u.utt_id = p.utt_id),
wd AS (SELECT sample_id, slot, truth, i, ws[i + 1] AS piece FROM (SELECT *, unnest(range(len(ws))) AS i FROM sw)),
num AS (SELECT sample_id, truth, piece, row_number() OVER (PARTITION BY sample_id ORDER BY slot, i) - 1 AS pos FROM wd)"""
_GUESSED = f"{_WORDS}, {BEST_SQL}, gs AS (SELECT num.*, b.lang AS guess FROM num LEFT JOIN best b ON b.piece = num.piece)"

ORACLES = {
    "encode_switched": f"""{_WORDS}, {VOCAB_SQL},
en AS (SELECT num.sample_id, num.pos, coalesce(v.local_id, 0) + {OFFSET_SQL.format('num.truth')} AS token_id FROM num LEFT JOIN vocab v ON v.lang = num.truth AND v.piece = num.piece)
SELECT sample_id, count(*) AS n_tokens, sum(token_id)::bigint AS id_sum, arg_min(token_id, pos) AS first_id, arg_max(token_id, pos) AS last_id FROM en GROUP BY sample_id""",
    "token_lid_switched": f"""{_GUESSED}
SELECT truth AS lang, count(*) AS n, count(*) FILTER (truth = guess) AS correct, round(100.0 * count(*) FILTER (truth = guess) / count(*), 6) AS accuracy FROM gs GROUP BY truth""",
    "switched_boundaries": f"""{_GUESSED},
fo AS (SELECT sample_id, pos FROM (SELECT *, lag(guess) OVER (PARTITION BY sample_id ORDER BY pos) AS before FROM gs WHERE guess IS NOT NULL) WHERE before <> guess),
tr AS (SELECT sample_id, pos FROM (SELECT *, lag(truth) OVER (PARTITION BY sample_id ORDER BY pos) AS before FROM gs) WHERE before <> truth),
c AS (SELECT (SELECT count(*) FROM fo) AS f, (SELECT count(*) FROM tr) AS t, (SELECT count(*) FROM fo JOIN tr USING (sample_id, pos)) AS h)
SELECT round(h / f, 6) AS precision, round(h / t, 6) AS recall, round(2 * h / (f + t), 6) AS f1 FROM c""",
}
