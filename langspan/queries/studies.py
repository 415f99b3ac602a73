"""Iterative and Arrow-backed methods: no SQL twin; tests hold them against brute force and invariants."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators import lid, metrics, recognise, unigram
from langspan.plans import experiments
from langspan.queries.base import VOCAB, docs, utts
from langspan.sources.tables import read


def unigram_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four subword tokenizers of 1024 pieces."""
    return unigram.train_unigram(docs(spark, sf_dir))


def unigram_pooled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: one subword tokenizer of 2048 pieces over English and Spanish together."""
    both = docs(spark, sf_dir).filter("lang IN ('en', 'es')").withColumn("lang", F.lit("all"))
    return unigram.train_unigram(both, size=2048, seed_size=4000)


def unigram_encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, n_words, n_tokens, n_unk of the held-out split by the tokenizers of ``unigram_vocab``."""
    offsets = {lang: o for lang, o, _ in VOCAB.entries}
    test = utts(spark, sf_dir).filter("split = 'test'")
    ids = unigram.encode_unigram(test, unigram_vocab(spark, sf_dir), "utt_id", offsets)
    unk = F.size(F.filter("pieces", lambda p: p == "<unk>"))
    return ids.groupBy("lang").agg(F.sum(F.size(F.filter("pieces", lambda p: p.startswith(unigram.MARK)))).alias("n_words"), F.sum(F.size("pieces")).alias("n_tokens"), F.sum(unk).alias("n_unk"))


def decode_mixed_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy on page titles decoded over all languages' subwords (of ``unigram_vocab``) at once."""
    offsets = {lang: o for lang, o, _ in VOCAB.entries}
    pages = read(spark, sf_dir, "pages").select("page_id", T.page_language(F.col("html")).alias("page_lang"), T.title(F.col("html")).alias("text"))
    found = unigram.decode_mixed(pages, unigram_vocab(spark, sf_dir), "page_id", offsets).select(F.col("page_id").alias("_p"), lid.vote_in_row(F.col("token_ids"), VOCAB).alias("pred"))
    return metrics.lid_accuracy(pages.join(found, F.col("page_id") == F.col("_p")), "page_lang", "pred")


def lexicon_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """key, cost: cheapest language paths of page titles over explicit arcs of per-language word costs."""
    model = lid.train_word_vote(docs(spark, sf_dir))
    pages = read(spark, sf_dir, "pages").select("page_id", F.posexplode(T.words(T.title(F.col("html")))).alias("pos", "piece"))
    known = model.select("piece", "lang", (-F.col("logp")).alias("cost"))
    arcs = pages.join(known, "piece").select("page_id", "pos", "lang", "cost")
    floor = pages.select("page_id", "pos", F.explode(F.array(*map(F.lit, VOCAB.langs))).alias("lang"), F.lit(20.0).alias("cost"))
    return recognise.lexicon_paths(arcs.union(floor), "page_id", VOCAB.langs, 4.0)


QUERIES = {
    f.__name__: f for f in (unigram_vocab, unigram_pooled, unigram_encode, decode_mixed_lid, lexicon_paths)
} | {"wer_monolingual": experiments.wer_monolingual, "wer_switched": experiments.wer_switched, "init_study": experiments.init_study, "ratio_study": experiments.ratio_study, "model_stickiness": experiments.stickiness}
ORACLES: dict[str, str] = {}
