"""Language identification from token ids, per token, span and utterance, and the classifiers beside it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from langspan.functions.binding import let
from langspan.functions.text import words
from langspan.operators.vocab import RangeVocab


def utterance_lid(tokens: DataFrame, vocab: RangeVocab, key: str, how: str = "count", score: str = "score") -> DataFrame:
    """key, pred_lang, n_votes: the commonest language of the tokens, or that of the largest summed score.

    A tie goes to the language of the lower range; sequences without tokens of any range get a null language.
    """
    value = F.count("_lang") if how == "count" else F.sum(score)
    votes = tokens.withColumn("_lang", vocab.lang_of(F.col("token_id"))).groupBy(key, "_lang").agg(value.alias("n_votes"))
    rank = F.struct(F.col("_lang").isNotNull(), F.round("n_votes", 6), -vocab.offset_of(F.col("_lang")))
    return votes.groupBy(key).agg(F.max_by(F.struct("_lang", "n_votes"), rank).alias("best")).select(key, F.col("best._lang").alias("pred_lang"), F.col("best.n_votes").alias("n_votes"))


def vote_in_row(token_ids: Column, vocab: RangeVocab) -> Column:
    """The same vote inside the row, from an array of ids: no shuffle."""
    within = lambda offset, size: lambda t: t.between(offset, offset + size - 1)
    counts = [F.struct(F.size(F.filter(token_ids, within(o, s))).alias("n"), F.lit(-o).alias("o"), F.lit(lang).alias("lang")) for lang, o, s in vocab.entries]
    best = F.array_max(F.array(*counts))
    return F.when(best["n"] > 0, best["lang"])


def runs(tokens: DataFrame, lang: Column, key: str) -> DataFrame:
    """key, span, lang, first_pos, last_pos, n: maximal runs of one language over the tokens that have one."""
    order = Window.partitionBy(key).orderBy("pos")
    known = tokens.withColumn("_lang", lang).filter(F.col("_lang").isNotNull())
    starts = known.withColumn("_new", F.when(F.lag("_lang").over(order) == F.col("_lang"), 0).otherwise(1))
    numbered = starts.withColumn("span", F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return numbered.groupBy(key, "span", F.col("_lang").alias("lang")).agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.count(F.lit(1)).alias("n"))


def language_spans(tokens: DataFrame, vocab: RangeVocab, key: str) -> DataFrame:
    return runs(tokens, vocab.lang_of(F.col("token_id")), key)


def spans_in_row(token_ids: Column, vocab: RangeVocab) -> Column:
    """Spans from an array of ids inside the row: array<struct<lang, first_pos>>, without a shuffle."""
    empty = F.array().cast("array<struct<lang string, first_pos int>>")

    def found(langs: Column) -> Column:
        begins = F.filter(F.sequence(F.lit(0), F.greatest(F.size(langs) - 1, F.lit(0))), lambda i: F.get(langs, i).isNotNull() & ((i == 0) | ~F.get(langs, F.greatest(i - 1, F.lit(0))).eqNullSafe(F.get(langs, i))))
        return F.transform(begins, lambda i: F.struct(F.get(langs, i).alias("lang"), i.alias("first_pos")))

    return F.when(F.size(token_ids) > 0, let(F.transform(token_ids, lambda t: vocab.lang_of(t)), found)).otherwise(empty)


def switch_kind(spans: DataFrame, ends: DataFrame, key: str) -> DataFrame:
    """kind, n of the switches between spans: inter-sentential where a sentence ends at the last token before, else intra."""
    order = Window.partitionBy(key).orderBy("span")
    switches = spans.withColumn("_next", F.lead("lang").over(order)).filter(F.col("_next").isNotNull()).select(key, F.col("last_pos").alias("pos"))
    ends = ends.select(F.col(key).alias("_key"), F.col("pos").alias("_pos")).distinct()
    kinds = switches.join(ends, (F.col(key) == F.col("_key")) & (F.col("pos") == F.col("_pos")), "left")
    return kinds.groupBy(F.when(F.col("_pos").isNull(), "intra").otherwise("inter").alias("kind")).agg(F.count(F.lit(1)).alias("n"))


def route_spans(span_words: DataFrame, models: DataFrame, floor: float) -> DataFrame:
    """Log score of every span (key columns, lang, piece) under its own language's unigram model (lang, piece, logp).

    The models are vocabularies, bounded by their ranges; words outside get ``floor``.
    """
    known = models.select(F.col("lang").alias("_lang"), F.col("piece").alias("_piece"), "logp")
    keys = [c for c in span_words.columns if c != "piece"]
    joined = span_words.join(F.broadcast(known), (F.col("lang") == F.col("_lang")) & (F.col("piece") == F.col("_piece")), "left")
    return joined.groupBy(*keys).agg(F.sum(F.coalesce("logp", F.lit(floor))).alias("score"), F.count(F.lit(1)).alias("n"))


def best_language(tokenizers: DataFrame, vocab: RangeVocab) -> DataFrame:
    """piece, lang, local_id, share: of the languages that know a piece the one in which it is most frequent.

    It stands in for the acoustic decision of a recogniser when the language of a text is unknown.
    """
    totals = tokenizers.groupBy(F.col("lang").alias("_of")).agg(F.sum("n").alias("_total"))
    rated = tokenizers.join(F.broadcast(totals), F.col("lang") == F.col("_of")).withColumn("share", F.col("n") / F.col("_total"))
    best = F.max_by(F.struct("lang", "local_id", "share"), F.struct(F.round("share", 12), -vocab.offset_of(F.col("lang"))))
    return rated.groupBy("piece").agg(best.alias("b")).select("piece", "b.lang", "b.local_id", "b.share")


def greedy_tokens(texts: DataFrame, best: DataFrame, vocab: RangeVocab, key: str, text_col: str = "text") -> DataFrame:
    """key, pos, piece, token_id, score of texts of unknown language: each word by the language it is most frequent in.

    Words that no language knows have a null token.
    """
    each = texts.select(key, F.posexplode(words(F.col(text_col))).alias("pos", "piece"))
    known = best.select(F.col("piece").alias("_piece"), (F.col("local_id") + vocab.offset_of(F.col("lang"))).cast("int").alias("token_id"), F.col("share").alias("score"))
    return each.join(F.broadcast(known), F.col("piece") == F.col("_piece"), "left").drop("_piece")


def train_word_vote(docs: DataFrame, size: int = 20_000) -> DataFrame:
    """Baseline classifier beside the recogniser: naive Bayes over words (lang, piece, logp, unseen), ``size`` words a language."""
    from langspan.operators.vocab import ranked, word_counts

    counts = ranked(word_counts(docs), ["lang"], "piece", size)
    totals = counts.groupBy(F.col("lang").alias("_of")).agg(F.sum("n").alias("_n"), F.count(F.lit(1)).alias("_v"))
    return counts.join(F.broadcast(totals), F.col("lang") == F.col("_of")).select(
        "lang", "piece", F.log((F.col("n") + 1) / (F.col("_n") + F.col("_v") + 1)).alias("logp"), F.log(F.lit(1.0) / (F.col("_n") + F.col("_v") + 1)).alias("unseen")
    )


def word_vote_lid(texts: DataFrame, model: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """key, pred, score: most probable language; a word adds what it says beyond being unseen, so only known words join."""
    each = texts.select(key, F.explode(words(F.col(text_col))).alias("piece"))
    known = model.select(F.col("piece").alias("_piece"), "lang", (F.col("logp") - F.col("unseen")).alias("gain"))
    unseen = model.groupBy("lang").agg(F.min("unseen").alias("unseen"))
    sizes = each.groupBy(F.col(key).alias("_key")).agg(F.count(F.lit(1)).alias("_n"))
    gains = each.join(known, F.col("piece") == F.col("_piece")).groupBy(key, "lang").agg(F.sum("gain").alias("gain"))
    scored = gains.join(F.broadcast(unseen), "lang").join(sizes, F.col(key) == F.col("_key")).withColumn("score", F.col("gain") + F.col("_n") * F.col("unseen"))
    return scored.groupBy(key).agg(F.max_by(F.struct("lang", "score"), F.struct(F.round("score", 6), F.col("lang"))).alias("b")).select(key, F.col("b.lang").alias("pred"), F.col("b.score").alias("score"))
