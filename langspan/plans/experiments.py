"""The experiments on stand-ins: error rates of monolingual, bilingual and switched models, initialisation, mixing.

Nothing here reproduces published figures, which come from recordings and trained networks; orderings can be compared.
Result rows are tidy: experiment, model, tokenizer, eval_set, n, errors, ref_words, wer.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators.recognise import NEVER, Recogniser, cost_of, error_rates, fit_scored, fit_switch, lexicon_rows, recognise, scored
from langspan.plans import synth
from langspan.session import durable
from langspan.sources.tables import read

PAIRS = (("en", "es"), ("en", "de"))
LEXICON, NOISE = 5_000, 0.05
#: Hours of generated samples that a switch cost is fitted on, and that are tested, as shares of their pools' hours.
FIT, TEST = 0.025, 0.4
#: Up to so many samples, the ids of their utterances go to all executors and the pool's texts stay where they are.
BROADCAST = 100_000


def models_for(pair: tuple[str, str], apart: float, switched: float) -> list[Recogniser]:
    """Two monolingual models; bilingual and switched ones with the pooled and the partitioned vocabulary, by the switch
    probabilities fitted on texts of one language each and on generated samples. ``ml_never`` may not switch, by definition."""
    mono = [Recogniser(f"mono_{lang}", "mono", (lang,)) for lang in pair]
    return mono + [Recogniser(name, tok, pair, cost_of(p)) for name, p in (("ml", apart), ("cs", switched)) for tok in ("agg", "con")] + [Recogniser("ml_never", "con", pair, NEVER)]


def _pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training and test utterances of the pairs' languages, cleaned and split once: every study reads them many times."""
    docs = read(spark, sf_dir, "documents").filter(F.col("lang").isin(sorted({lang for pair in PAIRS for lang in pair})))
    return durable(T.utterances(docs).filter("split <> 'dev'").select("utt_id", "lang", "text", "n_samples", "split"))


def _lexicon(pool: DataFrame) -> list[tuple[str, str, int]]:
    """The words of all languages of the pairs, counted once; models take those of their own."""
    return lexicon_rows(pool.filter("split = 'train'"), LEXICON)


#: Lengths of a pool's utterances, and ``synth.indexed_pool`` of them.
Numbered = tuple[DataFrame, tuple[DataFrame, dict[str, int]]]


def _numbered(pool: DataFrame) -> Numbered:
    """Made once for the plans of all pairs: an utterance has the same number in each."""
    lengths = durable(pool.select("lang", "utt_id", "n_samples"))
    index, sizes = synth.indexed_pool(lengths, synth.SynthConfig(weights=tuple((lang, 1.0) for lang in sorted({lang for pair in PAIRS for lang in pair}))))
    return lengths, (durable(index), sizes)


def drawn_texts(pool: DataFrame, pair: tuple[str, str], share: float, seed: int, numbered: Numbered | None = None) -> DataFrame:
    """sample_id, slot, lang, text of generated samples; text alone, no signals. ``numbered``: the pool's, if made before."""
    cfg = synth.SynthConfig(weights=tuple((lang, 0.5) for lang in pair), seed=seed)
    lengths, indexed = numbered or _numbered(pool)
    n = synth.count_for_share(lengths, cfg, share)
    planned = durable(synth.plan(lengths, cfg, n, indexed).select("sample_id", "slot", "lang", "utt_id"))
    used = planned.select(F.col("utt_id").alias("_used")).distinct()
    used = F.broadcast(used) if n <= BROADCAST else used
    drawn = pool.join(used, F.col("utt_id") == F.col("_used"), "left_semi")  # few of the pool's texts are moved on
    texts = drawn.dropDuplicates(["utt_id"]).select(F.col("utt_id").alias("_u"), "text")
    return durable(planned.join(texts, F.col("utt_id") == F.col("_u")).select("sample_id", "slot", "lang", "text"))


def joined(drawn: DataFrame) -> DataFrame:
    """sample_id, text, n_langs: the samples as a whole."""
    parts = F.sort_array(F.collect_list(F.struct("slot", "text")))
    return drawn.groupBy("sample_id").agg(F.array_join(F.transform(parts, lambda p: p["text"]), " ").alias("text"), F.countDistinct("lang").alias("n_langs"))


def switched_texts(pool: DataFrame, pair: tuple[str, str], share: float, seed: int, numbered: Numbered | None = None) -> DataFrame:
    return durable(joined(drawn_texts(pool, pair, share, seed, numbered)))


def fitted_starts(drawn: DataFrame, lexicon: list[tuple[str, str, int]], pair: tuple[str, str]) -> dict[str, float | None]:
    """Switch probabilities that fitting may start from: none, of a model fitted on either language's segments of the samples,
    and of one fitted on the segments of both. No segment holds a switch."""
    apart = drawn.select(F.concat_ws(":", "sample_id", "slot").alias("id"), "lang", "text")
    starts: dict[str, float | None] = {"scratch": None}
    for lang in pair:
        starts[f"mono:{lang}"] = fit_switch(apart.filter(F.col("lang") == lang), lexicon, (lang,), "id")[0]
    return starts | {"ml": fit_switch(apart, lexicon, pair, "id")[0]}


def fitted_models(pool: DataFrame, lexicon: list[tuple[str, str, int]], pair: tuple[str, str], numbered: Numbered | None = None) -> list[Recogniser]:
    """``models_for`` a pair: the bilingual one fitted on segments, the switched one from there on the samples."""
    drawn = drawn_texts(pool.filter("split = 'train'"), pair, FIT, 7, numbered)
    apart, _ = fit_switch(drawn.select(F.concat_ws(":", "sample_id", "slot").alias("id"), "text"), lexicon, pair, "id")
    return models_for(pair, apart, fit_switch(joined(drawn), lexicon, pair, "sample_id", apart)[0])


def _rates(rated: DataFrame, experiment: str) -> DataFrame:
    return rated.select(F.lit(experiment).alias("experiment"), "model", "tokenizer", "eval_set", "errors", "ref_words", "wer")


def wer_monolingual(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every model on each language's held-out utterances."""
    pool = _pool(spark, sf_dir)
    rows, train, out = _lexicon(pool), _numbered(pool.filter("split = 'train'")), None
    for pair in PAIRS:
        test = pool.filter((F.col("split") == "test") & F.col("lang").isin(*pair)).dropDuplicates(["text"])
        one = _rates(error_rates(test.withColumn("eval_set", F.col("lang")), fitted_models(pool, rows, pair, train), rows, "utt_id", ["eval_set"], noise=NOISE), "-".join(pair))
        out = one if out is None else out.union(one)
    return out


def wer_switched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every model on generated samples, on switched pages (blind) and on conversations (no switches)."""
    pool = _pool(spark, sf_dir)
    blocks = T.page_blocks(read(spark, sf_dir, "pages")).filter(F.length("text") > 0)
    pages = blocks.groupBy("page_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("block", "text"))), lambda b: b["text"]), " ").alias("text"), F.first("page_lang").alias("page_lang"))
    pages = durable(pages.filter(F.col("page_lang").isin(sorted({lang for pair in PAIRS for lang in pair}))))
    rows, out = _lexicon(pool), None
    train, test = (_numbered(pool.filter(F.col("split") == split)) for split in ("train", "test"))
    for pair in PAIRS:
        own = pages.filter(F.col("page_lang").isin(*pair))
        talk = read(spark, sf_dir, "conversations").filter(F.length("text") >= 30).select((F.col("conv_id") * 1000 + F.col("turn")).alias("key"), "text")
        sets = switched_texts(pool.filter("split = 'test'"), pair, TEST, 11, test).select(F.lit("generated").alias("eval_set"), F.col("sample_id").alias("key"), "text")
        sets = sets.union(own.select(F.lit("pages"), "page_id", "text")).union(talk.select(F.lit("conversations"), "key", "text"))
        sets = sets.withColumn("id", F.concat_ws(":", "eval_set", F.col("key").cast("string")))
        one = _rates(error_rates(sets, fitted_models(pool, rows, pair, train), rows, "id", ["eval_set"], noise=NOISE), "-".join(pair))
        out = one if out is None else out.union(one)
    return out


def init_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """experiment, init, start, switch, rounds, errors, ref_words, wer: switched models fitted from no model, from one of either
    language and from one of both, which were themselves fitted before; rates are over held-out generated samples."""
    pool = _pool(spark, sf_dir)
    lexicon, out = _lexicon(pool), None
    train, test = (_numbered(pool.filter(F.col("split") == split)) for split in ("train", "test"))
    for pair in PAIRS:
        drawn = drawn_texts(pool.filter("split = 'train'"), pair, FIT, 7, train)
        samples, rows, models = scored(joined(drawn), lexicon, pair, "sample_id"), [], []
        for init, start in fitted_starts(drawn, lexicon, pair).items():
            p, rounds = fit_scored(samples, pair, start)
            rows.append(("-".join(pair), init, None if start is None else round(start, 9), round(p, 6), rounds))
            models.append(Recogniser(init, "con", pair, cost_of(p)))
        held = switched_texts(pool.filter("split = 'test'"), pair, TEST, 11, test)
        rated = error_rates(held, models, lexicon, "sample_id", noise=NOISE).withColumnRenamed("model", "_model")
        told = spark.createDataFrame(rows, "experiment string, init string, start double, switch double, rounds int")
        one = told.join(F.broadcast(rated), F.col("init") == F.col("_model")).select(*told.columns, "errors", "ref_words", "wer")
        out = one if out is None else out.union(one)
    return out


def ratio_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ratio, tokenizer, trained, changed: tokenizers that a new mixture needs, and pooled pieces that it changes.

    A partitioned vocabulary is trained once for each language whatever the ratio; a pooled one for every ratio.
    """
    from langspan.operators.vocab import BLOCK, train_pooled

    pool = _pool(spark, sf_dir).filter("split = 'train' AND lang IN ('en', 'es')")
    base, rows = None, []
    for name, ratio in (("1:1", (("en", 1.0), ("es", 1.0))), ("2:1", (("en", 2.0), ("es", 1.0))), ("1:2", (("en", 1.0), ("es", 2.0)))):
        pieces = train_pooled(synth.mix(pool, ratio), 2 * BLOCK).select("piece")
        base = pieces if base is None else base
        rows += [(name, "agg", 1, pieces.join(base, "piece", "left_anti").count()), (name, "con", 0 if rows else 2, 0)]
    return spark.createDataFrame(rows, "ratio string, tokenizer string, trained int, changed bigint")


def stickiness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """model, tokenizer, n, n_single: outputs on mixed generated samples that stay in one language."""
    pool = _pool(spark, sf_dir)
    pair = PAIRS[0]
    rows = lexicon_rows(pool.filter("split = 'train'").filter(F.col("lang").isin(*pair)), LEXICON)
    mixed = switched_texts(pool.filter("split = 'test'"), pair, TEST, 11).filter("n_langs > 1")
    heard = recognise(mixed, fitted_models(pool, rows, pair), rows, "sample_id", noise=NOISE)
    return heard.groupBy("model", "tokenizer").agg(F.count(F.lit(1)).alias("n"), F.sum((F.size(F.array_distinct("langs")) <= 1).cast("int")).alias("n_single"))
