"""Decoder head, CTC, signals and the generator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import signal as S
from langspan.functions import text as T
from langspan.operators import head, vocab
from langspan.plans import synth
from langspan.queries.base import utts
from langspan.session import durable
from langspan.sources.tables import read

#: Ten labels of the embeddings as two languages of five tokens.
TWO = vocab.RangeVocab.allocate([("a", 5), ("b", 5)])
PAIRS = {"en-es": (("en", 0.5), ("es", 0.5)), "en-de": (("en", 0.5), ("de", 0.5))}
PLAN = synth.SynthConfig()
#: Hours planned, as shares of the pool's hours: the training corpus (10 h at sf0.01), sweeps, what is rendered; and the
#: test sets (10 h a pair at sf0.01, each pool used about four times).
TRAIN, SWEEP, RENDER, TEST = 0.5, 0.1, 0.1, 4.0


def _states(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    vectors = read(spark, sf_dir, "embeddings")
    return vectors.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("h")), head.class_means(vectors)


def head_argmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    states, layer = _states(spark, sf_dir)
    return head.project(states, layer, "vec_id")


def head_suppressed(spark: SparkSession, sf_dir: str) -> DataFrame:
    states, layer = _states(spark, sf_dir)
    return head.project(states, layer, "vec_id", TWO, ["a"])


def head_grown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The old languages' outputs of a layer that a third language was added to: as before."""
    states, layer = _states(spark, sf_dir)
    grown = TWO.extend("c", 8)
    return head.project(states, head.grow_head(layer, TWO, grown, 64), "vec_id", grown, ["a", "b"])


def head_merged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two monolingual layers with ids from 0 merged into one."""
    states, layer = _states(spark, sf_dir)
    own = [(lang, layer.filter(TWO.lang_predicate(F.col("token_id"), [lang])).withColumn("token_id", F.col("token_id") - TWO.range(lang)[0])) for lang in TWO.langs]
    return head.project(states, head.merge_heads(own, TWO), "vec_id")


def posterior_fusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    states, layer = _states(spark, sf_dir)
    scored = states.crossJoin(F.broadcast(layer)).select("vec_id", TWO.lang_of(F.col("token_id")).alias("lang"), F.exp(head.dot(F.col("h"), F.col("w"))).alias("e"))
    by_lang = scored.groupBy("vec_id", "lang").agg(F.max("e").alias("e"))
    total = by_lang.groupBy(F.col("vec_id").alias("_v")).agg(F.sum("e").alias("t"))
    lid = by_lang.join(total, F.col("vec_id") == F.col("_v")).select("vec_id", "lang", (F.col("e") / F.col("t")).alias("p"))
    return head.posterior_fusion(states, layer, lid, "vec_id", TWO)


def ctc_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of a user as frames: id = k mod 3, 0 the blank."""
    frames = read(spark, sf_dir, "events").select("user_id", "ts", "event_id", (F.from_json("props", "k INT")["k"] % 3).alias("id"))
    ordered = frames.groupBy("user_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("ts", "event_id", "id"))), lambda f: f["id"]).alias("ids"))
    return ordered.select("user_id", F.size("ids").cast("bigint").alias("n_in"), F.size(head.ctc_collapse(F.col("ids"), 0)).cast("bigint").alias("n_out"))


def trim_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = S.bounds(F.col("embedding"), 0.2)
    return read(spark, sf_dir, "embeddings").select("vec_id", b.alias("b")).select("vec_id", F.col("b.first").cast("bigint").alias("first_i"), F.col("b.last").cast("bigint").alias("last_i"))


def _sum6(signal) -> F.Column:
    return F.round(F.aggregate(signal, F.lit(0.0), lambda s, x: s + F.abs(x.cast("double"))), 6)


def peak_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    scaled = S.peak_scale(F.col("embedding"), 0.5)
    return read(spark, sf_dir, "embeddings").select("vec_id", F.round(S.peak(F.col("embedding")).cast("double"), 6).alias("peak"), scaled.alias("s")).select("vec_id", "peak", _sum6("s").alias("sum6"))


def concat_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signals of a label in groups of sixteen ids, trimmed, joined with silences of 15 samples between and 3 at the ends."""
    each = read(spark, sf_dir, "embeddings").select("label", F.expr("vec_id div 16").alias("part"), "vec_id", S.trim(F.col("embedding"), 0.2).alias("s"))
    grouped = each.groupBy("label", "part").agg(F.sort_array(F.collect_list(F.struct("vec_id", "s"))).alias("g")).select("label", "part", F.transform("g", lambda x: x["s"]).alias("g"))
    joined = grouped.select("label", "part", S.join_signals(F.col("g"), S.silence(3), S.silence(15), S.silence(3)).alias("s"))
    return joined.select("label", "part", F.size("s").cast("bigint").alias("n_samples"), _sum6("s").alias("sum6"))


def rms_snr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Root mean square of each signal, and that of noise ten decibels below."""
    level = S.rms(F.col("embedding"))
    return read(spark, sf_dir, "embeddings").select("vec_id", F.round(level, 6).alias("rms6"), F.round(S.noise_level(level, 10.0), 6).alias("noise6"))


def _pool(spark: SparkSession, sf_dir: str, split: str = "train") -> DataFrame:
    return utts(spark, sf_dir).filter(F.col("split") == split)


def _lengths(spark: SparkSession, sf_dir: str, split: str = "train") -> DataFrame:
    """What planning reads of the pool, made once."""
    return durable(_pool(spark, sf_dir, split).select("lang", "utt_id", "n_samples"))


def _planned_samples(spark: SparkSession, pool: DataFrame, cfg: synth.SynthConfig, share: float) -> DataFrame:
    return synth.plan_samples(synth.range_of(spark, synth.count_for_share(pool, cfg, share)), pool, cfg)


def planned(spark: SparkSession, sf_dir: str, share: float = TRAIN, split: str = "train", cfg: synth.SynthConfig = PLAN) -> DataFrame:
    return synth.slots(_planned_samples(spark, _lengths(spark, sf_dir, split), cfg, share))


def synth_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    planned = _planned_samples(spark, _lengths(spark, sf_dir), PLAN, TRAIN)
    return planned.select("sample_id", F.size("picks").cast("bigint").alias("n_segments"), F.col("total").cast("bigint").alias("total"))


def synth_plan_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planned(spark, sf_dir, SWEEP)


def synth_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return synth.profile(planned(spark, sf_dir))


def edge_bias(spark: SparkSession, sf_dir: str) -> DataFrame:
    return synth.edge_bias(planned(spark, sf_dir))


def padding_waste(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Padding in batches of 32: generated samples."""
    return synth.padding_waste(synth_plan(spark, sf_dir), 32)


def padding_waste_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over plain utterances, by ranges of 32 documents: what similar lengths save."""
    return synth.padding_waste(_pool(spark, sf_dir).filter("lang IN ('en', 'es')").select("doc_id", F.col("n_samples").alias("total")), 32, key="doc_id")


def pool_reuse(spark: SparkSession, sf_dir: str) -> DataFrame:
    pool = _lengths(spark, sf_dir).filter("lang IN ('en', 'es')")
    return synth.reuse(synth.slots(_planned_samples(spark, pool, PLAN, TRAIN)), pool)


def synth_switches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n_langs, n, switches: how mixed the samples are."""
    seen = synth.sample_profile(planned(spark, sf_dir))
    return seen.groupBy("n_langs").agg(F.count(F.lit(1)).alias("n"), F.sum("switches").cast("bigint").alias("switches"))


_SWEEP = {
    "equal": synth.SynthConfig(),
    "nine_to_one": synth.SynthConfig(weights=(("en", 0.9), ("es", 0.1))),
    "four_languages": synth.SynthConfig(weights=(("en", 0.25), ("es", 0.25), ("de", 0.25), ("fr", 0.25))),
    "short": synth.SynthConfig(min_s=7.0, max_s=9.0),
    "plain": synth.plain_config(synth.SynthConfig()),
}


def sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return synth.sweep(_lengths(spark, sf_dir), list(_SWEEP.items()), SWEEP)


def synth_test_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plans of both pairs over the held-out pool: pair, sample_id, n_segments, total."""
    pool = _lengths(spark, sf_dir, "test")
    out = None
    for pair, weights in PAIRS.items():
        one = _planned_samples(spark, pool, synth.SynthConfig(weights=weights, seed=1), TEST)
        one = one.select(F.lit(pair).alias("pair"), "sample_id", F.size("picks").cast("bigint").alias("n_segments"), F.col("total").cast("bigint").alias("total"))
        out = one if out is None else out.union(one)
    return out


def _rendered(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    drawn = durable(planned(spark, sf_dir, RENDER))
    used = drawn.select(F.col("utt_id").alias("_used")).distinct()
    voiced = _pool(spark, sf_dir).join(used, F.col("utt_id") == F.col("_used"), "left_semi").dropDuplicates(["utt_id"])
    voiced = voiced.select("utt_id", "text", S.sonify(F.col("text"), F.col("source"), F.col("utt_id")).alias("signal"))
    return synth.render(drawn, voiced, PLAN, **options)


def synth_render_len(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rendered from signals: lengths, and peaks equal to the scale."""
    done = _rendered(spark, sf_dir).select("sample_id", F.col("n_samples").cast("bigint").alias("n_samples"), F.size("segments").cast("bigint").alias("n_segments"), F.round(S.peak(F.col("signal")).cast("double"), 6).alias("peak"))
    return done


def synth_render(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rendered(spark, sf_dir)


def stitched_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: untouched signals stitched; spread of segment peaks within a sample against the generator's."""
    rows = []
    for name, options in (("stitched", {"trim": False, "normalise": False}), ("levelled", {})):
        cut = F.transform("segments", lambda g: S.peak(F.slice("signal", g["start"] + 1, g["n_samples"])))
        done = _rendered(spark, sf_dir, **options).select(cut.alias("peaks"))
        rows.append(done.select(F.lit(name).alias("method"), (F.array_max("peaks") - F.array_min("peaks")).alias("spread")).groupBy("method").agg(F.round(F.avg("spread"), 6).alias("mean_spread"), F.count(F.lit(1)).alias("n")))
    return rows[0].union(rows[1])


def mix_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ratio, lang, n_in, n_out, share of the natural, 1:1 and 2:1 mixtures of English and Spanish."""
    pool = _lengths(spark, sf_dir).filter("lang IN ('en', 'es')")
    have = {r["lang"]: float(r["n"]) for r in pool.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    rows = None
    for name, ratio in (("natural", have.items()), ("1:1", (("en", 1.0), ("es", 1.0))), ("2:1", (("en", 2.0), ("es", 1.0)))):
        times = synth.repeats(have, list(ratio), seed=0)
        one = pool.groupBy("lang").agg(F.count(F.lit(1)).alias("n_in"), F.sum(times).cast("bigint").alias("n_out")).withColumn("ratio", F.lit(name))
        rows = one if rows is None else rows.unionByName(one)
    share = F.col("n_out") / F.sum("n_out").over(Window.partitionBy("ratio"))
    return rows.select("ratio", "lang", "n_in", "n_out", F.round(share, 6).alias("share"))


def storage_overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of the training corpus as amplitudes: written offline, and online."""
    return synth.storage(planned(spark, sf_dir))


QUERIES = {
    f.__name__: f
    for f in (
        head_argmax, head_suppressed, head_grown, head_merged, posterior_fusion, ctc_collapse, trim_embeddings, peak_embeddings, concat_embeddings, rms_snr, synth_plan, synth_plan_slots, synth_profile, edge_bias,
        padding_waste, padding_waste_pool, pool_reuse, synth_switches, sweep, synth_test_plan, synth_render_len, synth_render, stitched_levels, mix_ratio, storage_overhead,
    )
}

_LOGITS = """m AS (SELECT label, i, avg(embedding[i]::double) AS x FROM (SELECT label, embedding, unnest(range(1, 65)) AS i FROM embeddings) GROUP BY label, i),
w AS (SELECT label AS token_id, list(x ORDER BY i) AS w FROM m GROUP BY label),
z AS (SELECT vec_id, token_id, list_dot_product(embedding::double[], w) AS raw, round(list_dot_product(embedding::double[], w), 6) AS score FROM embeddings, w)"""


def _argmax(where: str = "true") -> str:
    return f"WITH {_LOGITS} SELECT vec_id, token_id, score FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, token_id) AS k FROM z WHERE {where}) WHERE k = 1"


def _planned(cfg: synth.SynthConfig, n: float, split: str = "train") -> str:
    return f"WITH RECURSIVE {T.UTTERANCES_SQL}, pool AS (SELECT * FROM utt WHERE split = '{split}'), {synth.plan_sql(cfg, n, 'pool')}"


_PROFILE = "SELECT lang, count(*) AS n_segments, sum(n_samples)::bigint AS n_samples, round(sum(n_samples) / sum(sum(n_samples)) OVER (), 6) AS share FROM plan GROUP BY lang"
_MIX = """SELECT '{0}' AS ratio, lang, n_in, n_out, round(n_out / sum(n_out) OVER (), 6) AS share FROM (
  SELECT lang, count(*) AS n_in, sum(floor(f)::bigint + CASE WHEN h / 281474976710656.0 < f - floor(f) THEN 1 ELSE 0 END)::bigint AS n_out FROM (
    SELECT lang, {2} AS h, (SELECT max(n / w) FROM (SELECT count(*)::double AS n, CASE lang WHEN 'en' THEN {1} ELSE 1.0 END AS w FROM pool GROUP BY lang)) * CASE lang WHEN 'en' THEN {1} ELSE 1.0 END / count(*) OVER (PARTITION BY lang) AS f FROM pool)
  GROUP BY lang)"""
_MIX_POOL = f"WITH {T.UTTERANCES_SQL}, pool AS (SELECT * FROM utt WHERE split = 'train' AND lang IN ('en', 'es'))"
_TRIM = """b AS (SELECT vec_id, label, embedding AS e, list_max(list_transform(embedding, lambda x: abs(x)))::double AS top FROM embeddings),
l AS (SELECT *, list_filter(range(1, 65), lambda i: abs(e[i])::double > top * 0.2) AS loud FROM b)"""

ORACLES = {
    "head_argmax": _argmax(),
    "head_suppressed": _argmax("token_id < 5"),
    "head_grown": _argmax(),
    "head_merged": _argmax(),
    "posterior_fusion": f"""WITH {_LOGITS}, y AS (SELECT *, token_id // 5 AS g, ln(sum(exp(raw)) OVER (PARTITION BY vec_id, token_id // 5)) AS norm, max(exp(raw)) OVER (PARTITION BY vec_id, token_id // 5) AS e FROM z),
t AS (SELECT vec_id, sum(e) AS t FROM (SELECT DISTINCT vec_id, g, e FROM y) GROUP BY vec_id), f AS (SELECT y.vec_id, token_id, round(raw - norm + ln(e / t.t), 6) AS score FROM y JOIN t USING (vec_id))
SELECT vec_id, token_id, score FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, token_id) AS k FROM f) WHERE k = 1""",
    "ctc_collapse": """WITH f AS (SELECT user_id, ts, event_id, (props::json->>'k')::int % 3 AS id FROM events), l AS (SELECT *, lag(id) OVER (PARTITION BY user_id ORDER BY ts, event_id, id) AS before FROM f)
SELECT user_id, count(*) AS n_in, count(*) FILTER (id <> 0 AND id IS DISTINCT FROM before) AS n_out FROM l GROUP BY user_id""",
    "trim_embeddings": f"WITH {_TRIM} SELECT vec_id, loud[1] AS first_i, loud[-1] AS last_i FROM l",
    "peak_embeddings": "WITH b AS (SELECT vec_id, embedding AS e, list_max(list_transform(embedding, lambda x: abs(x))) AS top FROM embeddings) SELECT vec_id, round(top::double, 6) AS peak, round(list_sum(list_transform(e, lambda x: abs((x::double / top::double * 0.5)::float::double))), 6) AS sum6 FROM b",
    "concat_embeddings": f"WITH {_TRIM}, s AS (SELECT label, vec_id // 16 AS part, list_transform(e[loud[1]:loud[-1]], lambda x: abs(x::double)) AS s FROM l) SELECT label, part, (sum(len(s)) + 6 + 15 * (count(*) - 1))::bigint AS n_samples, round(sum(list_sum(s)), 6) AS sum6 FROM s GROUP BY label, part",
    "rms_snr": "WITH r AS (SELECT vec_id, sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double)) / len(embedding)) AS r FROM embeddings) SELECT vec_id, round(r, 6) AS rms6, round(r / pow(10, 0.5), 6) AS noise6 FROM r",
    "synth_plan": f"{_planned(PLAN, TRAIN)} SELECT sample_id, count(*) AS n_segments, max(total)::bigint AS total FROM plan GROUP BY sample_id",
    "synth_plan_slots": f"{_planned(PLAN, SWEEP)} SELECT sample_id, slot, lang, utt_id, start, n_samples, total FROM plan",
    "synth_profile": f"{_planned(PLAN, TRAIN)} {_PROFILE}",
    "edge_bias": f"{_planned(PLAN, TRAIN)}, e AS (SELECT sample_id, arg_min(lang, slot) AS a, arg_max(lang, slot) AS b FROM plan GROUP BY sample_id) SELECT lang, sum(f)::bigint AS n_first, sum(l)::bigint AS n_last FROM (SELECT a AS lang, 1 AS f, 0 AS l FROM e UNION ALL SELECT b, 0, 1 FROM e) GROUP BY lang",
    "padding_waste": f"{_planned(PLAN, TRAIN)}, s AS (SELECT DISTINCT sample_id, total FROM plan) SELECT sample_id // 32 AS batch_no, count(*) AS n, round(1 - sum(total) / (count(*) * max(total)), 6) AS waste FROM s GROUP BY 1",
    "padding_waste_pool": f"WITH {T.UTTERANCES_SQL} SELECT doc_id // 32 AS batch_no, count(*) AS n, round(1 - sum(n_samples) / (count(*) * max(n_samples)), 6) AS waste FROM utt WHERE split = 'train' AND lang IN ('en', 'es') GROUP BY 1",
    "pool_reuse": f"{_planned(PLAN, TRAIN)}, h AS (SELECT lang, sum(n_samples)::bigint AS pool_samples FROM pool GROUP BY lang), d AS (SELECT lang, sum(n_samples)::bigint AS drawn FROM plan GROUP BY lang) SELECT lang, drawn, pool_samples, round(drawn / pool_samples, 6) AS times FROM d JOIN h USING (lang)",
    "synth_switches": f"{_planned(PLAN, TRAIN)}, w AS (SELECT *, CASE WHEN lag(lang) OVER (PARTITION BY sample_id ORDER BY slot) <> lang THEN 1 ELSE 0 END AS sw FROM plan), s AS (SELECT sample_id, count(DISTINCT lang) AS n_langs, sum(sw) AS sw FROM w GROUP BY sample_id) SELECT n_langs, count(*) AS n, sum(sw)::bigint AS switches FROM s GROUP BY n_langs",
    "sweep": " UNION ALL ".join(f"SELECT '{name}' AS name, lang, n_segments, n_samples, share FROM ({_planned(cfg, SWEEP)} {_PROFILE})" for name, cfg in _SWEEP.items()),
    "synth_test_plan": " UNION ALL ".join(
        f"SELECT '{pair}' AS pair, * FROM ({_planned(synth.SynthConfig(weights=weights, seed=1), TEST, 'test')} SELECT sample_id, count(*) AS n_segments, max(total)::bigint AS total FROM plan GROUP BY sample_id)" for pair, weights in PAIRS.items()
    ),
    "synth_render_len": f"{_planned(PLAN, RENDER)} SELECT sample_id, max(total)::bigint AS n_samples, count(*) AS n_segments, 1.0::double AS peak FROM plan GROUP BY sample_id",
    "storage_overhead": f"{_planned(PLAN, TRAIN)}, s AS (SELECT DISTINCT sample_id, total FROM plan), t AS (SELECT count(*) AS n_samples, (sum(total) * 4)::bigint AS b FROM s) SELECT 'offline' AS mode, n_samples, b AS bytes FROM t UNION ALL SELECT 'online', n_samples, 0::bigint FROM t",
    "mix_ratio": f"{_MIX_POOL} SELECT 'natural' AS ratio, lang, count(*) AS n_in, count(*) AS n_out, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM pool GROUP BY lang UNION ALL " + " UNION ALL ".join(_MIX.format(name, w, T.hash48_sql("'mix:0:' || utt_id::varchar")) for name, w in (("1:1", "1.0"), ("2:1", "2.0"))),
}
