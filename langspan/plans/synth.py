"""Switched samples from monolingual pools: planned on lengths alone, rendered from signals afterwards.

All chance is a hash of (seed, sample, draw, purpose), so a plan is the same for any partitioning, on a retry, in batch
and in a stream. A sample draws a language by its weight, then an utterance of that language's pool, and takes it if
the sample stays within its maximum; it is finished from its minimum on. A sample that is not finished after ``draws``
draws starts anew with the draws behind them, so that no sample is lost; only where nothing fits at all (``attempts``
times over) does one stay out.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import signal as S
from langspan.functions.text import SAMPLE_RATE, hash48, hash48_sql
from langspan.session import durable

_SPAN = float(1 << 48)
#: Further attempts that all unfinished samples make before the others are made for those that need them.
SOON = 2


@dataclass(frozen=True)
class SynthConfig:
    weights: tuple[tuple[str, float], ...] = (("en", 0.5), ("es", 0.5))
    min_s: float = 17.0
    max_s: float = 19.0
    begin_s: float = 0.02
    end_s: float = 0.02
    join_s: float = 0.1
    trim_threshold: float = 0.02
    scale: float = 1.0
    gap: str = "silence"
    snr_db: float = 10.0
    seed: int = 0
    draws: int = 32
    attempts: int = 12
    #: Draws are made in waves; only unfinished samples take part in the next.
    waves: tuple[int, ...] = ()
    overflow: str = "skip"
    require_mixed: bool = False
    rate: int = SAMPLE_RATE
    #: Utterances that a task numbers, about.
    bucket_rows: int = 200_000

    def samples(self, seconds: float) -> int:
        return round(seconds * self.rate)

    @property
    def low(self) -> int:
        return self.samples(self.min_s)

    @property
    def high(self) -> int:
        return self.samples(self.max_s)

    @property
    def begin(self) -> int:
        return self.samples(self.begin_s)

    @property
    def end(self) -> int:
        return self.samples(self.end_s)

    @property
    def join(self) -> int:
        return self.samples(self.join_s)

    def count_for(self, hours: float) -> int:
        """Samples that make so many hours, at the middle of the window."""
        return max(1, round(hours * 3600 / ((self.min_s + self.max_s) / 2)))

    def count_sql(self, share: float, pool: str) -> str:
        """``count_for_share`` of a relation, as a scalar."""
        langs = ", ".join(f"'{lang}'" for lang, _, _ in self.shares)
        return f"(SELECT greatest(1, ceil(coalesce(sum(n_samples), 0) * {float(share)!r} / {(self.low + self.high) / 2!r}))::bigint FROM {pool} WHERE lang IN ({langs}))"

    @property
    def shares(self) -> list[tuple[str, float, float]]:
        """(language, from, to) of the unit interval."""
        total, at, out = sum(w for _, w in self.weights), 0.0, []
        for lang, w in self.weights:
            out.append((lang, at, at + w / total))
            at += w / total
        return [(lang, a, b if k < len(out) - 1 else 1.0) for k, (lang, a, b) in enumerate(out) if b > a]


def count_for_share(pool: DataFrame, cfg: SynthConfig, share: float) -> int:
    """Samples whose hours are a share of the hours of the pool's languages; at least one."""
    mine = pool.filter(F.col("lang").isin([lang for lang, _, _ in cfg.shares]))
    total = mine.select(F.sum(F.col("n_samples").cast("bigint"))).first()[0] or 0
    return max(1, math.ceil(total * share / ((cfg.low + cfg.high) / 2)))


def indexed_pool(pool: DataFrame, cfg: SynthConfig) -> tuple[DataFrame, dict[str, int]]:
    """(lang, idx, utt_id, n_samples) with idx dense from 0 in each language by utt_id, and the pools' sizes.

    Numbers come from the counts of ranges of ids, as many as ``bucket_rows`` asks for, which the driver adds up, and from
    the order inside a range; no task ever sorts a whole language. The pool is read three times: hand in a durable one.
    """
    rows = pool.filter(F.col("lang").isin([lang for lang, _, _ in cfg.shares])).select("lang", "utt_id", "n_samples")
    ends = rows.agg(F.count(F.lit(1)).alias("n"), F.min("utt_id").alias("low"), F.max("utt_id").alias("high")).first()
    low, width, buckets = ends["low"] or 0, (ends["high"] or 0) - (ends["low"] or 0) + 1, max(1, -(-ends["n"] // cfg.bucket_rows))
    rows = rows.withColumn("_bucket", F.least(F.floor((F.col("utt_id") - low) / float(width) * buckets), F.lit(buckets - 1)).cast("int"))
    counts = rows.groupBy("lang", "_bucket").agg(F.count(F.lit(1)).alias("n")).orderBy("lang", "_bucket").collect()
    sizes: dict[str, int] = {}
    firsts = []
    for r in counts:
        firsts.append((r["lang"], r["_bucket"], sizes.get(r["lang"], 0)))
        sizes[r["lang"]] = sizes.get(r["lang"], 0) + r["n"]
    first = pool.sparkSession.createDataFrame(firsts, "_lang string, _b int, _first bigint")
    order = Window.partitionBy("lang", "_bucket").orderBy("utt_id", "n_samples")
    joined = rows.join(F.broadcast(first), (F.col("lang") == F.col("_lang")) & (F.col("_bucket") == F.col("_b")))
    return joined.select("lang", (F.col("_first") + F.row_number().over(order) - 1).alias("idx"), "utt_id", "n_samples"), sizes


def _uniform(cfg: SynthConfig, sample: Column, draw: Column, purpose: str) -> Column:
    return hash48(F.concat_ws(":", F.lit(str(cfg.seed)), sample.cast("string"), draw.cast("string"), F.lit(purpose)))


def drawn(samples: DataFrame, cfg: SynthConfig, sizes: dict[str, int], first: int, last: int) -> DataFrame:
    """sample_id, draw, lang, idx of draws first to last - 1.

    The two hashes of a draw come from a generator of one row, below which no filter moves: moved, a filter on the language or
    the number would hash once more for every place that names them.
    """
    each = samples.withColumn("draw", F.explode(F.sequence(F.lit(first), F.lit(last - 1))))
    hashes = F.struct(*(_uniform(cfg, F.col("sample_id"), F.col("draw"), what).alias(name) for what, name in (("lang", "_u"), ("utt", "_v"))))
    each = each.select("*", F.inline(F.array(hashes))).withColumn("_u", F.col("_u") / _SPAN)
    lang, size = F.lit(None).cast("string"), F.lit(None).cast("bigint")
    for name, low, high in reversed(cfg.shares):
        inside = (F.col("_u") >= low) & (F.col("_u") < high)
        lang = F.when(inside, name).otherwise(lang)
        size = F.when(inside, sizes.get(name, 0)).otherwise(size)
    each = each.withColumn("lang", lang).withColumn("_size", size).filter(F.col("_size") > 0)
    return each.withColumn("idx", F.col("_v") % F.col("_size")).drop("_u", "_v", "_size")


def candidates(samples: DataFrame, index: DataFrame, sizes: dict[str, int], cfg: SynthConfig, first: int, last: int) -> DataFrame:
    """sample_id, draw, lang, utt_id, n_samples of draws first to last - 1; index: ``_lang``, ``_idx``, utt_id, n_samples.

    Every draw has its utterance, so that an outer join gives what an inner one would. Spark takes a sample's draws to be as
    small as its id and would broadcast millions of them through the driver; of an outer join it may only broadcast the index.
    """
    found = drawn(samples, cfg, sizes, first, last).join(index, (F.col("lang") == F.col("_lang")) & (F.col("idx") == F.col("_idx")), "left")
    return found.select("sample_id", "draw", "lang", "utt_id", "n_samples")


_PICK = "array<struct<lang string, utt_id bigint, start int, n_samples int>>"


def fold(candidates: Column, state: Column, cfg: SynthConfig) -> Column:
    """Greedy filling of one sample from its candidates in order: struct<total, picks>."""

    def step(s, c):
        gap = F.when(F.size(s["picks"]) > 0, cfg.join).otherwise(0)
        length = c["n_samples"]
        if cfg.overflow == "truncate":
            length = F.least(length, F.lit(cfg.high) - s["total"] - gap)
        fits = (s["total"] < cfg.low) & (s["total"] + gap + length <= cfg.high) & (length > 0)
        if cfg.overflow == "reject":
            fits = fits & ~s["dead"]
        pick = F.struct(c["lang"].alias("lang"), c["utt_id"].alias("utt_id"), (s["total"] - cfg.end + gap).cast("int").alias("start"), length.cast("int").alias("n_samples"))
        dead = s["dead"] | ((s["total"] < cfg.low) & ~fits) if cfg.overflow == "reject" else s["dead"]
        return F.struct(
            F.when(fits, s["total"] + gap + length).otherwise(s["total"]).cast("int").alias("total"),
            F.when(fits, F.concat(s["picks"], F.array(pick))).otherwise(s["picks"]).cast(_PICK).alias("picks"),
            dead.alias("dead"),
        )

    return F.aggregate(candidates, state, step)


def _finished(cfg: SynthConfig) -> Column:
    """Whether the state of a sample's attempt is one of a sample."""
    done = (F.col("state.total") >= cfg.low) & ~F.col("state.dead")
    if cfg.require_mixed:
        done = done & (F.size(F.array_distinct(F.transform("state.picks", lambda p: p["lang"]))) > 1)
    return done


def _listed(samples: DataFrame, index: DataFrame, sizes: dict[str, int], cfg: SynthConfig, low: int, high: int) -> DataFrame:
    """_of (the sample), attempt, c: the candidates of draws low to high - 1 in order."""
    found = candidates(samples, index, sizes, cfg, low, high)
    listed = found.groupBy(F.col("sample_id").alias("_of"), F.expr(f"draw div {cfg.draws}").cast("int").alias("attempt"))
    return listed.agg(F.sort_array(F.collect_list(F.struct("draw", "lang", "utt_id", "n_samples"))).alias("c"))


def _filled(samples: DataFrame, index: DataFrame, sizes: dict[str, int], cfg: SynthConfig, first: int, last: int) -> DataFrame:
    """sample_id, attempt, state of every sample after the draws from first to last - 1 of each attempt; the first attempt in
    waves, further ones a few (SOON) at first and the others for the samples that those did not finish.

    Draws are numbered on from attempt to attempt. Waves only make draws that are still needed."""
    empty = F.struct(F.lit(cfg.begin + cfg.end).alias("total"), F.array().cast(_PICK).alias("picks"), F.lit(False).alias("dead"))
    if (first, last) != (0, 1):
        going, done = samples.select("sample_id"), None
        for low, high in ((first, min(first + SOON, last)), (first + SOON, last)):
            if low < high:
                listed = _listed(going, index, sizes, cfg, low * cfg.draws, high * cfg.draws)
                filled = durable(listed.select(F.col("_of").alias("sample_id"), "attempt", fold(F.col("c"), empty, cfg).alias("state")))
                done = filled if done is None else done.union(filled)
                ended = filled.filter(_finished(cfg)).select(F.col("sample_id").alias("_ended")).distinct()
                going = going.join(ended, F.col("sample_id") == F.col("_ended"), "left_anti")
        return done
    waves = cfg.waves or (cfg.draws,)
    if sum(waves) != cfg.draws:
        raise ValueError("waves must add up to the draws")
    going, done, at = samples.select("sample_id").withColumn("state", empty), None, 0
    for wave in waves:
        listed = _listed(going.select("sample_id"), index, sizes, cfg, at, at + wave)
        state = going.join(listed, F.col("sample_id") == F.col("_of")) if at else listed.select(F.col("_of").alias("sample_id"), "attempt", empty.alias("state"), "c")
        filled = durable(state.select("sample_id", "attempt", fold(F.col("c"), F.col("state"), cfg).alias("state")))
        done = filled if done is None else done.filter(F.col("state.total") >= cfg.low).union(filled)
        going = filled.filter(F.col("state.total") < cfg.low).select("sample_id", "state")
        at += wave
    return done


def plan_samples(samples: DataFrame, pool: DataFrame, cfg: SynthConfig, indexed: tuple[DataFrame, dict[str, int]] | None = None) -> DataFrame:
    """sample_id, total, picks of ``samples`` (sample_id): each one's first attempt that is finished. ``indexed``: the pool's
    ``indexed_pool``, if it was made before.

    Most samples need one attempt; all further attempts of the others are made in a second pass over them alone.
    """
    if indexed is None:
        index, sizes = indexed_pool(pool, cfg)
        indexed = durable(index), sizes
    index, sizes = indexed
    index = index.select(F.col("lang").alias("_lang"), F.col("idx").alias("_idx"), "utt_id", "n_samples")
    finished = _finished(cfg)
    done = _filled(samples, index, sizes, cfg, 0, 1).filter(finished).select("sample_id", "state.total", "state.picks")
    if cfg.attempts < 2:
        return done
    left = durable(samples.select("sample_id").join(done.select(F.col("sample_id").alias("_done")), F.col("sample_id") == F.col("_done"), "left_anti"))
    dealt = left.repartition(pool.sparkSession.sparkContext.defaultParallelism)  # few ids, which lie together, with hundreds of draws each
    more = _filled(dealt, index, sizes, cfg, 1, cfg.attempts).filter(finished)
    more = more.groupBy("sample_id").agg(F.min_by("state", "attempt").alias("state"))
    return done.union(more.select("sample_id", "state.total", "state.picks"))


def plan(pool: DataFrame, cfg: SynthConfig, n_samples: int, indexed: tuple[DataFrame, dict[str, int]] | None = None) -> DataFrame:
    """sample_id, slot, lang, utt_id, start, n_samples, total of samples 0 to n_samples - 1; starts count from the sample's begin."""
    return slots(plan_samples(pool.sparkSession.range(n_samples).withColumnRenamed("id", "sample_id"), pool, cfg, indexed))


def slots(planned: DataFrame) -> DataFrame:
    each = planned.select("sample_id", "total", F.posexplode("picks").alias("slot", "p"))
    return each.select("sample_id", "slot", "p.lang", "p.utt_id", "p.start", "p.n_samples", "total")


def plan_sql(cfg: SynthConfig, share: float, pool: str) -> str:
    """The same plan in SQL, as CTEs ending in ``plan``; ``pool`` is a relation (lang, utt_id, n_samples), ``share`` as for
    ``count_for_share``. Skip overflow only."""
    case = " ".join(f"WHEN u >= {a!r} AND u < {b!r} THEN '{lang}'" for lang, a, b in cfg.shares)
    draw = lambda what: hash48_sql(f"'{cfg.seed}:' || s.id::varchar || ':' || d.k::varchar || ':{what}'")
    langs = ", ".join(f"'{lang}'" for lang, _, _ in cfg.shares)
    return f"""
idx AS (SELECT lang, utt_id, n_samples, row_number() OVER (PARTITION BY lang ORDER BY utt_id, n_samples) - 1 AS idx FROM {pool} WHERE lang IN ({langs})),
sizes AS (SELECT lang, count(*) AS size FROM idx GROUP BY lang),
ids AS (SELECT unnest(range(n)) AS id FROM (SELECT {cfg.count_sql(share, pool)} AS n)),
draws AS (SELECT s.id AS sample_id, d.k, {draw("lang")} / {_SPAN!r} AS u, {draw("utt")} AS v FROM ids s, range({cfg.draws * cfg.attempts}) d(k)),
chosen AS (SELECT sample_id, k, k // {cfg.draws} AS a, v, CASE {case} END AS lang FROM draws),
cand AS (
  SELECT c.sample_id, c.a, row_number() OVER (PARTITION BY c.sample_id, c.a ORDER BY c.k) AS k, i.lang, i.utt_id, i.n_samples
  FROM chosen c JOIN sizes z ON z.lang = c.lang JOIN idx i ON i.lang = c.lang AND i.idx = c.v % z.size),
fill AS (
  SELECT DISTINCT sample_id, a, 0::bigint AS k, {cfg.begin + cfg.end}::int AS total, 0::int AS slots, false AS took, NULL::varchar AS lang, NULL::bigint AS utt_id, 0::int AS start, 0::int AS n_samples FROM cand
  UNION ALL
  SELECT sample_id, a, k, CASE WHEN took THEN total + gap + n ELSE total END, CASE WHEN took THEN slots + 1 ELSE slots END, took, lang, utt_id, (total - {cfg.end} + gap)::int, n FROM (
    SELECT f.sample_id, f.a, c.k, f.total, f.slots, c.lang, c.utt_id, c.n_samples AS n, CASE WHEN f.slots > 0 THEN {cfg.join} ELSE 0 END AS gap,
      f.total < {cfg.low} AND f.total + CASE WHEN f.slots > 0 THEN {cfg.join} ELSE 0 END + c.n_samples <= {cfg.high} AS took
    FROM fill f JOIN cand c ON c.sample_id = f.sample_id AND c.a = f.a AND c.k = f.k + 1)),
tries AS (SELECT sample_id, a, max(total) AS total FROM fill GROUP BY sample_id, a HAVING max(total) >= {cfg.low}),
ended AS (SELECT sample_id, min(a) AS a, arg_min(total, a) AS total FROM tries GROUP BY sample_id),
plan AS (SELECT f.sample_id, f.slots - 1 AS slot, f.lang, f.utt_id, f.start, f.n_samples, e.total FROM fill f JOIN ended e ON e.sample_id = f.sample_id AND e.a = f.a WHERE f.took)"""


def trimmed_lengths(utterances: DataFrame, cfg: SynthConfig) -> DataFrame:
    """Utterances with n_samples of the trimmed signal: planning then needs no signals. utterances: also ``signal``."""
    return utterances.withColumn("n_samples", F.size(S.trim(F.col("signal"), cfg.trim_threshold))).drop("signal")


def render(planned: DataFrame, utterances: DataFrame, cfg: SynthConfig, trim: bool = True, normalise: bool = True) -> DataFrame:
    """sample_id, signal, n_samples, segments, text of a plan (sample_id, slot, lang, utt_id, start, n_samples, total).

    utterances: utt_id, text, signal. Signals are trimmed and levelled once for each utterance, before the join that
    repeats them. ``trim`` and ``normalise`` off give plain stitching, the baseline.
    """
    signal = F.col("signal")
    if trim:
        signal = S.trim(signal, cfg.trim_threshold)
    if normalise:
        signal = S.peak_scale(signal, cfg.scale)
    ready = utterances.select(F.col("utt_id").alias("_utt"), "text", signal.alias("signal"))
    joined = planned.join(ready, F.col("utt_id") == F.col("_utt"))
    parts = F.sort_array(F.collect_list(F.struct("slot", "lang", "start", "n_samples", "text", "signal")))
    built = joined.groupBy("sample_id", "total").agg(parts.alias("parts"))
    ordered = F.transform("parts", lambda p: F.slice(p["signal"], F.lit(1), p["n_samples"]) if trim else p["signal"])
    if cfg.gap == "noise":
        level = S.noise_level(F.sqrt(F.aggregate("parts", F.lit(0.0), lambda s, p: s + S.energy(p["signal"])) / F.size("parts")), cfg.snr_db)
        make = lambda n, salt: S.noise(n, level, F.xxhash64("sample_id", F.lit(salt)))
    else:
        make = lambda n, salt: S.silence(n)
    whole = S.join_signals(ordered, make(cfg.begin, "begin"), make(cfg.join, "join"), make(cfg.end, "end"))
    segments = F.transform("parts", lambda p: F.struct(p["slot"], p["lang"], p["start"], p["n_samples"], p["text"]))
    out = built.select("sample_id", whole.alias("signal"), segments.alias("segments"), F.array_join(F.transform("parts", lambda p: p["text"]), " ").alias("text"))
    return out.select("sample_id", "signal", F.size("signal").alias("n_samples"), "segments", "text")


def within_hours(planned: DataFrame, cfg: SynthConfig, hours: float, block: int = 1000) -> DataFrame:
    """``planned`` (sample_id, total, ...) up to the first sample that fills so many hours, by running sums over blocks of ids."""
    limit = round(hours * 3600 * cfg.rate)
    each = planned.select("sample_id", "total").distinct().withColumn("_b", F.expr(f"sample_id div {int(block)}"))
    sums = each.groupBy("_b").agg(F.sum("total").alias("n"))
    firsts = sums.select(F.col("_b").alias("_at"), (F.sum("n").over(Window.orderBy("_b")) - F.col("n")).alias("_first"))
    inside = Window.partitionBy("_b").orderBy("sample_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    before = each.withColumn("_in", F.sum("total").over(inside) - F.col("total")).join(firsts, F.col("_b") == F.col("_at"))
    kept = before.filter(F.col("_first") + F.col("_in") < limit).select(F.col("sample_id").alias("_kept"))
    return planned.join(kept, F.col("sample_id") == F.col("_kept"), "left_semi")


def generate_offline(pool: DataFrame, cfg: SynthConfig, hours: float, path: str, shard_size: int = 1000) -> int:
    """Writes rendered samples of ``hours`` (to within one sample) as sharded Parquet; returns how many. pool: also ``signal``.

    As many samples are planned as the hours need at their shortest, and cut by running sums of their lengths.
    """
    from langspan.sources.tables import write_sharded

    most = math.ceil(hours * 3600 / cfg.min_s) + 1
    lengths = durable(trimmed_lengths(pool, cfg).select("lang", "utt_id", "n_samples"))
    planned = durable(within_hours(plan(lengths, cfg, most), cfg, hours))
    write_sharded(render(planned, pool, cfg), path, shard_size)
    return planned.select("sample_id").distinct().count()


def storage(planned: DataFrame) -> DataFrame:
    """mode, n_samples, bytes: what a corpus takes on disk as 32-bit amplitudes, offline and online."""
    whole = planned.select("sample_id", "total").distinct().agg(F.count(F.lit(1)).alias("n_samples"), (F.coalesce(F.sum("total"), F.lit(0)) * 4).cast("bigint").alias("offline"))
    modes = F.array(F.struct(F.lit("offline").alias("mode"), F.col("offline").alias("bytes")), F.struct(F.lit("online").alias("mode"), F.lit(0).cast("bigint").alias("bytes")))
    return whole.select("n_samples", F.inline(modes)).select("mode", "n_samples", "bytes")


def plain_config(cfg: SynthConfig) -> SynthConfig:
    """The earlier, less parametrised generator: no silences, no scale."""
    return replace(cfg, begin_s=0.0, end_s=0.0, join_s=0.0, scale=1.0)


# measures of plans


def profile(planned: DataFrame) -> DataFrame:
    """lang, n_segments, n_samples, share (of samples)."""
    by_lang = planned.groupBy("lang").agg(F.count(F.lit(1)).alias("n_segments"), F.sum("n_samples").alias("n_samples"))
    total = by_lang.agg(F.sum("n_samples").alias("_total"))
    return by_lang.crossJoin(F.broadcast(total)).select("lang", "n_segments", "n_samples", F.round(F.col("n_samples") / F.col("_total"), 6).alias("share"))


def edge_bias(planned: DataFrame) -> DataFrame:
    """lang, n_first, n_last: how often each language begins and ends a sample."""
    ends = planned.groupBy("sample_id").agg(F.min_by("lang", "slot").alias("first"), F.max_by("lang", "slot").alias("last"))
    sides = ends.select(F.inline(F.array(F.struct(F.col("first").alias("lang"), F.lit(1).alias("f"), F.lit(0).alias("l")), F.struct(F.col("last").alias("lang"), F.lit(0).alias("f"), F.lit(1).alias("l")))))
    return sides.groupBy("lang").agg(F.sum("f").alias("n_first"), F.sum("l").alias("n_last"))


def padding_waste(lengths: DataFrame, batch: int, key: str = "sample_id", length: str = "total") -> DataFrame:
    """batch_no, n, waste of batches of consecutive keys: 1 - sum / (n * max)."""
    by = lengths.groupBy(F.expr(f"{key} div {int(batch)}").alias("batch_no"))
    return by.agg(F.count(F.lit(1)).alias("n"), F.round(1 - F.sum(length) / (F.count(F.lit(1)) * F.max(length)), 6).alias("waste"))


def sample_profile(planned: DataFrame) -> DataFrame:
    """sample_id, n_segments, n_langs, switches, total."""
    order = Window.partitionBy("sample_id").orderBy("slot")
    seen = planned.withColumn("_switch", F.coalesce((F.lag("lang").over(order) != F.col("lang")).cast("int"), F.lit(0)))
    return seen.groupBy("sample_id").agg(F.count(F.lit(1)).alias("n_segments"), F.countDistinct("lang").alias("n_langs"), F.sum("_switch").alias("switches"), F.max("total").alias("total"))


def reuse(planned: DataFrame, pool: DataFrame) -> DataFrame:
    """lang, drawn, pool_samples, times: how often a pool's audio is used."""
    drawn_ = planned.groupBy("lang").agg(F.sum("n_samples").alias("drawn"))
    have = pool.groupBy(F.col("lang").alias("_lang")).agg(F.sum("n_samples").alias("pool_samples"))
    return drawn_.join(have, F.col("lang") == F.col("_lang")).select("lang", "drawn", "pool_samples", F.round(F.col("drawn") / F.col("pool_samples"), 6).alias("times"))


def sweep(pool: DataFrame, configs: Sequence[tuple[str, SynthConfig]], share: float) -> DataFrame:
    """name, lang, n_segments, n_samples, share of every configuration, from plans alone; the profiles are kept, no plan is.

    Configurations of the same languages share one index of the pool. A profile is done before the next plan begins, so that
    the driver never holds the plans of all configurations, nor runs them in one query."""
    out, indexes = None, {}
    for name, cfg in configs:
        langs = frozenset(lang for lang, _, _ in cfg.shares)
        if langs not in indexes:
            index, sizes = indexed_pool(pool, cfg)
            indexes[langs] = durable(index), sizes
        one = durable(profile(plan(pool, cfg, count_for_share(pool, cfg, share), indexes[langs]))).withColumn("name", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out.select("name", "lang", "n_segments", "n_samples", "share")


def repeats(have: dict[str, float], ratio: Sequence[tuple[str, float]], seed: int = 0) -> Column:
    """How often each utterance (lang, utt_id) of pools of these sizes is used: floor(r) times and once more by a hash chance."""
    wanted = [(lang, w) for lang, w in ratio if w > 0 and have.get(lang)]
    unit = max((have[lang] / w for lang, w in wanted), default=0.0)
    factor = F.lit(0.0)
    for lang, w in wanted:
        factor = F.when(F.col("lang") == lang, unit * w / have[lang]).otherwise(factor)
    chance = hash48(F.concat_ws(":", F.lit(f"mix:{seed}"), F.col("utt_id").cast("string"))) / _SPAN
    return (F.floor(factor) + F.when(chance < factor - F.floor(factor), 1).otherwise(0)).cast("int")


def mix(pools: DataFrame, ratio: Sequence[tuple[str, float]], by: str = "utterances", seed: int = 0) -> DataFrame:
    """Training set of monolingual pools at a ratio: the pool that is largest for its share is used once, the others repeat.

    Every utterance repeats floor(r) times and once more by a hash chance of the rest; ``copy`` counts from 1.
    """
    value = F.count(F.lit(1)) if by == "utterances" else F.sum("n_samples")
    have = {r["lang"]: float(r["n"]) for r in pools.groupBy("lang").agg(value.alias("n")).collect()}
    times = repeats(have, ratio, seed)
    return pools.withColumn("_times", times).filter("_times > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).drop("_times")


def range_of(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).withColumnRenamed("id", "sample_id")
