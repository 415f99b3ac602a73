import math
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from langspan.functions import signal as S
from langspan.functions import text as T
from langspan.plans import synth
from langspan.streaming import online

CFG = synth.SynthConfig()
N = 150


@pytest.fixture(scope="module")
def pool(spark, sf):
    return T.utterances(spark.read.parquet(f"{sf}/documents.parquet")).dropDuplicates(["utt_id"]).cache()


@pytest.fixture(scope="module")
def planned(pool):
    return synth.plan(pool, CFG, N).cache()


def _rows(df):
    return sorted(tuple(r) for r in df.select("sample_id", "slot", "lang", "utt_id", "start", "n_samples", "total").collect())


def test_window_and_silences_hold_exactly(planned):
    by = {}
    for r in planned.collect():
        by.setdefault(r["sample_id"], []).append(r)
    assert sorted(by) == list(range(N))  # none is lost
    for rows in by.values():
        rows.sort(key=lambda r: r["slot"])
        assert CFG.low <= rows[0]["total"] <= CFG.high
        assert rows[0]["total"] == CFG.begin + CFG.end + sum(r["n_samples"] for r in rows) + CFG.join * (len(rows) - 1)
        at = CFG.begin
        for r in rows:
            assert r["start"] == at
            at += r["n_samples"] + CFG.join


def test_plan_does_not_depend_on_partitions_or_waves(spark, pool, planned):
    expected = _rows(planned)
    for parts in (1, 17):
        assert _rows(synth.slots(synth.plan_samples(synth.range_of(spark, N).repartition(parts), pool.repartition(parts), CFG))) == expected
    assert _rows(synth.plan(pool, replace(CFG, waves=(8, 8, 16)), N)) == expected


def test_weights_and_edges(planned):
    ends = {r["lang"]: (r["n_first"], r["n_last"]) for r in synth.edge_bias(planned).collect()}
    n = sum(a for a, _ in ends.values())
    assert all(abs(a - n / 2) < 4 * math.sqrt(n / 4) for a, _ in ends.values())


def test_overflow_rules_and_edge_cases(spark, pool):
    count = lambda cfg: synth.plan_samples(synth.range_of(spark, 60), pool, cfg).count()
    skip, reject, cut = (count(replace(CFG, overflow=o)) for o in ("skip", "reject", "truncate"))
    assert reject <= skip == cut == 60
    assert count(replace(CFG, min_s=0.2, max_s=0.3)) == 0  # nothing fits, nothing hangs
    assert count(replace(CFG, weights=(("xx", 1.0),))) == 0
    only = synth.plan(pool, replace(CFG, weights=(("en", 1.0), ("es", 0.0))), 40)
    assert {r[0] for r in only.select("lang").distinct().collect()} == {"en"}
    mixed = synth.sample_profile(synth.plan(pool, replace(CFG, require_mixed=True), 60))
    assert mixed.filter("n_langs < 2").count() == 0 and mixed.count() == 60


def test_rendered_signals(spark, pool, tmp_path):
    cfg = replace(CFG, scale=0.8)
    planned = synth.plan(pool, cfg, 12)
    voiced = pool.select("utt_id", "text", S.sonify(F.col("text"), F.col("source"), F.col("utt_id")).alias("signal"))
    for r in synth.render(planned, voiced, cfg).collect():
        s = r["signal"]
        assert len(s) == r["n_samples"] and s[: cfg.begin] == [0.0] * cfg.begin and s[-cfg.end :] == [0.0] * cfg.end
        for k, g in enumerate(r["segments"]):
            part = s[g["start"] : g["start"] + g["n_samples"]]
            assert max(map(abs, part)) == pytest.approx(0.8, abs=1e-6) and abs(part[0]) > 0 and abs(part[-1]) > 0
            if k:
                assert s[g["start"] - cfg.join : g["start"]] == [0.0] * cfg.join
        assert r["text"] == " ".join(g["text"] for g in r["segments"])
    noisy = synth.render(planned, voiced, replace(cfg, gap="noise", snr_db=10.0)).first()["signal"]
    assert any(x != 0 for x in noisy[: cfg.begin])
    with_signal = pool.join(voiced.select(F.col("utt_id").alias("u"), "signal"), F.col("utt_id") == F.col("u")).drop("u")
    wanted = synth.generate_offline(with_signal, cfg, 0.05, str(tmp_path / "out"), shard_size=4)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == wanted and back.filter("shard <> sample_id div 4").count() == 0
    seconds = back.agg(F.sum("n_samples")).first()[0] / cfg.rate
    assert 180 <= seconds < 180 + cfg.max_s  # the first sample that fills the hours is the last


def test_noise_has_the_wanted_ratio(spark, pool):
    """Level of the noise in the gaps against that of the speech, in decibels."""
    cfg = replace(CFG, gap="noise", snr_db=12.0, begin_s=4.0, end_s=4.0, join_s=0.1, min_s=25.0, max_s=27.0)
    planned = synth.plan(pool, cfg, 6)
    voiced = pool.select("utt_id", "text", S.sonify(F.col("text"), F.col("source"), F.col("utt_id")).alias("signal"))
    for r in synth.render(planned, voiced, cfg).collect():
        s = r["signal"]
        rms = lambda x: math.sqrt(sum(v * v for v in x) / len(x))
        gaps = s[: cfg.begin] + s[-cfg.end :]
        speech = math.sqrt(sum(rms(s[g["start"] : g["start"] + g["n_samples"]]) ** 2 for g in r["segments"]) / len(r["segments"]))
        assert 20 * math.log10(speech / rms(gaps)) == pytest.approx(12.0, abs=0.6)


def test_mixture_repeats_the_smaller_pool(pool):
    rows = {r["lang"]: r["n"] for r in synth.mix(pool.filter("lang IN ('en', 'es')"), (("en", 2.0), ("es", 1.0))).groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert rows["en"] / rows["es"] == pytest.approx(2, rel=0.1)


def test_online_by_id_equals_offline(spark, pool, tmp_path):
    ids = tmp_path / "ids"
    spark.range(40).withColumnRenamed("id", "value").repartition(3).write.parquet(str(ids))
    got = []
    stream = spark.readStream.schema("value bigint").option("maxFilesPerTrigger", 1).parquet(str(ids))
    online.online_from_ids(stream, pool, CFG, lambda df, n: got.extend(_rows(synth.slots(df))), str(tmp_path / "cp")).awaitTermination()
    assert sorted(got) == _rows(synth.plan(pool, CFG, 40))


def test_online_by_arrival_keeps_the_window(spark, pool, tmp_path):
    few = pool.filter("lang IN ('en', 'es')").select("lang", "utt_id", "n_samples").limit(600)
    few.repartition(4).write.parquet(str(tmp_path / "u"))
    stream = spark.readStream.schema("lang string, utt_id bigint, n_samples int").option("maxFilesPerTrigger", 2).parquet(str(tmp_path / "u"))
    out = online.online_from_arrivals(stream, CFG, shards=2)
    q = out.writeStream.format("memory").queryName("arrived").outputMode("append").option("checkpointLocation", str(tmp_path / "cp2")).trigger(availableNow=True).start()
    q.awaitTermination()
    rows = spark.table("arrived").collect()
    by = {}
    for r in rows:
        by.setdefault((r["shard"], r["made"]), []).append(r)
    assert by
    for parts in by.values():
        assert CFG.low <= parts[0]["total"] <= CFG.high
        assert parts[0]["total"] == CFG.begin + CFG.end + sum(p["n_samples"] for p in parts) + CFG.join * (len(parts) - 1)


def test_event_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.union(events.limit(50)).repartition(1).write.parquet(str(tmp_path / "e"))
    case = "CASE event_type WHEN 'x' THEN 0 ELSE 128 END"
    stream = online.without_repeats(online.event_tokens(online.stream_table(spark, str(tmp_path / "e"), events.schema), case))
    q = online.windowed_languages(stream, lateness=None).writeStream.format("memory").queryName("win").outputMode("complete").option("checkpointLocation", str(tmp_path / "cp3")).trigger(availableNow=True).start()
    q.awaitTermination()
    batch = online.windowed_languages(online.event_tokens(events, case))
    assert sorted(map(tuple, spark.table("win").collect())) == sorted(map(tuple, batch.collect()))


def test_sweep_keeps_profiles_alone(spark, pool, monkeypatch):
    """One index for all configurations of the same languages, and no plan in the query that is left."""
    made = []
    index = synth.indexed_pool
    monkeypatch.setattr(synth, "indexed_pool", lambda p, c: made.append(c) or index(p, c))
    configs = [("a", synth.SynthConfig()), ("b", synth.SynthConfig(min_s=7.0, max_s=9.0)), ("c", synth.SynthConfig(weights=(("en", 0.5), ("de", 0.5))))]
    got = synth.sweep(pool, configs, 0.05)
    assert len(made) == 2
    assert not {"Join", "Generate", "Aggregate"} & set(str(got._jdf.queryExecution().optimizedPlan()).replace("(", " ").split())
    apart = [(name, *r) for name, cfg in configs for r in synth.profile(synth.plan(pool, cfg, synth.count_for_share(pool, cfg, 0.05))).collect()]
    assert sorted(map(tuple, got.collect())) == sorted(apart)


def test_further_attempts_are_dealt_out(spark, monkeypatch):
    """Samples that need more attempts are few and lie in one part; their many draws are made by all cores."""
    cfg = synth.SynthConfig(draws=8, attempts=30, seed=3)
    pool = spark.createDataFrame([(lang, 1000 * k + j, 300 + 7 * j) for k, lang in enumerate(("en", "es")) for j in range(200)], "lang string, utt_id long, n_samples int")
    seen = []
    monkeypatch.setattr(synth, "_filled", lambda samples, *a, f=synth._filled: seen.append((samples.count(), samples.rdd.getNumPartitions())) or f(samples, *a))
    planned = synth.plan_samples(synth.range_of(spark, 300), pool, cfg)
    assert planned.count() == planned.select("sample_id").distinct().count() == 300
    assert len(seen) == 2 and 0 < seen[1][0] < 300 and seen[1][1] == spark.sparkContext.defaultParallelism


def _queries(monkeypatch, make):
    """Plans of the queries whose results ``make`` keeps."""
    seen = []
    with monkeypatch.context() as m:
        m.setattr(synth, "durable", lambda df, f=synth.durable: seen.append(str(df._jdf.queryExecution().executedPlan())) or f(df))
        make()
    return seen


def test_draws_are_hashed_once_and_never_broadcast(spark, monkeypatch):
    """Spark takes the draws of few samples for small; as a broadcast they all pass through the driver."""
    pool = spark.createDataFrame([(lang, 1000 * k + j, 300 + 7 * j) for k, lang in enumerate(("en", "es")) for j in range(200)], "lang string, utt_id long, n_samples int")
    drawing = [q for q in _queries(monkeypatch, lambda: synth.plan(pool, synth.SynthConfig(draws=8), 300).count()) if "md5" in q]
    assert len(drawing) == 3  # the first attempts, a few more, the others
    for q in drawing:
        assert q.count("md5(") == 2
        depth = None
        for line in q.splitlines():
            at = len(line) - len(line.lstrip(" :+-*"))
            depth = at if "BroadcastExchange" in line else None if depth is not None and at <= depth else depth
            assert depth is None or "Generate" not in line


def test_further_attempts_are_made_as_they_are_needed(spark, monkeypatch):
    """All further attempts of every unfinished sample were drawn before; the plan is that of the first finished attempt."""
    pool = spark.createDataFrame([(lang, 1000 * k + j, 300 + 7 * j) for k, lang in enumerate(("en", "es")) for j in range(200)], "lang string, utt_id long, n_samples int")
    cfg, made = synth.SynthConfig(draws=8, attempts=30, seed=3), []
    monkeypatch.setattr(synth, "drawn", lambda samples, c, sizes, low, high, f=synth.drawn: made.append((samples.count(), low, high)) or f(samples, c, sizes, low, high))
    got = _rows(synth.plan(pool, cfg, 300))
    (_, first, last), *more = made
    assert (first, last) == (0, 8) and [m[1:] for m in more] == [(8, 24), (24, 240)] and more[1][0] < more[0][0] / 2
    index, sizes = synth.indexed_pool(pool, cfg)
    index = index.select(F.col("lang").alias("_lang"), F.col("idx").alias("_idx"), "utt_id", "n_samples")
    empty = F.struct(F.lit(cfg.begin + cfg.end).alias("total"), F.array().cast(synth._PICK).alias("picks"), F.lit(False).alias("dead"))
    every = synth._listed(synth.range_of(spark, 300), index, sizes, cfg, 0, 240).select(F.col("_of").alias("sample_id"), "attempt", synth.fold(F.col("c"), empty, cfg).alias("state"))
    first_done = every.filter(synth._finished(cfg)).groupBy("sample_id").agg(F.min_by("state", "attempt").alias("state")).select("sample_id", "state.total", "state.picks")
    assert got == _rows(synth.slots(first_done))
