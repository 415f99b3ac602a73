"""Generation while it is consumed, and language identification over event streams."""

from __future__ import annotations

import json
import zlib
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from langspan.plans.synth import SynthConfig, plan_samples
from langspan.shipping import ship


def online_from_ids(ids: DataFrame, pool: DataFrame, cfg: SynthConfig, deliver: Callable[[DataFrame, int], None], checkpoint: str, id_col: str = "value", once: bool = True) -> StreamingQuery:
    """Plans the samples whose ids a stream asks for (``rate`` source: ``value``); nothing is stored.

    A plan is a function of the id, so a replayed batch is the same, and equal to the offline corpus. ``deliver`` gets
    (plan of the batch, batch number) and should be idempotent in the number.
    """

    def batch(rows: DataFrame, number: int) -> None:
        deliver(plan_samples(rows.select(F.col(id_col).cast("bigint").alias("sample_id")).distinct(), pool, cfg), number)

    writer = ids.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def _gathering(cfg: SynthConfig, reservoir: int) -> Callable[[tuple, Iterator[pd.DataFrame], GroupState], Iterator[pd.DataFrame]]:
    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        (shard,) = key
        open_ = json.loads(state.get[0]) if state.exists else {"made": 0, "draw": 0, "total": cfg.begin + cfg.end, "picks": [], "wait": {}}
        rows = pd.concat(list(batches)).sort_values("utt_id")
        out = []
        for lang, utt, n in zip(rows["lang"], rows["utt_id"], rows["n_samples"], strict=True):
            kept = open_["wait"].setdefault(lang, [])
            kept.append([int(utt), int(n)])
            del kept[:-reservoir]
            while True:
                u = zlib.crc32(f"{cfg.seed}:{shard}:{open_['draw']}".encode()) / 2**32
                want = next((name for name, a, b in cfg.shares if a <= u < b), None)
                if not open_["wait"].get(want):
                    break  # the drawn language has to arrive first
                open_["draw"] += 1
                utt_id, length = open_["wait"][want].pop(0)
                gap = cfg.join if open_["picks"] else 0
                if open_["total"] + gap + length <= cfg.high:
                    open_["picks"].append([want, utt_id, open_["total"] - cfg.end + gap, length])
                    open_["total"] += gap + length
                if open_["total"] >= cfg.low:
                    out += [(int(shard), open_["made"], k, *p, open_["total"]) for k, p in enumerate(open_["picks"])]
                    open_ |= {"made": open_["made"] + 1, "total": cfg.begin + cfg.end, "picks": []}
        state.update((json.dumps(open_),))
        yield pd.DataFrame(out, columns=["shard", "made", "slot", "lang", "utt_id", "start", "n_samples", "total"])

    return run


def online_from_arrivals(utterances: DataFrame, cfg: SynthConfig, shards: int = 8, reservoir: int = 16) -> DataFrame:
    """shard, made, slot, lang, utt_id, start, n_samples, total from a stream of utterances (lang, utt_id, n_samples).

    Each shard keeps one open sample and at most ``reservoir`` waiting utterances of each language, so that state is bounded
    by shards and languages and needs no timeout (one by processing time would also keep an ``availableNow`` run from
    ever ending). Samples keep the window, the silences and the weights; which utterances meet depends on arrival.
    """
    ship(utterances.sparkSession)
    keyed = utterances.select(F.pmod(F.xxhash64("utt_id"), F.lit(shards)).cast("bigint").alias("shard"), "lang", "utt_id", "n_samples")
    return keyed.groupBy("shard").applyInPandasWithState(
        _gathering(cfg, reservoir),
        "shard bigint, made bigint, slot bigint, lang string, utt_id bigint, start bigint, n_samples bigint, total bigint",
        "open string", "append", GroupStateTimeout.NoTimeout,
    )


def event_tokens(events: DataFrame, lang_case: str) -> DataFrame:
    """event_id, ts, user_id, token_id, lang of raw events; the same on a stream and a table. lang_case: SQL of the offset."""
    parsed = events.withColumn("k", F.from_json("props", "k INT")["k"])
    return parsed.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", (F.expr(lang_case) + F.col("k")).alias("token_id"), F.col("event_type").alias("lang"))


def windowed_languages(tokens: DataFrame, length: str = "1 day", slide: str | None = None, lateness: str | None = "1 hour") -> DataFrame:
    """window_start, lang, n over event time; late rows beyond the watermark are dropped (streams only). ``lateness`` None:
    the stream has a watermark already (like one of ``without_repeats``)."""
    windowed = tokens.withWatermark("ts", lateness) if tokens.isStreaming and lateness else tokens
    return windowed.groupBy(F.window("ts", length, slide or length).alias("w"), "lang").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "lang", "n")


def session_languages(tokens: DataFrame, gap: str = "6 hours", lateness: str | None = "1 hour") -> DataFrame:
    """user_id, session_start, lang, n: tokens of each language in each of a user's sessions; ``lateness`` as above."""
    windowed = tokens.withWatermark("ts", lateness) if tokens.isStreaming and lateness else tokens
    return windowed.groupBy("user_id", F.session_window("ts", gap).alias("w"), "lang").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("session_start"), "lang", "n")


def without_repeats(events: DataFrame, key: str = "event_id", lateness: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark([key]) if events.isStreaming else events.dropDuplicates([key])


def stream_table(spark: SparkSession, path: str, schema: str, files: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
