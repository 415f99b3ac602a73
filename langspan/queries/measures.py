"""Error rates, averages, joins around the methods, integer carriers, events."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.functions.binding import let
from langspan.operators import lid, metrics, vocab
from langspan.queries.base import utts
from langspan.queries.waves import PLAN, SWEEP, _planned, planned as planned_slots
from langspan.sources.tables import read
from langspan.streaming import online


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Utterances and a spoilt copy: every tenth word gone, every tenth replaced."""
    pool = utts(spark, sf_dir).withColumn("w", T.words(F.col("text")))
    fate = lambda i: T.hash48(F.concat_ws(":", F.col("utt_id").cast("string"), i.cast("string"))) % 10
    heard = F.transform("w", lambda w, i: let(fate(i), lambda f: F.when(f == 0, "").when(f == 1, "zz").otherwise(w)))
    return pool.select("utt_id", "lang", F.col("text").alias("ref"), F.array_join(F.filter(heard, lambda w: w != ""), " ").alias("hyp"))


def wer_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """grp, errors, ref_words, wer over every utterance."""
    return metrics.wer(_pairs(spark, sf_dir), ["lang"]).withColumnRenamed("lang", "grp")


def cer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """grp, errors, ref_chars, cer over every utterance, by code points."""
    return metrics.cer(_pairs(spark, sf_dir), ["lang"]).withColumnRenamed("lang", "grp")


def edit_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, substitutions, deletions, insertions over every utterance (Arrow)."""
    return metrics.edit_ops(_pairs(spark, sf_dir), "lang").groupBy("lang").agg(*(F.sum(c).alias(c) for c in ("substitutions", "deletions", "insertions")))


def top5_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """experiment, wer: event types as experiments, users as their runs, events as checkpoints and their values as rates."""
    events = read(spark, sf_dir, "events").filter(F.col("value").isNotNull())
    return metrics.average_runs(events.select(F.col("event_type").alias("experiment"), F.col("user_id").alias("run"), F.col("event_id").alias("checkpoint"), F.col("value").alias("wer")))


def asof_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, t, slot: the segment that was begun last at every 500th sample (-1 before the first), by one sort instead of a range join."""
    planned = planned_slots(spark, sf_dir, SWEEP)
    starts = planned.select("sample_id", F.col("start").cast("bigint").alias("t"), F.col("slot").cast("bigint").alias("slot"), F.lit(0).alias("asked"))
    times = planned.select("sample_id", "total").distinct().select("sample_id", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("total").cast("bigint"), F.lit(500).cast("bigint"))).alias("t"), F.lit(None).cast("bigint").alias("slot"), F.lit(1).alias("asked"))
    order = Window.partitionBy("sample_id").orderBy("t", "asked").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return starts.union(times).withColumn("slot", F.coalesce(F.last("slot", ignorenulls=True).over(order), F.lit(-1))).filter("asked = 1").select("sample_id", "t", "slot")


# integer carrier: orders as utterances, suppliers as tokens, regions as languages of unequal size


def _region_ranges(spark: SparkSession, sf_dir: str) -> tuple[vocab.RangeVocab, DataFrame]:
    suppliers = read(spark, sf_dir, "supplier").join(F.broadcast(read(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    counts = suppliers.groupBy("r_name").agg(F.count(F.lit(1)).alias("n")).orderBy("r_name").collect()
    ranges = vocab.RangeVocab.allocate([(r["r_name"], r["n"]) for r in counts])
    local = F.row_number().over(Window.partitionBy("r_name").orderBy("s_suppkey")) - 1
    return ranges, suppliers.select("s_suppkey", "r_name", (local + ranges.offset_of(F.col("r_name"))).alias("token_id"))


def _order_tokens(spark: SparkSession, sf_dir: str) -> tuple[vocab.RangeVocab, DataFrame]:
    ranges, tokens = _region_ranges(spark, sf_dir)
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_suppkey", "l_partkey")
    joined = lines.join(tokens.select("s_suppkey", "token_id"), F.col("l_suppkey") == F.col("s_suppkey"))
    return ranges, joined.select("l_orderkey", (F.row_number().over(order) - 1).alias("pos"), "token_id")


def order_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, tokens = _order_tokens(spark, sf_dir)
    return tokens.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum("token_id").alias("id_sum"), F.min_by("token_id", "pos").cast("bigint").alias("first_id"), F.max_by("token_id", "pos").cast("bigint").alias("last_id"))


def order_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranges, tokens = _order_tokens(spark, sf_dir)
    return lid.utterance_lid(tokens, ranges, "l_orderkey")


def order_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranges, tokens = _order_tokens(spark, sf_dir)
    return lid.language_spans(tokens, ranges, "l_orderkey").withColumnRenamed("lang", "region")


def region_switch_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = order_spans(spark, sf_dir).withColumn("to_region", F.lead("region").over(Window.partitionBy("l_orderkey").orderBy("span")))
    return spans.filter("to_region IS NOT NULL").groupBy(F.col("region").alias("from_region"), "to_region").agg(F.count(F.lit(1)).alias("n"))


# events: tokens over time


def _event_case(spark: SparkSession, sf_dir: str) -> str:
    types = sorted(r[0] for r in read(spark, sf_dir, "events").select("event_type").distinct().collect())
    return "CASE event_type " + " ".join(f"WHEN '{t}' THEN {128 * k}" for k, t in enumerate(types)) + " END"


def _event_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return online.event_tokens(read(spark, sf_dir, "events"), _event_case(spark, sf_dir))


def event_token_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    tokens = _event_tokens(spark, sf_dir)
    return tokens.groupBy(F.col("lang").alias("event_type")).agg(F.count(F.lit(1)).alias("n"), F.min("token_id").cast("bigint").alias("id_min"), F.max("token_id").cast("bigint").alias("id_max"))


def _stamp(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")


def event_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, session_start, n, lang: sessions end after six hours; the commonest type, ties by name."""
    by_lang = online.session_languages(_event_tokens(spark, sf_dir).withColumn("lang", F.lit("all")))
    whole = by_lang.select("user_id", "session_start", F.col("n"))
    tokens = _event_tokens(spark, sf_dir).select("user_id", "ts", "lang")
    order = Window.partitionBy("user_id").orderBy("ts")
    begun = tokens.withColumn("_new", F.when(F.col("ts") - F.lag("ts").over(order) > F.expr("INTERVAL 6 HOURS"), 1).otherwise(0))
    numbered = begun.withColumn("s", F.sum("_new").over(order.rangeBetween(Window.unboundedPreceding, Window.currentRow)))
    votes = numbered.groupBy("user_id", "s", "lang").agg(F.count(F.lit(1)).alias("v"), F.min("ts").alias("t"))
    best = votes.groupBy(F.col("user_id").alias("_u"), "s").agg(F.min("t").alias("_t"), F.min_by("lang", F.struct(-F.col("v"), F.col("lang"))).alias("lang"))
    return whole.join(best, (F.col("user_id") == F.col("_u")) & (F.col("session_start") == F.col("_t"))).select("user_id", _stamp("session_start").alias("session_start"), "n", "lang")


def event_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return online.windowed_languages(_event_tokens(spark, sf_dir)).select(_stamp("window_start").alias("window_start"), "lang", "n")


def event_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return online.windowed_languages(_event_tokens(spark, sf_dir), "1 day", "6 hours").select(_stamp("window_start").alias("window_start"), "lang", "n")


QUERIES = {f.__name__: f for f in (wer_words, cer, edit_ops, top5_avg, asof_segment, order_tokens, order_lid, order_spans, region_switch_matrix, event_token_lid, event_sessions, event_windows, event_sliding)}

_FATE = T.hash48_sql("utt_id::varchar || ':' || (i - 1)::varchar")
_PAIRS = f"""p AS (SELECT utt_id, lang, text AS ref, {T.WORDS_SQL.format('text')} AS w FROM utt),
q AS (SELECT utt_id, lang, ref, w, list_filter(list_transform(w, lambda x, i: CASE WHEN {_FATE} % 10 = 0 THEN '' WHEN {_FATE} % 10 = 1 THEN 'zz' ELSE x END), lambda x: x <> '') AS h FROM p)"""
_LETTERS = "array_to_string(list_transform({0}, lambda x: chr((33 + list_position(k, x))::int)), '')"
_REGIONS = """s AS (SELECT s_suppkey, r_name, row_number() OVER (ORDER BY r_name, s_suppkey) - 1 AS token_id FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
o AS (SELECT l_orderkey, r_name AS region, token_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_suppkey, l_partkey) - 1 AS pos FROM lineitem JOIN s ON l_suppkey = s_suppkey)"""
_RUNS = _REGIONS + """,
f AS (SELECT *, CASE WHEN lag(region) OVER w = region THEN 0 ELSE 1 END AS fresh FROM o WINDOW w AS (PARTITION BY l_orderkey ORDER BY pos)),
r AS (SELECT *, sum(fresh) OVER (PARTITION BY l_orderkey ORDER BY pos)::bigint AS span FROM f),
sp AS (SELECT l_orderkey, span, region, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS n FROM r GROUP BY l_orderkey, span, region)"""
_EVENTS = """ty AS (SELECT event_type, (row_number() OVER (ORDER BY event_type) - 1) * 128 AS o FROM (SELECT DISTINCT event_type FROM events)),
ev AS (SELECT event_id, ts, user_id, event_type AS lang, o + (props::json->>'k')::int AS token_id FROM events JOIN ty USING (event_type))"""

ORACLES = {
    "wer_words": f"WITH {T.UTTERANCES_SQL}, {_PAIRS}, k AS (SELECT *, list_sort(list_distinct(list_concat(w, h))) AS k FROM q), e AS (SELECT lang, levenshtein({_LETTERS.format('w')}, {_LETTERS.format('h')}) AS e, len(w) AS n FROM k) SELECT lang AS grp, sum(e)::bigint AS errors, sum(n)::bigint AS ref_words, round(100 * sum(e) / sum(n), 6) AS wer FROM e GROUP BY lang",
    "cer": f"""WITH {T.UTTERANCES_SQL}, {_PAIRS},
e AS (SELECT lang, levenshtein({T.one_byte_sql('ref')}, {T.one_byte_sql("coalesce(array_to_string(h, ' '), '')")}) AS e, length(ref) AS n FROM q)
SELECT lang AS grp, sum(e)::bigint AS errors, sum(n)::bigint AS ref_chars, round(100 * sum(e) / sum(n), 6) AS cer FROM e GROUP BY lang""",
    "top5_avg": """WITH b AS (SELECT event_type AS experiment, user_id, value AS wer, row_number() OVER (PARTITION BY event_type, user_id ORDER BY value, event_id) AS k FROM events WHERE value IS NOT NULL),
a AS (SELECT experiment, user_id, avg(wer) AS wer FROM b WHERE k <= 5 GROUP BY experiment, user_id) SELECT experiment, round(avg(wer), 6) AS wer FROM a GROUP BY experiment""",
    "asof_segment": f"{_planned(PLAN, SWEEP)}, tm AS (SELECT sample_id, unnest(range(0, total + 1, 500))::bigint AS t FROM (SELECT DISTINCT sample_id, total FROM plan)) SELECT tm.sample_id, tm.t, coalesce(p.slot, -1)::bigint AS slot FROM tm ASOF LEFT JOIN plan p ON p.sample_id = tm.sample_id AND p.start <= tm.t",
    "order_tokens": f"WITH {_REGIONS} SELECT l_orderkey, count(*) AS n_tokens, sum(token_id)::bigint AS id_sum, arg_min(token_id, pos) AS first_id, arg_max(token_id, pos) AS last_id FROM o GROUP BY l_orderkey",
    "order_lid": f"WITH {_REGIONS}, v AS (SELECT l_orderkey, region, count(*) AS n FROM o GROUP BY ALL) SELECT l_orderkey, region AS pred_lang, n AS n_votes FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY n DESC, region) AS k FROM v) WHERE k = 1",
    "order_spans": f"WITH {_RUNS} SELECT l_orderkey, span, region, first_pos, last_pos, n FROM sp",
    "region_switch_matrix": f"WITH {_RUNS} SELECT region AS from_region, nx AS to_region, count(*) AS n FROM (SELECT *, lead(region) OVER (PARTITION BY l_orderkey ORDER BY span) AS nx FROM sp) WHERE nx IS NOT NULL GROUP BY ALL",
    "event_token_lid": f"WITH {_EVENTS} SELECT lang AS event_type, count(*) AS n, min(token_id)::bigint AS id_min, max(token_id)::bigint AS id_max FROM ev GROUP BY lang",
    "event_sessions": f"""WITH {_EVENTS}, b AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) > INTERVAL 6 HOURS THEN 1 ELSE 0 END AS fresh FROM ev), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM b),
v AS (SELECT user_id, s, lang, count(*) AS v, min(ts) AS t FROM s GROUP BY ALL), k AS (SELECT *, row_number() OVER (PARTITION BY user_id, s ORDER BY v DESC, lang) AS k, sum(v) OVER (PARTITION BY user_id, s)::bigint AS n, min(t) OVER (PARTITION BY user_id, s) AS t0 FROM v)
SELECT user_id, strftime(t0, '%Y-%m-%d %H:%M:%S.%f') AS session_start, n, lang FROM k WHERE k = 1""",
    "event_windows": f"WITH {_EVENTS} SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S.%f') AS window_start, lang, count(*) AS n FROM ev GROUP BY ALL",
    "event_sliding": f"WITH {_EVENTS} SELECT strftime(time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOURS * j, '%Y-%m-%d %H:%M:%S.%f') AS window_start, lang, count(*) AS n FROM ev, range(4) x(j) GROUP BY ALL",
}
