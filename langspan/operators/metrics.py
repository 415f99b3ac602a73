"""Accuracy measures: word and character error rates, language identification accuracy, averages over runs, profiles."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from langspan.functions.binding import let
from langspan.functions.text import SAMPLE_RATE, words

#: Code points from here stand for words; there are so many before the surrogates begin.
FIRST_CODE, MOST_WORDS = 256, 0xD700


def _as_letters(text_words: Column, known: Column) -> Column:
    """Each word as one code point, by its place among the known words."""
    code = lambda w: F.decode(F.unhex(F.lpad(F.hex(F.array_position(known, w).cast("int") + (FIRST_CODE - 1)), 4, "0")), "UTF-16BE")
    return F.array_join(F.transform(text_words, code), "")


def word_errors(ref: Column, hyp: Column) -> Column:
    """Least substitutions, deletions and insertions between the words of two texts: Spark's own distance on one code
    point a word, inside generated code. A pair of more than MOST_WORDS distinct words raises an error (``edit_ops`` takes
    any) instead of a wrong count."""
    both = F.struct(words(ref).alias("r"), words(hyp).alias("h"))
    too_many = F.raise_error(F.lit(f"a pair has more than {MOST_WORDS} distinct words: use edit_ops")).cast("int")

    def distance(b: Column, known: Column) -> Column:
        return F.when(F.size(known) > MOST_WORDS, too_many).otherwise(F.levenshtein(_as_letters(b["r"], known), _as_letters(b["h"], known)))

    return let(both, lambda b: let(F.array_distinct(F.concat(b["r"], b["h"])), lambda known: distance(b, known)))


def wer(pairs: DataFrame, by: Sequence[str] = (), ref: str = "ref", hyp: str = "hyp") -> DataFrame:
    """by, errors, ref_words, wer (%) over all pairs of a group; null texts are empty; no reference words give a null rate."""
    r, h = F.coalesce(F.col(ref), F.lit("")), F.coalesce(F.col(hyp), F.lit(""))
    out = pairs.groupBy(*by).agg(F.coalesce(F.sum(word_errors(r, h)), F.lit(0)).cast("bigint").alias("errors"), F.coalesce(F.sum(F.size(words(r))), F.lit(0)).cast("bigint").alias("ref_words"))
    return out.withColumn("wer", F.when(F.col("ref_words") > 0, F.round(100 * F.col("errors") / F.col("ref_words"), 6)))


def cer(pairs: DataFrame, by: Sequence[str] = (), ref: str = "ref", hyp: str = "hyp") -> DataFrame:
    r, h = F.coalesce(F.col(ref), F.lit("")), F.coalesce(F.col(hyp), F.lit(""))
    out = pairs.groupBy(*by).agg(F.sum(F.levenshtein(r, h)).cast("bigint").alias("errors"), F.sum(F.length(r)).cast("bigint").alias("ref_chars"))
    return out.withColumn("cer", F.when(F.col("ref_chars") > 0, F.round(100 * F.col("errors") / F.col("ref_chars"), 6)))


def align(ref: list[str], hyp: list[str]) -> tuple[int, int, int]:
    """Substitutions, deletions, insertions of a cheapest alignment; of equals the one with most substitutions."""
    width = len(hyp) + 1
    cost = np.zeros((len(ref) + 1, width), np.int64)
    cost[:, 0], cost[0, :] = np.arange(len(ref) + 1), np.arange(width)
    for i in range(1, len(ref) + 1):
        for j in range(1, width):
            cost[i, j] = min(cost[i - 1, j - 1] + (ref[i - 1] != hyp[j - 1]), cost[i - 1, j] + 1, cost[i, j - 1] + 1)
    i, j, s, d, ins = len(ref), len(hyp), 0, 0, 0
    while i or j:
        if i and j and cost[i, j] == cost[i - 1, j - 1] + (ref[i - 1] != hyp[j - 1]):
            s += ref[i - 1] != hyp[j - 1]
            i, j = i - 1, j - 1
        elif i and cost[i, j] == cost[i - 1, j] + 1:
            d, i = d + 1, i - 1
        else:
            ins, j = ins + 1, j - 1
    return int(s), d, ins


#: Cells of alignment tables that are worked on at a time.
CELLS = 1 << 21


def align_all(refs: Sequence[list[str]], hyps: Sequence[list[str]]) -> np.ndarray:
    """(pairs, 3): ``align`` of every pair, many tables at a time, those of like sizes together."""
    codes: dict[str, int] = {}
    out = np.zeros((len(refs), 3), np.int64)
    sizes = np.array([(len(r), len(h)) for r, h in zip(refs, hyps, strict=True)], np.int64).reshape(-1, 2)
    order = np.lexsort((sizes[:, 1], sizes[:, 0]))
    first = 0
    while first < len(order):
        end, rows, width = first, 0, 0
        while end < len(order):
            rows, width = max(rows, sizes[order[end], 0] + 1), max(width, sizes[order[end], 1] + 1)
            if end > first and (end + 1 - first) * rows * width > CELLS:
                break
            end += 1
        some = order[first:end]
        out[some] = _align_block([[codes.setdefault(w, len(codes)) for w in refs[k]] for k in some], [[codes.setdefault(w, len(codes)) for w in hyps[k]] for k in some])
        first = end
    return out


def _align_block(refs: list[list[int]], hyps: list[list[int]]) -> np.ndarray:
    n, i, j = len(refs), np.array([len(r) for r in refs]), np.array([len(h) for h in hyps])
    ref, hyp = np.full((n, i.max(initial=0)), -1), np.full((n, j.max(initial=0)), -2)
    for k in range(n):
        ref[k, : i[k]], hyp[k, : j[k]] = refs[k], hyps[k]
    across = np.arange(hyp.shape[1] + 1)
    cost = np.empty((n, ref.shape[1] + 1, hyp.shape[1] + 1), np.int32)
    cost[:, 0] = across
    for a in range(ref.shape[1]):
        here = cost[:, a] + 1
        np.minimum(here[:, 1:], cost[:, a, :-1] + (hyp != ref[:, a : a + 1]), out=here[:, 1:])
        cost[:, a + 1] = np.minimum.accumulate(here - across, axis=1) + across
    out, at = np.zeros((n, 3), np.int64), np.arange(n)
    while len(at := at[(i[at] > 0) | (j[at] > 0)]):
        a, b, now = i[at], j[at], cost[at, i[at], j[at]]
        up, left = np.maximum(a - 1, 0), np.maximum(b - 1, 0)
        inner = (a > 0) & (b > 0)
        differ = np.zeros(len(at), bool)
        differ[inner] = ref[at[inner], up[inner]] != hyp[at[inner], left[inner]]
        slant = inner & (now == cost[at, up, left] + differ)
        down = ~slant & (a > 0) & (now == cost[at, up, b] + 1)
        out[at, 0] += slant & differ
        out[at, 1] += down
        out[at, 2] += ~slant & ~down
        i[at] -= slant | down
        j[at] -= ~down
    return out


def edit_ops(pairs: DataFrame, key: str, ref: str = "ref", hyp: str = "hyp") -> DataFrame:
    """key, substitutions, deletions, insertions of every pair (Arrow)."""
    from langspan.shipping import ship

    ship(pairs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ops = align_all(*([x or [] for x in b.column(c).to_pylist()] for c in ("r", "h")))
            yield pa.RecordBatch.from_arrays([b.column("key"), *(pa.array(ops[:, k]) for k in range(3))], ["key", "s", "d", "i"])

    told = pairs.select(F.col(key).alias("key"), words(F.col(ref)).alias("r"), words(F.col(hyp)).alias("h"))
    kind = dict(told.dtypes)["key"]
    return told.mapInArrow(run, f"key {kind}, s bigint, d bigint, i bigint").toDF(key, "substitutions", "deletions", "insertions")


def lid_accuracy(judged: DataFrame, truth: str, pred: str) -> DataFrame:
    """lang, n, correct, accuracy (%) for each true language."""
    right = F.sum(F.coalesce((F.col(truth) == F.col(pred)).cast("int"), F.lit(0)))
    return judged.groupBy(F.col(truth).alias("lang")).agg(F.count(F.lit(1)).alias("n"), right.alias("correct")).withColumn("accuracy", F.round(100 * F.col("correct") / F.col("n"), 6))


def lid_micro_macro(judged: DataFrame, truth: str, pred: str) -> DataFrame:
    """micro, macro: accuracy over all, and the mean of the languages' accuracies."""
    by = lid_accuracy(judged, truth, pred)
    return by.agg(F.round(100 * F.sum("correct") / F.sum("n"), 6).alias("micro"), F.round(F.avg("accuracy"), 6).alias("macro"))


def confusion(judged: DataFrame, truth: str, pred: str) -> DataFrame:
    return judged.groupBy(F.col(truth).alias("truth"), F.col(pred).alias("pred")).agg(F.count(F.lit(1)).alias("n"))


def boundary_f1(found: DataFrame, truth: DataFrame, key: str) -> DataFrame:
    """precision, recall, f1 of span starts (key, first_pos), the first of a sequence left out."""
    inner = lambda df: df.filter("span > 1").select(key, "first_pos").distinct()
    a, b = inner(found), inner(truth).select(F.col(key).alias("_k"), F.col("first_pos").alias("_p"))
    both = a.join(b, (F.col(key) == F.col("_k")) & (F.col("first_pos") == F.col("_p")), "full")
    counts = both.agg(F.count(key).alias("found"), F.count("_k").alias("true"), F.count_if(F.col(key).isNotNull() & F.col("_k").isNotNull()).alias("hit"))
    return counts.select(F.round(F.col("hit") / F.col("found"), 6).alias("precision"), F.round(F.col("hit") / F.col("true"), 6).alias("recall"), F.round(2 * F.col("hit") / (F.col("found") + F.col("true")), 6).alias("f1"))


def average_runs(runs: DataFrame, top: int = 5) -> DataFrame:
    """experiment, wer: mean over runs of the mean of each run's best checkpoints (ties by checkpoint)."""
    order = Window.partitionBy("experiment", "run").orderBy("wer", "checkpoint")
    best = runs.withColumn("_k", F.row_number().over(order)).filter(F.col("_k") <= top)
    return best.groupBy("experiment", "run").agg(F.avg("wer").alias("wer")).groupBy("experiment").agg(F.round(F.avg("wer"), 6).alias("wer"))


def corpus_profile(utts: DataFrame, by: Sequence[str] = ("lang",), exact: bool = True) -> DataFrame:
    """by, n_utts, n_samples, hours, n_unique_chars (white space aside)."""
    sizes = utts.groupBy(*by).agg(F.count(F.lit(1)).alias("n_utts"), F.sum("n_samples").cast("bigint").alias("n_samples"))
    letters = utts.select(*by, F.explode(F.array_distinct(F.split("text", ""))).alias("ch")).filter("ch <> '' AND ch <> ' '")
    count = F.countDistinct("ch") if exact else F.approx_count_distinct("ch")
    chars = letters.groupBy(*(F.col(c).alias(f"_{c}") for c in by)).agg(count.alias("n_unique_chars"))
    on = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in by]
    joined = sizes.join(chars, on, "left") if by else sizes.crossJoin(chars)
    return joined.select(*by, "n_utts", "n_samples", F.round(F.col("n_samples") / SAMPLE_RATE / 3600, 6).alias("hours"), F.coalesce("n_unique_chars", F.lit(0)).cast("bigint").alias("n_unique_chars"))


def stickiness(langs: DataFrame, by: str) -> DataFrame:
    """by, n, n_single: sequences, and those whose output stays in one language. langs: by, key, n_langs."""
    return langs.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("n_langs") <= 1).cast("int")).alias("n_single"))


def fertility(tokens: DataFrame, unk_ids: Sequence[int]) -> DataFrame:
    """lang, n_tokens, n_unk, unk_rate of encoded words."""
    unk = F.col("token_id").isin([int(u) for u in unk_ids])
    out = tokens.groupBy("lang").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(unk.cast("int")).alias("n_unk"))
    return out.withColumn("unk_rate", F.round(F.col("n_unk") / F.col("n_tokens"), 6))
