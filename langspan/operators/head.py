"""The output layer of a decoder over a partitioned vocabulary: suppression, growth, merging, CTC collapse, fusion.

States are rows (key, h array<double>), the layer is rows (token_id, w array<double>). A layer has as many rows as the
vocabulary has ids, a bound the ranges give, so it is broadcast.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from langspan.operators.vocab import RangeVocab


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def class_means(vectors: DataFrame, label: str = "label", vector: str = "embedding") -> DataFrame:
    """A layer from labelled vectors: (token_id, w) with the mean of each label."""
    each = vectors.select(F.col(label).alias("token_id"), F.posexplode(vector).alias("i", "x"))
    means = each.groupBy("token_id", "i").agg(F.avg(F.col("x").cast("double")).alias("x"))
    return means.groupBy("token_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "x"))), lambda p: p["x"]).alias("w"))


def project(states: DataFrame, layer: DataFrame, key: str, vocab: RangeVocab | None = None, allowed: Sequence[str] | None = None, blank: int | None = None, h: str = "h") -> DataFrame:
    """key, token_id, score: the best id of every state. With ``allowed`` only the ranges of these languages (and the
    blank) are scored at all: the filter is on the layer, before the product. Ties go to the lower id."""
    if allowed is not None:
        if not allowed:
            raise ValueError("no language is allowed")
        keep = vocab.lang_predicate(F.col("token_id"), allowed)
        layer = layer.filter(keep if blank is None else keep | (F.col("token_id") == blank))
    scored = states.crossJoin(F.broadcast(layer.select("token_id", "w"))).select(key, "token_id", F.round(dot(F.col(h), F.col("w")), 6).alias("score"))
    return scored.groupBy(key).agg(F.max_by(F.struct("token_id", "score"), F.struct("score", -F.col("token_id"))).alias("b")).select(key, "b.token_id", "b.score")


def project_joint(states: DataFrame, contexts: DataFrame, layer: DataFrame, key: str, vocab: RangeVocab, allowed: Sequence[str] | None = None, blank: int | None = None) -> DataFrame:
    """The transducer's form: encoder state and prediction context are added before the same filtered layer."""
    joint = states.join(contexts.select(F.col(key).alias("_key"), "context"), F.col(key) == F.col("_key"))
    joint = joint.withColumn("h", F.zip_with("h", "context", lambda a, b: F.tanh(a + b))).select(key, "h")
    return project(joint, layer, key, vocab, allowed, blank)


def scored_ids(vocab: RangeVocab, allowed: Sequence[str]) -> float:
    """Share of the ids that suppression leaves to be scored."""
    return sum(vocab.range(lang)[1] for lang in allowed) / vocab.total


def grow_head(layer: DataFrame, old: RangeVocab, new: RangeVocab, dim: int, scale: float = 0.02, seed: int = 0) -> DataFrame:
    """The layer for an extended vocabulary: old rows are copied, the others start as seeded normal values."""
    spark = layer.sparkSession
    have = {lang for lang in old.langs}
    out = layer.select("token_id", "w")
    for lang, offset, size in new.entries:
        if lang in have:
            if old.range(lang) != (offset, size):
                raise ValueError(f"the range of {lang} has moved")
            continue
        uniform = lambda i, salt: (F.pmod(F.xxhash64(F.lit(seed), F.col("id"), i, F.lit(salt)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
        values = F.transform(F.sequence(F.lit(1), F.lit(dim)), lambda i: F.sqrt(-2 * F.log(uniform(i, 1))) * F.cos(2 * 3.141592653589793 * uniform(i, 2)) * scale)
        out = out.union(spark.range(offset, offset + size).select(F.col("id").cast("int").alias("token_id"), values.alias("w")))
    return out


def merge_heads(heads: Sequence[tuple[str, DataFrame]], vocab: RangeVocab) -> DataFrame:
    """One layer from monolingual ones, each shifted into its language's range."""
    out = None
    for lang, layer in heads:
        shifted = layer.select((F.col("token_id") + vocab.range(lang)[0]).cast("int").alias("token_id"), "w")
        out = shifted if out is None else out.unionByName(shifted)
    return out


def drop_language(layer: DataFrame, vocab: RangeVocab, lang: str, repack: bool = False) -> tuple[DataFrame, RangeVocab]:
    """Suppression made permanent: without the language's rows; ids behind it stay or close up."""
    smaller, moves = vocab.drop(lang, repack)
    left = layer.filter(~vocab.lang_predicate(F.col("token_id"), [lang]))
    shift = F.lit(0)
    for first, end, by in moves:
        shift = F.when(F.col("token_id").between(first, end - 1), by).otherwise(shift)
    return left.select((F.col("token_id") + shift).cast("int").alias("token_id"), "w"), smaller


def ctc_collapse(ids: Column, blank: Column | int) -> Column:
    """Greedy CTC: repeats merge, then blanks go. ids: a column, not an expression that is dear to evaluate."""
    kept = F.filter(F.sequence(F.lit(1), F.greatest(F.size(ids), F.lit(1))), lambda i: (F.get(ids, i - 1) != blank) & ((i == 1) | (F.get(ids, i - 1) != F.get(ids, F.greatest(i - 2, F.lit(0))))))
    return F.when(F.size(ids) > 0, F.transform(kept, lambda i: F.get(ids, i - 1))).otherwise(ids)


def posterior_fusion(states: DataFrame, layer: DataFrame, lid: DataFrame, key: str, vocab: RangeVocab) -> DataFrame:
    """Baseline: two monolingual layers, each normalised by itself, weighed by a separate language classifier.

    lid: key, lang, p. Both layers are always scored. Returns key, token_id, score (log probability).
    """
    logits = states.crossJoin(F.broadcast(layer.select("token_id", "w"))).select(key, "token_id", vocab.lang_of(F.col("token_id")).alias("lang"), dot(F.col("h"), F.col("w")).alias("z"))
    norm = logits.groupBy(F.col(key).alias("_key"), F.col("lang").alias("_lang")).agg(F.log(F.sum(F.exp("z"))).alias("_norm"))
    weighed = logits.join(norm, (F.col(key) == F.col("_key")) & (F.col("lang") == F.col("_lang"))).select(key, "token_id", "lang", (F.col("z") - F.col("_norm")).alias("logp"))
    lid = lid.select(F.col(key).alias("_key"), F.col("lang").alias("_lang"), F.log("p").alias("_lid"))
    fused = weighed.join(lid, (F.col(key) == F.col("_key")) & (F.col("lang") == F.col("_lang"))).select(key, "token_id", F.round(F.col("logp") + F.col("_lid"), 6).alias("score"))
    return fused.groupBy(key).agg(F.max_by(F.struct("token_id", "score"), F.struct("score", -F.col("token_id"))).alias("b")).select(key, "b.token_id", "b.score")
