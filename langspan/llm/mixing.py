"""Mixing sources to target weights by distributed prefix sums over hash-random order, in DataFrame functions only.

Targets: a budget is shared by weight; no source is read more than ``most`` times, and what it cannot take is shared
anew among the others (water filling: source s gets min(most * size_s, level * weight_s), the level spends the budget).

Selection: a source is read whole as often as its target holds it; the rest is the head of its documents in the order
of a hash of their ids. Each source's documents fall into about sqrt(rows) consecutive hash ranges; sums of the ranges
give each its first word, running sums inside a range do the rest, and the document at the cut gives its first words.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import durable, hash48, inner_names, table, without, word_count

MOST_READS = 3
#: Sources are planned on the driver, a few numbers for each; more than this raises an error.
MAX_SOURCES = 200_000
_SPAN = float(1 << 48)


def cyclic_weight(rank: int, size: int) -> float:
    """Weights 1, 2, 3, repeating, in code-point order of the sources, null last."""
    return float(rank % 3 + 1)


def tempered_weight(power: float) -> Callable[[int, int], float]:
    """Weight of a source of ``size`` words: size ** power, which flattens the natural mixture."""
    return lambda rank, size: float(size) ** power


def water_fill(sizes: list[int], weights: list[float], budget: float, most: float) -> list[float]:
    """Targets of the sources: proportional to weight, at most ``most`` times the size, summing to the budget if they can."""
    targets = [0.0] * len(sizes)
    order = sorted((i for i, n in enumerate(sizes) if n > 0), key=lambda i: (most * sizes[i] / weights[i], i))
    left, weight = min(budget, most * sum(sizes)), sum(weights[i] for i in order)
    for i in order:
        targets[i] = min(most * sizes[i], left * weights[i] / weight)
        left -= targets[i]
        weight -= weights[i]
    return targets


def plan_sources(docs: DataFrame, size: Column, source_col: str, weight: Callable[[int, int], float], share: float | None, most: float) -> list[tuple]:
    """(source, rows, words, target) of every source, ascending, null last. The budget is ``share`` of all words, or, for
    None, the least with which every source is read once at least."""
    found = docs.groupBy(F.col(source_col).cast("string").alias("_s")).agg(F.count(F.lit(1)).alias("rows"), F.sum(size).alias("words")).limit(MAX_SOURCES + 1).collect()
    if len(found) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    found.sort(key=lambda r: (r["_s"] is None, r["_s"] or ""))
    sizes = [int(r["words"] or 0) for r in found]
    weights = [weight(i, n) if n else 1.0 for i, n in enumerate(sizes)]
    if share is None:
        level = max((n / w for n, w in zip(sizes, weights, strict=True)), default=0.0)
        targets = [max(float(n), min(most * n, level * w)) if n else 0.0 for n, w in zip(sizes, weights, strict=True)]
    else:
        targets = water_fill(sizes, weights, share * sum(sizes), most)
    return [(r["_s"], r["rows"], n, t) for r, n, t in zip(found, sizes, targets, strict=True)]


def take_words(
    docs: DataFrame,
    size: Column,
    id_col: str = "doc_id",
    source_col: str = "source",
    weight: Callable[[int, int], float] = cyclic_weight,
    share: float | None = 1.0,
    most: float = MOST_READS,
    seed: str = "mix",
    spare: Column | None = None,
) -> DataFrame:
    """``docs`` with ``size``, ``source_size``, ``target`` and ``taken`` (words taken, repeats counted) at the end; columns of
    these names are replaced, no others.

    Null sources are one source, last in order. Null ids go by ``spare`` (a digest of the text; without it by size alone),
    repeated ids by size: equals are ordered together. Documents without words take nothing; an empty table stays empty.
    Every run gives the same counts.
    """
    docs = docs.withColumn("size", size.cast("bigint"))
    names = [c for c in without(docs, "size", "source_size", "target", "taken").columns]
    own = inner_names(docs, "_source", "_rows", "_reads", "_rest", "_ranges", "_key", "_range", "_from", "_at", "_first")
    source, rows, reads, rest, ranges, key, range_, from_, at, first = own
    c = F.col
    docs = without(docs, "source_size", "target", "taken")
    sources = plan_sources(docs, c("size"), source_col, weight, share, most)
    plan = docs.sparkSession.createDataFrame(sources, f"{source} string, {rows} bigint, source_size bigint, target double")
    plan = plan.withColumn(reads, F.when(c("source_size") > 0, F.floor(c("target") / c("source_size"))).otherwise(0))
    plan = plan.withColumn(rest, F.round(c("target") - c(reads) * c("source_size")).cast("bigint"))
    plan = F.broadcast(plan.withColumn(ranges, F.ceil(F.sqrt(c(rows)))))
    told = F.coalesce(c(f"`{id_col}`").cast("string"), F.lit("") if spare is None else F.concat(F.lit("#"), spare))
    order = hash48(F.concat(F.lit(f"{seed}:"), told, F.lit(":"), c("size").cast("string")))
    keyed = (
        docs.join(plan, c(f"`{source_col}`").cast("string").eqNullSafe(c(source)))
        .withColumn(key, order)
        .withColumn(range_, F.floor(c(key) / F.lit(_SPAN) * c(ranges)).cast("bigint"))
    )
    by_source = Window.partitionBy(source).orderBy(range_)
    firsts = keyed.groupBy(source, range_).agg(F.sum("size").alias("n"))
    firsts = firsts.select(c(source).alias(from_), c(range_).alias(at), (F.sum("n").over(by_source) - c("n")).alias(first))
    inside = Window.partitionBy(source, range_).orderBy(key, id_col, "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    before = c(first) + F.sum("size").over(inside) - c("size")
    more = F.greatest(F.lit(0), F.least(c("size"), c(rest) - before))
    joined = keyed.join(firsts, c(source).eqNullSafe(c(from_)) & (c(range_) == c(at)))
    taken = (c(reads) * c("size") + more).cast("bigint").alias("taken")
    return joined.select(*(f"`{n}`" for n in names), "size", "source_size", "target", taken)


def mix(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """The mixed corpus: one row for each reading of a document, columns as in ``docs``.

    A document at a source's cut is read up to the cut's word; ``n_chars`` (if there is one) follows the text. Empty and
    null texts and others without a word take nothing from any target: each stays once, as it is.
    """
    names = docs.columns
    own = [f"_column_{k}" for k in range(len(names))]  # so that no name of theirs meets one of ours
    text, source, id_ = (own[[n.lower() for n in names].index(c.lower())] for c in (text_col, options.pop("source_col", "source"), options.pop("id_col", "doc_id")))
    told = docs.select(*(F.col(f"`{c}`").alias(o) for c, o in zip(names, own, strict=True)))
    spare = F.md5(F.coalesce(F.col(text).cast("string"), F.lit("")))
    taken = take_words(told, word_count(F.col(text)), id_, source, spare=spare, **options)
    reads = F.col("taken") / F.greatest(F.col("size"), F.lit(1))
    part = F.col("taken") - F.floor(reads) * F.col("size")
    times = F.greatest(F.lit(1), F.ceil(reads).cast("int"))
    copies = taken.filter((F.col("taken") > 0) | (F.col("size") == 0)).withColumn("copy", F.explode(F.sequence(F.lit(1), times)))
    cut = (F.col("copy") > F.floor(reads)) & (part > 0)
    out = {o: F.col(o) for o in own}
    out[text] = F.when(cut, _head_words(F.col(text), part)).otherwise(F.col(text))
    if "n_chars" in names:
        count = own[names.index("n_chars")]
        out[count] = F.when(cut, F.length(out[text])).otherwise(F.col(count)).cast("bigint")
    return copies.select(*(out[o].alias(c) for c, o in zip(names, own, strict=True)))


def _head_words(text: Column, n: Column) -> Column:
    """The text up to the end of its n-th word, white space as it was."""
    pieces = F.split(text, r"(?<=[^\x20\x09-\x0D])(?=[\x20\x09-\x0D])")
    return F.array_join(F.slice(pieces, F.lit(1), n.cast("int")), "")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of mixing all documents: weights 1, 2, 3 repeating over the sources, all words, 3 readings at most.

    Texts are read once, for their sizes; planning, sums and selection read those."""
    spare = F.when(F.col("doc_id").isNull(), F.md5(F.coalesce(F.col("text"), F.lit("")))).alias("spare")
    small = durable(table(spark, sf_dir, "documents").select("doc_id", "source", word_count(F.col("text")).alias("size"), spare))
    return take_words(small, F.col("size"), spare=F.col("spare")).select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), "taken")


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, source, coalesce(doc_id::varchar, '#' || md5(coalesce(text, ''))) AS told, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint AS size FROM documents),
s AS (SELECT source, count(*) AS n, sum(size)::bigint AS source_size, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::double AS w FROM d GROUP BY source),
o AS (SELECT *, row_number() OVER (ORDER BY 3.0 * source_size / w, source NULLS LAST) AS k FROM s WHERE source_size > 0),
f AS (
  SELECT 0::bigint AS k, NULL::varchar AS source, 0::double AS target, sum(source_size)::double AS budget, sum(w)::double AS weight FROM o
  UNION ALL
  SELECT o.k, o.source, least(3.0 * source_size, budget * w / weight), budget - least(3.0 * source_size, budget * w / weight), weight - w FROM f JOIN o ON o.k = f.k + 1),
p AS (SELECT s.source, s.source_size, coalesce(f.target, 0) AS target FROM s LEFT JOIN f ON f.k > 0 AND f.source IS NOT DISTINCT FROM s.source),
q AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS reads FROM p),
t AS (
  SELECT d.doc_id, d.size, q.source_size, q.target, q.reads, round(q.target - q.reads * q.source_size)::bigint AS rest,
    sum(d.size) OVER (PARTITION BY d.source ORDER BY ('0x' || substr(md5('mix:' || told || ':' || d.size::varchar), 1, 12))::bigint, doc_id, d.size ROWS UNBOUNDED PRECEDING) - d.size AS before
  FROM d JOIN q ON d.source IS NOT DISTINCT FROM q.source)
SELECT doc_id, size, source_size, round(target, 6) AS target, (reads * size + greatest(0, least(size, rest - before)))::bigint AS taken FROM t"""
