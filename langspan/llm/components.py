"""Connected components by alternating stars: every vertex points its neighbours at its smallest neighbour until nothing moves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable


def _least(edges: DataFrame) -> DataFrame:
    """edges (a, b) with, for every a, the least of a and its b as m."""
    least = edges.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("_a"), F.least("a", "m").alias("m"))
    return edges.join(least, F.col("a") == F.col("_a")).select("a", "b", "m")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every vertex of ``edges`` (a, b), both BIGINT: root is the smallest vertex of its component.

    Loops and repeated edges are harmless; no edges give no rows. Vertices alone in their component do not appear.
    """
    pairs = edges.filter(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    pairs = durable(pairs)
    state = None
    while True:
        both = pairs.union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = _least(both).filter(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        small = _least(large.distinct())
        small = small.select("b", "m").union(small.select(F.col("a").alias("b"), "m")).filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        pairs = durable(small.distinct())
        now = pairs.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b") % 1_000_000_007)).first()
        if now == state:
            break
        state = now
    roots = pairs.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots.union(pairs.select(F.col("b").alias("node"), F.col("b").alias("root"))).distinct()
