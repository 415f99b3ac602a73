"""Exact Jaccard self-join on word shingles with adaptive multi-match prefixes, down to linked components.

1. *Sets.* A kernel turns every text into its set of shingle hashes. Documents with equal sets become one node.
2. *Screen.* In hash order, two sets that link share at least ``l`` of their first ``n - ceil(t*n) + l`` shingles. With a
   long prefix (``l`` grows with ``n``) most sets find too few shingles that any other set has, and leave. Shingles that
   very many sets have are found in a sample first and then need no grouping.
3. *Prefixes.* What is left is ordered by document frequency, rare first. Each set picks its own ``l`` from 1 to 4: one
   more prefix shingle costs its posting list, but every partner must then share one more, so the estimated cost is
   ``sum(df) * (1 + VERIFY / l)`` over the prefix. Two sets must share min(l, l') of their shingles at that length.
4. *Stars.* Each prefix shingle has one hub. A member and a hub that meet in min(l, l') shingles are verified. A group of
   near copies, however large, collapses here at a cost that is linear in it.
5. *Rest.* Shingles whose members are still in different components are compared member by member in blocks of bounded
   bytes; pairs of one component are skipped, the others need min(l, l') shared prefix shingles, then the sets decide.

Joins on shingles take those with very many members (at most HEAVY of them) by broadcast, so that none falls to one task.

Every pair that links ends in one component: it is seen in 4, or in 5, or was joined by others before. Nodes and
shingles are 64-bit hashes: two different ones coincide with a chance of about N**2 / 2**65.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.shipping import ship

from . import kernels
from .common import durable, inner_names, table
from .components import components

#: Sets of a block, and shingles in all of them together (one set at least): a worker holds two blocks.
BLOCK, BLOCK_SHINGLES = 512, 1 << 21
LENGTHS = 4
VERIFY = 8
#: A shingle with more members than MEMBERS is heavy; the HEAVY heaviest are broadcast (about 50 bytes each), others are dealt.
MEMBERS, HEAVY = 200, 50_000
#: One of so many rows is looked at for heavy shingles of the screen.
SAMPLED = 16
#: Bits of the filter that keeps most texts out of the second shuffle: at most 2 ** 17 broadcast rows.
BITMAP = 1 << 23


@dataclass(frozen=True)
class Rule:
    """Sets of ``words``-word shingles link when intersection / union >= num / den."""

    words: int = 5
    num: int = 80
    den: int = 100
    #: Share of a set by which the screen's prefix is longer than the shortest sound one.
    longer: float = 0.12

    def least(self, n):
        """Shingles that a set of ``n`` shares with any set it links with."""
        return -(-(n * self.num) // self.den)

    def least_sql(self, n: Column) -> Column:
        return F.ceil(n * self.num / self.den).cast("bigint")

    def overlap(self, n, m):
        """Shared shingles that sets of ``n`` and ``m`` need (over integers or arrays)."""
        return -(-((n + m) * self.num) // (self.num + self.den))


def _lists(rows: list[np.ndarray]) -> pa.Array:
    offsets = np.zeros(len(rows) + 1, np.int32)
    np.cumsum([len(x) for x in rows], out=offsets[1:])
    flat = np.concatenate(rows) if rows else np.zeros(0, np.uint64)
    return pa.ListArray.from_arrays(offsets, flat.astype(np.uint64).view(np.int64))


def _row_sets(column: pa.Array, words: int) -> Iterator[np.ndarray]:
    for _, _, data, offsets in kernels.slices(column):
        starts, ends, bounds = kernels.words(data, offsets)
        yield from kernels.row_shingles(kernels.word_hashes(data, starts, ends), bounds, words)


def _node(tokens: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        return int(kernels.mix(np.array([tokens.sum(dtype=np.uint64) + np.uint64(len(tokens)) * np.uint64(0x9E3779B97F4A7C15)], np.uint64)).view(np.int64)[0])


def _describe(rule: Rule):
    """id, text -> id, text hash, n, node, and of each node's first row in a batch the screen's prefix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, nodes, prefixes, seen = [], [], [], set()
            for tokens in _row_sets(batch.column("text"), rule.words):
                n = len(tokens)
                node = _node(tokens) if n else None
                first = n > 0 and node not in seen
                seen.add(node)
                sizes.append(n)
                nodes.append(node)
                prefixes.append(tokens[: n - rule.least(n) + 1 + int(rule.longer * n)].copy() if first else tokens[:0])
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), batch.column("text_hash"), pa.array(sizes, pa.int64()), pa.array(nodes, pa.int64()), _lists(prefixes)], ["id", "text_hash", "n", "node", "screen"]
            )

    return run


def _whole_sets(rule: Rule):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("node"), _lists(list(_row_sets(batch.column("text"), rule.words)))], ["node", "tokens"])

    return run


def _blocks(rule: Rule):
    """One block pair -> links (a, b) between different components, as few as join them.

    Rows: node, n, comp, side (0 and 1 are compared with each other, 2 all with all), l, first (prefix length for l = 1),
    prefix (in global order) and tokens (sorted). A null prefix stands for a hub, which needs no shared prefix.
    """

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.combine_chunks()
        node, n, comp, side = (rows.column(c).to_numpy() for c in ("node", "n", "comp", "side"))
        split = lambda c: (lambda a: [a.values.slice(s, e - s).to_numpy(zero_copy_only=False).view(np.uint64) for s, e in zip(a.offsets[:-1].to_pylist(), a.offsets[1:].to_pylist(), strict=True)])(rows.column(c).chunk(0) if isinstance(rows.column(c), pa.ChunkedArray) else rows.column(c))
        count = len(node)
        tokens = split("tokens")
        if bool(rows.column("by_prefix").to_numpy(zero_copy_only=False)[0]):
            match, first = rows.column("l").to_numpy(), rows.column("first").to_numpy()
            prefix = split("prefix")
            flat = np.concatenate(prefix)
            owner = np.repeat(np.arange(count), [len(x) for x in prefix])
            level = np.concatenate([np.maximum(1, np.arange(len(x)) + 2 - f) for x, f in zip(prefix, first, strict=True)])
            order = np.argsort(flat, kind="stable")
            flat, owner, level = flat[order], owner[order], level[order]
            cuts = np.flatnonzero(np.r_[True, flat[1:] != flat[:-1], True])
            shared = np.zeros((LENGTHS + 1, count, count), np.int16)
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if b - a > 1:
                    for k in range(1, LENGTHS + 1):
                        who = owner[a:b][level[a:b] <= k]
                        if len(who) > 1:
                            shared[k][np.ix_(who, who)] += 1
            wanted = np.minimum(match[:, None], match[None, :])
            maybe = np.take_along_axis(shared, wanted[None].astype(np.int64), 0)[0] >= wanted
            del shared
        else:
            maybe = np.ones((count, count), bool)
        maybe &= (side[:, None] != side[None, :]) | (side[:, None] == 2)
        maybe &= np.minimum(n[:, None], n[None, :]) * rule.den >= np.maximum(n[:, None], n[None, :]) * rule.num
        maybe &= np.triu(np.ones((count, count), bool), 1)
        label = np.unique(comp, return_inverse=True)[1]
        out: list[tuple[int, int]] = []
        for i in range(count):
            others = np.flatnonzero(maybe[i])
            others = others[label[others] != label[i]]
            if not len(others):
                continue
            mine = tokens[i]
            flat = np.concatenate([tokens[j] for j in others])
            hit = mine[np.minimum(np.searchsorted(mine, flat), len(mine) - 1)] == flat
            both = np.add.reduceat(hit, np.r_[0, np.cumsum(n[others])[:-1]], dtype=np.int64)
            for j in others[both >= rule.overlap(n[i], n[others])]:
                if label[j] != label[i]:
                    out.append((int(node[i]), int(node[j])))
                    label[label == label[j]] = label[i]
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([x for _, x in out], pa.int64())})

    return run


def _compared(tasks: DataFrame, sets: DataFrame, keys: list[str], rule: Rule) -> DataFrame:
    return tasks.join(sets, "node").groupBy(*keys).applyInArrow(_blocks(rule), "a bigint, b bigint")


def _likely(told: DataFrame, alive: DataFrame) -> DataFrame:
    """Rows of ``told`` that may be in ``alive``, by a bitmap of BITMAP bits over text hashes: its size is fixed, and where
    it fills up it lets more rows through, never fewer."""
    spot = F.pmod(F.xxhash64(F.lit("bitmap"), "text_hash"), F.lit(BITMAP))
    bits = alive.select(F.xxhash64(F.lit("bitmap"), "_hash").alias("h")).select(F.pmod("h", F.lit(BITMAP)).alias("spot"))
    bits = bits.groupBy(F.shiftright("spot", 6).alias("_word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(spot & 63 as int))")).alias("_bits"))
    return (
        told.withColumn("_spot", spot)
        .join(F.broadcast(bits), (F.shiftright("_spot", 6) == F.col("_word")) & (F.expr("shiftleft(1L, cast(_spot & 63 as int)) & _bits") != 0))
        .drop("_spot", "_word", "_bits")
    )


def linked_sets(docs: DataFrame, rule: Rule, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """Descriptions (id, text_hash, n, node) of all rows, and links (a, b) between nodes that span each component."""
    ship(docs.sparkSession)
    told = docs.select(F.col(id_col).cast("bigint").alias("id"), F.xxhash64(text_col).alias("text_hash"), F.col(text_col).cast("string").alias("text"))
    described = durable(told.mapInArrow(_describe(rule), "id bigint, text_hash bigint, n bigint, node bigint, screen array<bigint>"))

    # 2: a shingle of the screen counts if another node has it there too
    found = described.select("node", "n", F.explode("screen").alias("t"))
    some = found.filter(F.pmod(F.xxhash64("node", "t"), F.lit(SAMPLED)) == 0).groupBy("t").agg(F.count(F.lit(1)).alias("c"), F.min("node").alias("a"), F.max("node").alias("b"))
    known = durable(some.filter(f"c >= {MEMBERS // SAMPLED} AND a <> b").orderBy(F.desc("c"), "t").limit(HEAVY).select("t"))
    flagged = found.join(F.broadcast(known.withColumnRenamed("t", "sure")), F.col("t") == F.col("sure"), "left")
    shingle = Window.partitionBy(F.when(F.col("sure").isNotNull(), F.xxhash64("node", "t")).otherwise(F.col("t")))
    shared = flagged.withColumn("both", F.col("sure").isNotNull() | (F.min("node").over(shingle) != F.max("node").over(shingle))).filter("both")
    enough = 1 + F.floor(rule.longer * rule.least_sql(F.col("n")))
    alive = shared.groupBy("node").agg(F.count(F.lit(1)).alias("hits"), F.max("n").alias("n")).filter(F.col("hits") >= enough)
    holder = described.filter("n > 0").groupBy("node").agg(F.min(F.struct("id", "text_hash")).alias("row"))
    alive = durable(alive.join(holder, "node").select("node", F.col("row.id").alias("_id"), F.col("row.text_hash").alias("_hash")))
    same_row = F.col("id").eqNullSafe(F.col("_id")) & (F.col("text_hash") == F.col("_hash"))
    sets = _likely(told, alive).join(alive, same_row).select("node", "text")
    sets = durable(sets.mapInArrow(_whole_sets(rule), "node bigint, tokens array<bigint>"))

    prefixes = durable(_prefixes(sets, rule))
    postings = prefixes.select("node", "n", "l", F.explode("prefix").alias("t"))

    # 4: every member of a shingle against its hub
    hubs = postings.groupBy("t").agg(F.min(F.struct("node", "n", "l")).alias("hub"), F.count(F.lit(1)).alias("members")).filter("members > 1")
    hubs = durable(hubs)
    heavy = durable(hubs.filter(f"members > {MEMBERS}").orderBy(F.desc("members"), "t").limit(HEAVY).select("t"))
    near = (F.least("n", "hub.n") * rule.den) >= (F.greatest("n", "hub.n") * rule.num)
    met = _by_shingle(postings, hubs.select("t", "hub"), heavy).filter((F.col("node") != F.col("hub.node")) & near)
    met = met.groupBy(F.col("hub.node").alias("hub"), F.col("hub.n").alias("hub_n"), F.col("hub.l").alias("hub_l"), "node", "n", "l").agg(F.count(F.lit(1)).alias("shared"))
    spokes = durable(met.filter(F.col("shared") >= F.least("l", "hub_l")).select("hub", "hub_n", "node", "n"))
    blocks = spokes.groupBy("hub", "hub_n").agg(_block_count("n"))
    side = lambda k: [F.lit(k).alias("side"), F.lit(1).alias("l"), F.lit(1).alias("first"), F.array().cast("array<bigint>").alias("prefix"), F.lit(False).alias("by_prefix")]
    members = spokes.join(blocks.drop("hub_n"), "hub")
    members = members.select("hub", F.pmod(F.xxhash64("node"), "blocks").cast("int").alias("block"), "node", "n", F.col("node").alias("comp"), *side(1))
    centres = blocks.select("hub", "hub_n", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"))
    centres = centres.select("hub", "block", F.col("hub").alias("node"), F.col("hub_n").alias("n"), F.col("hub").alias("comp"), *side(0))
    links = durable(_compared(members.unionByName(centres), sets, ["hub", "block"], rule))

    # 5: shingles of at least three members that are not in one component yet (a pair that meets in shingles of its own
    # alone has one hub for all of them and was verified above)
    joined = postings.drop("l").join(components(links), "node", "left").select("t", "node", "n", F.coalesce("root", "node").alias("comp"))
    open_ = joined.groupBy("t").agg(F.min("comp").alias("a"), F.max("comp").alias("b"), F.count(F.lit(1)).alias("members")).filter("members > 2 AND a <> b").select("t")
    rest = durable(_by_shingle(joined, open_, heavy))
    # shingles with common members go to one group: the smallest shingle that any member has
    least = rest.groupBy("node").agg(F.min("t").alias("least"))
    group = rest.join(least, "node").groupBy("t").agg(F.min("least").alias("g"))
    grouped = durable(_by_shingle(rest, group, heavy).select("g", "node", "n", "comp").distinct())
    blocks = grouped.groupBy("g").agg(_block_count("n"))
    mine, other = F.col("mine"), F.col("other")
    tasks = (
        grouped.drop("n")
        .join(blocks, "g")
        .withColumn("mine", F.pmod(F.xxhash64("node"), "blocks").cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .withColumn("side", F.when(mine == other, 2).when(mine < other, 0).otherwise(1))
        .select("g", F.least(mine, other).alias("low"), F.greatest(mine, other).alias("high"), "node", "comp", "side")
        .join(prefixes, "node")
        .withColumn("by_prefix", F.lit(True))
    )
    more = _compared(tasks, sets, ["g", "low", "high"], rule)
    return described, links.union(more)


def _block_count(n: str) -> Column:
    """Blocks of a group by its members and by the shingles in their sets."""
    return F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK, F.sum(n) / BLOCK_SHINGLES)).cast("int").alias("blocks")


def _by_shingle(rows: DataFrame, facts: DataFrame, heavy: DataFrame) -> DataFrame:
    """``rows`` (node, t, ...) joined with ``facts`` (one row a shingle) on ``t``. The heavy shingles' facts, HEAVY at most,
    are broadcast; rows that found theirs take no shingle's place in the other join but are spread by a hash."""
    few = F.broadcast(heavy)
    packed = facts.select("t", F.struct(*[c for c in facts.columns if c != "t"], F.lit(1).alias("_one")).alias("f"))
    many = packed.join(few, "t", "left_semi").select(F.col("t").alias("_many"), F.col("f").alias("_f"))
    others = packed.join(few, "t", "left_anti").select(F.col("t").alias("_other"), F.col("f").alias("_g"))
    found = rows.join(F.broadcast(many), F.col("t") == F.col("_many"), "left")
    found = found.withColumn("_place", F.when(F.col("_many").isNotNull(), F.xxhash64("node", "t")).otherwise(F.col("t")))
    found = found.join(others, (F.col("_place") == F.col("_other")) & F.col("_many").isNull(), "left")
    return found.withColumn("_f", F.coalesce("_f", "_g")).filter("_f IS NOT NULL").select(*rows.columns, "_f.*").drop("_one")


def _prefixes(sets: DataFrame, rule: Rule) -> DataFrame:
    """node, n, l, first, prefix: each set's prefix under the global order, at the length that is estimated cheapest.

    Only shingles of at least two sets count, rare first; those of one set come before them and match nothing.
    """
    each = sets.select("node", F.size("tokens").cast("bigint").alias("n"), F.explode("tokens").alias("t"))
    frequency = durable(each.groupBy("t").agg(F.count(F.lit(1)).alias("c")).filter("c > 1"))
    heavy = durable(frequency.filter(f"c > {MEMBERS}").orderBy(F.desc("c"), "t").limit(HEAVY).select("t"))
    known = _by_shingle(each, frequency, heavy).groupBy("node", "n").agg(F.sort_array(F.collect_list(F.struct("c", "t"))).alias("known"))
    known = known.withColumn("first", (F.size("known") - rule.least_sql(F.col("n")) + 1).cast("int")).filter("first > 0")
    reach = lambda k: F.slice("known", F.lit(1), F.col("first") + (k - 1))
    lists = lambda k: F.aggregate(reach(k), F.lit(0).cast("bigint"), lambda s, x: s + x["c"])
    costs = (F.struct((lists(k) * (1.0 + VERIFY / k)).alias("cost"), F.lit(k).alias("l")) for k in range(1, LENGTHS + 1))
    length = F.least(F.array_min(F.array(*costs))["l"], F.greatest(F.lit(1), rule.least_sql(F.col("n"))))
    known = known.withColumn("l", length.cast("int"))
    return known.select("node", "n", "l", "first", F.transform(reach(F.col("l")), lambda x: x["t"]).alias("prefix"))


def cluster(docs: DataFrame, rule: Rule = Rule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:  # noqa: B008
    """(doc_id, n_shingles, component_id, text_hash) of every row of ``docs``.

    ``component_id`` is the smallest id reachable over links.
    A text without words (or null) has an empty set, links with nothing and is its own
    component; a null id is no component's smallest (the component of null ids alone is null); an empty table gives none.
    """
    described, links = linked_sets(docs, rule, id_col, text_col)
    nodes = described.filter("n > 0").groupBy("node").agg(F.min("id").alias("least"))
    nodes = nodes.join(components(links), "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = durable(nodes.groupBy("root").agg(F.min("least").alias("component_id")))
    named = durable(nodes.join(least, "root").select(F.col("node").alias("_node"), "component_id"))
    return (
        described.drop("screen")
        .join(named, F.col("node") == F.col("_node"), "left")
        .select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("id")).alias("component_id"), "text_hash")
    )


CONTRACT = Rule(words=3, num=90, den=100, longer=0.1)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of all documents over links at 0.9 on three-word shingles."""
    return cluster(table(spark, sf_dir, "documents"), CONTRACT).select("doc_id", "n_shingles", "component_id")


def one_of_each(docs: DataFrame, rule: Rule = Rule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:  # noqa: B008
    """``docs`` with one row of every component: the smallest id's (null ids last), of one id the smallest text hash's.

    Rows are told apart by id and text: a row that shares its id with another text stays unless its own text has a
    partner; of rows equal in both one stays (any: they may differ in other columns). Rows without words all stay.
    """
    described, links = linked_sets(docs, rule, id_col, text_col)
    rows = described.filter("n > 0").groupBy("node", "id", "text_hash").agg(F.count(F.lit(1)).alias("copies"))
    rows = rows.join(components(links), "node", "left").select(F.coalesce("root", "node").alias("root"), "id", "text_hash", "copies")
    rows = durable(rows)
    # only components of several rows matter; most have one
    groups = rows.groupBy("root").agg(F.min(F.struct(F.col("id").isNull(), "id", "text_hash", "copies")).alias("stays"), F.sum("copies").alias("all")).filter("all > 1")
    own = F.col("id").eqNullSafe(F.col("stays.id")) & (F.col("text_hash") == F.col("stays.text_hash"))
    grouped = rows.join(groups.select("root", "stays"), "root").withColumn("own", own)
    grouped = durable(grouped.filter("NOT own OR copies > 1").select("id", "text_hash", "own"))
    key, told = inner_names(docs, "_id", "_hash")
    keyed = lambda df: df.select(F.col("id").alias(key), F.col("text_hash").alias(told)).distinct()
    on = F.col(f"`{id_col}`").cast("bigint").eqNullSafe(F.col(key)) & (F.xxhash64(f"`{text_col}`") == F.col(told))
    kept = docs.join(keyed(grouped.filter("NOT own")), on, "left_anti")
    repeated = keyed(grouped.filter("own"))
    if repeated.isEmpty():
        return kept
    hashed = kept.withColumn(told, F.xxhash64(f"`{text_col}`"))
    single = hashed.join(repeated.withColumnRenamed(told, told + "r"), F.col(f"`{id_col}`").cast("bigint").eqNullSafe(F.col(key)) & (F.col(told) == F.col(told + "r")), "left_semi")
    return kept.join(repeated, on, "left_anti").unionByName(single.dropDuplicates([id_col, told]).drop(told))
