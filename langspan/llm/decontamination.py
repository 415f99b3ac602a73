"""Benchmark leaks: SimHash of item-sized windows, a multi-index over Hamming blocks, exact weighted-shingle check.

Words are runs of ASCII letters, digits and non-ASCII bytes, lower-cased, so that case and punctuation do not hide a
leak. A window has as many words as the item it is held against (the whole text if that is shorter). Its SimHash sums
the signed bits of its five-word shingles. A shingle weighs ln(1 + items / items that have it), counted once over the
whole benchmark; its bits count by the square root of that, so that the angle between two sums follows their weighted
overlap. Two fingerprints within RADIUS of each other differ by at most RADIUS // 5 bits in one of five blocks, so a
table of every block value within that distance of an item's finds them all. What it finds is decided by weighted
Jaccard of the shingle multisets. Only windows that share a shingle with some item are fingerprinted: any other has
similarity 0.

Texts never move and are read once: the items, in blocks of bounded size, go to the documents, and with them a filter of
all items' shingles and the weights of those that several items have (any other weighs as one that a single item has), so
that neither fingerprints nor similarities depend on the blocks. A worker holds one block of items at a time.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.shipping import ship

from . import kernels
from .common import table

WORDS = 5
THRESHOLD = 0.8
RADIUS = 19
#: Widths of the blocks of a fingerprint.
BITS = (13, 13, 13, 13, 12)
#: Items and bytes of items in a block (about 8 KB of tables an item); more items make more blocks for every batch of texts.
ITEMS, ITEM_BYTES = 4000, 8 << 20
#: Bits of the filter over all items' shingles; where it fills up it lets more rows through, never fewer.
FILTER = 1 << 23
#: Windows fingerprinted at a time.
AT_ONCE = 4096
_SHIFTS = np.arange(64, dtype=np.uint64)


def _hashes(column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, word hashes, row bounds) of slices."""
    for first, _, data, offsets in kernels.slices(column):
        data = kernels.lowered(data)
        starts, ends, bounds = kernels.words(data, offsets, kernels.NOT_LETTER)
        yield first, kernels.word_hashes(data, starts, ends), bounds


def _signs(shingles: np.ndarray) -> np.ndarray:
    return ((shingles[:, None] >> _SHIFTS) & np.uint64(1)).astype(np.float32) * 2 - 1


def _pull(shingles: np.ndarray, weight: Weights) -> np.ndarray:
    """What each shingle adds to the sums of the bits."""
    return _signs(shingles) * np.sqrt(weight(shingles))[:, None]


def _fingerprint(sums: np.ndarray) -> np.ndarray:
    return ((np.round(sums, 6) > 0).astype(np.uint64) << _SHIFTS).sum(axis=1, dtype=np.uint64)


class Weights:
    """What shingles weigh over a whole benchmark: those that several items have are listed, all others are as rare as can be."""

    def __init__(self, items: int, shingles: np.ndarray, counts: np.ndarray):
        order = np.argsort(shingles)
        self.shingles, self.values = shingles[order], np.log1p(items / np.maximum(1, counts[order]))
        self.rare = float(np.log1p(max(1, items)))

    def __call__(self, shingles: np.ndarray) -> np.ndarray:
        if not len(self.shingles):
            return np.full(len(shingles), self.rare)
        at = np.minimum(np.searchsorted(self.shingles, shingles), len(self.shingles) - 1)
        return np.where(self.shingles[at] == shingles, self.values[at], self.rare)


def _distinct_shingles(column: pa.Array) -> Iterator[np.ndarray]:
    """The distinct shingles of each row that has WORDS words at least."""
    for _, hashes, bounds in _hashes(column):
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            if b - a >= WORDS:
                yield np.unique(kernels.shingles(hashes[a:b], WORDS))


def benchmark_weights(benchmark: DataFrame, text_col: str = "text") -> Weights:
    """Weights over all items; null texts and items under five words do not count. The driver gets the shared shingles, 16 bytes each."""
    ship(benchmark.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for own in _distinct_shingles(batch.column(0)):  # a null stands for the item itself
                yield pa.RecordBatch.from_arrays([pa.concat_arrays([pa.nulls(1, pa.int64()), pa.array(own.view(np.int64))])], ["shingle"])

    counted = benchmark.select(F.col(text_col).cast("string").alias("text")).mapInArrow(run, "shingle bigint").groupBy("shingle").agg(F.count(F.lit(1)).alias("n"))
    found = counted.filter("n > 1 OR shingle IS NULL").toArrow()
    shingles, n = found.column("shingle"), found.column("n").to_numpy()
    item = shingles.is_null().to_numpy()
    return Weights(int(n[item].sum()), shingles.drop_null().to_numpy().astype(np.int64).view(np.uint64), n[~item])


class Items:
    """A block of benchmark items, indexed: their shingles, sizes, fingerprints and the block tables, under the weights
    of the whole benchmark (of these items if none are given)."""

    def __init__(self, ids: list[int], texts: list[str], weights: Weights | None = None):
        per_item = []
        for _, hashes, bounds in _hashes(pa.array(texts, pa.string())):
            per_item += [hashes[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        keep = [i for i, h in enumerate(per_item) if len(h) >= WORDS]
        self.ids = np.array([ids[i] for i in keep], np.int64)
        self.sizes = np.array([len(per_item[i]) for i in keep], np.int64)
        runs = [kernels.shingles(per_item[i], WORDS) for i in keep]
        owner = np.repeat(np.arange(len(keep)), [len(r) for r in runs])
        flat = np.concatenate(runs) if runs else np.zeros(0, np.uint64)
        pairs = np.unique(np.rec.fromarrays([flat, owner], names="s,i"))
        self.shingles, at, count = np.unique(pairs["s"], return_index=True, return_counts=True)
        self.holders, self.first_holder = pairs["i"].astype(np.int64), np.r_[at, len(pairs)].astype(np.int64)
        self.weight = Weights(len(keep), self.shingles, count) if weights is None else weights
        self.multisets = [dict(zip(*(x.tolist() for x in np.unique(r, return_counts=True)), strict=True)) for r in runs]
        self.prints = np.array([_fingerprint(_pull(r, self.weight).sum(axis=0)[None])[0] for r in runs], np.uint64)
        self.filter = np.zeros(1 << 20, bool)
        self.filter[self.shingles & np.uint64((1 << 20) - 1)] = True
        # sizes of the items that hold a shingle, like holders
        sized = np.unique(np.rec.fromarrays([np.repeat(np.arange(len(count)), count), self.sizes[self.holders]], names="s,n"))
        self.held_sizes, self.first_size = sized["n"].astype(np.int64), np.searchsorted(sized["s"], np.arange(len(count) + 1))
        self.tables = []
        for b, width in enumerate(BITS):
            masks = np.array([sum(1 << i for i in c) for k in range(RADIUS // len(BITS) + 1) for c in combinations(range(width), k)], np.int64)
            values = (self.block(self.prints, b)[:, None] ^ masks[None, :]).ravel()
            order = np.argsort(values, kind="stable")
            self.tables.append((np.searchsorted(values[order], np.arange((1 << width) + 1)), (order // len(masks)).astype(np.int32)))

    @staticmethod
    def block(prints: np.ndarray, b: int) -> np.ndarray:
        return ((prints >> np.uint64(sum(BITS[:b]))) & np.uint64((1 << BITS[b]) - 1)).astype(np.int64)

    def find(self, shingles: np.ndarray) -> np.ndarray:
        """Index of each shingle among the items', -1 for others."""
        maybe = np.flatnonzero(self.filter[shingles & np.uint64((1 << 20) - 1)])
        out = np.full(len(shingles), -1, np.int64)
        if len(maybe) and len(self.shingles):
            at = np.minimum(np.searchsorted(self.shingles, shingles[maybe]), len(self.shingles) - 1)
            same = self.shingles[at] == shingles[maybe]
            out[maybe[same]] = at[same]
        return out

    def under(self, weights: Weights) -> Items:
        """These items with weights that came by themselves."""
        self.weight = weights
        return self

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "weight"}  # they go to the workers once, not with every block

    def within(self, prints: np.ndarray, size: int) -> Iterator[tuple[int, int, int]]:
        """(print, item, distance) of all items of ``size`` words within the radius."""
        pairs = []
        for b, (starts, members) in enumerate(self.tables):
            values = self.block(prints, b)
            counts = starts[values + 1] - starts[values]
            who = np.repeat(np.arange(len(prints)), counts)
            at = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts) + np.repeat(starts[values], counts)
            item = members[at].astype(np.int64)
            same = self.sizes[item] == size
            pairs.append(who[same] * len(self.ids) + item[same])
        found = np.unique(np.concatenate(pairs))
        who, item = found // len(self.ids), found % len(self.ids)
        distance = np.bitwise_count(prints[who] ^ self.prints[item]).astype(np.int64)
        near = distance <= RADIUS
        yield from zip(who[near].tolist(), item[near].tolist(), distance[near].tolist(), strict=True)

    def similarity(self, window: np.ndarray, item: int) -> float:
        mine, theirs = {}, self.multisets[item]
        for s in window.tolist():
            mine[s] = mine.get(s, 0) + 1
        every = np.array(list(mine.keys() | theirs.keys()), np.uint64)
        weight = dict(zip(every.tolist(), self.weight(every).tolist(), strict=True))
        both = sum(weight[s] * min(n, theirs[s]) for s, n in mine.items() if s in theirs)
        total = sum(weight[s] * n for s, n in mine.items()) + sum(weight[s] * n for s, n in theirs.items()) - both
        return round(both / total, 9) if total else 0.0

    def leaks(self, words: np.ndarray) -> list[tuple[int, int, int, int, float]]:
        """(item, first word, words, distance, similarity): of every run of overlapping windows the most similar."""
        return self.in_row(kernels.shingles(words, WORDS), len(words)) if len(words) >= WORDS else []

    def in_row(self, shingles: np.ndarray, n_words: int) -> list[tuple[int, int, int, int, float]]:
        known = self.find(shingles)
        hits = np.flatnonzero(known >= 0)
        found: dict[int, list[tuple[int, int, int, float]]] = {}
        for size, starts in self.starts(hits, known[hits], n_words):
            length = min(size, n_words) - WORDS + 1
            for part in np.split(starts, np.flatnonzero(np.diff(starts) > length) + 1):
                for a in range(0, len(part), AT_ONCE):
                    some = part[a : a + AT_ONCE]
                    region = shingles[some[0] : some[-1] + length]
                    sums = np.zeros((len(region) + 1, 64), np.float64)
                    np.cumsum(_pull(region, self.weight), axis=0, out=sums[1:])
                    at = some - some[0]
                    for w, item, distance in self.within(_fingerprint(sums[at + length] - sums[at]), size):
                        start = int(some[w])
                        alike = self.similarity(shingles[start : start + length], item)
                        if alike >= THRESHOLD:
                            found.setdefault(item, []).append((start, length + WORDS - 1, distance, alike))
        out = []
        for item, windows in found.items():
            best = None
            for w in sorted(windows):
                if best is not None and w[0] < reach:  # noqa: F821
                    best = max(best, w, key=lambda x: (x[3], -x[0]))
                else:
                    if best is not None:
                        out.append((int(self.ids[item]), *best))
                    best = w
                reach = w[0] + w[1]
            out.append((int(self.ids[item]), *best))
        return sorted(out, key=lambda x: (x[1], x[0]))

    def starts(self, hits: np.ndarray, shingles: np.ndarray, n_words: int) -> Iterator[tuple[int, np.ndarray]]:
        """(size, first words) of all windows that hold a hit which an item of that size has; in time linear in the hits
        of each size and the windows. hits: ascending places of shingles."""
        counts = self.first_size[shingles + 1] - self.first_size[shingles]
        at = np.repeat(self.first_size[shingles] - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())
        sizes, places = self.held_sizes[at], np.repeat(hits, counts)
        for size in np.unique(sizes).tolist():
            p = places[sizes == size]
            low, high = np.maximum(0, p - size + WORDS), np.minimum(p, max(0, n_words - size))
            low, high = low[low <= high], high[low <= high]
            begins = np.flatnonzero(np.r_[True, low[1:] > high[:-1] + 1])[: len(low)]
            if len(begins):
                spans = zip(low[begins].tolist(), high[np.r_[begins[1:] - 1, len(high) - 1]].tolist(), strict=True)
                yield size, np.concatenate([np.arange(a, b + 1) for a, b in spans])


def item_blocks(benchmark: DataFrame, weights: Weights, id_col: str = "item_id", text_col: str = "text") -> Iterator[Items]:
    """The items in blocks of at most ITEMS items and about ITEM_BYTES; null texts and items under five words are left out."""
    ids, texts, size = [], [], 0
    for row in benchmark.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string")).filter(F.col(text_col).isNotNull()).orderBy(id_col, text_col).toLocalIterator():
        if ids and (len(ids) >= ITEMS or size + len(row[1]) > ITEM_BYTES):
            yield Items(ids, texts, weights)
            ids, texts, size = [], [], 0
        ids.append(row[0] if row[0] is not None else -1)
        texts.append(row[1])
        size += len(row[1])
    if ids:
        yield Items(ids, texts, weights)


class Benchmark:
    """All of a benchmark on its way to the documents: a filter, weights and blocks of items as broadcasts."""

    def __init__(self, benchmark: DataFrame):
        ship(benchmark.sparkSession)
        context = benchmark.sparkSession.sparkContext
        weights, bits, self.blocks = benchmark_weights(benchmark), np.zeros(FILTER, bool), []
        for items in item_blocks(benchmark, weights):
            bits[(items.shingles & np.uint64(FILTER - 1)).astype(np.int64)] = True
            self.blocks.append(context.broadcast(items))
        self.common = context.broadcast((weights, np.packbits(bits, bitorder="little")))

    def leaks(self, column: pa.Array) -> Iterator[tuple[int, list[tuple[int, int, int, int, float]]]]:
        """(row, leaks) of a text column, each block's in turn; a block leaves memory before the next one comes."""
        weights, bits = self.common.value
        kept = []
        for first, words, bounds in _hashes(column):
            shingles = kernels.shingles(words, WORDS)
            spot = (shingles & np.uint64(FILTER - 1)).astype(np.int64)
            hits = np.flatnonzero((bits[spot >> 3] >> (spot & 7).astype(np.uint8)) & 1)
            for row in np.unique(np.searchsorted(bounds, hits, "right") - 1).tolist():
                a, b = int(bounds[row]), int(bounds[row + 1])
                if b - a >= WORDS:
                    kept.append((first + row, shingles[a : b - WORDS + 1].copy(), b - a))
        for block in self.blocks if kept else ():
            items = block.value.under(weights)
            for row, shingles, n_words in kept:
                if found := items.in_row(shingles, n_words):
                    yield row, found
            if len(self.blocks) > 1 and hasattr(block, "_value"):
                del block._value  # it is read again from the worker's disk for the next batch


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each leak: doc_id, item_id, first_word, n_words, distance, similarity; documents are read once.

    Null or empty texts have no leaks; repeated rows each report theirs; a null item id reads -1; without items or
    documents there are no rows.
    """
    told = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    items = Benchmark(benchmark)
    names = ["doc_id", "item_id", "first_word", "n_words", "distance", "similarity"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            rows = [(ids[row], *leak) for row, leaks in items.leaks(batch.column("text")) for leak in leaks]
            columns = list(zip(*rows, strict=True)) or [()] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.float64() if k == 5 else pa.int64()) for k, c in enumerate(columns)], names)

    return told.mapInArrow(run, "doc_id bigint, item_id bigint, first_word bigint, n_words bigint, distance bigint, similarity double")


def drop_leaking(docs: DataFrame, benchmark: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that hold a leak; all columns, whatever their names, and other rows as they are."""
    items, at = Benchmark(benchmark), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            keep[[row for row, _ in items.leaks(batch.column(at).cast(pa.string()))]] = False
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every leak of a benchmark item in any document."""
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
