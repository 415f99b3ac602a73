"""Document fingerprints by locally consistent parsing.

A text is cut into phrases, the row of phrase names is cut into phrases again, and so on to one name for all of it. Cuts
come from deterministic coin tossing: a name's label is the lowest bit in which it differs from the name before it, and
that bit's value; four rounds leave six labels, neighbours always differ, and a phrase begins at every local maximum.
Runs of one name are joined first. A cut thus depends on a few names around it, never on the offset: equal substrings
have equal phrases, but for a few at their ends, on every level.

The fingerprint is the root's name and a sketch of the multiset of phrase names from level 2 up (one-permutation minima,
128 bins of one byte). The share of equal bins estimates the Jaccard similarity of the multisets.
"""

from __future__ import annotations

import hashlib
import json
from collections import Counter
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.shipping import ship

from .common import hash48, table
from .kernels import _BASE, _INVERSE, mix

U = np.uint64
BINS = 128
#: First level whose phrases are sketched; texts under SHORT code points are sketched from level 1.
LEVEL, SHORT = 2, 64
#: Code points and rows parsed together, at most (one row at least). A row's number and bin have 21 bits in ``_sketch``.
AT_ONCE, ROWS = 1 << 17, 1 << 12
#: Bytes of text that a range of ids should hold, and ranges at most (further data makes them larger; rows stream through).
RANGE_BYTES, RANGES = 32 << 20, 20_000
_LOWEST = np.array([8] + [(k & -k).bit_length() - 1 for k in range(1, 256)], np.uint8)
_tables: list[np.ndarray] = [np.ones(1, U), np.ones(1, U)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_tables[0]) < n:
        for k, base in enumerate((_BASE, _INVERSE)):
            t = np.full(max(n, 2 * AT_ONCE), U(base))
            t[0] = U(1)
            _tables[k] = np.multiply.accumulate(t)
    return _tables[0], _tables[1]


def _labels(names: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Coin tossing: labels 0 to 5, different from the neighbours' wherever the names are. first: where rows begin."""
    differ = np.zeros_like(names)
    differ[1:] = names[1:] ^ names[:-1]
    differ[first] = U(1)
    bit = np.bitwise_count((differ & (~differ + U(1))) - U(1))
    label = (2 * bit + ((names >> bit.astype(U)) & U(1)).astype(np.uint8)).astype(np.uint8)
    for _ in range(3):
        differ = np.zeros_like(label)
        differ[1:] = label[1:] ^ label[:-1]
        differ[first] = 1
        bit = _LOWEST[differ]
        label = 2 * bit + ((label >> bit) & 1)
    return label


def parse(names: np.ndarray, bounds: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Levels 1, 2, ...: phrase names, row bounds and which rows these are. Rows must not be empty; one that has come
    down to one name has no further level, so that its names don't depend on the rows beside it."""
    level, rows = 0, np.arange(len(bounds) - 1)
    while len(rows):
        level += 1
        # runs
        begin = np.ones(len(names), bool)
        np.not_equal(names[1:], names[:-1], out=begin[1:])
        begin[bounds[:-1]] = True
        at = np.flatnonzero(begin)
        length = np.diff(np.r_[at, len(names)])
        names = names[at]
        long = length > 1
        names[long] = mix(names[long] * U(_BASE) + length[long].astype(U))
        bounds = np.searchsorted(at, bounds)
        # cuts
        first = bounds[:-1]
        label = _labels(names, first)
        cut = np.zeros(len(names), bool)
        cut[1:-1] = (label[1:-1] > label[:-2]) & (label[1:-1] > label[2:])
        cut[bounds[1:] - 1] = False
        cut[first] = True
        second = first[first + 1 < bounds[1:]] + 1
        cut[second] = False
        at = np.flatnonzero(cut)
        # names
        powers, inverses = _powers(len(names) + 1)
        sums = np.zeros(len(names) + 1, U)
        np.cumsum(mix(names + U(level)) * powers[: len(names)], out=sums[1:])
        names = mix((sums[np.r_[at[1:], len(names)]] - sums[at]) * inverses[at] + U(level))
        bounds = np.searchsorted(at, bounds)
        yield names, bounds, rows
        sizes = np.diff(bounds)
        going = sizes > 1
        names, rows = names[np.repeat(going, sizes)], rows[going]
        bounds = np.r_[0, np.cumsum(sizes[going])]


def _sketch(rows: int, of: np.ndarray, names: np.ndarray) -> np.ndarray:
    """(rows, BINS) bytes: of each bin of a row's names the smallest, empty bins like the next full one. The second,
    third, ... occurrence of a name counts as a name of its own."""
    order = np.lexsort((names, of))
    names, of = names[order], of[order]
    fresh = np.flatnonzero(np.r_[True, (names[1:] != names[:-1]) | (of[1:] != of[:-1])])
    names = mix(names + (np.arange(len(names)) - np.repeat(fresh, np.diff(np.r_[fresh, len(names)]))).astype(U) * U(_BASE))
    packed = np.sort((of.astype(U) * U(BINS) + (names >> U(57))) << U(43) | ((names >> U(14)) & U((1 << 43) - 1)))
    key = (packed >> U(43)).astype(np.int64)
    least = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)
    out = np.zeros(rows * BINS, np.uint8)
    full = np.zeros(rows * BINS, bool)
    out[key[least]] = mix(packed[least] & U((1 << 43) - 1)) & U(0xFF)
    full[key[least]] = True
    out, full = out.reshape(rows, BINS), full.reshape(rows, BINS)
    places = np.where(full, np.arange(BINS), 2 * BINS)
    twice = np.hstack([places, np.where(full, np.arange(BINS) + BINS, 2 * BINS)])
    following = np.minimum.accumulate(twice[:, ::-1], axis=1)[:, ::-1][:, :BINS]
    return np.where(following < 2 * BINS, np.take_along_axis(out, np.where(following < 2 * BINS, following % BINS, 0), axis=1) + np.where(full, 0, following).astype(np.uint8), 0).astype(np.uint8)


def fingerprints(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Root names and sketches of the texts, ROWS of them at a time; an empty text has root 0 and an empty sketch."""
    if len(texts) > ROWS:
        parts = [fingerprints(texts[k : k + ROWS]) for k in range(0, len(texts), ROWS)]
        return np.concatenate([r for r, _ in parts]), np.concatenate([s for _, s in parts])
    roots, sketches = np.zeros(len(texts), U), np.zeros((len(texts), BINS), np.uint8)
    some = [k for k, t in enumerate(texts) if t]
    if some:
        names = np.frombuffer("".join(texts[k] for k in some).encode("utf-32-le", "surrogatepass"), np.uint32).astype(U)
        sizes = np.array([len(texts[k]) for k in some])
        bounds = np.r_[0, np.cumsum(sizes)]
        low, last = sizes < SHORT, np.zeros(len(some), U)
        of, kept = [], []
        for level, (names, bounds, rows) in enumerate(parse(names, bounds), 1):
            owner = np.repeat(rows, np.diff(bounds))
            keep = low[owner] if level < LEVEL else slice(None)
            of.append(owner[keep])
            kept.append(names[keep])
            done = np.diff(bounds) == 1
            last[rows[done]] = names[bounds[:-1][done]]
        roots[some] = last
        sketches[some] = _sketch(len(some), np.concatenate([*of, np.arange(len(some))]), np.concatenate([*kept, last]))
    return roots, sketches


def likeness(roots_a, sketches_a, roots_b, sketches_b) -> np.ndarray:
    """Estimated similarity, 0 to 1; 1 for equal roots, 0 between an empty and another text."""
    same = (sketches_a == sketches_b).mean(axis=1)
    out = np.clip((same - 1 / 256) / (1 - 1 / 256), 0, 1)
    out[(roots_a == 0) != (roots_b == 0)] = 0.0
    out[roots_a == roots_b] = 1.0
    return out


def rendered(root: int, sketch: np.ndarray) -> str:
    return f"{int(root):016x}{sketch.tobytes().hex()}"


def edited(text: str, following: str) -> str:
    """The last quarter replaced by as much of the beginning of the following text."""
    n = len(text) // 4
    return text[: len(text) - n] + following[:n]


_OUT = "n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple[object, str | None]]]:
    """Stretches of (id, text) in order; the last of a stretch is only the next of the one before."""
    part, rows, size, closed = None, [], 0, False
    for batch in batches:
        for p, guest, key, text in zip(*(batch.column(c).to_pylist() for c in ("part", "guest", "doc_id", "text")), strict=True):
            if p != part:
                part, rows, size, closed = p, [], 0, False
            if closed or (guest and not rows):
                continue
            rows.append((key, text or ""))
            size += len(text or "")
            closed = bool(guest)
            if len(rows) > 1 and (closed or size >= AT_ONCE or len(rows) > ROWS // 2):
                yield rows
                rows, size = rows[-1:], len(rows[-1][1])


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows in _neighbours(batches):
        texts = [t for _, t in rows]
        own = texts[:-1]
        changed = [edited(a, b) for a, b in zip(own, texts[1:], strict=True)]
        roots, sketches = fingerprints(texts + changed)
        n = len(own)
        r, s, cr, cs = roots[:n], sketches[:n], roots[n + 1 :], sketches[n + 1 :]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([k for k, _ in rows[:-1]], pa.int64()),
                pa.array([len(t) for t in own], pa.int64()),
                pa.array([hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in changed]),
                pa.array([rendered(a, b) for a, b in zip(r, s, strict=True)]),
                pa.array([rendered(a, b) for a, b in zip(cr, cs, strict=True)]),
                pa.array(likeness(r, s, cr, cs)),
                pa.array(likeness(r, s, roots[1 : n + 1], sketches[1 : n + 1])),
            ],
            ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
        )


def fingerprint_texts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with ``fingerprint`` (replacing a column of this name); nothing is shuffled. Null texts count as empty."""
    ship(docs.sparkSession)
    names = [c for c in docs.columns if c.lower() != "fingerprint"]
    docs = docs.select(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, out, group, size = [t or "" for t in batch.column(text_col).to_pylist()], [], [], 0
            for k, t in enumerate(texts):
                group.append(t)
                size += len(t)
                if size >= AT_ONCE or len(group) >= ROWS or k == len(texts) - 1:
                    out += [rendered(*x) for x in zip(*fingerprints(group), strict=True)]
                    group, size = [], 0
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], [*names, "fingerprint"])

    return docs.mapInArrow(run, docs.select("*", F.lit("").alias("fingerprint")).schema)


def _array(values: list, kind: str) -> Column:
    """A literal array; one call to the JVM however many values there are."""
    return F.from_json(F.lit(json.dumps(values)), f"array<{kind}>")


def _below(key: Column, cuts: list[int]) -> Column:
    """How many of the ascending cuts are below the key: a search in two steps over literal arrays."""
    if not cuts:
        return F.lit(0)
    step = max(1, int(len(cuts) ** 0.5))
    groups = [cuts[k : k + step] for k in range(0, len(cuts), step)]
    below = lambda values: F.size(F.filter(values, lambda c: c < key))
    group = below(_array([g[-1] for g in groups], "bigint"))
    inside = below(F.element_at(_array(groups, "array<bigint>"), F.least(group, F.lit(len(groups) - 1)) + 1))
    return F.when(group < len(groups), group * step + inside).otherwise(len(cuts)).cast("int")


def _ranged(told: DataFrame, parts: int) -> tuple[DataFrame, int]:
    """``told`` with ``_key``, ``_hash`` (order of rows of one key) and ``_range``, which ascends with both; and their number.

    Cuts are quantiles of the ids. An id that holds several of them is dealt to as many ranges by the hash of its texts.
    """
    key = F.coalesce(F.col("doc_id"), F.lit(-(1 << 63)).cast("bigint"))
    found = told.select(F.percentile_approx(key, [k / parts for k in range(1, parts)], 20 * parts).alias("cuts")).first()["cuts"] if parts > 1 else []
    held = Counter(found or [])
    cuts = sorted(held)
    spread = [held[c] if held[c] > 1 else 0 for c in cuts]
    firsts = list(accumulate((1 + n for n in spread), initial=0))
    keyed = told.withColumn("_key", key).withColumn("_hash", hash48(F.coalesce("text", F.lit(""))))
    keyed = keyed.withColumn("_range", _below(F.col("_key"), cuts))
    if any(spread):
        many = F.element_at(_array([*spread, 0], "int"), F.col("_range") + 1)
        hot = (many > 0) & (F.col("_key") == F.element_at(_array([*cuts, 0], "bigint"), F.col("_range") + 1))
        inside = F.when(hot, 1 + F.floor(F.col("_hash") / float(1 << 48) * many)).otherwise(0)
        keyed = keyed.withColumn("_range", (F.element_at(_array(firsts, "int"), F.col("_range") + 1) + inside).cast("int"))
    return keyed, firsts[-1] + 1


def compare_in_order(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", range_bytes: int = RANGE_BYTES) -> DataFrame:
    """doc_id with fingerprints of each text and its edited text, and their likeness, also to the next text by id.

    Texts move once, to id ranges of about ``range_bytes``; a range's first document also visits the range before it (the
    first of all: the last range). Null ids come first and null texts are empty; rows that share an id follow by the MD5
    of their text, so that an id with very many rows is spread over ranges (rows equal in both stream through one task);
    a single row is its own next; an empty table gives none.
    """
    spark = docs.sparkSession
    ship(spark)
    told = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    size = told.select(F.sum(F.octet_length("text").cast("bigint") + 16)).first()[0] or 0
    ranged, parts = _ranged(told, min(RANGES, max(2, -(-size // range_bytes), spark.sparkContext.defaultParallelism)))
    firsts = {r["_range"]: (r["f"]["_key"], r["f"]["_hash"]) for r in ranged.groupBy("_range").agg(F.min(F.struct("_key", "_hash")).alias("f")).collect()}
    full = sorted(firsts)
    before = {p: full[k - 1] for k, p in enumerate(full)}
    at = F.col("_range") + 1
    first_key, first_hash = (F.element_at(_array([firsts.get(p, (0, -1))[k] for p in range(parts)], "bigint"), at) for k in (0, 1))
    visit = F.element_at(_array([before.get(p, -1) for p in range(parts)], "int"), at)
    home = F.struct(F.col("_range").alias("part"), F.lit(0).alias("guest"))
    away = F.struct(visit.alias("part"), F.lit(1).alias("guest"))
    is_first = (F.col("_key") == first_key) & (F.col("_hash") == first_hash)
    dealt = ranged.select("doc_id", "text", "_key", "_hash", F.inline(F.when(is_first, F.array(home, away)).otherwise(F.array(home))))
    ordered = dealt.repartitionById(parts, F.col("part")).sortWithinPartitions("part", "guest", "_key", "_hash", "text").select("part", "guest", "doc_id", "text")
    return ordered.mapInArrow(_compared, f"doc_id bigint, {_OUT}")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of all documents and of their edited texts."""
    return compare_in_order(table(spark, sf_dir, "documents"))
