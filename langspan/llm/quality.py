"""Document quality by hierarchical empirical Bayes over a trained text classifier.

A bounded sample of labelled documents trains two logistic regressions (low quality, toxic) on style measures and on
the presence of words and word beginnings that chi-square picks out (beginnings tell inflected and compound words that
are each too rare to be picked). Toxic documents have a cut of their own, fitted on out-of-fold scores: neither the
document's quality nor its site's rate makes up for toxicity. The classifier's probability that a document is good is its
evidence. Sites form a tree: all, host, path (here ``source`` and ``source`` with ``lang``). A site's rate of good
documents is shrunk towards its parent's with a strength estimated by moments from the spread of the rates, so sparse
sites follow their parent. A document's posterior adds, in log odds, its evidence and what its path's rate, without
the document itself, says beyond the global rate.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.shipping import ship

from . import kernels
from .common import durable, hash48, table

#: Labelled documents that the classifier is trained on, at most (the first by hash of the id), and words per target.
LABELLED, PICKED = 20_000, 256
#: Bytes of the word beginnings that count beside whole words.
BEGINNINGS = (4, 5, 6, 7, 8)
#: Folds of the labels that the toxic cut is fitted on, and the share of their good documents that it may lose.
FOLDS, LOST = 4, 0.005
#: A host may hold most documents: site rates are spread over so many salted copies for the join.
SALTS = 64
KEEP = 0.5
STYLE = ("log_words", "word_bytes", "junk", "exclaim", "bars", "capitals", "digits", "wide", "lines", "distinct", "echo")
_CLASSES = {"junk": b"#$%&*^~", "exclaim": b"!", "bars": b"|<>{}", "capitals": bytes(range(65, 91)), "digits": b"0123456789", "wide": bytes(range(192, 256)), "lines": b"\n"}


def _measures(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Style measures of every row, and hashes of the rows' words and word beginnings with bounds."""
    rows = len(offsets) - 1
    starts, ends, bounds = kernels.words(data, offsets, kernels.NOT_LETTER)
    hashes = kernels.word_hashes(kernels.lowered(data), starts, ends)
    n = np.diff(bounds)
    size = np.maximum(1, np.diff(offsets))
    out = np.zeros((rows, len(STYLE)))
    out[:, 0] = np.log1p(n)
    lengths = np.r_[0, np.cumsum(ends - starts)]
    out[:, 1] = (lengths[bounds[1:]] - lengths[bounds[:-1]]) / np.maximum(1, n)
    for k, name in enumerate(STYLE):
        if name in _CLASSES:
            member = np.zeros(256, bool)
            member[list(_CLASSES[name])] = True
            at = np.flatnonzero(member[data])
            out[:, k] = np.diff(np.searchsorted(at, offsets)) / size
    same = np.r_[0, np.cumsum(hashes[1:] == hashes[:-1]), 0]
    for row, (a, b) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)):
        if b > a:
            out[row, 9] = len(np.unique(hashes[a:b])) / (b - a) ** 0.7
            out[row, 10] = (same[b - 1] - same[a]) / (b - a)
    return out, *_with_beginnings(kernels.lowered(data), starts, ends, hashes, bounds)


def _with_beginnings(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The word hashes with those of the words' beginnings among them, and the rows' bounds in all of them."""
    every = np.empty((len(hashes), 1 + len(BEGINNINGS)), np.uint64)
    every[:, 0] = hashes
    has = (ends - starts)[:, None] >= np.array([0, *BEGINNINGS])
    for k, n in enumerate(BEGINNINGS, 1):
        long = np.flatnonzero(has[:, k])
        every[long, k] = kernels.mix(kernels.word_hashes(data, starts[long], starts[long] + n) + np.uint64(n))
    return every[has], np.r_[0, np.cumsum(has.sum(axis=1))][bounds]


def _present(hashes: np.ndarray, bounds: np.ndarray, picked: np.ndarray) -> np.ndarray:
    """Which of the (sorted) picked words each row has."""
    out = np.zeros((len(bounds) - 1, len(picked)), np.float64)
    if len(picked) and len(hashes):
        fast = np.zeros(1 << 16, bool)
        fast[picked & np.uint64(0xFFFF)] = True
        maybe = np.flatnonzero(fast[hashes & np.uint64(0xFFFF)])
        at = np.minimum(np.searchsorted(picked, hashes[maybe]), len(picked) - 1)
        hit = picked[at] == hashes[maybe]
        out[np.searchsorted(bounds, maybe[hit], "right") - 1, at[hit]] = 1
    return out


@dataclass(frozen=True)
class Model:
    """Two logistic regressions over style measures and picked words; from ``cut`` on a text counts as toxic."""

    picked: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    low: np.ndarray
    toxic: np.ndarray
    cut: float = KEEP

    def good(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Probability that each text is neither of low quality nor toxic, and whether it is beyond the toxic cut."""
        out, beyond = np.zeros(len(column)), np.zeros(len(column), bool)
        for first, end, data, offsets in kernels.slices(column):
            style, hashes, bounds = _measures(data, offsets)
            x = np.hstack([(style - self.mean) / self.scale, _present(hashes, bounds, self.picked), np.ones((end - first, 1))])
            toxic = _logistic(x @ self.toxic)
            out[first:end] = (1 - _logistic(x @ self.low)) * (1 - toxic)
            beyond[first:end] = toxic >= self.cut
        return out, beyond


def _logistic(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


#: Rows of the training matrix that are worked on in double precision at a time.
ROWS = 2048


class _Rows:
    """The training matrix: scaled style measures, picked words as bits, an intercept; unpacked ROWS rows at a time."""

    def __init__(self, style: np.ndarray, bits: np.ndarray, words: int):
        self.style, self.bits, self.words = style.astype(np.float32), bits, words

    def __len__(self) -> int:
        return len(self.style)

    @property
    def width(self) -> int:
        return self.style.shape[1] + self.words + 1

    def blocks(self, rows: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Row numbers and the rows in double precision."""
        for k in range(0, len(rows), ROWS):
            some, width = rows[k : k + ROWS], self.style.shape[1]
            part = np.ones((len(some), self.width))
            part[:, :width] = self.style[some]
            if self.words:
                part[:, width:-1] = np.unpackbits(self.bits[some], axis=1)[:, : self.words]
            yield some, part


def _fit(x: _Rows, y: np.ndarray, ridge: float = 0.1, rounds: int = 25, rows: np.ndarray | None = None) -> np.ndarray:
    """Ridge logistic regression by Newton steps, on some rows or all; the last column is the intercept and is hardly penalised."""
    w = np.zeros(x.width)
    rows = np.arange(len(x)) if rows is None else rows
    penalty = np.full(x.width, ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        slope, curve = -penalty * w, np.diag(penalty)
        for some, part in x.blocks(rows):
            p = _logistic(part @ w)
            slope += part.T @ (y[some] - p)
            curve += (part * (p * (1 - p))[:, None]).T @ part
        step = np.linalg.solve(curve, slope)
        w = w + step * min(1.0, 5 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-5:
            break
    return w


def toxic_cut(p: np.ndarray, low: np.ndarray, toxic: np.ndarray) -> float:
    """Where toxic documents are best told from good ones by held-out scores: KEEP at most, and no more than LOST of the good are lost."""
    bad, good = np.sort(p[toxic > 0]), np.sort(p[(toxic <= 0) & (low <= 0)])
    if not len(bad) or not len(good):
        return KEEP
    cuts = np.unique(np.r_[p[p < KEEP], KEEP])[::-1]
    caught, lost = 1 - np.searchsorted(bad, cuts) / len(bad), 1 - np.searchsorted(good, cuts) / len(good)
    return float(cuts[np.argmax(np.where((lost <= LOST) | (cuts >= KEEP), caught - lost, -1.0))])


def labelled_sample(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(text, low, toxic) of at most LABELLED documents; of repeated labels the worst holds, null labels are left out."""
    flags = (
        labels.filter(F.col("doc_id").isNotNull() & F.col("quality").isNotNull() & F.col("toxic").isNotNull())
        .groupBy("doc_id")
        .agg((F.min("quality") <= 0).cast("int").alias("low"), (F.max("toxic") > 0).cast("int").alias("toxic"))
        .orderBy(hash48(F.col("doc_id").cast("string")), "doc_id")
        .limit(LABELLED)
        .withColumnRenamed("doc_id", "_labelled")
    )
    return docs.join(F.broadcast(flags), F.col(id_col) == F.col("_labelled")).select(F.col(text_col).cast("string").alias("text"), "low", "toxic")


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """The classifier; without labelled documents every text is as good as any other."""
    ship(docs.sparkSession)
    sample = durable(labelled_sample(docs, labels, id_col, text_col))

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            low, toxic = (batch.column(c).to_numpy() for c in ("low", "toxic"))
            seen, of = [], []
            for first, _, data, offsets in kernels.slices(batch.column("text")):
                _, hashes, bounds = _measures(data, offsets)
                for row, (a, b) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
                    found = np.unique(hashes[a:b])
                    seen.append(found)
                    of.append(np.full(len(found), first + row))
            if seen:
                word, at = np.unique(np.concatenate(seen), return_inverse=True)
                of = np.concatenate(of)
                counts = [np.bincount(at, weights=w, minlength=len(word)).astype(np.int64) for w in (None, low[of], toxic[of])]
                yield pa.RecordBatch.from_arrays([pa.array(word.view(np.int64)), *map(pa.array, counts)], ["word", "n", "low", "toxic"])

    total = sample.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("low"), F.lit(0)).alias("low"), F.coalesce(F.sum("toxic"), F.lit(0)).alias("toxic")).first()
    counted = sample.mapInArrow(words, "word bigint, n bigint, low bigint, toxic bigint").groupBy("word").agg(*(F.sum(c).alias(c) for c in ("n", "low", "toxic"))).filter("n >= 5")
    counted = durable(counted)
    picked: set[int] = set()
    for target in ("low", "toxic"):
        expected = F.col("n") * float(total[target]) / max(1, total["n"])
        score = F.pow(F.col(target) - expected, 2) / (expected + F.lit(0.5))
        picked |= {r["word"] for r in counted.orderBy(score.desc(), "word").limit(PICKED).select("word").collect()}
    chosen = np.sort(np.array(sorted(picked), np.int64).view(np.uint64))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            features = []
            for _, _, data, offsets in kernels.slices(batch.column("text")):
                measures, hashes, bounds = _measures(data, offsets)
                present = np.packbits(_present(hashes, bounds, chosen).astype(bool), axis=1)
                features += [a.tobytes() + b.tobytes() for a, b in zip(measures.astype(np.float32), present, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(features, pa.binary()), batch.column("low"), batch.column("toxic")], ["features", "low", "toxic"])

    # about 110 bytes for each of at most LABELLED documents, by one job for all partitions, in an order that none of them changes
    found = sorted((bytes(r["features"]), r["low"], r["toxic"]) for r in sample.mapInArrow(rows, "features binary, low int, toxic int").collect())
    width = len(STYLE)
    if not found:
        return Model(chosen, np.zeros(width), np.ones(width), np.zeros(width + len(chosen) + 1), np.zeros(width + len(chosen) + 1))
    packed = np.frombuffer(b"".join(f for f, _, _ in found), np.uint8).reshape(len(found), -1)
    low, toxic = (np.array([f[k] for f in found], float) for k in (1, 2))
    fold = np.array([zlib.crc32(f) % FOLDS for f, _, _ in found])  # equal texts share one
    del found
    style = packed[:, : 4 * width].copy().view(np.float32).astype(np.float64)
    mean, scale = style.mean(axis=0), style.std(axis=0) + 1e-6
    x = _Rows((style - mean) / scale, packed[:, 4 * width :], len(chosen))
    p = np.zeros(len(x))
    for k in range(FOLDS):
        w = _fit(x, toxic, rows=np.flatnonzero(fold != k))
        for some, part in x.blocks(np.flatnonzero(fold == k)):
            p[some] = _logistic(part @ w)
    return Model(chosen, mean, scale, _fit(x, low), _fit(x, toxic), toxic_cut(p, low, toxic))


def with_evidence(docs: DataFrame, model: Model, text_col: str) -> DataFrame:
    """``docs`` with ``evidence``, the classifier's probability, and ``_beyond``, whether they are beyond its toxic cut."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good, beyond = shared.value.good(batch.column(text_col).cast(pa.string()))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(good), pa.array(beyond)], [*batch.schema.names, "evidence", "_beyond"])

    return docs.mapInArrow(run, docs.select("*", F.lit(0.0).alias("evidence"), F.lit(False).alias("_beyond")).schema)


def _strength(rates: DataFrame, parent: Column) -> float:
    """Prior observations of a level: how much its rates spread around their parents', beyond what chance makes."""
    r = rates.filter("n > 1").agg(
        F.count(F.lit(1)).alias("k"),
        F.sum("n").alias("n"),
        F.sum(_exact(F.col("n") * F.pow(F.col("s") / F.col("n") - parent, 2))).alias("spread"),
        F.sum(_exact(parent * (1 - parent))).alias("chance"),
    ).first()
    if not r["k"] or not r["chance"]:
        return 1e6
    spread, chance = float(r["spread"]), float(r["chance"]) / r["k"]
    between = (spread - r["k"] * chance) / r["n"]
    return float(np.clip(chance / between - 1, 1.0, 1e6)) if between > 0 else 1e6


def _exact(x: Column) -> Column:
    """A number whose sum does not depend on the order of the rows, so that reruns judge alike."""
    return x.cast("decimal(28,12)")


def site_rates(evidence: DataFrame) -> tuple[DataFrame, float]:
    """(host, path, path_n, path_s, path_prior, strength) of every path, and the global rate; evidence: host, path, evidence."""
    paths = durable(evidence.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), F.sum(_exact(F.col("evidence"))).alias("s")))
    total = paths.agg(F.sum("n").alias("n"), F.sum("s").alias("s")).first()
    paths = paths.withColumn("s", F.col("s").cast("double"))
    rate = float(np.clip((float(total["s"] or 0) + 0.5) / (total["n"] + 1), 1e-6, 1 - 1e-6)) if total["n"] else 0.5
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), F.sum(_exact(F.col("s"))).cast("double").alias("s"))
    strong = _strength(hosts, F.lit(rate))
    hosts = hosts.select(F.col("host").alias("_host"), ((F.col("s") + strong * rate) / (F.col("n") + strong)).alias("host_posterior"))
    paths = paths.join(hosts, F.col("host").eqNullSafe(F.col("_host"))).drop("_host")
    strength = _strength(paths, F.col("host_posterior"))
    return paths.withColumn("strength", F.lit(strength)), rate


def _logit(p: Column) -> Column:
    held = F.greatest(F.lit(1e-6), F.least(F.lit(1 - 1e-6), p))
    return F.log(held / (1 - held))


def judge(scored: DataFrame, sites: DataFrame, rate: float) -> DataFrame:
    """``scored`` (host, path, evidence, _beyond and more) with host_posterior, path_posterior, posterior and keep."""
    salted = sites.select(*(F.col(c).alias(f"_{c}") for c in ("host", "path", "n", "s", "strength")), "host_posterior", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("_salt"))
    joined = scored.withColumn("_at", F.pmod(F.xxhash64("evidence"), F.lit(SALTS)).cast("int")).join(
        salted, F.col("host").eqNullSafe(F.col("_host")) & F.col("path").eqNullSafe(F.col("_path")) & (F.col("_at") == F.col("_salt"))
    )
    others = (F.col("_s") - F.col("evidence") + F.col("_strength") * F.col("host_posterior")) / (F.col("_n") - 1 + F.col("_strength"))
    return (
        joined.withColumn("path_posterior", others)
        .withColumn("posterior", 1 / (1 + F.exp(-(_logit(F.col("evidence")) + _logit(F.col("path_posterior")) - _logit(F.lit(rate))))))
        .withColumn("keep", (F.col("posterior") >= KEEP) & ~F.col("_beyond"))
        .drop("_beyond", "_at", "_salt", "_host", "_path", "_n", "_s", "_strength")
    )


def assess(docs: DataFrame, labels: DataFrame, host: Column, path: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, host, path, evidence, host_posterior, path_posterior, posterior, keep), one row for each row of ``docs``.

    A null text is judged as an empty one; null hosts and paths are sites of their own; repeated rows are judged alike;
    an empty table gives none.
    """
    model = train(docs, labels, id_col, text_col)
    told = docs.select(F.col(id_col).alias("doc_id"), host.cast("string").alias("host"), path.cast("string").alias("path"), F.col(text_col).cast("string").alias("text"))
    scored = durable(with_evidence(told, model, "text").drop("text"))
    sites, rate = site_rates(scored.select("host", "path", "evidence"))
    return judge(scored, sites, rate)


def drop_poor(docs: DataFrame, labels: DataFrame, host: Column, path: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without what ``assess`` would not keep; columns as they are. Texts are scored twice instead of moved."""
    model = train(docs, labels, id_col, text_col)
    names = docs.columns
    own = [f"_column_{k}" for k in range(len(names))]  # so that no name of theirs meets one of ours
    told = docs.select(*(F.col(f"`{c}`").alias(o) for c, o in zip(names, own, strict=True)), host.cast("string").alias("host"), path.cast("string").alias("path"))
    scored = with_evidence(told, model, own[names.index(text_col)])
    sites, rate = site_rates(scored.select("host", "path", "evidence"))
    return judge(scored, sites, rate).filter("keep").select(*(F.col(o).alias(c) for c, o in zip(names, own, strict=True)))


def document_sites() -> tuple[Column, Column]:
    """Host and path of the ``documents`` table: its source, and within it the language."""
    return F.col("source"), F.concat_ws("/", F.coalesce(F.col("source"), F.lit("")), F.coalesce(F.col("lang"), F.lit("")))


def url_sites(url: Column) -> tuple[Column, Column]:
    """Host and first path segment of a URL."""
    host = F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]*)", 1))
    return host, F.concat_ws("/", host, F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]*)", 1))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents judged; trained on the labels table."""
    return assess(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), *document_sites())
