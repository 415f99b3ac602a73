"""A stand-in for a recogniser, since neither recordings nor a trainable network are given.

Words are heard with letters changed by a seeded hash. A model looks each heard word up in its lexicons (the word itself,
or words at most one edit away, by symmetric deletes), and picks the cheapest path of words and languages. Models differ
only in their lexicons and in what a switch of language costs: one lexicon (monolingual), two and a cost fitted on texts of
one language each (bilingual without switched data), two and a cost fitted on generated samples (switched). Figures from it compare orderings,
never values, with published ones.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from langspan.functions.text import words
from langspan.operators.vocab import ranked, word_counts
from langspan.session import durable
from langspan.shipping import ship

#: ``NEVER`` is for models of one language, which have nothing to switch to.
UNKNOWN, EDIT, NEVER = -16.0, 5.0, 1e9


@dataclass
class Lexicons:
    """Words with log probabilities by language, and the deletes that lead to them. ``pooled``: one distribution for all."""

    scores: dict[str, dict[str, float]]
    deletes: dict[str, list[tuple[str, str]]] = field(default_factory=dict)

    @staticmethod
    def scores_of(rows: Sequence[tuple[str, str, int]], langs: Sequence[str], pooled: bool) -> dict[str, dict[str, float]]:
        mine = [(lang, w, n) for lang, w, n in rows if lang in langs]
        totals: dict[str, int] = {}
        pool: dict[str, int] = {}
        for lang, w, n in mine:
            totals[lang] = totals.get(lang, 0) + n
            pool[w] = pool.get(w, 0) + n
        whole = sum(totals.values())
        scores: dict[str, dict[str, float]] = {lang: {} for lang in langs}
        for lang, w, n in mine:
            scores[lang][w] = math.log(pool[w] / whole) if pooled else math.log(n / totals[lang])
        return scores

    @classmethod
    def from_counts(cls, rows: Sequence[tuple[str, str, int]], langs: Sequence[str], pooled: bool) -> Lexicons:
        out = cls(cls.scores_of(rows, langs, pooled))
        for lang, have in out.scores.items():
            for w in have:
                for d in _deletes(w):
                    out.deletes.setdefault(d, []).append((lang, w))
        return out

    def near(self, heard: str) -> dict[tuple[str, str], int]:
        """Edits of every (language, word) that a heard word may stand for."""
        near = {(lang, heard): 0 for lang, have in self.scores.items() if heard in have}
        if len(heard) > 2:
            for d in _deletes(heard):
                for lang, w in self.deletes.get(d, ()):
                    if (lang, w) not in near and abs(len(w) - len(heard)) <= 1:
                        near[lang, w] = 1
        return near

    def candidates(self, heard: str) -> list[tuple[str, str, float]]:
        """(language, word, score) of each language's best reading of a heard word."""
        return best_of(self.near(heard), self.scores)


def best_of(near: dict[tuple[str, str], int], scores: dict[str, dict[str, float]]) -> list[tuple[str, str, float]]:
    """(language, word, score) of the best of ``Lexicons.near`` in each language of ``scores``, by name."""
    best: dict[str, tuple[float, str]] = {lang: (UNKNOWN, "?") for lang in scores}
    for (lang, w), edits in near.items():
        if lang in best:
            score = scores[lang][w] - EDIT * edits
            if (score, w) > best[lang]:
                best[lang] = (score, w)
    return [(lang, w, s) for lang, (s, w) in sorted(best.items())]


def _deletes(word: str) -> set[str]:
    return {word, *(word[:k] + word[k + 1 :] for k in range(len(word)))} if len(word) <= 24 else {word}


def heard(word: str, key: object, pos: int, rate: float, seed: int) -> str:
    """A word with one letter changed, for ``rate`` of the words."""
    return _misheard(word, zlib.crc32(f"{seed}:{key}:{pos}:{word}".encode()), rate)


def heard_words(words_: Sequence[str], key: object, rate: float, seed: int) -> list[str]:
    """``heard`` for all words of a text: what their hashes share is hashed once."""
    begun, most = zlib.crc32(f"{seed}:{key}:".encode()), rate * 10_000
    hashes = [zlib.crc32(f"{i}:{w}".encode(), begun) for i, w in enumerate(words_)]
    return [w if h % 10_000 >= most else _misheard(w, h, rate) for w, h in zip(words_, hashes, strict=True)]


def _misheard(word: str, h: int, rate: float) -> str:
    if h % 10_000 >= rate * 10_000 or len(word) < 3:
        return word
    k = (h >> 16) % len(word)
    return word[:k] + "abcdefghijklmnopqrstuvwxyz"[(h >> 8) % 26] + word[k + 1 :]


def best_path(readings: list[list[tuple[str, str, float]]], switch_cost: float) -> tuple[list[str], list[str]]:
    """Words and languages of the cheapest path."""
    if not readings:
        return [], []
    cost = {lang: -s for lang, _, s in readings[0]}
    back: list[dict[str, str]] = []
    for row in readings[1:]:
        fresh, came = {}, {}
        for lang, _, s in row:
            before = min(cost, key=lambda o, lang=lang: (cost[o] + switch_cost * (o != lang), o != lang, o))
            fresh[lang], came[lang] = cost[before] + switch_cost * (before != lang) - s, before
        cost = fresh
        back.append(came)
    lang = min(cost, key=lambda o: (cost[o], o))
    path = [lang]
    for came in reversed(back):
        lang = came[lang]
        path.append(lang)
    path.reverse()
    return [next(w for name, w, _ in row if name == lang) for row, lang in zip(readings, path, strict=True)], path


@dataclass(frozen=True)
class Recogniser:
    """name, tokenizer (mono, con, agg), languages and switch cost of a model."""

    name: str
    tokenizer: str
    langs: tuple[str, ...]
    switch_cost: float = NEVER


def lexicon_rows(docs: DataFrame, size: int) -> list[tuple[str, str, int]]:
    """The most frequent words of each language: at most ``size`` for each."""
    return [tuple(r) for r in ranked(word_counts(docs), ["lang"], "piece", size).select("lang", "piece", "n").collect()]


def recognise(texts: DataFrame, models: Sequence[Recogniser], rows: Sequence[tuple[str, str, int]], key: str, text_col: str = "text", noise: float = 0.05, seed: int = 0) -> DataFrame:
    """model, tokenizer, key, ref, hyp, langs: what each model makes of each text."""
    spark = texts.sparkSession
    ship(spark)
    built = [(m, Lexicons.from_counts(rows, m.langs, m.tokenizer == "agg")) for m in models]
    shared = spark.sparkContext.broadcast(built)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[tuple[int, str], list[tuple[str, str, float]]] = {}
        for b in batches:
            out: list[tuple] = []
            for k, ws in zip(b.column("key").to_pylist(), b.column("w").to_pylist(), strict=True):
                ws = ws or []
                sound = [heard(w, k, i, noise, seed) for i, w in enumerate(ws)]
                for at, (m, lexicons) in enumerate(shared.value):
                    readings = []
                    for w in sound:
                        if (at, w) not in memo:
                            if len(memo) > 300_000:
                                memo.clear()
                            memo[at, w] = lexicons.candidates(w)
                        readings.append(memo[at, w])
                    hyp, langs = best_path(readings, m.switch_cost)
                    out.append((m.name, m.tokenizer, k, " ".join(ws), " ".join("qqunknown" if w == "?" else w for w in hyp), langs))
            kinds = [pa.string(), pa.string(), b.schema.field("key").type, pa.string(), pa.string(), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], t) for c, t in enumerate(kinds)], ["model", "tokenizer", "key", "ref", "hyp", "langs"])

    told = texts.select(F.col(key).alias("key"), words(F.col(text_col)).alias("w"))
    return told.mapInArrow(run, f"model string, tokenizer string, key {dict(told.dtypes)['key']}, ref string, hyp string, langs array<string>").withColumnRenamed("key", key)


#: Cells (text, word) of padded tables and words of texts that are worked on at a time.
CELLS, SLICE = 1 << 19, 300_000
#: Code points stand for words from here on; the surrogates are passed over.
FIRST, LAST = 256, 0x10FFFF - 0x800


def best_paths(scores: np.ndarray, lengths: np.ndarray, switch_cost: float | np.ndarray) -> np.ndarray:
    """(texts, words): the language numbers that ``best_path`` finds, for many texts at a time. scores: (texts, words,
    languages), texts by falling length and none empty, languages by name; what lies beyond a text's length is undefined.
    ``switch_cost``: one for all, or one for each text."""
    n, width, langs = scores.shape
    path = np.zeros((n, width), np.int8)
    if langs < 2 or not n:
        return path
    live = np.searchsorted(-lengths, -np.arange(width), "left")  # texts of more than k words
    came, cost, price = np.zeros((width, n, langs), np.int8), -scores[:, 0], np.broadcast_to(switch_cost, (n,))
    for k in range(1, width):
        m = live[k]
        before, fresh = cost[:m], np.empty((m, langs))
        for to in range(langs):
            least, at = before[:, to] + 0.0, np.full(m, to, np.int8)
            for o in range(langs):
                if o != to:
                    via = before[:, o] + price[:m]
                    better = via < least
                    least, at = np.where(better, via, least), np.where(better, np.int8(o), at)
            fresh[:, to], came[k, :m, to] = least - scores[:m, k, to], at
        cost[:m] = fresh
    path[np.arange(n), lengths - 1] = cost.argmin(axis=1)
    for k in range(width - 1, 0, -1):
        m = live[k]
        path[:m, k - 1] = np.take_along_axis(came[k, :m], path[:m, k, None].astype(np.int64), 1)[:, 0]
    return path


def _tables(lengths: np.ndarray) -> Iterator[np.ndarray]:
    """Numbers of the texts that have words, by falling length, as many at a time as fill CELLS."""
    order = np.argsort(-lengths, kind="stable")[: int((lengths > 0).sum())]
    while len(order):
        some, order = np.split(order, [max(1, CELLS // int(lengths[order[0]]))])
        yield some


def _padded(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray, some: np.ndarray) -> np.ndarray:
    """(texts, words) of a flat array, the last of its entries repeated beyond a text's end."""
    return flat[np.minimum(starts[some, None] + np.arange(lengths[some[0]]), len(flat) - 1)]


def _letters(numbers: np.ndarray) -> str:
    """Words by number as code points."""
    codes = numbers + FIRST
    return (codes + np.where(codes >= 0xD800, 0x800, 0)).astype("<u4").tobytes().decode("utf-32-le")


#: From so many words on, Python finds the errors of a text: Spark's edit distance costs the square of the words for each model.
LONG = 30


def distances(ref: str, hyps: Sequence[str]) -> list[int]:
    """Levenshtein distances of texts of one length from ``ref``, a column of their tables at a time: bits tell where the
    columns go up or down by one. The columns of all texts lie in one number, a zero bit between them."""
    size = len(hyps[0])
    starts = sum(1 << k * (size + 1) for k in range(len(hyps)))
    where = dict.fromkeys(ref, 0)
    for k, column in enumerate(zip(*hyps, strict=True)):
        if column.count(column[0]) == len(column):
            if column[0] in where:
                where[column[0]] |= starts << k
            continue
        for at, c in enumerate(column):
            if c in where:
                where[c] |= 1 << k + at * (size + 1)
    every = starts * ((1 << size) - 1)
    starts &= every
    up, down = every, 0
    for c in ref:
        same = where[c]
        flat = ((((same & up) + up) ^ up) | same | down) & every
        right, left = (down | every & ~(flat | up)) << 1 & every | starts, (flat & up) << 1 & every
        up, down = left | every & ~(flat | right), flat & right
    one = (1 << size) - 1
    return [len(ref) + (up >> k & one).bit_count() - (down >> k & one).bit_count() for k in range(0, len(hyps) * (size + 1), size + 1)]


#: (languages, pooled): what a model's lexicons are made of.
Kind = tuple[tuple[str, ...], bool]


class _Hearing:
    """The lexicons of several kinds of models, and the readings that a worker keeps of them from task to task.

    What a heard word may stand for is looked up once, in the lexicons of all languages, and scored once for all models whose
    vocabulary is not pooled, since a language's own scores are the same in each of these."""

    def __init__(self, rows: Sequence[tuple[str, str, int]], kinds: Sequence[Kind], noise: float, seed: int):
        self.whole, self.noise, self.seed = Lexicons.from_counts(rows, sorted({lang for langs, _ in kinds for lang in langs}), False), noise, seed
        #: Scores by language; those of all languages by themselves come first. Of each kind: its scores, its languages in them.
        self.scores, self.of = [self.whole.scores], []
        for langs, pooled in kinds:
            if pooled:
                self.scores.append(Lexicons.scores_of(rows, langs, True))
            names = sorted(self.scores[-1 if pooled else 0])
            self.of.append((len(self.scores) - 1 if pooled else 0, [names.index(lang) for lang in sorted(langs)]))
        self.memo: dict[str, list[list[tuple[str, str, float]]]] = {}

    def listen(self, keys: list, texts: list[list[str]]) -> tuple[list[str], np.ndarray]:
        """Distinct heard words, and the number among them of every word of the texts, one text after the other."""
        known: dict[str, int] = {}
        flat = [known.setdefault(w, len(known)) for k, ws in zip(keys, texts, strict=True) for w in heard_words(ws, k, self.noise, self.seed)]
        return list(known), np.array(flat, np.int64)

    def readings(self, sounds: list[str]) -> list[list[list[tuple[str, str, float]]]]:
        """Of every kind: each sound's reading in every language, by name."""
        memo, found = self.memo, []
        for w in sounds:
            got = memo.get(w)
            if got is None:
                if len(memo) > 300_000:
                    memo.clear()
                near = self.whole.near(w)
                got = memo[w] = [best_of(near, scores) for scores in self.scores]
            found.append(got)
        return [[[row[at][c] for c in columns] for row in found] for at, columns in self.of]


def _sliced(texts: list[list[str]]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of SLICE words together at most, or of one text."""
    first, total = 0, 0
    for k, ws in enumerate(texts):
        if k > first and total + len(ws) > SLICE:
            yield first, k
            first, total = k, 0
        total += len(ws)
    if first < len(texts):
        yield first, len(texts)


def error_rates(texts: DataFrame, models: Sequence[Recogniser], rows: Sequence[tuple[str, str, int]], key: str, by: Sequence[str] = (), text_col: str = "text", noise: float = 0.05, seed: int = 0) -> DataFrame:
    """by, model, tokenizer, errors, ref_words, wer: ``metrics.wer`` of what ``recognise`` gives, by model.

    Words are heard once for all models, and read once for those of the same lexicons; paths are found for many texts at a
    time. References and what models make of them leave Python as one code point a word, so that Spark has only the
    distances to find: one row for each text, no text for each model. Of texts of LONG words the errors themselves leave Python,
    found once for models that make the same of a text.
    """
    spark = texts.sparkSession
    ship(spark)
    kinds = list(dict.fromkeys((m.langs, m.tokenizer == "agg") for m in models))
    of = [kinds.index((m.langs, m.tokenizer == "agg")) for m in models]
    by_langs = [[at for at, m in enumerate(models) if len(m.langs) == n] for n in sorted({len(m.langs) for m in models})]
    shared = spark.sparkContext.broadcast(_Hearing(rows, kinds, noise, seed))

    def rate(ear: _Hearing, keys: list, ws: list[list[str]]) -> tuple[list[str], list[list[str]]]:
        sounds, flat = ear.listen(keys, ws)
        number: dict[str, int] = {}
        ref = np.array([number.setdefault(w, len(number)) for text in ws for w in text], np.int64)
        lengths = np.array([len(text) for text in ws], np.int64)
        starts = np.cumsum(lengths) - lengths
        read = []
        for found in ear.readings(sounds):
            read.append((np.array([[s for _, _, s in row] for row in found]), np.array([[number.setdefault("qqunknown" if w == "?" else w, len(number)) for _, w, _ in row] for row in found], np.int64)))
        if len(number) > LAST - FIRST:
            raise ValueError("a text has too many distinct words")
        whole = _letters(ref)
        told = [whole[a : a + n] for a, n in zip(starts.tolist(), lengths.tolist(), strict=True)]
        hyps = [[""] * len(models) for _ in ws]
        for some in _tables(lengths):
            heard_ = _padded(flat, starts, lengths, some)
            for same in by_langs:
                # the paths of all models of as many languages at once: what a step costs is hardly more for more rows
                stacked = np.stack([read[of[at]][0][heard_] for at in same], axis=1)
                paths = best_paths(stacked.reshape(-1, *stacked.shape[2:]), np.repeat(lengths[some], len(same)), np.tile([models[at].switch_cost for at in same], len(some)))
                for one, at in enumerate(same):
                    path = paths[one :: len(same)]
                    said, width = _letters(read[of[at]][1][heard_, path].ravel()), path.shape[1]
                    for row, (k, n) in enumerate(zip(some.tolist(), lengths[some].tolist(), strict=True)):
                        hyps[k][at] = said[row * width : row * width + n]
        return told, hyps

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ear = shared.value
        for b in batches:
            keys, ws = b.column("key").to_pylist(), [w or [] for w in b.column("w").to_pylist()]
            told, hyps = [], []
            for first, end in _sliced(ws):
                some = rate(ear, keys[first:end], ws[first:end])
                told += some[0]
                hyps += some[1]
            errors = [[0] * len(models) for _ in ws]
            for k, ref in enumerate(told):
                if len(ref) >= LONG:
                    apart = list(dict.fromkeys(hyps[k]))
                    known = dict(zip(apart, distances(ref, apart), strict=True))
                    errors[k], told[k], hyps[k] = [known[hyp] for hyp in hyps[k]], "", [""] * len(models)
            columns = [*(b.column(f"by{k}") for k in range(len(by))), pa.array(told, pa.string()), pa.array(map(len, ws), pa.int32()), pa.array(hyps, pa.list_(pa.string())), pa.array(errors, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays(columns, [*(f"by{k}" for k in range(len(by))), "r", "n", "h", "e"])

    asked = texts.select(*(F.col(c).alias(f"by{k}") for k, c in enumerate(by)), F.col(key).alias("key"), words(F.col(text_col)).alias("w"))
    types = dict(asked.dtypes)
    said = asked.mapInArrow(run, ", ".join([*(f"by{k} {types[f'by{k}']}" for k in range(len(by))), "r string, n int, h array<string>, e array<int>"]))
    sums = said.groupBy(*(f"by{k}" for k in range(len(by)))).agg(F.count(F.lit(1)).alias("_n"), F.sum("n").cast("bigint").alias("ref_words"), *(F.sum(F.levenshtein("r", F.get("h", F.lit(k))) + F.get("e", F.lit(k))).cast("bigint").alias(f"_e{k}") for k in range(len(models))))
    each = F.array(*(F.struct(F.lit(m.name).alias("model"), F.lit(m.tokenizer).alias("tokenizer"), F.col(f"_e{k}").alias("errors")) for k, m in enumerate(models)))
    out = sums.filter("_n > 0").select(*(F.col(f"by{k}").alias(c) for k, c in enumerate(by)), "ref_words", F.inline(each))
    return out.select(*by, "model", "tokenizer", "errors", "ref_words", F.when(F.col("ref_words") > 0, F.round(100 * F.col("errors") / F.col("ref_words"), 6)).alias("wer"))


def scored(samples: DataFrame, rows: Sequence[tuple[str, str, int]], langs: tuple[str, ...], key: str, text_col: str = "text", noise: float = 0.05, seed: int = 0) -> DataFrame:
    """n, scores of every text, made once for all rounds of ``fit_scored``: its words, and their readings' scores in each
    language (doubles, by name; none for one language, whose path is known)."""
    told = samples.select(F.col(key).alias("key"), words(F.col(text_col)).alias("w"))
    if len(langs) < 2:
        return durable(told.select(F.coalesce(F.size("w"), F.lit(0)).alias("n"), F.lit(None).cast("binary").alias("scores")))
    spark = samples.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(_Hearing(rows, [(tuple(langs), False)], noise, seed))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ear = shared.value
        for b in batches:
            ws = [w or [] for w in b.column("w").to_pylist()]
            sounds, flat = ear.listen(b.column("key").to_pylist(), ws)
            found = np.array([[s for _, _, s in row] for row in ear.readings(sounds)[0]])
            out, at = [], 0
            for text in ws:
                out.append(found[flat[at : at + len(text)]].tobytes() if text else b"")
                at += len(text)
            yield pa.RecordBatch.from_arrays([pa.array(map(len, ws), pa.int32()), pa.array(out, pa.binary())], ["n", "scores"])

    return durable(told.mapInArrow(run, "n int, scores binary"))


def fit_scored(told: DataFrame, langs: tuple[str, ...], start: float | None = None, tolerance: float = 0.01, most: int = 30) -> tuple[float, int]:
    """``fit_switch`` on what ``scored`` has made of the texts."""
    p = start or 1 - 1 / max(2, len(langs))

    def counted(switch_cost: float) -> int:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                lengths = b.column("n").to_numpy().astype(np.int64)
                flat = np.frombuffer(b"".join(b.column("scores").to_pylist()), np.float64).reshape(-1, len(langs))
                starts, moved = np.cumsum(lengths) - lengths, 0
                for some in _tables(lengths):
                    path, n = best_paths(_padded(flat, starts, lengths, some), lengths[some], switch_cost), lengths[some]
                    moved += int(((path[:, 1:] != path[:, :-1]) & (np.arange(1, path.shape[1]) < n[:, None])).sum())
                yield pa.RecordBatch.from_arrays([pa.array([moved], pa.int64())], ["s"])

        return told.mapInArrow(run, "s bigint").agg(F.sum("s")).first()[0] or 0

    n = told.agg(F.sum(F.greatest(F.col("n") - 1, F.lit(0)).cast("bigint"))).first()[0] or 0
    for k in range(1, most + 1):
        fresh = min(0.5, ((counted(cost_of(p)) if len(langs) > 1 else 0) + 0.5) / (n + 1))
        if abs(math.log(fresh / p)) < tolerance:
            return fresh, k
        p = fresh
    return p, most


def fit_switch(samples: DataFrame, rows: Sequence[tuple[str, str, int]], langs: tuple[str, ...], key: str, start: float | None = None, tolerance: float = 0.01, most: int = 30) -> tuple[float, int]:
    """Switch probability between words by hard expectation-maximisation, and the rounds until it moved by less than
    ``tolerance`` of itself. ``start`` is that of a fitted model; without it every language is as likely as any other.

    Half a switch is added to what is counted, so that texts without switches give a small probability and not zero.
    """
    return fit_scored(scored(samples, rows, langs, key), langs, start, tolerance, most)


def cost_of(p: float) -> float:
    """Cost of a switch that has probability ``p``, against staying."""
    return -math.log(p / (1 - p))


def lexicon_paths(arcs: DataFrame, key: str, langs: Sequence[str], switch_cost: float) -> DataFrame:
    """key, cost: the shortest path over explicit arcs (key, pos, lang, cost), one language at each position; a switch adds
    ``switch_cost``. A fold over the positions inside the row."""
    by_pos = arcs.groupBy(key, "pos").agg(*(F.min(F.when(F.col("lang") == lang, F.col("cost"))).alias(f"_c{k}") for k, lang in enumerate(langs)))
    listed = by_pos.groupBy(key).agg(F.sort_array(F.collect_list(F.struct("pos", F.array(*(F.coalesce(f"_c{k}", F.lit(1e18)) for k in range(len(langs)))).alias("c")))).alias("rows"))

    def step(state, row):
        return F.transform(state, lambda _, i: F.array_min(F.transform(state, lambda s, j: s + F.when(i == j, 0.0).otherwise(switch_cost))) + F.get(row["c"], i))

    start = F.array(*(F.lit(0.0) for _ in langs))
    # a path may begin in any language: the first position pays no switch
    first = F.zip_with(start, F.get("rows", 0)["c"], lambda a, b: a + b)
    return listed.select(key, F.round(F.array_min(F.aggregate(F.slice("rows", F.lit(2), F.greatest(F.size("rows") - 1, F.lit(0))), first, step)), 6).alias("cost"))
