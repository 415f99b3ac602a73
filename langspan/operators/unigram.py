"""Unigram-LM subword tokenizers: seeds, expectation-maximisation with pruning, and Viterbi encoding.

All languages train together, keyed by language: word counts are made once, and each round is one pass over them with
the current pieces (at most ``seed`` a language, hence broadcast).
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from langspan.functions.text import words
from langspan.operators.vocab import UNK, ranked, word_counts
from langspan.session import durable
from langspan.shipping import ship

MARK = "▁"
FLOOR = -20.0
#: Cells (text, letter) of tables that are worked on at a time, and the most rows of a table in a task of Python.
CELLS, ROWS = 1 << 18, 100_000


def viterbi(word: str, pieces: dict[str, float], longest: int, without: str | None = None) -> tuple[float, list[str]]:
    """Best log probability and pieces of a word; a letter that no piece covers costs FLOOR and reads as unknown."""
    best: list[tuple[float, int, str]] = [(0.0, 0, "")] + [(-math.inf, 0, "")] * len(word)
    for end in range(1, len(word) + 1):
        for start in range(max(0, end - longest), end):
            piece = word[start:end]
            p = pieces.get(piece) if piece != without else None
            if p is None:
                if end - start > 1:
                    continue
                p, piece = FLOOR, UNK
            if best[start][0] + p > best[end][0]:
                best[end] = (best[start][0] + p, start, piece)
    out, at = [], len(word)
    while at:
        out.append(best[at][2])
        at = best[at][1]
    return best[-1][0], out[::-1]


class Spans:
    """Where pieces lie in many texts at a time. A prefix of a piece has a number (0 the empty one); (prefix, letter) leads to the
    longer prefix."""

    def __init__(self, pieces: dict[str, float], longest: int):
        self.names, self.longest = list(pieces), longest
        number, own, keys = {"": 0}, [-1], []
        for at, piece in enumerate(self.names):
            for k in range(1, len(piece) + 1):
                if piece[:k] not in number:
                    keys.append((number[piece[: k - 1]] << 32 | ord(piece[k - 1]), len(number)))
                    number[piece[:k]] = len(number)
                    own.append(-1)
            own[number[piece]] = at
        self.table, self.own = np.array(sorted(keys) or [(-1, 0)], np.int64), np.array(own)
        self.score = np.array([*pieces.values(), -math.inf])  # the last is of no piece

    def found(self, texts: list[str], width: int) -> tuple[np.ndarray, np.ndarray]:
        """(length, text, start): log probabilities of the pieces there, and their numbers; -inf and -1 for none."""
        letters = np.frombuffer("".join(t.ljust(width, "\0") for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(texts), width)
        which = np.full((self.longest + 1, len(texts), width), -1, np.int32)
        at, alive = np.zeros((len(texts), width), np.int64), np.ones((len(texts), width), bool)
        for n in range(1, min(self.longest, width) + 1):
            at, alive = at[:, : width - n + 1], alive[:, : width - n + 1]
            row, column = np.nonzero(alive)
            asked = at[row, column] << 32 | letters[row, column + n - 1]
            spot = np.minimum(np.searchsorted(self.table[:, 0], asked), len(self.table) - 1)
            hit = self.table[spot, 0] == asked
            at, alive = np.zeros_like(at), np.zeros_like(alive)
            at[row[hit], column[hit]], alive[row[hit], column[hit]] = self.table[spot[hit], 1], True
            which[n, :, : width - n + 1][alive] = self.own[at[alive]]
        return self.score[which], which


def _tables(lengths: np.ndarray) -> Iterator[np.ndarray]:
    """Numbers of all texts, by falling length, as many at a time as fill CELLS."""
    order = np.argsort(-lengths, kind="stable")
    while len(order):
        some, order = np.split(order, [max(1, CELLS // (int(lengths[order[0]]) + 1))])
        yield some


def piece_ends(texts: Sequence[str], pieces: dict[str, float], longest: int) -> Iterator[tuple[list[int], np.ndarray]]:
    """Where the pieces that ``viterbi`` finds end, for many texts at a time: numbers of texts and a row for each, true at k
    where a piece ends behind k letters. Every text comes once; sums are made in the order of ``viterbi``."""
    lengths, spans = np.array([len(t) for t in texts], np.int64), Spans(pieces, longest)
    for some in _tables(lengths):
        likely, _ = spans.found([texts[k] for k in some], int(lengths[some[0]]))
        out = np.zeros((len(some), likely.shape[2] + 1), bool)
        for rows, ends, _ in _cut(likely, lengths[some]):
            out[rows, ends] = True
        yield some.tolist(), out


def _live(lengths: np.ndarray, width: int) -> np.ndarray:
    """How many texts, by falling length, have k letters at least."""
    return np.searchsorted(-lengths, -np.arange(width + 1), "right")


def _cut(likely: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The pieces of the likeliest cut of texts by falling length, from the last to the first: numbers of texts, and where a
    piece of each ends, and its length. A letter that no piece covers costs FLOOR."""
    longest, (count, width) = likely.shape[0] - 1, likely.shape[1:]
    live, first = _live(lengths, width), np.where(likely[1] == -math.inf, FLOOR, likely[1])
    best, step = np.full((count, width + 1), -math.inf), np.ones((count, width + 1), np.int64)
    best[:, 0] = 0.0
    for end in range(1, width + 1):
        m = live[end]
        for n in range(min(longest, end), 0, -1):
            found = best[:m, end - n] + (likely[n] if n > 1 else first)[:m, end - n]
            better = found > best[:m, end]
            best[:m, end], step[:m, end] = np.where(better, found, best[:m, end]), np.where(better, n, step[:m, end])
    where = lengths.copy()
    rows = np.flatnonzero(where > 0)
    while len(rows):
        ends = where[rows]
        yield rows, ends, step[rows, ends]
        where[rows] -= step[rows, ends]
        rows = rows[where[rows] > 0]


def _shares(likely: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, Iterator[tuple[int, np.ndarray]]]:
    """``expected`` of texts by falling length: log likelihoods over all cuts, and for each length of pieces the shares of
    (text, start); sums are made in the order of ``expected``."""
    longest, (count, width) = likely.shape[0] - 1, likely.shape[1:]
    live, rows = _live(lengths, width), np.arange(count)
    fore, back = np.full((count, width + 1), -math.inf), np.full((count, width + 1), -math.inf)
    fore[:, 0], back[rows, lengths] = 0.0, 0.0
    for end in range(1, width + 1):
        m = live[end]
        for n in range(min(longest, end), 0, -1):
            fore[:m, end] = np.logaddexp(fore[:m, end], fore[:m, end - n] + likely[n, :m, end - n])
    for start in range(width - 1, -1, -1):
        m = live[start + 1]
        for n in range(1, min(longest, width - start) + 1):
            back[:m, start] = np.logaddexp(back[:m, start], back[:m, start + n] + likely[n, :m, start])
    total = fore[rows, lengths]
    whole = np.where(total > -math.inf, total, math.inf)[:, None]  # no share of what has no cut

    def shares() -> Iterator[tuple[int, np.ndarray]]:
        for n in range(1, min(longest, width) + 1):
            yield n, np.exp(np.minimum(0.0, fore[:, : width - n + 1] + likely[n, :, : width - n + 1] + back[:, n:] - whole))

    return total, shares()


def dealt_rows(table: DataFrame) -> DataFrame:
    """A kept table over all cores at least: small in bytes it comes in few parts, but its rows cost Python much time."""
    parts = max(table.sparkSession.sparkContext.defaultParallelism, -(-table.count() // ROWS))
    return durable(table.repartition(parts)) if table.rdd.getNumPartitions() < parts else table


def _add(a: float, b: float) -> float:
    if a == -math.inf:
        return b
    top = max(a, b)
    return top + math.log1p(math.exp(min(a, b) - top))


def expected(word: str, pieces: dict[str, float], longest: int) -> tuple[float, dict[str, float]]:
    """Log likelihood of a word over all its segmentations, and the expected count of every piece."""
    n = len(word)
    fore, back = [0.0] + [-math.inf] * n, [-math.inf] * n + [0.0]
    spans = [(s, e, pieces[word[s:e]]) for e in range(1, n + 1) for s in range(max(0, e - longest), e) if word[s:e] in pieces]
    for s, e, p in spans:
        fore[e] = _add(fore[e], fore[s] + p)
    for s, e, p in sorted(spans, key=lambda x: -x[0]):
        back[s] = _add(back[s], back[e] + p)
    counts: dict[str, float] = {}
    if fore[n] > -math.inf:
        for s, e, p in spans:
            if (share := math.exp(min(0.0, fore[s] + p + back[e] - fore[n]))) > 1e-9:
                counts[word[s:e]] = counts.get(word[s:e], 0.0) + share
    return fore[n], counts


def seeds(counts: DataFrame, size: int, longest: int) -> DataFrame:
    """lang, piece, n: all letters, and the substrings with the largest count times length."""
    word = F.concat(F.lit(MARK), F.col("piece"))
    starts = counts.select("lang", "n", word.alias("w")).withColumn("s", F.explode(F.sequence(F.lit(1), F.length("w"))))
    subs = starts.withColumn("l", F.explode(F.sequence(F.lit(1), F.least(F.lit(longest), F.length("w") - F.col("s") + 1))))
    subs = subs.groupBy("lang", F.substr("w", F.col("s"), F.col("l")).alias("piece")).agg(F.sum("n").alias("n"))
    letters = subs.filter(F.length("piece") == 1)
    long = ranked(subs.filter((F.length("piece") > 1) & (F.col("n") > 1)).withColumn("_n", F.col("n")).withColumn("n", F.col("n") * F.length("piece")), ["lang"], "piece", size)
    return letters.select("lang", "piece", "n").union(long.select("lang", "piece", F.col("_n").alias("n")))


def pair_counts(docs: DataFrame, keys: Sequence[str] = ("lang",)) -> DataFrame:
    """Counts of adjacent words as ``first▁second`` (a lone word: itself): what pieces that cross words are learnt from."""
    told = docs.select(*keys, words(F.col("text")).alias("_w"))
    after = F.slice("_w", F.lit(2), F.greatest(F.size("_w") - 1, F.lit(0)))
    joined = F.filter(F.zip_with("_w", after, lambda a, b: F.concat(a, F.lit(MARK), b)), lambda p: p.isNotNull())
    each = told.select(*keys, F.explode(F.when(F.size("_w") > 1, joined).otherwise(F.col("_w"))).alias("piece"))
    return each.groupBy(*keys, "piece").agg(F.count(F.lit(1)).alias("n"))


def expected_of(words_: Sequence[str], counts: np.ndarray, spans: Spans, used: bool) -> tuple[float, np.ndarray, np.ndarray]:
    """Of words that come so often: the log likelihood of those that the pieces can make, the ``expected`` count of every
    piece by number, and with ``used`` how often each is in the likeliest cuts."""
    lengths, size = np.array([len(w) for w in words_], np.int64), len(spans.names)
    likelihood, share, cut = 0.0, np.zeros(size), np.zeros(size)
    for some in _tables(lengths):
        likely, which = spans.found([words_[k] for k in some], int(lengths[some[0]]))
        n_of, long_ = counts[some].astype(np.float64), lengths[some]
        total, shares = _shares(likely, long_)
        made = total > -math.inf
        likelihood += float((n_of[made] * total[made]).sum())
        for n, part in shares:
            row, column = np.nonzero((part > 1e-9) & (which[n, :, : part.shape[1]] >= 0))
            share += np.bincount(which[n, row, column], weights=part[row, column] * n_of[row], minlength=size)
        for rows, ends, n in _cut(likely, long_) if used else ():
            number = which[n, rows, ends - n]
            own = made[rows] & (number >= 0)
            cut += np.bincount(number[own], weights=n_of[rows[own]], minlength=size)
    return likelihood, share, cut


def _pass(counts: DataFrame, pieces: dict[str, dict[str, float]], longest: int, losses: bool) -> dict[str, dict[str, tuple[float, float]]]:
    """lang -> piece -> (expected count, likelihood lost without it); and under "" the log likelihood.

    Tasks work on many words at a time. What one use of a piece loses without it is the same in every word: it is found once,
    on the driver, which holds the pieces, for those that are used."""
    spark = counts.sparkSession
    shared = spark.sparkContext.broadcast(pieces)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans: dict[str, Spans] = {}
        total: dict[tuple[str, str], list[float]] = {}
        for b in batches:
            langs, n = b.column("lang").to_pylist(), b.column("n").to_numpy()
            marked = [MARK + w for w in b.column("piece").to_pylist()]
            by: dict[str, list[int]] = {}
            for k, lang in enumerate(langs):
                by.setdefault(lang, []).append(k)
            for lang, rows in by.items():
                if lang not in spans:
                    spans[lang] = Spans(shared.value.get(lang, {}), longest)
                likelihood, share, cut = expected_of([marked[k] for k in rows], n[rows], spans[lang], losses)
                total.setdefault((lang, ""), [0.0, 0.0])[0] += likelihood
                for at in np.flatnonzero((share > 0) | (cut > 0)).tolist():
                    sums = total.setdefault((lang, spans[lang].names[at]), [0.0, 0.0])
                    sums[0] += float(share[at])
                    sums[1] += float(cut[at])
        keys = list(total)
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.string()), *(pa.array([total[k][c] for k in keys], pa.float64()) for c in (0, 1))], ["lang", "piece", "e", "used"])

    sums = counts.mapInArrow(run, "lang string, piece string, e double, used double").groupBy("lang", "piece").agg(F.round(F.sum("e"), 6).alias("e"), F.sum("used").alias("used"))
    out: dict[str, dict[str, tuple[float, float]]] = {}
    for r in sums.collect():
        lang, piece, have, lost = r["lang"], r["piece"], pieces.get(r["lang"], {}), 0.0
        if r["used"] and len(piece) > 1:
            lost = r["used"] * (have[piece] - viterbi(piece, have, longest, without=piece)[0])
        out.setdefault(lang, {})[piece] = (r["e"], round(lost, 6))
    return out


def train_unigram(docs: DataFrame, size: int = 1024, seed_size: int = 3000, longest: int = 8, shrink: float = 0.6, rounds: int = 2, min_count: int = 2, log: list | None = None, across: bool = False) -> DataFrame:
    """lang, local_id, piece, score: ``size`` ids for each language, 0 the unknown piece; by score, then piece.

    Words rarer than ``min_count`` are left out of training. ``log`` collects (lang, pieces, log likelihood) of each pass.
    A language with fewer seeds than ids keeps what it has. Letters are never pruned for longer pieces, but where they alone
    are more than the ids, the rarest go (and read as unknown), so that training ends on any alphabet. ``across``: pieces may
    cross words, learnt from adjacent pairs of them.
    """
    spark = docs.sparkSession
    ship(spark)
    counts = dealt_rows(durable((pair_counts if across else word_counts)(docs).filter(F.col("n") >= min_count)))
    pieces: dict[str, dict[str, float]] = {}
    for r in seeds(counts, seed_size, longest).collect():
        pieces.setdefault(r["lang"], {})[r["piece"]] = float(r["n"])
    for lang, have in pieces.items():
        letters = sorted((p for p in have if len(p) == 1), key=lambda p: (p != MARK, -have[p], p))
        for p in letters[size - 1 :]:
            del have[p]
    pieces = {lang: _normal(p) for lang, p in pieces.items()}
    while True:
        for k in range(rounds):
            found = _pass(counts, pieces, longest, losses=k == rounds - 1)
            if log is not None:
                log += [(lang, len(pieces[lang]), f.get("", (0.0, 0.0))[0]) for lang, f in sorted(found.items())]
            fresh = {}
            for lang, have in pieces.items():
                seen = found.get(lang, {})
                # a piece that no word uses now stays, with next to nothing, until its turn to be pruned
                fresh[lang] = _normal({p: max(seen.get(p, (0.0, 0.0))[0], 1e-3) for p in have})
            if k < rounds - 1:
                pieces = fresh
        if all(len(p) <= size - 1 for p in fresh.values()):
            break
        pieces = {}
        for lang, have in fresh.items():
            room = max(size - 1, int(len(have) * shrink))
            letters = [p for p in have if len(p) == 1]
            others = sorted((p for p in have if len(p) > 1), key=lambda p: (-found[lang].get(p, (0.0, 0.0))[1], -have[p], p))[: max(0, room - len(letters))]
            pieces[lang] = _normal({p: math.exp(have[p]) for p in letters + others})
    rows = [(lang, 0, UNK, 0.0) for lang in sorted(fresh)]
    for lang in sorted(fresh):
        order = sorted(fresh[lang].items(), key=lambda x: (-round(x[1], 9), x[0]))[: size - 1]
        rows += [(lang, k, p, round(s, 9)) for k, (p, s) in enumerate(order, 1)]
    return spark.createDataFrame(rows, "lang string, local_id int, piece string, score double")


def _normal(weights: dict[str, float]) -> dict[str, float]:
    total = sum(weights.values())
    return {p: math.log(w / total) for p, w in weights.items() if w > 0}


def encode_unigram(texts: DataFrame, tokenizers: DataFrame, key: str, offsets: dict[str, int], lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """key, lang, token_ids, pieces: Viterbi segmentation by the language's own tokenizer, ids shifted into its range."""
    spark = texts.sparkSession
    ship(spark)
    models: dict[str, tuple[dict[str, float], dict[str, int]]] = {}
    for r in tokenizers.collect():
        scores, ids = models.setdefault(r["lang"], ({}, {}))
        ids[r["piece"]] = r["local_id"] + offsets[r["lang"]]
        if r["piece"] != UNK:
            scores[r["piece"]] = r["score"]
    shared = spark.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[tuple[str, str], list[str]] = {}
        for b in batches:
            ids, pieces = [], []
            for lang, ws in zip(b.column("lang").to_pylist(), b.column("w").to_pylist(), strict=True):
                scores, known = shared.value.get(lang, ({}, {}))
                longest = max(map(len, scores), default=1)
                row: list[str] = []
                for w in ws or []:
                    if (lang, w) not in memo:
                        if len(memo) > 200_000:
                            memo.clear()
                        memo[lang, w] = viterbi(MARK + w, scores, longest)[1]
                    row += memo[lang, w]
                pieces.append(row)
                ids.append([known.get(p, known.get(UNK)) for p in row])
            yield pa.RecordBatch.from_arrays([b.column("key"), b.column("lang"), pa.array(ids, pa.list_(pa.int32())), pa.array(pieces, pa.list_(pa.string()))], ["key", "lang", "token_ids", "pieces"])

    told = texts.select(F.col(key).alias("key"), F.col(lang_col).alias("lang"), words(F.col(text_col)).alias("w"))
    return told.mapInArrow(run, f"key {dict(told.dtypes)['key']}, lang string, token_ids array<int>, pieces array<string>").withColumnRenamed("key", key)


def mixed_path(text_words: list[str], models: dict[str, tuple[dict[str, float], int]], switch_cost: float) -> list[tuple[str, list[str]]]:
    """(language, pieces) of every word: the cheapest path through all languages' segmentations, switching between words only."""
    langs = sorted(models)
    cost = {lang: 0.0 for lang in langs}
    steps: list[dict[str, tuple[str, list[str]]]] = []
    for w in text_words:
        here, fresh = {}, {}
        for lang in langs:
            score, pieces = viterbi(MARK + w, *models[lang])
            before = min(langs, key=lambda o, lang=lang: (cost[o] + switch_cost * (o != lang), o != lang, o))
            fresh[lang] = cost[before] + switch_cost * (before != lang) - score
            here[lang] = (before, pieces)
        cost = fresh
        steps.append(here)
    out: list[tuple[str, list[str]]] = []
    lang = min(langs, key=lambda o: (cost[o], o)) if steps else ""
    for here in reversed(steps):
        before, pieces = here[lang]
        out.append((lang, pieces))
        lang = before
    return out[::-1]


def decode_mixed(texts: DataFrame, tokenizers: DataFrame, key: str, offsets: dict[str, int], switch_cost: float = 4.0, text_col: str = "text") -> DataFrame:
    """key, token_ids of texts of unknown language: every id tells its language."""
    spark = texts.sparkSession
    ship(spark)
    scores: dict[str, dict[str, float]] = {}
    ids: dict[str, dict[str, int]] = {}
    for r in tokenizers.collect():
        ids.setdefault(r["lang"], {})[r["piece"]] = r["local_id"] + offsets[r["lang"]]
        if r["piece"] != UNK:
            scores.setdefault(r["lang"], {})[r["piece"]] = r["score"]
    shared = spark.sparkContext.broadcast(({lang: (s, max(map(len, s), default=1)) for lang, s in scores.items()}, ids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models, known = shared.value
        for b in batches:
            rows = [[known[lang].get(p, known[lang][UNK]) for lang, pieces in mixed_path(ws or [], models, switch_cost) for p in pieces] for ws in b.column("w").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(rows, pa.list_(pa.int32()))], ["key", "token_ids"])

    told = texts.select(F.col(key).alias("key"), words(F.col(text_col)).alias("w"))
    return told.mapInArrow(run, f"key {dict(told.dtypes)['key']}, token_ids array<int>").withColumnRenamed("key", key)


def straddles(ends: Sequence[int], pieces: Sequence[str]) -> int:
    """How many of the places ``ends`` (letters from the start) lie inside a piece; an unknown piece is one letter."""
    starts, at = {0}, 0
    for p in pieces:
        at += 1 if p == UNK else len(p)
        starts.add(at)
    return sum(e not in starts for e in ends)


def encode_switched(samples: DataFrame, tokenizers: DataFrame, pooled: str | None = None) -> DataFrame:
    """sample_id, n_tokens, n_switches, n_straddled of samples (sample_id, segments: slot, lang, text) as subwords.

    Without ``pooled`` every segment goes by its own language's tokenizer; with it the whole sample goes by the tokenizer of
    that name. A switch is straddled where one piece holds letters of both sides. Segments without words are passed over;
    null segments give zeros.
    """
    spark = samples.sparkSession
    ship(spark)
    models: dict[str, dict[str, float]] = {}
    for r in tokenizers.filter(F.col("piece") != UNK).collect():
        models.setdefault(r["lang"], {})[r["piece"]] = r["score"]
    shared = spark.sparkContext.broadcast({lang: (have, max(map(len, have), default=1)) for lang, have in models.items()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none: tuple[dict[str, float], int] = ({}, 1)
        for b in batches:
            asked: dict[str | None, list[tuple[int, str]]] = {}
            switches: list[list[int]] = []
            for k, segments in enumerate(b.column("segments").to_pylist()):
                parts = [(s["lang"], "".join(MARK + w for w in s["w"])) for s in segments or [] if s["w"]]
                ends, at = [], 0
                for (lang, text), (after, _) in zip(parts, parts[1:]):
                    at += len(text)
                    if lang != after:
                        ends.append(at)
                switches.append(ends)
                for lang, text in parts if pooled is None else [(pooled, "".join(text for _, text in parts))]:
                    asked.setdefault(lang, []).append((k, text))
            n_tokens, n_inside = np.zeros(len(b), np.int64), np.zeros(len(b), np.int64)
            for lang, texts in asked.items():
                for some, cut in piece_ends([text for _, text in texts], *shared.value.get(lang, none)):
                    for k, row in zip((texts[i][0] for i in some), cut, strict=True):
                        n_tokens[k] += row.sum()
                        if pooled is not None:
                            n_inside[k] = len(switches[k]) - row[switches[k]].sum()
            told = list(zip(n_tokens.tolist(), map(len, switches), n_inside.tolist(), strict=True))
            columns = [pa.array([t[c] for t in told], pa.int64()) for c in range(3)]
            yield pa.RecordBatch.from_arrays([b.column("sample_id"), *columns], ["sample_id", "n_tokens", "n_switches", "n_straddled"])

    ordered = F.transform(F.sort_array("segments"), lambda s: F.struct(s["lang"].alias("lang"), words(s["text"]).alias("w")))
    kind = dict(samples.dtypes)["sample_id"]
    return samples.select("sample_id", ordered.alias("segments")).mapInArrow(run, f"sample_id {kind}, n_tokens bigint, n_switches bigint, n_straddled bigint")
