"""Personal data by a skip-chain conditional random field over tokens with digits or @.

Fixed patterns find the base spans (emails, IP addresses, payment cards, phone numbers); they stay as they are. The
field labels the tokens of a text: a token's shape gives its own potential, tokens that follow each other share a
chain potential, and repeated or similar tokens of a document (same letters and digits, or one the end of the other)
share a skip potential. All repeats of a form are tied to one of them, a labelled one if there is any, so that a label
reaches the whole document in one step. Loopy sum-product passing gives the beliefs, and the beliefs alone decide what
is added: tokens the patterns could not take, like numbers written against each other, a number repeated without its
prefix, a key repeated without its name. Values that are named as tokens, passwords or keys are a kind of their own,
``secret``, beside the contract's four.

Potentials are trained here by pseudo-likelihood, on counts over all documents: every token given its shape, its
neighbours' labels and its repeats' labels, where labels are what the patterns say. Tokens about which the patterns say
nothing certain (in a failed match, or repeating a labelled one) are left out. A shape that was never seen has no
potential of its own: only neighbours and repeats can label it. Tokens without a digit or @ have no part in the field.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from langspan.shipping import ship

from .common import table

KINDS = ("email", "ip", "card", "phone")
LABELS = ("none", *KINDS, "secret")
#: Belief that an added span's tokens need, rounds of message passing at most, and the change that ends them.
BELIEF, ROUNDS, STILL = 0.8, 200, 1e-4
#: Edges whose messages are worked on at a time.
EDGES = 1 << 17
#: Training: strength of the normal prior of every potential; its mean is 0, but AGREE for equal labels of repeats.
PRIOR, AGREE = 0.1, 4.0
#: Training tells this many equally labelled repeats of a token from fewer, and no more.
REPEATS = 3

# fixed values: patterns of the contract
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGITS = re.compile(r"[0-9]+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")

_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_USEFUL = re.compile(r"[0-9@]")
#: A name, what assigns, and the value: what counts as a secret without the field's help.
_NAMED = re.compile(r"(?i)(?:token|secret|passw(?:or)?d|credential|auth|(?:api|access|private)[_-]?key)[\"']?[\x20\t]*[=:][\x20\t]*[\"']?([A-Za-z0-9_+/=-]{12,})")
_KEY = re.compile(r"[A-Za-z_-]{2,}[=:][\"']?(?=[^\x20])")
_LEFT, _RIGHT = "\"'<[{,;:*#$%&|", "\"'>]},;:!?.*#$%&|"
Span = tuple[int, int, str]


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


_HEX = re.compile(r"[0-9A-Fa-f]+")


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _emails(text: str) -> Iterator[Span]:
    """In linear time: only what stands before and behind each @ is looked at."""
    done = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end(), "email"
            done = m.end()
        else:
            done = at + 1
        at = text.find("@", done)


def _addresses(text: str) -> Iterator[tuple[int, int, bool]]:
    """Four digit runs with dots between, from the left of each dotted chain, and whether the parts are at most 255."""
    chain: list[tuple[int, int]] = []
    for m in _DIGITS.finditer(text):
        if chain and not (m.start() == chain[-1][1] + 1 and text[chain[-1][1]] == "."):
            chain = []
        chain.append(m.span())
        if len(chain) == 4:
            yield chain[0][0], chain[3][1], all(int(text[a:b][-4:]) <= 255 and not text[a:b].lstrip("0")[3:] for a, b in chain)
            chain = []


def base_spans(text: str) -> tuple[list[Span], dict[str, list[tuple[int, int]]]]:
    """Spans of the fixed patterns by start, and by kind the extents of matches with many digits that failed their check."""
    found, failed = list(_emails(text)), {kind: [] for kind in KINDS}
    for start, end, ok in _addresses(text):
        found.append((start, end, "ip")) if ok else failed["ip"].append((start, end))
    for m in _CARD.finditer(text):
        digits = _digits(m.group())
        found.append((*m.span(), "card")) if 12 <= len(digits) <= 19 and luhn(digits) else failed["card"].append(m.span())
    for m in _PHONE.finditer(text):
        found.append((*m.span(), "phone")) if 9 <= len(_digits(m.group())) <= 15 else failed["phone"].append(m.span())
    found.sort(key=lambda s: (s[0], KINDS.index(s[2])))
    return found, {kind: [f for f in fs if len(_digits(text[f[0] : f[1]])) >= 9] for kind, fs in failed.items()}


def tokens(text: str) -> list[tuple[int, int, int, int]]:
    """(core start, core end, start, end) of the words with a digit or @; the core lacks outer punctuation."""
    out = []
    for m in _WORD.finditer(text):
        word = m.group()
        if _USEFUL.search(word):
            a = len(word) - len(word.lstrip(_LEFT))
            b = len(word.rstrip(_RIGHT))
            if "(" not in word[a:b]:
                b = len(word[:b].rstrip(")"))
            key = _KEY.match(word[a:b])
            if key and _USEFUL.search(word[a + key.end() : b]) and "@" not in word:
                a += key.end()
            if b > a:
                out.append((m.start() + a, m.start() + b, m.start(), m.end()))
    return out


def secrets(text: str) -> list[Span]:
    """Named values with letters and digits."""
    found = ((*m.span(1), "secret") for m in _NAMED.finditer(text))
    return [s for s in found if _USEFUL.search(text[s[0] : s[1]]) and any(c.isalpha() for c in text[s[0] : s[1]])]


SHAPES = 18


def shape(core: str, before: str, after: str, assigned: bool = False) -> int:
    """Yes-or-no facts about a token and its neighbours (empty if they do not touch it) as bits."""
    digits = _digits(core)
    mixed = len(core) >= 12 and core.isascii() and any(c.isalpha() for c in core) and all(c.isalnum() or c in "_+/=-" for c in core)
    plain = len(digits) == len(core)
    quad = core.split(".")
    facts = (
        "@" in core and bool(_DOMAIN.search(core.partition("@")[2])),
        any(c.isalpha() for c in core),
        12 <= len(digits) <= 19 and luhn(digits),
        12 <= len(digits) <= 19,
        len(quad) == 4 and all(q.isdigit() and len(q) <= 3 and int(q) <= 255 for q in quad),
        core.startswith("+"),
        core.startswith("(") and core.endswith(")") and 2 <= len(digits) <= 5,
        "-" in core and 6 <= len(digits) <= 11,
        plain and len(digits) <= 4,
        9 <= len(digits) <= 15 and core.startswith("+"),
        before.startswith("+"),
        before.startswith("("),
        after.startswith("("),
        mixed and 4 * len(digits) >= len(core),
        mixed and bool(_HEX.fullmatch(core)),
        mixed and core.upper() == core,
        assigned,
        plain and 5 <= len(digits) <= 11,
    )
    return sum(1 << k for k, fact in enumerate(facts) if fact)


@dataclass
class Document:
    """The tokens of a text with labels by the patterns, shapes, and the edges between them.

    A label of 0 is none, or not known where ``unsure``.
    """

    spans: list[Span]
    secrets: list[Span]
    places: list[tuple[int, int, int, int]]
    shapes: list[int]
    labels: list[int]
    unsure: list[bool]
    chain: list[tuple[int, int]]
    skip: list[tuple[int, int]]


class _Extents:
    """Disjoint ascending extents that can be asked for what they overlap."""

    def __init__(self, extents: list[tuple]):
        self.all = sorted(extents)
        self.ends = [e[1] for e in self.all]

    def over(self, a: int, b: int) -> int:
        """The largest overlap with [a, b)."""
        best, k = 0, bisect_right(self.ends, a)
        while k < len(self.all) and self.all[k][0] < b:
            best = max(best, min(b, self.all[k][1]) - max(a, self.all[k][0]))
            k += 1
        return best


def _forms(core: str) -> set[str]:
    """What a token's repeats share with it: its letters and digits, and for a number its last seven."""
    same = re.sub(r"[^0-9A-Za-z@]", "", core).lower()
    if len(same) < 6:
        return set()
    return {same, "…" + same[-7:]} if same.isdigit() else {same}


def analyse(text: str) -> Document:
    spans, failed = base_spans(text)
    named = secrets(text)
    places = tokens(text)
    cores = [text[a:b] for a, b, _, _ in places]
    touch = [k > 0 and not text[places[k - 1][3] : places[k][2]].strip("\x20\t") for k in range(len(places))]
    by_kind = [_Extents([s for s in spans + named if s[2] == kind]) for kind in LABELS[1:]]
    lost = {kind: _Extents(f) for kind, f in failed.items()}
    shapes, labels, unsure = [], [], []
    for k, (a, b, _, _) in enumerate(places):
        before, after = cores[k - 1] if touch[k] else "", cores[k + 1] if k + 1 < len(cores) and touch[k + 1] else ""
        shapes.append(shape(cores[k], before, after, text[max(0, a - 6) : a].rstrip("\x20\t\"'")[-1:] in ("=", ":")))
        shares = [e.over(a, b) for e in by_kind]
        labels.append(1 + shares.index(max(shares)) if any(shares) else 0)
        # of a number that no card can be the patterns say enough, whatever match it is in
        no_card = not shapes[-1] & 0b100 and shapes[-1] & 0b1000
        unsure.append(not labels[-1] and not no_card and any(e.over(a, b) for e in lost.values()))
    hubs: dict[str, int] = {}
    for k, core in enumerate(cores):
        for form in _forms(core):
            if form not in hubs or (labels[k] and not labels[hubs[form]]):
                hubs[form] = k
    skip = set()
    for k, core in enumerate(cores):
        for form in _forms(core):
            if (hub := hubs[form]) != k:
                skip.add((min(hub, k), max(hub, k)))
                unsure[k] = unsure[k] or (not labels[k] and labels[hub] > 0)
    chain = [(k - 1, k) for k in range(1, len(places)) if touch[k]]
    return Document(spans, named, places, shapes, labels, unsure, chain, sorted(skip))


@dataclass(frozen=True)
class Field:
    """Trained log potentials: by shape bit and label (last row: intercept), between neighbours, between repeats; and the
    shapes that were seen (None: any counts as seen)."""

    shape: np.ndarray
    chain: np.ndarray
    skip: np.ndarray
    seen: frozenset[int] | None = None

    def own(self, shapes: list[int]) -> np.ndarray:
        bits = (np.array(shapes, np.int64).reshape(-1, 1) >> np.arange(SHAPES)) & 1
        out = np.hstack([bits, np.ones((len(shapes), 1))]) @ self.shape
        if self.seen is not None:
            out[[s not in self.seen for s in shapes]] = 0.0
        return out

    def beliefs(self, doc: Document) -> np.ndarray:
        """Label probabilities of the tokens by loopy message passing."""
        own = self.own(doc.shapes)
        held = np.array(doc.labels)
        own[held > 0] = -30.0
        own[held > 0, held[held > 0]] = 0.0
        own -= own.max(axis=1, keepdims=True)
        edges = np.array(doc.chain + doc.skip, np.int64).reshape(-1, 2)
        total = own
        if len(edges):
            source, target = np.r_[edges[:, 0], edges[:, 1]], np.r_[edges[:, 1], edges[:, 0]]
            back = np.r_[np.arange(len(edges)) + len(edges), np.arange(len(edges))]
            pairs = np.stack([self.chain, self.skip, self.chain.T, self.skip.T])
            kind = np.r_[np.zeros(len(doc.chain), np.int64), np.ones(len(doc.skip), np.int64)]
            kind = np.r_[kind, kind + 2]
            sent = np.zeros((len(source), len(LABELS)))
            for _ in range(ROUNDS):
                total = own.copy()
                np.add.at(total, target, sent)
                fresh = np.empty_like(sent)
                for k in range(0, len(source), EDGES):
                    some = slice(k, k + EDGES)
                    joint = (total[source[some]] - sent[back[some]])[:, :, None] + pairs[kind[some]]
                    top = joint.max(axis=1)
                    fresh[some] = top + np.log(np.exp(joint - top[:, None, :]).sum(axis=1))
                fresh -= fresh.max(axis=1, keepdims=True)
                moved = np.abs(fresh - sent).max()
                sent = 0.5 * (fresh + sent)
                if moved < STILL:
                    break
            total = own.copy()
            np.add.at(total, target, sent)
        total = np.exp(total - total.max(axis=1, keepdims=True))
        return total / total.sum(axis=1, keepdims=True)

    def added(self, doc: Document) -> list[Span]:
        """What the beliefs add: tokens, and runs of tokens for phone numbers, that no pattern took."""
        if not doc.places or all(doc.labels):
            return []
        belief = self.beliefs(doc)
        best = belief.argmax(axis=1)
        free = (best > 0) & (np.array(doc.labels) == 0) & (belief.max(axis=1) >= BELIEF)
        touching, base = {b for _, b in doc.chain}, [_Extents([s for s in doc.spans + doc.secrets if s[2] == kind]) for kind in LABELS[1:]]
        out, k = [], 0
        while k < len(best):
            end = k + 1
            if free[k]:
                kind = LABELS[best[k]]
                # "+" begins a number: its shape's fifth fact
                while kind == "phone" and end < len(best) and end in touching and free[end] and best[end] == best[k] and not doc.shapes[end] >> 5 & 1:
                    end += 1
                start, stop = doc.places[k][0], doc.places[end - 1][1]
                if not any(e.over(start, stop) for e in base):
                    out.append((start, stop, kind))
            k = end
        return out


def _texts(batch: pa.RecordBatch) -> Iterator[tuple[int, str]]:
    """Rows of a batch that have a digit or @."""
    column = batch.column("text").fill_null("") if batch.column("text").null_count else batch.column("text")
    for row in np.flatnonzero(pc.match_substring_regex(column, "[0-9@]").to_numpy(zero_copy_only=False)).tolist():
        yield row, column[row].as_py()


def _around(doc: Document) -> Iterator[tuple[int, ...]]:
    """What pseudo-likelihood needs of each certain token: label, shape, label before and after (-1: none that counts), and
    how many repeats have each label."""
    before, after = [-1] * len(doc.places), [-1] * len(doc.places)
    repeats = [[0] * len(LABELS) for _ in doc.places]
    for a, b in doc.chain:
        if not doc.unsure[a]:
            before[b] = doc.labels[a]
        if not doc.unsure[b]:
            after[a] = doc.labels[b]
    for pair in doc.skip:
        for a, b in (pair, pair[::-1]):
            if not doc.unsure[a]:
                repeats[b][doc.labels[a]] = min(REPEATS, repeats[b][doc.labels[a]] + 1)
    for k, label in enumerate(doc.labels):
        if not doc.unsure[k]:
            yield label, doc.shapes[k], before[k], after[k], *repeats[k]


_AROUND = ["label", "shape", "before", "after", *(f"r{k}" for k in range(len(LABELS)))]


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What the potentials are trained on, with counts."""
    for batch in batches:
        counts: Counter = Counter()
        for _, text in _texts(batch):
            counts.update(_around(analyse(text)))
        keys = list(counts)
        columns = [pa.array([k[c] for k in keys], pa.int64()) for c in range(len(_AROUND))]
        yield pa.RecordBatch.from_arrays([*columns, pa.array(list(counts.values()), pa.int64())], [*_AROUND, "n"])


def _told(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Field:
    """Potentials from all documents. The driver gets one row for each distinct surrounding of a token, which shapes and
    labels bound, not the documents."""
    schema = ", ".join(f"{c} bigint" for c in (*_AROUND, "n"))
    rows = _told(docs, id_col, text_col).mapInArrow(_counted, schema).groupBy(*_AROUND).agg(F.sum("n").alias("n")).collect()
    return fitted(sorted(tuple(r) for r in rows))


def fitted(rows: list[tuple[int, ...]]) -> Field:
    """Maximum of the penalised pseudo-likelihood by Newton steps; rows: like ``_around``'s, and a count."""
    size = len(LABELS)
    n_shape, n_chain = (SHAPES + 1) * size, size * size
    upper = np.triu_indices(size)
    place = np.zeros((size, size), np.int64)
    place[upper] = place.T[upper] = np.arange(len(upper[0]))
    width = n_shape + n_chain + len(upper[0])
    mean = np.zeros(width)
    mean[n_shape + n_chain + np.diag(place)] = AGREE
    at = mean.copy()
    table = np.array(rows, np.int64).reshape(-1, len(_AROUND) + 1)

    def features(part: np.ndarray) -> np.ndarray:
        """(rows, label, parameter)"""
        out = np.zeros((len(part), size, width))
        bits = np.hstack([(part[:, 1:2] >> np.arange(SHAPES)) & 1, np.ones((len(part), 1), np.int64)])
        for y in range(size):
            out[:, y, y:n_shape:size] = bits
            for column, cell in ((2, lambda other, y=y: other * size + y), (3, lambda other, y=y: y * size + other)):
                has = np.flatnonzero(part[:, column] >= 0)
                out[has, y, n_shape + cell(part[has, column])] += 1
            for other in range(size):
                out[:, y, n_shape + n_chain + place[other, y]] += part[:, 4 + other]
        return out

    for _ in range(50 if len(table) else 0):
        slope, curve = -PRIOR * (at - mean), np.eye(width) * PRIOR
        for k in range(0, len(table), 1024):
            part = table[k : k + 1024]
            f, n = features(part), part[:, -1].astype(float)
            z = f @ at
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            expected = np.einsum("ry,ryp->rp", p, f)
            slope += n @ (f[np.arange(len(part)), part[:, 0]] - expected)
            weighted = (f * np.sqrt(p * n[:, None])[:, :, None]).reshape(-1, width)
            curve += weighted.T @ weighted - (expected * n[:, None]).T @ expected
        step = np.linalg.solve(curve, slope)
        at = at + step * min(1.0, 2 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-6:
            break
    shape_, chain = at[:n_shape].reshape(SHAPES + 1, size), at[n_shape : n_shape + n_chain].reshape(size, size)
    return Field(shape_, chain, at[n_shape + n_chain :][place], frozenset(table[:, 1].tolist()))


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def find_personal_data(docs: DataFrame, field: Field | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row: doc_id, base counts n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added, secrets, n_found.

    Spans are ``kind:start:end`` in code points, end exclusive, by start and kind; ``secrets`` has those of the kind
    ``secret``, ``spans`` the others; n_found counts both, n_added what the field added to either. Null texts are empty;
    repeated rows are found alike; an empty table gives none. Without a field one is trained on ``docs``.
    """
    told = _told(docs, id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(field or train(docs, id_col, text_col))
    nothing = hashlib.sha256(b"").hexdigest()
    names = [*(f"n_{k}" for k in KINDS), "n_added", "n_found"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.num_rows
            counts = np.zeros((len(names), rows), np.int64)
            digests, spans, hidden = [nothing] * rows, [""] * rows, [""] * rows
            for row, text in _texts(batch):
                doc = analyse(text)
                more = shared.value.added(doc)
                for _, _, kind in doc.spans:
                    counts[KINDS.index(kind), row] += 1
                every = sorted(doc.spans + doc.secrets + more, key=lambda s: (s[0], LABELS.index(s[2])))
                counts[-2:, row] = len(more), len(every)
                digests[row] = hashlib.sha256(_joined(doc.spans).encode()).hexdigest()
                spans[row] = _joined([s for s in every if s[2] != "secret"])
                hidden[row] = _joined([s for s in every if s[2] == "secret"])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(pa.array, counts), *map(pa.array, (digests, spans, hidden))], ["doc_id", *names, "base_sha256", "spans", "secrets"])

    kind = dict(docs.dtypes)[id_col]
    schema = f"doc_id {kind}, {', '.join(f'{n} bigint' for n in names)}, base_sha256 string, spans string, secrets string"
    return told.mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data in every document."""
    return find_personal_data(table(spark, sf_dir, "documents"))
