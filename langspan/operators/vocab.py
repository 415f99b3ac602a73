"""Language-partitioned vocabularies: private id ranges, tokenizers, encoding and decoding, and the baselines beside them."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.functions.text import words

UNK = "<unk>"
BLOCK = 1024
#: Word counts are ranked in so many parts before the parts' heads are ranked together.
RANK_PARTS = 64
#: Vocabularies of so many ids become constants of a plan; each language's pieces are spread over so many small maps.
MOST_IDS, BOOK_SLOTS = 1 << 16, BLOCK


@dataclass(frozen=True)
class RangeVocab:
    """Disjoint contiguous id ranges, one for each language; ids from ``total`` on (the blank) belong to none."""

    entries: tuple[tuple[str, int, int], ...]

    def __post_init__(self):
        if len({lang for lang, _, _ in self.entries}) < len(self.entries):
            raise ValueError("a language has two ranges")
        end = 0
        for lang, offset, size in sorted(self.entries, key=lambda e: e[1]):
            if size <= 0 or offset < end:
                raise ValueError(f"the range of {lang} is empty or overlaps")
            end = offset + size

    @classmethod
    def allocate(cls, sizes: Iterable[tuple[str, int]]) -> RangeVocab:
        entries, offset = [], 0
        for lang, size in sizes:
            entries.append((lang, offset, size))
            offset += size
        return cls(tuple(entries))

    @property
    def langs(self) -> tuple[str, ...]:
        return tuple(e[0] for e in self.entries)

    @property
    def total(self) -> int:
        return max((o + s for _, o, s in self.entries), default=0)

    def range(self, lang: str) -> tuple[int, int]:
        for name, offset, size in self.entries:
            if name == lang:
                return offset, size
        raise KeyError(lang)

    def extend(self, lang: str, size: int) -> RangeVocab:
        """One more language behind the others; their ids stay."""
        return RangeVocab((*self.entries, (lang, self.total, size)))

    def drop(self, lang: str, repack: bool = False) -> tuple[RangeVocab, list[tuple[int, int, int]]]:
        """Without a language; its ids stay a hole or are closed up. Also (first id, end, shift) of the ids that move."""
        self.range(lang)
        kept = [e for e in self.entries if e[0] != lang]
        if not repack:
            return RangeVocab(tuple(kept)), []
        packed = RangeVocab.allocate((n, s) for n, _, s in kept)
        moves = [(o, o + s, new[1] - o) for (_, o, s), new in zip(kept, packed.entries, strict=True) if new[1] != o]
        return packed, moves

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(list(self.entries), "lang string, offset int, size int")

    # columns

    def lang_of(self, token: Column) -> Column:
        """Language of an id, null outside all ranges; a chain of comparisons, no join."""
        out = None
        for lang, offset, size in self.entries:
            hit = token.between(offset, offset + size - 1)
            out = F.when(hit, lang) if out is None else out.when(hit, lang)
        return F.lit(None).cast("string") if out is None else out

    def offset_of(self, lang: Column) -> Column:
        out = None
        for name, offset, _ in self.entries:
            out = F.when(lang == name, offset) if out is None else out.when(lang == name, offset)
        return F.lit(None).cast("int") if out is None else out

    def lang_predicate(self, token: Column, langs: Sequence[str]) -> Column:
        """The ids of some languages as intervals, which reach the scan's statistics."""
        out = F.lit(False)
        for lang in langs:
            offset, size = self.range(lang)
            out = out | token.between(offset, offset + size - 1)
        return out

    def sql_case(self, token: str) -> str:
        return "CASE " + " ".join(f"WHEN {token} BETWEEN {o} AND {o + s - 1} THEN '{lang}'" for lang, o, s in self.entries) + " END"


def ranges_by_size(sizes: DataFrame, key: str, size: str) -> DataFrame:
    """(key, offset, size) of ranges allocated in key order, as a query; one row for each language."""
    order = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select(key, F.coalesce(F.sum(size).over(order), F.lit(0)).cast("bigint").alias("offset"), F.col(size).cast("bigint").alias("size"))


def ranked(counts: DataFrame, group: list[str], piece: str, size: int) -> DataFrame:
    """The ``size`` most frequent pieces of each group with ``local_id`` from 1 (by count, then piece).

    Heads of hash parts are ranked first, so that no task sorts all words of a language.
    """
    part = F.pmod(F.xxhash64(piece), F.lit(RANK_PARTS))
    order = [F.col("n").desc(), F.col(piece)]
    heads = counts.withColumn("_part", part).withColumn("_k", F.row_number().over(Window.partitionBy(*group, "_part").orderBy(*order))).filter(F.col("_k") <= size)
    by_group = Window.partitionBy(*group) if group else Window.partitionBy(F.lit(0))
    return heads.withColumn("local_id", F.row_number().over(by_group.orderBy(*order))).filter(F.col("local_id") <= size).drop("_part", "_k")


def word_counts(docs: DataFrame, keys: Sequence[str] = ("lang",)) -> DataFrame:
    return docs.select(*keys, F.explode(words(F.col("text"))).alias("piece")).groupBy(*keys, "piece").agg(F.count(F.lit(1)).alias("n"))


def train_word(docs: DataFrame, size: int = BLOCK) -> DataFrame:
    """lang, local_id, piece, n: each language's most frequent words; id 0 is left to the unknown word."""
    return ranked(word_counts(docs), ["lang"], "piece", size - 1).select("lang", F.col("local_id").cast("int").alias("local_id"), "piece", "n")


def train_pooled(docs: DataFrame, size: int = 2 * BLOCK) -> DataFrame:
    """Baseline: one vocabulary over all languages together (local_id, piece, n); pieces lose their language."""
    return ranked(word_counts(docs, ()), [], "piece", size - 1).select(F.col("local_id").cast("int").alias("local_id"), "piece", "n")


def train_char(docs: DataFrame, size: int = 64) -> DataFrame:
    """The smallest tokenizer: letters."""
    letters = docs.select("lang", F.explode(words(F.col("text"))).alias("w")).select("lang", F.explode(F.split("w", "")).alias("piece")).filter("piece <> ''")
    return ranked(letters.groupBy("lang", "piece").agg(F.count(F.lit(1)).alias("n")), ["lang"], "piece", size - 1).select("lang", F.col("local_id").cast("int").alias("local_id"), "piece", "n")


def union_vocab(tokenizers: DataFrame) -> DataFrame:
    """Baseline: equal pieces share one id (token_id, piece, langs, n_langs); where n_langs > 1 the language is lost."""
    merged = tokenizers.groupBy("piece").agg(F.sort_array(F.collect_set("lang")).alias("langs"))
    return merged.withColumn("token_id", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("piece")) - 1).select("token_id", "piece", "langs", F.size("langs").alias("n_langs"))


def tokens_long(texts: DataFrame, tokenizers: DataFrame, vocab: RangeVocab, key: str, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """key, pos, token_id, lang: every word by its own language's tokenizer, shifted into the language's range.

    Unknown words get their language's id 0, so that even they keep their language. The vocabulary is bounded by its
    ranges (a thousand rows a language), which is why it is broadcast.
    """
    each = texts.select(key, F.col(lang_col).alias("lang"), F.posexplode(words(F.col(text_col))).alias("pos", "piece"))
    known = tokenizers.select(F.col("lang").alias("_lang"), F.col("piece").alias("_piece"), "local_id")
    joined = each.join(F.broadcast(known), (F.col("lang") == F.col("_lang")) & (F.col("piece") == F.col("_piece")), "left")
    return joined.select(key, "pos", (F.coalesce("local_id", F.lit(0)) + vocab.offset_of(F.col("lang"))).cast("int").alias("token_id"), "lang")


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _checked(vocab: RangeVocab) -> None:
    if vocab.total > MOST_IDS:
        raise ValueError(f"{vocab.total} ids are more than the {MOST_IDS} of a constant: use tokens_long and decode_long, which join")


def _books(tokenizers: DataFrame, vocab: RangeVocab) -> dict[str, Column]:
    """For each language a constant array of small maps (piece to token id), a piece's map chosen by its hash.

    Spark reads a map from front to back, so one map of a thousand pieces would cost hundreds of comparisons a word. The
    vocabulary is collected; its ranges bound it.
    """
    _checked(vocab)
    rows = tokenizers.filter(F.col("lang").isin(*vocab.langs)).groupBy("lang", "piece").agg(F.min("local_id").alias("id")).withColumn("slot", _slot(F.col("piece")))
    maps: dict[str, list[list[str]]] = {lang: [[] for _ in range(BOOK_SLOTS)] for lang in vocab.langs}
    for r in sorted(rows.collect()):
        maps[r["lang"]][r["slot"]].append(f"{_quoted(r['piece'])}, {r['id'] + vocab.range(r['lang'])[0]}")
    one = lambda entries: f"map({', '.join(entries)})" if entries else "cast(map() AS map<string, int>)"
    return {lang: F.expr(f"array({', '.join(map(one, slots))})") for lang, slots in maps.items()}


def _slot(piece: Column) -> Column:
    return F.pmod(F.xxhash64(piece), F.lit(BOOK_SLOTS)).cast("int")


def ids_in_row(text: Column, lang: Column, books: dict[str, Column], vocab: RangeVocab) -> Column:
    """The ids of a text's words by its language's tokenizer (its id 0 for unknown words); null for other languages."""

    def found(name: str) -> Column:
        unknown = F.lit(vocab.range(name)[0])
        return F.transform(words(text), lambda w: F.coalesce(F.element_at(F.get(books[name], _slot(w)), w), unknown))

    out = F.lit(None).cast("array<int>")
    for name in books:
        out = F.when(lang == name, found(name)).otherwise(out)
    return out


def encode(texts: DataFrame, tokenizers: DataFrame, vocab: RangeVocab, key: str, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """key, lang, token_ids: one row for each row with at least one word and a language of the vocabulary.

    Words are looked up inside the row, so that no token is shuffled, however long a text is.
    """
    lang = F.col(lang_col)
    ids = ids_in_row(F.col(text_col), lang, _books(tokenizers, vocab), vocab)
    return texts.select(key, lang.alias("lang"), F.explode(F.array(ids)).alias("token_ids")).filter(F.size("token_ids") > 0)


def encode_segments(samples: DataFrame, tokenizers: DataFrame, vocab: RangeVocab) -> DataFrame:
    """sample_id, token_ids of switched samples (segments: slot, lang, text): each segment by its own tokenizer, in order of
    the slots; no token crosses a switch. Segments in other languages give none; samples without tokens are left out."""
    books = _books(tokenizers, vocab)
    part = lambda s: F.coalesce(ids_in_row(s["text"], s["lang"], books, vocab), F.array().cast("array<int>"))
    ordered = F.sort_array(F.transform("segments", lambda s: F.struct(s["slot"].alias("slot"), s["lang"].alias("lang"), s["text"].alias("text"))))
    return samples.select("sample_id", F.explode(F.array(F.flatten(F.transform(ordered, part)))).alias("token_ids")).filter(F.size("token_ids") > 0)


def decode(encoded: DataFrame, tokenizers: DataFrame, vocab: RangeVocab, key: str) -> DataFrame:
    """key, text from key, token_ids: each id goes to the tokenizer of its range, inside the row; unknown ids read as ``<unk>``."""
    _checked(vocab)
    pieces = ["null"] * vocab.total
    for r in tokenizers.filter(F.col("lang").isin(*vocab.langs)).select("lang", "local_id", "piece").collect():
        offset, size = vocab.range(r["lang"])
        if 0 <= r["local_id"] < size:
            pieces[offset + r["local_id"]] = _quoted(r["piece"])
    book = F.expr(f"array({', '.join(pieces)})")
    return encoded.select(key, F.array_join(F.transform("token_ids", lambda t: F.coalesce(F.get(book, t), F.lit(UNK))), " ").alias("text"))


def decode_long(tokens: DataFrame, tokenizers: DataFrame, vocab: RangeVocab, key: str) -> DataFrame:
    """key, text from key, pos, token_id, where tokens are rows of their own: they are brought together by key."""
    lang = vocab.lang_of(F.col("token_id"))
    shifted = tokens.withColumn("_of", lang).withColumn("_id", F.col("token_id") - vocab.offset_of(lang))
    known = tokenizers.select(F.col("lang").alias("_lang"), F.col("local_id").alias("_local"), "piece")
    joined = shifted.join(F.broadcast(known), (F.col("_of") == F.col("_lang")) & (F.col("_id") == F.col("_local")), "left")
    return joined.groupBy(key).agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", F.coalesce("piece", F.lit(UNK)).alias("piece")))), lambda t: t["piece"]), " ").alias("text"))


# tag tokens: the baseline that puts language symbols into the sequence


def inject_tags(tokens: DataFrame, vocab: RangeVocab, key: str, where: str = "span") -> DataFrame:
    """key, pos, token_id with language tags: one before the sequence (``start``) or one at either end of every span."""
    tag = lambda lang: F.lit(vocab.total + 1) + F.array_position(F.array(*map(F.lit, vocab.langs)), lang).cast("int")
    order = Window.partitionBy(key).orderBy("pos")
    seen = tokens.withColumn("_lang", vocab.lang_of(F.col("token_id"))).withColumn("_before", F.lag("_lang").over(order)).withColumn("_after", F.lead("_lang").over(order))
    first = F.lag("pos").over(order).isNull()
    opens = first if where == "start" else first | ~F.col("_before").eqNullSafe(F.col("_lang"))
    closes = F.lit(False) if where == "start" else F.lead("pos").over(order).isNull() | ~F.col("_after").eqNullSafe(F.col("_lang"))
    seen = seen.withColumn("_open", opens).withColumn("_close", closes)
    item = lambda keep, at, token: F.when(keep, F.array(F.struct(at.cast("int").alias("rank"), token.cast("int").alias("token_id")))).otherwise(F.array().cast("array<struct<rank int, token_id int>>"))
    each = F.concat(item(F.col("_open"), F.lit(0), tag(F.col("_lang"))), item(F.lit(True), F.lit(1), F.col("token_id")), item(F.col("_close"), F.lit(2), tag(F.col("_lang"))))
    flat = seen.select(key, F.col("pos").alias("_pos"), F.inline(each))
    return flat.withColumn("pos", F.row_number().over(Window.partitionBy(key).orderBy("_pos", "rank")) - 1).select(key, "pos", "token_id")


def is_tag(token: Column, vocab: RangeVocab) -> Column:
    return token > vocab.total


def strip_tags(tagged: DataFrame, vocab: RangeVocab, key: str) -> DataFrame:
    kept = tagged.filter(~is_tag(F.col("token_id"), vocab))
    return kept.withColumn("pos", F.row_number().over(Window.partitionBy(key).orderBy("pos")) - 1)


def lid_from_tags(tagged: DataFrame, vocab: RangeVocab, key: str) -> DataFrame:
    """key, lang by the first tag of each sequence."""
    tags = tagged.filter(is_tag(F.col("token_id"), vocab)).groupBy(key).agg(F.min(F.struct("pos", "token_id"))["token_id"].alias("tag"))
    return tags.select(key, F.element_at(F.array(*map(F.lit, vocab.langs)), F.col("tag") - vocab.total - 1).alias("lang"))
