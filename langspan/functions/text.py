"""Text as columns: words, sentences, cleaning, splits, HTML. Each has the SQL that DuckDB runs to the same result."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Everything that is no letter of the four languages, in lower case.
NOT_LETTERS = "[^a-zà-öø-ÿß]+"
#: The same class letter by letter for Spark: Java looks these up in a table, but tries ranges one after the other for every
#: character.
_LISTED = "[^" + "".join(chr(c) for c in (*range(ord("a"), ord("z") + 1), *range(0xDF, 0x100)) if c != 0xF7) + "]+"
SAMPLES_PER_CHAR, SAMPLE_RATE = 10, 150
MIN_CHARS, MAX_CHARS = 30, 285
MODULUS = 1_000_000_007


def hash48(text: Column) -> Column:
    """48 bits of MD5, the same in every engine."""
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("bigint")


def hash48_sql(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 12))::bigint"


def words(text: Column) -> Column:
    """Lower-cased runs of letters, in order."""
    return F.filter(F.split(F.lower(text), _LISTED), lambda w: w != "")


WORDS_SQL = f"list_filter(string_split_regex(lower({{0}}), '{NOT_LETTERS}'), lambda w: w <> '')"


#: The letters of ``words`` beyond a-z, and as many signs that no word holds.
_ACCENTED = "".join(chr(c) for c in range(0xDF, 0x100) if c != 0xF7)
_SIGNS = "".join(chr(c) for c in range(ord("A"), ord("Z") + 1)) + "0123456789"


def one_byte_sql(text: str) -> str:
    """Normalised text with one byte a letter, as DuckDB's edit distance counts bytes."""
    return f"translate({text}, '{_ACCENTED}', '{_SIGNS[: len(_ACCENTED)]}')"


def normalise(text: Column) -> Column:
    """``words``, joined by blanks."""
    return F.trim(F.regexp_replace(F.lower(text), _LISTED, " "))


def sentences(text: Column) -> Column:
    """Sentences by end marks and line breaks, in order, untrimmed."""
    return F.split(F.regexp_replace(text, r"([.!?])\s+", "$1\n"), "\n+")


def segments(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, pos, raw: every sentence that is not blank."""
    each = docs.select("doc_id", "lang", "source", F.posexplode(sentences(F.col("text"))).alias("pos", "raw"))
    return each.withColumn("raw", F.trim("raw")).filter(F.col("raw") != "")


SEGMENTS_SQL = r"""sents AS (SELECT doc_id, lang, source, string_split_regex(regexp_replace(text, '([.!?])\s+', '\1' || chr(10), 'g'), '\n+') AS s FROM documents),
seg AS (SELECT * FROM (SELECT doc_id, lang, source, i AS pos, trim(s[i + 1]) AS raw FROM (SELECT *, unnest(range(len(s))) AS i FROM sents)) WHERE raw <> '')"""


def cleaned(segs: DataFrame) -> DataFrame:
    """Basic cleaning: letters only, words joined by blanks; sentences under three fifths letters go (junk, tables, numbers).

    The text comes from a generator of one row, below which no filter moves: moved, it would clean each sentence once more
    for every place that names it.
    """
    text = F.explode(F.array(normalise(F.col("raw"))))
    return segs.select("*", text.alias("text")).filter((F.col("text") != "") & (F.length("text") >= 0.6 * F.length("raw")))


def split_of(text: Column) -> Column:
    """train, dev or test by a hash of the text, so that copies stay together."""
    h = hash48(text) % 10
    return F.when(h < 8, "train").when(h == 8, "dev").otherwise("test")


def utterances(docs: DataFrame) -> DataFrame:
    """utt_id, doc_id, pos, lang, source, text, n_samples, split of the pool of monolingual utterances."""
    pool = cleaned(segments(docs)).filter(F.length("text").between(MIN_CHARS, MAX_CHARS))
    return pool.select(
        hash48(F.concat_ws(":", F.col("doc_id").cast("string"), F.col("pos").cast("string"))).alias("utt_id"),
        "doc_id", "pos", "lang", "source", "text", (F.length("text") * SAMPLES_PER_CHAR).cast("int").alias("n_samples"), split_of(F.col("text")).alias("split"),
    )


CLEAN_SQL = SEGMENTS_SQL + f""",
clean AS (SELECT * FROM (SELECT *, array_to_string({WORDS_SQL.format('raw')}, ' ') AS text FROM seg) WHERE text <> '' AND length(text) >= 0.6 * length(raw))"""

UTTERANCES_SQL = CLEAN_SQL + f""",
utt AS (
  SELECT {hash48_sql("doc_id::varchar || ':' || pos::varchar")} AS utt_id, doc_id, pos, lang, source, text, (length(text) * {SAMPLES_PER_CHAR})::int AS n_samples,
    CASE WHEN {hash48_sql('text')} % 10 < 8 THEN 'train' WHEN {hash48_sql('text')} % 10 = 8 THEN 'dev' ELSE 'test' END AS split
  FROM clean WHERE length(text) BETWEEN {MIN_CHARS} AND {MAX_CHARS})"""


def page_language(html: Column) -> Column:
    return F.regexp_extract(html, r'<html lang="([a-z]+)"', 1)


def page_blocks(pages: DataFrame) -> DataFrame:
    """page_id, page_lang, tag, block, text: the navigation, advertisement, article and footer of a page, without markup."""
    bare = F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", "")
    pages = pages.select("page_id", page_language(F.col("html")).alias("page_lang"), bare.alias("bare"))
    patterns = (("nav", r"(?s)<nav>(.*?)</nav>"), ("ad", r'(?s)<div class="ad">(.*?)</div>'), ("article", r"(?s)<article>(.*?)</article>"), ("footer", r"(?s)<footer>(.*?)</footer>"))
    each = F.array(*(F.struct(F.lit(k).alias("block"), F.lit(tag).alias("tag"), F.regexp_extract("bare", p, 1).alias("markup")) for k, (tag, p) in enumerate(patterns)))
    blocks = pages.select("page_id", "page_lang", F.inline(each))
    return blocks.withColumn("text", plain(F.col("markup"))).drop("markup")


def plain(markup: Column) -> Column:
    """Markup to text: tags and entities give way to blanks."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.regexp_replace(markup, "<[^>]*>", " "), "&[A-Za-z#0-9]+;", " "), r"[ \t\r\n]+", " "))


PAGES_SQL = r"""bare AS (SELECT page_id, regexp_extract(html, '<html lang="([a-z]+)"', 1) AS page_lang, regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', '', 'g') AS b FROM pages),
marked AS (
  SELECT page_id, page_lang, 0 AS block, 'nav' AS tag, regexp_extract(b, '(?s)<nav>(.*?)</nav>', 1) AS m FROM bare
  UNION ALL SELECT page_id, page_lang, 1, 'ad', regexp_extract(b, '(?s)<div class="ad">(.*?)</div>', 1) FROM bare
  UNION ALL SELECT page_id, page_lang, 2, 'article', regexp_extract(b, '(?s)<article>(.*?)</article>', 1) FROM bare
  UNION ALL SELECT page_id, page_lang, 3, 'footer', regexp_extract(b, '(?s)<footer>(.*?)</footer>', 1) FROM bare),
blocks AS (SELECT page_id, page_lang, block, tag, trim(regexp_replace(regexp_replace(regexp_replace(m, '<[^>]*>', ' ', 'g'), '&[A-Za-z#0-9]+;', ' ', 'g'), '[ \t\r\n]+', ' ', 'g')) AS text FROM marked)"""


def title(html: Column) -> Column:
    return plain(F.regexp_extract(html, r"(?s)<title>(.*?)</title>", 1))
