"""WARC archives of pages, and a Merkle audit of their replicas.

Pages are laid into archive files by a hash of their ids and contents, ordered inside a file, each record at its byte
offset. Every record is hashed with its offset; every 2 ** BITS consecutive records of a file's offset order make a range
whose hash covers theirs in order, as many ranges make a larger one, up to the file, groups of files and one root. Two
replicas, each laid out or read by itself, are compared from the root: only the children of nodes that differ are looked
at. Records of the ranges that differ are matched by their ids: altered, missing, extra, or intact but moved by others.
Bytes are read once for each replica; what moves is a hash and an address for each record.
"""

from __future__ import annotations

import gzip
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from langspan.shipping import ship

from .common import durable, hash48, table

PER_FILE = 1000
#: Children of a node: 2 ** BITS.
BITS = 5
DATE = "2024-01-01T00:00:00Z"


def record(key: Column, url: Column, html: Column) -> Column:
    """A page as the text of a WARC resource record; nulls are empty."""
    html = F.coalesce(html, F.lit(""))
    head = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:"), key,
        F.lit(">\r\nWARC-Target-URI: "), F.coalesce(url, F.lit("")),
        F.lit(f"\r\nWARC-Date: {DATE}\r\nContent-Type: text/html\r\nContent-Length: "), F.octet_length(html).cast("string"), F.lit("\r\n\r\n"),
    )
    return F.concat(head, html, F.lit("\r\n\r\n"))


def lay_out(records: DataFrame) -> DataFrame:
    """``records`` (file, rid, length and more) with ``offset``: a file's records in the order of their ids, end to end."""
    order = Window.partitionBy("file").orderBy("rid").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return records.withColumn("offset", F.sum("length").over(order) - F.col("length"))


def file_of(rid: Column, records: int, per_file: int | None = None) -> Column:
    """One of as many files as hold about ``per_file`` records each."""
    return (hash48(F.concat(F.lit("file:"), rid)) % max(1, -(-records // (per_file or PER_FILE)))).cast("bigint")


def tree(leaves: DataFrame, levels: int) -> list[DataFrame]:
    """(address, digest) of every level, leaves first; a node's address is its children's without their last BITS."""
    out = [durable(leaves.select("address", "digest"))]
    for _ in range(levels):
        up = out[-1].groupBy(F.shiftright("address", BITS).alias("parent")).agg(F.sort_array(F.collect_list(F.struct("address", "digest"))).alias("children"))
        told = F.transform("children", lambda c: F.concat(c["address"].cast("string"), F.lit(":"), c["digest"]))
        out.append(durable(up.select(F.col("parent").alias("address"), F.sha2(F.array_join(told, ","), 256).alias("digest"))))
    return out


def audit(primary: DataFrame, replica: DataFrame) -> DataFrame:
    """(file, rid, status, replica_offset) of the records that are not the same in both; inputs: file, offset, rid, digest.

    Status: ``altered`` (another digest), ``moved`` (same digest at another offset or place), ``missing`` or ``extra`` in
    the replica. A file is known by its number, a record by its id (rid), unique within its file. Null digests differ
    from all but each other; equal or empty inputs give no rows.
    """
    order = Window.partitionBy("file").orderBy("offset", "rid")
    placed = [side.select("file", "offset", "rid", "digest", (F.row_number().over(order) - 1).alias("place")) for side in (primary, replica)]
    placed = [durable(side) for side in placed]
    top = placed[0].union(placed[1]).agg(F.max("place"), F.max("file")).first()
    width = int(top[0] or 0).bit_length()
    levels = max(1, -(-(width + int(top[1] or 0).bit_length()) // BITS))
    address = F.shiftleft("file", width) + F.col("place")
    told = F.concat_ws(":", F.col("offset").cast("string"), "rid", F.coalesce("digest", F.lit("-")))
    placed = [side.select("file", "offset", "rid", "digest", address.alias("address"), F.sha2(told, 256).alias("leaf")) for side in placed]
    a, b = (tree(side.select("address", F.col("leaf").alias("digest")), levels) for side in placed)
    bad = None
    for level in range(levels, -1, -1):
        left = a[level].select("address", F.col("digest").alias("_a"))
        right = b[level].select("address", F.col("digest").alias("_b"))
        if bad is not None:
            parents = bad.select(F.col("address").alias("_parent"))
            left, right = (side.join(parents, F.shiftright("address", BITS) == F.col("_parent"), "left_semi") for side in (left, right))
        bad = durable(left.join(right, "address", "full").filter(~F.col("_a").eqNullSafe(F.col("_b"))).select("address"))
    left, right = (side.join(bad, "address", "left_semi").select("file", "rid", *(F.col(c).alias(f"_{c}_{k}") for c in ("digest", "offset"))) for k, side in zip("ab", placed, strict=True))
    both = left.withColumn("_in_a", F.lit(1)).join(right.withColumn("_in_b", F.lit(1)), ["file", "rid"], "full")
    status = (
        F.when(F.col("_in_b").isNull(), "missing")
        .when(F.col("_in_a").isNull(), "extra")
        .when(~F.col("_digest_a").eqNullSafe(F.col("_digest_b")), "altered")
        .otherwise("moved")
    )
    return both.select("file", "rid", status.alias("status"), F.col("_offset_b").alias("replica_offset"))


def audit_files(primary: DataFrame, replica: DataFrame) -> DataFrame:
    """``audit`` of archive files (path, content) of which equal names are replicas; both are read record by record.

    ``file`` is the path's last part, as a hash; rid is the record's id in its header.
    """
    sides = []
    for files in (primary, replica):
        name = F.xxhash64(F.substring_index("path", "/", -1)) % (1 << 31)
        told = read_records(files.select(F.col("path").cast("string").alias("path"), "content"))
        text = F.concat(F.array_join(F.transform(F.array_sort(F.map_entries("headers")), lambda h: F.concat(h["key"], F.lit(":"), h["value"])), "|").cast("binary"), F.col("content"))
        sides.append(told.select(F.abs(name).alias("file"), "offset", F.coalesce(F.col("headers")["WARC-Record-ID"], F.lit("")).alias("rid"), F.sha2(text, 256).alias("digest")))
    return audit(*sides)


def page_key(id_col: str = "page_id") -> Column:
    """The id as text; pages without one are keyed by their content."""
    return F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("#"), F.md5(F.concat_ws("\n", F.coalesce("url", F.lit("")), F.coalesce("html", F.lit(""))))))


def record_id(key: Column, digest: Column) -> Column:
    """Key and the beginning of the first digest: pages that share an id are records of their own."""
    return F.concat(key, F.lit("."), F.substring(digest, 1, 16))


def hashed_records(pages: DataFrame, html: Column | None = None, suffix: str = "") -> DataFrame:
    """page_id, rid, length (bytes of the record) and digest of every page as it is or with another ``html``; rid is always
    the page's as it is. Pages that repeat with id and content are one record, with ``copies``."""
    key = page_key()
    first = record(key, F.col("url"), F.col("html"))
    text = first if html is None else record(key, F.col("url"), html)
    rid = F.concat(record_id(key, F.sha2(first, 256)), F.lit(suffix))
    told = pages.select("page_id", rid.alias("rid"), F.octet_length(text).cast("bigint").alias("length"), F.sha2(text, 256).alias("digest"))
    return told.groupBy(told.columns).agg(F.count(F.lit(1)).alias("copies"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages archived, and audited against a replica that is laid out by itself: of 211 records about one is altered,
    one lost, one cut short (those behind it move), and one is there twice. Offsets and lengths of what a side lacks are -1."""
    pages = table(spark, sf_dir, "pages")
    fate = hash48(F.concat(F.lit("fate:"), page_key())) % 211
    html = F.coalesce(F.col("html"), F.lit(""))
    spoilt = F.when(fate == 0, F.concat(F.lit("~"), F.substr(html, F.lit(2)))).when(fate == 2, F.left(html, F.length(html) - 1)).otherwise(html)
    first = durable(hashed_records(pages))
    home = file_of(F.col("rid"), first.count())
    primary = durable(lay_out(first.withColumn("file", home)))
    copy = hashed_records(pages.filter(fate != 1), spoilt).union(hashed_records(pages.filter(fate == 3), suffix="+"))
    replica = lay_out(copy.withColumn("file", file_of(F.rtrim(F.col("rid"), F.lit("+")), first.count())))
    names = ["file", "offset", "rid", "digest"]
    found = audit(primary.select(names), replica.select(names)).select("rid", F.col("file").alias("_file"), "status", "replica_offset")
    out = primary.join(found, "rid", "full")
    none = F.lit(-1).cast("bigint")
    return out.select(
        "rid",
        F.coalesce("page_id", F.expr("try_cast(split_part(rid, '.', 1) AS bigint)")).alias("page_id"),
        F.coalesce("file", "_file").alias("file"),
        *(F.coalesce(c, none).alias(c) for c in ("offset", "length")),
        F.coalesce("digest", F.lit("")).alias("digest"),
        F.coalesce("copies", F.lit(0)).cast("bigint").alias("copies"),
        F.coalesce("status", F.lit("intact")).alias("status"),
        F.coalesce(F.when(F.col("status").isNull(), F.col("offset")).otherwise(F.col("replica_offset")), none).alias("replica_offset"),
    )


ORACLE = r"""
WITH p AS (SELECT page_id, page_id::varchar AS key, coalesce(url, '') AS url, coalesce(html, '') AS html FROM pages),
f AS (SELECT *, ('0x' || substr(md5('fate:' || key), 1, 12))::bigint % 211 AS fate FROM p),
s AS (SELECT *, CASE fate WHEN 0 THEN '~' || substr(html, 2) WHEN 2 THEN left(html, greatest(length(html) - 1, 0)) ELSE html END AS spoilt FROM f),
r AS (
  SELECT page_id, key, fate,
    'WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Record-ID: <urn:page:' || key || '>' || chr(13) || chr(10) || 'WARC-Target-URI: ' || url || chr(13) || chr(10)
      || 'WARC-Date: 2024-01-01T00:00:00Z' || chr(13) || chr(10) || 'Content-Type: text/html' || chr(13) || chr(10) || 'Content-Length: ' AS head, html, spoilt, chr(13) || chr(10) || chr(13) || chr(10) AS gap
  FROM s),
h AS (
  SELECT page_id, key, fate, head || octet_length(encode(html))::varchar || gap || html || gap AS a, head || octet_length(encode(spoilt))::varchar || gap || spoilt || gap AS b FROM r),
d AS (
  SELECT page_id, fate, key || '.' || substr(sha256(a), 1, 16) AS rid, octet_length(encode(a))::bigint AS length, sha256(a) AS digest, octet_length(encode(b))::bigint AS length_b, sha256(b) AS digest_b, count(*) AS copies
  FROM h GROUP BY ALL),
n AS (SELECT greatest(1, ceil(count(*) / 1000.0))::bigint AS files FROM d),
x AS (SELECT d.*, ('0x' || substr(md5('file:' || rid), 1, 12))::bigint % files AS file FROM d, n),
u AS (SELECT rid, file, length_b AS length, digest_b AS digest FROM x WHERE fate <> 1 UNION ALL SELECT rid || '+', file, length, digest FROM x WHERE fate = 3),
a AS (
  SELECT *, sum(length) OVER w - length AS "offset", row_number() OVER w AS place FROM x WINDOW w AS (PARTITION BY file ORDER BY rid ROWS UNBOUNDED PRECEDING)),
b AS (
  SELECT *, sum(length) OVER w - length AS "offset", row_number() OVER w AS place FROM u WINDOW w AS (PARTITION BY file ORDER BY rid ROWS UNBOUNDED PRECEDING))
SELECT coalesce(a.rid, b.rid) AS rid, coalesce(a.page_id, try_cast(split_part(b.rid, '.', 1) AS bigint)) AS page_id, coalesce(a.file, b.file) AS file,
  coalesce(a."offset", -1)::bigint AS "offset", coalesce(a.length, -1)::bigint AS length, coalesce(a.digest, '') AS digest, coalesce(a.copies, 0)::bigint AS copies,
  CASE WHEN b.rid IS NULL THEN 'missing' WHEN a.rid IS NULL THEN 'extra' WHEN a.digest <> b.digest THEN 'altered' WHEN a."offset" <> b."offset" OR a.place <> b.place THEN 'moved' ELSE 'intact' END AS status,
  coalesce(b."offset", -1)::bigint AS replica_offset
FROM a FULL JOIN b ON a.rid = b.rid"""


def archive_bytes(laid: DataFrame) -> DataFrame:
    """(file, content): each file's records in offset order; laid: file, offset and record. Files hold about PER_FILE records."""
    row = F.struct("offset", F.encode("record", "UTF-8").alias("bytes"))
    ordered = F.transform(F.sort_array(F.collect_list(row)), lambda r: F.hex(r["bytes"]))
    return laid.groupBy("file").agg(F.unhex(F.array_join(ordered, "")).alias("content"))


def read_records(files: DataFrame) -> DataFrame:
    """Records of archive files (path, content; also gzip members, as ``spark.read.format("binaryFile")`` gives them):
    path, offset, length, headers (map), content. Offsets of gzip files count the unpacked bytes. A broken header ends
    its file; null contents have no records."""
    ship(files.sparkSession)
    schema = "path string, offset bigint, length bigint, headers map<string,string>, content binary"
    return files.select(F.col("path").cast("string").alias("path"), "content").mapInArrow(_parsed, schema)


def _parsed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = [pa.string(), pa.int64(), pa.int64(), pa.map_(pa.string(), pa.string()), pa.binary()]
    for batch in batches:
        for path, data in zip(batch.column("path").to_pylist(), batch.column("content").to_pylist(), strict=True):
            rows = [(path, *r) for r in split_records(gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data)] if data else []
            for k in range(0, len(rows), 256):
                columns = zip(*rows[k : k + 256], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, kinds, strict=True)], ["path", "offset", "length", "headers", "content"])


def split_records(data: bytes) -> Iterator[tuple[int, int, list[tuple[str, str]], bytes]]:
    """(offset, length, headers, content) of the records in the bytes of an archive."""
    at = 0
    while data.startswith(b"WARC/", at):
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        headers = [tuple(x.strip() for x in line.partition(":")[::2]) for line in data[at:end].decode("utf-8", "replace").split("\r\n")[1:]]
        size = next((v for k, v in headers if k.lower() == "content-length"), "")
        if not size.isdigit():
            return
        stop = end + 4 + int(size)
        yield at, stop + 4 - at, list(dict(headers).items()), data[end + 4 : stop]
        at = stop + 4
