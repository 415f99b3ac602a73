"""Weighted rendezvous sharding with gapless slots, in DataFrame functions only.

Every shard scores every record key, ``-weight / ln(u)`` with ``u`` uniform from a hash of (key, shard); the highest
score wins. A shard that is added can only win records for itself, and takes its weight's share of them.

Slots number a shard's rows from 0 without a gap. A shard's rows fall into about sqrt(rows) hash buckets; the
buckets' counts give each its first slot, and only a bucket's rows are ever sorted together.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import hash48, inner_names, table, without

LAW = "key"


def record_key(id_col: str = "doc_id", text_col: str = "text") -> Column:
    """The id as text; rows without one are keyed by their text, so that many of them do not meet."""
    return F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("#"), F.md5(F.coalesce(F.col(text_col), F.lit("")))))


def rendezvous(key: Column, weights: Sequence[float]) -> Column:
    """Index of the shard with the highest score; a tie goes to the lower index."""
    if not weights or any(not w > 0 for w in weights):
        raise ValueError("weights must be positive, one for each shard")
    scores = []
    for i, w in enumerate(weights):
        u = (hash48(F.concat(key, F.lit(f":{i}"))) + F.lit(0.5)) / F.lit(float(1 << 48))
        scores.append(F.struct((F.lit(-float(w)) / F.log(u)).alias("score"), F.lit(-i).alias("negated")))
    return (-F.array_max(F.array(*scores))["negated"]).cast("int")


def assign_shards(docs: DataFrame, weights: Sequence[float] = (1.0,) * 8, id_col: str = "doc_id", text_col: str = "text", checksum: Column | None = None) -> DataFrame:
    """``docs`` with ``shard`` INT and ``slot`` BIGINT at the end (columns of these two names are replaced, no others).

    A null id is keyed by its text, a null text counts as empty; repeated rows all stay and get slots of their own;
    an empty table stays empty. Order inside a shard: hash bucket of key and text checksum, key, checksum; rows of one id
    are thus spread over buckets by their texts, and only rows equal in both are numbered by one task. ``checksum``
    stands in for the text's CRC-32 where the texts are not at hand.
    """
    rows = docs.count()
    buckets = max(1, math.ceil(math.sqrt(rows / len(weights))))
    docs = without(docs, "shard", "slot")
    key, crc, bucket, first = inner_names(docs, "_key", "_crc", "_bucket", "_first")
    dealt = (
        docs.withColumn(key, record_key(id_col, text_col))
        .withColumn(crc, F.crc32(F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))) if checksum is None else checksum)
        .withColumn("shard", rendezvous(F.col(key), weights))
        .withColumn(bucket, F.pmod(hash48(F.concat(F.col(key), F.lit(":"), F.col(crc).cast("string"))), F.lit(buckets)).cast("int"))
    )
    by_shard = Window.partitionBy("shard").orderBy(bucket)
    firsts = dealt.groupBy("shard", bucket).agg(F.count(F.lit(1)).alias("n"))
    firsts = firsts.select("shard", bucket, (F.sum("n").over(by_shard) - F.col("n")).alias(first))
    inside = Window.partitionBy("shard", bucket).orderBy(key, crc)
    slot = (F.col(first) + F.row_number().over(inside) - 1).cast("bigint")
    return dealt.join(firsts, ["shard", bucket]).select(*(f"`{c}`" for c in docs.columns), "shard", slot.alias("slot"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of sharding all documents over 8 equal shards."""
    text = F.coalesce(F.col("text"), F.lit(""))
    small = table(spark, sf_dir, "documents").select(
        "doc_id",
        (F.octet_length(text) + 1).cast("bigint").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.when(F.col("doc_id").isNull(), F.md5(text)).alias("text"),
    )
    # rows without an id are keyed by a digest of their text; the texts themselves are not moved
    return assign_shards(small, checksum=F.col("text_crc32")).select(
        "doc_id", "size", "text_crc32", F.lit(LAW).alias("law"), "shard", "slot", rendezvous(record_key(), (1.0,) * 9).alias("grown_shard")
    )


def crc_table() -> list[int]:
    """The byte table of CRC-32 (reflected polynomial 0xEDB88320)."""
    out = []
    for byte in range(256):
        for _ in range(8):
            byte = byte >> 1 ^ (0xEDB88320 if byte & 1 else 0)
        out.append(byte)
    return out


def crc_sql(text: str) -> str:
    """CRC-32 of a text in DuckDB, which has no function for it: a fold of its bytes over the table."""
    values = f"[{', '.join(map(str, crc_table()))}]::bigint[]"
    data = f"list_transform(regexp_extract_all(hex(encode({text})), '..'), lambda b: ('0x' || b)::bigint)"
    step = f"lambda c, b: xor(c >> 8, list_extract({values}, (xor(c, b) & 255) + 1))"
    return f"xor(list_reduce(list_concat([4294967295::bigint], {data}), {step}), 4294967295::bigint)"


def oracle() -> str:
    def winner(n: int) -> str:
        scores = ", ".join(f"{{'s': -1.0 / ln((h48(k || ':{i}') + 0.5) / 281474976710656.0), 'i': -{i}}}" for i in range(n))
        return f"(-(list_max([{scores}]).i))::int"

    def inlined(sql: str) -> str:
        while "h48(" in sql:
            a = sql.index("h48(")
            depth, b = 1, a + 4
            while depth:
                depth += {"(": 1, ")": -1}.get(sql[b], 0)
                b += 1
            sql = f"{sql[:a]}('0x' || substr(md5({sql[a + 4 : b - 1]}), 1, 12))::bigint{sql[b:]}"
        return sql

    return inlined(f"""
WITH d AS (SELECT doc_id, coalesce(doc_id::varchar, '#' || md5(md5(coalesce(text, '')))) AS k, (octet_length(encode(coalesce(text, ''))) + 1)::bigint AS size, {crc_sql("coalesce(text, '')")} AS crc FROM documents),
m AS (SELECT greatest(1, ceil(sqrt(count(*) / 8.0)))::bigint AS buckets FROM d),
s AS (SELECT doc_id, k, crc, size, {winner(8)} AS shard, {winner(9)} AS grown_shard, h48(k || ':' || crc::varchar) % buckets AS bucket FROM d, m)
SELECT doc_id, size, crc AS text_crc32, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY bucket, k) - 1 AS slot, grown_shard FROM s""")


ORACLE = oracle()
