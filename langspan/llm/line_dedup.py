"""Removal of repeated passages of three lines, in DataFrame functions only.

Every window of three consecutive lines (outer blanks trimmed, wholly blank windows left out) is hashed to 128 bits.
The first window of a hash, by (document, line), stays; every later one covers its three lines, and a document loses
the union of its covered lines. Windows are counted before they move, so a passage that a third of all documents
share costs one row for each task; the windows are then matched with the table of repeated hashes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, inner_names, table, without

WINDOW = 3


def line_windows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """_id, _text_hash, _pos (from 1), _h1, _h2 of every window."""
    lines = F.transform(F.split(F.col(text_col), "\n"), lambda line: F.trim(line))
    long_enough = docs.select(F.col(id_col).alias("_id"), F.xxhash64(text_col).alias("_text_hash"), lines.alias("_lines")).filter(F.size("_lines") >= WINDOW)

    def hashed(i):
        parts = [F.element_at("_lines", (i + k).cast("int")) for k in range(WINDOW)]
        blank = F.concat(*parts) == ""
        return F.struct(i.alias("_pos"), F.xxhash64(*parts).alias("_h1"), F.xxhash64(F.lit("second"), *reversed(parts)).alias("_h2"), blank.alias("_blank"))

    windows = F.transform(F.sequence(F.lit(1), F.size("_lines") - (WINDOW - 1)), hashed)
    return long_enough.select("_id", "_text_hash", F.inline(windows)).filter(~F.col("_blank")).drop("_blank")


def later_windows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """_id, _text_hash, _pos of every window that repeats an earlier one."""
    windows = line_windows(docs, id_col, text_col)
    here = F.struct("_id", "_text_hash", "_pos")
    first = windows.groupBy("_h1", "_h2").agg(F.min(here).alias("_first"), F.max(here).alias("_last")).filter(F.col("_first") != F.col("_last"))
    # written out, so that both sides of the join are dealt anew and Spark can split a hash with very many windows
    repeated = durable(first.select("_h1", "_h2", "_first"))
    return windows.join(repeated, ["_h1", "_h2"]).filter(here != F.col("_first")).select("_id", "_text_hash", "_pos")


def drop_repeated_windows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with the shortened text, ``n_lines`` (before) and ``n_removed`` (these two names are replaced).

    Rows with the same id and text are one document and fare alike; a null id comes first; a null text stays null and
    has no lines; texts of fewer than three lines stay; an empty table stays empty.
    """
    covered = (
        later_windows(docs, id_col, text_col)
        .groupBy("_id", "_text_hash")
        .agg(F.sort_array(F.collect_set("_pos")).alias("_pos"))
        .select(
            F.col("_id").alias("_of"),
            F.col("_text_hash").alias("_of_hash"),
            F.array_distinct(F.flatten(F.transform("_pos", lambda p: F.array(*(p + k for k in range(WINDOW)))))).alias("_covered"),
        )
    )
    docs = without(docs, "n_lines", "n_removed")
    hash_, of, of_hash, gone, lines = inner_names(docs, "_hash", "_of", "_of_hash", "_covered", "_lines")
    covered = covered.toDF(of, of_hash, gone)
    on = F.col(id_col).eqNullSafe(F.col(of)) & (F.col(hash_) == F.col(of_hash))
    joined = docs.withColumn(hash_, F.xxhash64(text_col)).join(covered.hint("shuffle_hash"), on, "left").withColumn(lines, F.split(F.col(text_col), "\n"))
    kept = F.transform(F.array_except(F.sequence(F.lit(1), F.size(lines)), F.col(gone)), lambda i: F.element_at(lines, i))
    return (
        joined.withColumn("n_lines", F.when(F.col(text_col).isNull(), 0).otherwise(F.size(lines)).cast("bigint"))
        .withColumn("n_removed", F.when(F.col(gone).isNull(), F.lit(0)).otherwise(F.size(gone)).cast("bigint"))
        .withColumn(text_col, F.when(F.col(gone).isNull(), F.col(text_col)).otherwise(F.array_join(kept, "\n")))
        .drop(hash_, of, of_hash, gone, lines)
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without its repeated three-line passages."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return drop_repeated_windows(docs).select("doc_id", "n_lines", "n_removed", "text")


ORACLE = r"""
WITH l AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
w AS (SELECT doc_id, i, trim(ls[i]) || chr(10) || trim(ls[i + 1]) || chr(10) || trim(ls[i + 2]) AS win FROM (SELECT doc_id, ls, unnest(range(1, len(ls) - 1)) AS i FROM l)),
r AS (SELECT doc_id, i, row_number() OVER (PARTITION BY win ORDER BY doc_id, i) AS k FROM w WHERE replace(win, chr(10), '') <> ''),
c AS (SELECT doc_id, list_distinct(flatten(list([i, i + 1, i + 2]))) AS covered FROM r WHERE k > 1 GROUP BY doc_id)
SELECT l.doc_id, coalesce(len(ls), 0)::bigint AS n_lines, coalesce(len(covered), 0)::bigint AS n_removed,
  CASE WHEN covered IS NULL THEN text ELSE coalesce(array_to_string(list_filter(ls, lambda x, i: NOT list_contains(covered, i)), chr(10)), '') END AS text
FROM l LEFT JOIN c ON l.doc_id = c.doc_id"""
