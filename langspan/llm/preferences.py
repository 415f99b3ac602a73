"""Preference formatting: a chosen and a rejected conversation share a prompt and differ in masked completions.

The longest common prefix of turns (same role, same text) is rendered once as the prompt. The rest of either
conversation is its completion; a mask of runs (characters, trained or not) tells the assistant's words and end marks
from headers and other roles' turns. Column functions only: no Python touches the rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, without

TURN = "array<struct<turn bigint, role string, text string>>"


@dataclass(frozen=True)
class Template:
    """A turn reads: opening, role, closing, text, end."""

    opening: str = "<|"
    closing: str = "|>\n"
    end: str = "<|end|>\n"
    trained: str = "assistant"

    def header(self, role: Column) -> Column:
        return F.concat(F.lit(self.opening), F.coalesce(role, F.lit("")), F.lit(self.closing))

    def body(self, text: Column) -> Column:
        return F.concat(F.coalesce(text, F.lit("")), F.lit(self.end))

    def rendered(self, turns: Column) -> Column:
        return F.array_join(F.transform(turns, lambda t: F.concat(self.header(t["role"]), self.body(t["text"]))), "")

    def mask(self, turns: Column) -> Column:
        """array<struct<n, train>>: the completion's characters in order, header and body of each turn."""

        def runs(t):
            train = F.coalesce(t["role"] == self.trained, F.lit(False))
            return F.array(F.struct(F.length(self.header(t["role"])).alias("n"), F.lit(False).alias("train")), F.struct(F.length(self.body(t["text"])).alias("n"), train.alias("train")))

        return F.flatten(F.transform(turns, runs))


def conversations(turns: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """conv_id and its turns in order, one row for each conversation.

    Order: turn, role, text, nulls first; repeated rows are repeated turns; null ids are one conversation; an empty table
    gives none. A conversation is one record and has to fit into one.
    """
    turn = F.struct(F.col("turn").cast("bigint").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    return turns.groupBy(F.col(conv_col).alias("conv_id")).agg(F.sort_array(F.collect_list(turn)).alias("turns"))


def common_turns(chosen: Column, rejected: Column) -> Column:
    """Length of the longest common prefix of two arrays of turns."""
    both = F.least(F.size(chosen), F.size(rejected))
    unlike = F.filter(
        F.when(both > 0, F.sequence(F.lit(1), both)).otherwise(F.array().cast("array<int>")),
        lambda i: ~(F.element_at(chosen, i)["role"].eqNullSafe(F.element_at(rejected, i)["role"]) & F.element_at(chosen, i)["text"].eqNullSafe(F.element_at(rejected, i)["text"])),
    )
    return F.coalesce(F.array_min(unlike) - 1, both)


def format_pairs(pairs: DataFrame, chosen: str = "chosen", rejected: str = "rejected", template: Template = Template()) -> DataFrame:  # noqa: B008
    """``pairs`` with the two arrays of turns replaced by their completions, and prompt, prompt_turns, chosen_mask, rejected_mask.

    A null conversation counts as one without turns; equal conversations give empty completions; null roles and texts
    are equal to each other and render as nothing. Columns with the new names are replaced.
    """
    none = F.array().cast(TURN)
    pairs = without(pairs, "prompt", "prompt_turns", "chosen_mask", "rejected_mask")
    pairs = pairs.withColumn(chosen, F.coalesce(F.col(chosen).cast(TURN), none)).withColumn(rejected, F.coalesce(F.col(rejected).cast(TURN), none))
    pairs = pairs.withColumn("prompt_turns", common_turns(F.col(chosen), F.col(rejected)))
    rest = lambda c: F.slice(c, F.col("prompt_turns") + 1, F.size(c))
    return (
        pairs.withColumn("prompt", template.rendered(F.slice(chosen, F.lit(1), F.col("prompt_turns"))))
        .withColumn("chosen_mask", template.mask(rest(F.col(chosen))))
        .withColumn("rejected_mask", template.mask(rest(F.col(rejected))))
        .withColumn(chosen, template.rendered(rest(F.col(chosen))))
        .withColumn(rejected, template.rendered(rest(F.col(rejected))))
    )


def swapped_replies(turns: DataFrame) -> DataFrame:
    """Pairs from plain conversations: chosen is the conversation, rejected has the last reply of the next one (by id, + 1)
    in place of its own last reply, and ends there; without a next reply it ends before."""
    whole = conversations(turns).withColumn("at", F.array_max(F.transform("turns", lambda t, i: F.when(t["role"] == "assistant", i + 1))))
    reply = whole.filter("at is not null").select((F.col("conv_id") - 1).alias("_of"), F.element_at("turns", F.col("at"))["text"].alias("_text"))
    swap = F.when(F.col("_of").isNotNull(), F.array(F.struct(F.element_at("turns", F.col("at"))["turn"].alias("turn"), F.lit("assistant").alias("role"), F.col("_text").alias("text")))).otherwise(F.array().cast(TURN))
    return whole.join(reply, F.col("conv_id") == F.col("_of"), "left").select(
        "conv_id", F.col("turns").alias("chosen"), F.when(F.col("at").isNull(), F.col("turns")).otherwise(F.concat(F.slice("turns", F.lit(1), F.col("at") - 1), swap)).alias("rejected")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A formatted pair for every conversation; masks as text, ``characters:trained`` joined by commas."""
    shown = lambda m: F.array_join(F.transform(m, lambda r: F.concat(r["n"].cast("string"), F.lit(":"), r["train"].cast("int").cast("string"))), ",")
    pairs = format_pairs(swapped_replies(table(spark, sf_dir, "conversations")))
    return pairs.select("conv_id", "prompt_turns", "prompt", "chosen", "rejected", shown("chosen_mask").alias("chosen_mask"), shown("rejected_mask").alias("rejected_mask"))


ORACLE = r"""
WITH g AS (SELECT conv_id, list(struct_pack(turn := turn, role := role, text := text) ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS c FROM conversations GROUP BY conv_id),
a AS (SELECT conv_id, c, list_max(list_filter(range(1, len(c) + 1), lambda i: c[i].role = 'assistant')) AS at FROM g),
p AS (
  SELECT a.conv_id, a.c, CASE WHEN a.at IS NULL THEN a.c
    ELSE list_concat(a.c[1:a.at - 1], CASE WHEN n.conv_id IS NULL THEN [] ELSE [struct_pack(turn := a.c[a.at].turn, role := 'assistant', text := n.c[n.at].text)] END) END AS r
  FROM a LEFT JOIN a n ON n.conv_id = a.conv_id + 1 AND n.at IS NOT NULL),
k AS (
  SELECT *, coalesce(list_min(list_filter(range(1, least(len(c), len(r)) + 1), lambda i: c[i].role IS DISTINCT FROM r[i].role OR c[i].text IS DISTINCT FROM r[i].text)) - 1, least(len(c), len(r))) AS k FROM p)
SELECT conv_id, k::int AS prompt_turns,
  coalesce(array_to_string(list_transform(c[1:k], lambda t: '<|' || coalesce(t.role, '') || '|>' || chr(10) || coalesce(t.text, '') || '<|end|>' || chr(10)), ''), '') AS prompt,
  coalesce(array_to_string(list_transform(c[k + 1:], lambda t: '<|' || coalesce(t.role, '') || '|>' || chr(10) || coalesce(t.text, '') || '<|end|>' || chr(10)), ''), '') AS chosen,
  coalesce(array_to_string(list_transform(r[k + 1:], lambda t: '<|' || coalesce(t.role, '') || '|>' || chr(10) || coalesce(t.text, '') || '<|end|>' || chr(10)), ''), '') AS rejected,
  coalesce(array_to_string(list_transform(c[k + 1:], lambda t: (length(coalesce(t.role, '')) + 5)::varchar || ':0,' || (length(coalesce(t.text, '')) + 8)::varchar || ':' || (coalesce(t.role = 'assistant', false))::int::varchar), ','), '') AS chosen_mask,
  coalesce(array_to_string(list_transform(r[k + 1:], lambda t: (length(coalesce(t.role, '')) + 5)::varchar || ':0,' || (length(coalesce(t.text, '')) + 8)::varchar || ':' || (coalesce(t.role = 'assistant', false))::int::varchar), ','), '') AS rejected_mask
FROM k"""
