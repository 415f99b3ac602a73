import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from langspan.llm import line_dedup, mixing, preferences, registry, sharding, warc
from tests.oracle import same


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_equals_sql(spark, sf, name):
    same(spark, sf, registry.QUERIES[name], registry.ORACLES[name])


def _h48(s):
    return int(hashlib.md5(s.encode()).hexdigest()[:12], 16)


def test_shards_equal_brute_force(spark, sf):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    win = lambda k, n: max(range(n), key=lambda i: (-1 / math.log((_h48(f"{k}:{i}") + 0.5) / 2**48), -i))
    rows = sharding.query(spark, sf).collect()
    slots = defaultdict(list)
    for r in rows:
        text = docs[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["shard"], r["grown_shard"]) == (len(text) + 1, zlib.crc32(text), win(r["doc_id"], 8), win(r["doc_id"], 9))
        assert r["grown_shard"] in (r["shard"], 8)
        slots[r["shard"]].append(r["slot"])
    assert len(rows) == len(docs) and all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_shards_take_odd_rows(spark):
    docs = spark.createDataFrame([(None, "a", 1), (None, None, 2), (3, "", 3), (3, "", 3), (4, "x" * 200_000, 4)], "doc_id bigint, text string, slot int")
    rows = sharding.assign_shards(docs, (1.0, 3.0)).collect()
    assert len(rows) == 5
    assert all(sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows))) for s in (0, 1))
    assert sharding.assign_shards(docs.limit(0)).count() == 0
    with pytest.raises(ValueError):
        sharding.assign_shards(docs, (1.0, 0.0))
    heavy = sharding.assign_shards(spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("t").alias("text")), (1.0, 3.0))
    assert abs(heavy.filter("shard = 1").count() / 4000 - 0.75) < 0.04


def test_targets():
    assert mixing.water_fill([10, 10, 10], [1, 2, 3], 30, 3) == pytest.approx([5, 10, 15])
    assert mixing.water_fill([1, 100], [9, 1], 101, 3) == pytest.approx([3, 98])
    assert mixing.water_fill([0, 5], [1, 1], 5, 3) == [0, 5]
    assert mixing.water_fill([], [], 0, 3) == []


def test_mixture_of_odd_rows(spark):
    rows = [(k, " ".join(["w"] * (k % 7)), None if k % 3 == 0 else f"s{k % 2}", k) for k in range(60)] + [(None, "a b", "s0", 1), (5, None, "s1", 1)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string, size int")
    out = mixing.take_words(docs, mixing.word_count(F.col("text")))
    got = out.collect()
    assert len(got) == len(rows) and all(0 <= r["taken"] <= 3 * r["size"] for r in got)
    for s in {r["source"] for r in got}:
        mine = [r for r in got if r["source"] == s]
        assert abs(sum(r["taken"] for r in mine) - mine[0]["target"]) <= 1
    again = mixing.take_words(docs.repartition(5), mixing.word_count(F.col("text"))).collect()
    key = lambda r: str((r["doc_id"], r["text"], r["source"], r["taken"]))
    assert sorted(map(key, got)) == sorted(map(key, again))
    assert mixing.take_words(docs.limit(0), mixing.word_count(F.col("text"))).count() == 0


def test_mixing_query_reads_texts_once(spark, sf):
    """Sums and selection run over sizes that are kept, without another scan of the documents."""
    plan = str(mixing.query(spark, sf)._jdf.queryExecution().optimizedPlan())
    assert "Relation [" not in plan and "RelationV2" not in plan and "text" not in plan


def test_mixed_rows_hold_the_words_taken(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    taken = {r["doc_id"]: r["taken"] for r in mixing.take_words(docs, mixing.word_count(F.col("text"))).collect()}
    have = Counter()
    for r in mixing.mix(docs).collect():
        have[r["doc_id"]] += len(re.findall(r"[^\x20\x09-\x0D]+", r["text"]))
        assert r["n_chars"] == len(r["text"])
    assert have == Counter({k: v for k, v in taken.items() if v})
    whole = mixing.mix(docs, weight=mixing.tempered_weight(0.8), share=None)
    assert whole.select("doc_id").distinct().count() == docs.filter("text rlike '[^ ]'").count()


def test_lines_of_odd_rows(spark):
    p = "one\ntwo\nthree"
    rows = [(1, p), (2, f"x\n{p}\nfour\ny"), (3, None), (4, ""), (5, "a\nb"), (6, p), (6, p), (None, "q\n" + p), (7, "\n\n\n\n"), (8, "one \n two\nthree\n" * 2)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("n_lines", F.lit("clash"))
    got = sorted(((r["doc_id"], r["text"], r["n_removed"]) for r in line_dedup.drop_repeated_windows(docs).collect()), key=str)
    want = [(None, "q\n" + p, 0), (1, "", 3), (2, "x\nfour\ny", 3), (3, None, 0), (4, "", 0), (5, "a\nb", 0), (6, "", 3), (6, "", 3), (7, "\n\n\n\n", 0), (8, "", 6)]
    assert [g for g in got if g[0] != 8] == sorted((w for w in want if w[0] != 8), key=str)
    assert next(g for g in got if g[0] == 8)[2] == 6
    assert line_dedup.drop_repeated_windows(docs.limit(0)).count() == 0


def test_preference_pairs(spark):
    turn = lambda k, role, text: (k, role, text)
    rows = [
        (1, [turn(0, "user", "hi"), turn(1, "assistant", "yes")], [turn(0, "user", "hi"), turn(1, "assistant", "no")]),
        (2, None, [turn(0, None, None)]),
        (3, [turn(0, "user", "same")], [turn(0, "user", "same")]),
    ]
    pairs = spark.createDataFrame(rows, f"id bigint, chosen {preferences.TURN}, rejected {preferences.TURN}").withColumn("prompt", F.lit(1))
    got = {r["id"]: r for r in preferences.format_pairs(pairs).collect()}
    assert got[1]["prompt"] == "<|user|>\nhi<|end|>\n" and got[1]["chosen"] == "<|assistant|>\nyes<|end|>\n" and got[1]["prompt_turns"] == 1
    for r in got.values():
        for side in ("chosen", "rejected"):
            assert sum(m["n"] for m in r[f"{side}_mask"]) == len(r[side])
    assert [(m["n"], m["train"]) for m in got[1]["rejected_mask"]] == [(14, False), (10, True)]
    assert (got[2]["prompt"], got[2]["rejected"]) == ("", "<||>\n<|end|>\n") and got[3]["chosen"] == got[3]["rejected"] == ""
    assert preferences.format_pairs(pairs.limit(0)).count() == 0


def test_audit_finds_what_was_spoilt(spark):
    """Records changed, lost and added in some of 20 files; those behind them move; the rest is never reported."""
    rng = random.Random(2)
    primary = {(f, f"r{k:04d}"): (f"d{f}.{k}", rng.randint(1, 50)) for f in range(20) for k in range(rng.choice([0, 1, 60, 100]))}
    replica = dict(primary)
    for key in rng.sample(sorted(primary), 6):
        replica[key] = ("bad", primary[key][1])
    for key in rng.sample(sorted(replica), 2):
        del replica[key]
    replica[3, "r0001x"] = ("new", 7)
    replica[77, "alone"] = ("new", 7)
    first, at = sorted(primary)[0], {}
    replica[first] = (None, primary[first][1])

    def laid(records):
        out, ends = [], Counter()
        for (f, rid), (digest, length) in sorted(records.items()):
            out.append((f, ends[f], rid, digest))
            ends[f] += length
        return out

    a, b = laid(primary), laid(replica)
    frame = lambda rows: spark.createDataFrame(rows, "file bigint, offset bigint, rid string, digest string")
    place = lambda rows: {(f, rid): (o, d, sum(x[0] == f for x in rows[:k])) for k, (f, o, rid, d) in enumerate(rows)}
    was, now, want = place(a), place(b), {}
    for key in was.keys() | now.keys():
        if key not in now or key not in was:
            want[key] = "missing" if key in was else "extra"
        elif was[key] != now[key]:
            want[key] = "altered" if was[key][1] != now[key][1] else "moved"
    got = {(r["file"], r["rid"]): r["status"] for r in warc.audit(frame(a), frame(b)).collect()}
    assert got == want and set(want.values()) == {"altered", "moved", "missing", "extra"}
    assert warc.audit(frame(a), frame(a)).count() == 0
    assert warc.audit(frame([]), frame([])).count() == 0
    assert warc.audit(frame(a[:3]), frame([])).count() == 3


def _laid(pages, per_file=10):
    text = warc.record(warc.page_key(), F.col("url"), F.col("html"))
    told = pages.select("page_id", "html", text.alias("record"), F.octet_length(text).cast("bigint").alias("length"), warc.record_id(warc.page_key(), F.sha2(text, 256)).alias("rid"))
    return warc.lay_out(told.withColumn("file", warc.file_of(F.col("rid"), told.count(), per_file)))


def test_archive_round_trip(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet").limit(30).union(spark.createDataFrame([(None, None, None)], "page_id bigint, url string, html string"))
    laid = _laid(pages)
    files = warc.archive_bytes(laid).select(F.col("file").cast("string").alias("path"), "content")
    back = {(int(r["path"]), r["offset"]): r for r in warc.read_records(files).collect()}
    want = {(r["file"], r["offset"]): r for r in laid.collect()}
    assert set(back) == set(want)
    assert all(back[k]["length"] == want[k]["length"] and back[k]["content"].decode() == (want[k]["html"] or "") for k in want)


def test_audit_of_files(spark, sf):
    """A byte of a file is changed: one record of it is altered."""
    files = [(f"primary/{r['file']}.warc", bytes(r["content"])) for r in warc.archive_bytes(_laid(spark.read.parquet(f"{sf}/pages.parquet").limit(40))).collect()]
    frame = lambda rows: spark.createDataFrame(rows, "path string, content binary")
    copy = [(p.replace("primary", "replica"), c) for p, c in files]
    assert warc.audit_files(frame(files), frame(copy)).count() == 0
    at = copy[0][1].index(b"<body") + 2
    copy[0] = (copy[0][0], copy[0][1][:at] + b"#" + copy[0][1][at + 1 :])
    rows = warc.audit_files(frame(files), frame(copy)).collect()
    assert [r["status"] for r in rows] == ["altered"]


def test_pages_of_odd_rows(spark, tmp_path):
    """Null ids, urls and texts; repeated pages are one record with copies; one id with several contents."""
    rows = [(1, "u", "a"), (1, "u", "a"), (1, "u", "b"), (None, None, None), (None, None, None), (None, "v", "x" * 200_000), (2, None, "")]
    spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("rid", F.lit("clash")).write.parquet(f"{tmp_path}/pages.parquet")
    got = warc.query(spark, str(tmp_path)).filter("status <> 'extra'").collect()
    assert sorted(r["copies"] for r in got) == [1, 1, 1, 2, 2]
    spark.createDataFrame([], "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/none/pages.parquet")
    assert warc.query(spark, f"{tmp_path}/none").count() == 0


def test_mixing_keeps_texts_without_words(spark):
    rows = [(1, "a", "one two three"), (2, "a", ""), (3, "b", None), (4, "b", " \t\n"), (5, "empty", ""), (6, "b", "four five")]
    docs = spark.createDataFrame(rows, "doc_id bigint, source string, text string")
    mixed = mixing.mix(docs, weight=mixing.tempered_weight(0.8), share=None).collect()
    assert {tuple(r) for r in mixed} >= set(rows)
    assert [sum(r["doc_id"] == k for r in mixed) for k in (2, 3, 4, 5)] == [1, 1, 1, 1]


def test_names_of_the_callers_columns_stay(spark):
    """Columns named like inner ones pass through with their values."""
    names = ["_key", "_bucket", "_first", "_crc", "_source", "_rows", "_range", "_at", "_hash", "_of", "_lines", "_covered", "n", "copy"]
    docs = spark.createDataFrame([(k, f"w{k} x\ny\nz", "s") for k in range(12)], "doc_id bigint, text string, source string")
    docs = docs.select("*", *(F.lit(f"kept {n}").alias(n) for n in names))
    for out in (sharding.assign_shards(docs), mixing.take_words(docs, mixing.word_count(F.col("text"))), mixing.mix(docs), line_dedup.drop_repeated_windows(docs)):
        assert set(docs.columns) <= set(out.columns)
        rows = out.collect()
        assert rows and all(r[n] == f"kept {n}" for r in rows for n in names)


def test_one_id_or_none_for_most_rows(spark):
    """Rows of one id, or of none, are spread over buckets and ranges by their texts."""
    rows = [(None if k % 2 else 7, f"text {k} " + "w " * (k % 50), "s") for k in range(4000)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    slots = sharding.assign_shards(docs, (1.0,)).select("slot").collect()
    assert sorted(r["slot"] for r in slots) == list(range(4000))
    taken = mixing.take_words(docs, mixing.word_count(F.col("text")), spare=F.md5("text")).collect()
    assert sum(r["taken"] for r in taken) == sum(r["size"] for r in taken) == taken[0]["target"]


def test_very_long_texts(spark):
    long = "\n".join(f"line {k} of many" for k in range(60_000))
    docs = spark.createDataFrame([(1, long, "s"), (2, long, "s"), (3, "word " * 300_000, "t")], "doc_id bigint, text string, source string")
    lines = {r["doc_id"]: (r["n_lines"], r["n_removed"]) for r in line_dedup.drop_repeated_windows(docs).collect()}
    assert lines == {1: (60_000, 0), 2: (60_000, 60_000), 3: (1, 0)}
    words = Counter()
    for r in mixing.mix(docs).collect():
        words[r["source"]] += len(r["text"].split())
    total = 2 * 240_000 + 300_000
    assert sum(words.values()) == total and abs(words["s"] - total / 3) <= 1


def test_audit_over_many_files(spark, sf, monkeypatch):
    """The query on files of five records equals its SQL on such files."""
    monkeypatch.setattr(warc, "PER_FILE", 5)
    same(spark, sf, warc.query, warc.ORACLE.replace("1000.0", "5.0"))
    rows = warc.query(spark, sf).groupBy("status").count().collect()
    counts = {r["status"]: r["count"] for r in rows}
    assert counts["intact"] > 10 and counts.get("extra", 0) <= 2
