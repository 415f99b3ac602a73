import random
import re
import time
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from langspan import session
from langspan.llm import components, decontamination, similarity_join
from langspan.llm.similarity_join import Rule

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def _set(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def brute_components(rows, rule):
    sets, parent = [(i, _set(t, rule.words)) for i, t in rows], {i: i for i, _ in rows}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for x in range(len(sets)):
        for y in range(x):
            (i, a), (j, b) = sets[x], sets[y]
            if a and b and rule.den * len(a & b) >= rule.num * len(a | b):
                i, j = find(i), find(j)
                parent[max(i, j)] = min(i, j)
    return {i: (len(s), find(i)) for i, s in sets}


def _corpus(seed):
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(300)]
    texts = [" ".join(rng.choices(vocabulary, k=rng.randint(3, 90))) for _ in range(30)]
    for base in texts[:8]:
        for _ in range(6):  # near copies of all degrees
            w = base.split()
            for _ in range(rng.randint(0, 4)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            texts.append(" ".join(w).upper() if rng.random() < 0.3 else "  ".join(w))
    long = " ".join(rng.choices(vocabulary, k=5000))
    return list(enumerate([*texts, "", "   ", "one", "one", "one two", long, long + " tail"], 10))


@pytest.mark.parametrize("rule", [similarity_join.CONTRACT, Rule()])
def test_components_equal_brute_force(spark, rule):
    rows = _corpus(4)
    docs = spark.createDataFrame([*rows], "doc_id bigint, text string").withColumn("node", F.lit("clash"))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in similarity_join.cluster(docs, rule).collect()}
    assert got == brute_components(rows, rule)


def test_join_takes_nulls_and_empty_tables(spark):
    docs = spark.createDataFrame([(1, None), (None, "a b c d e f"), (2, "a b c d e f"), (2, "a b c d e f")], "doc_id bigint, text string")
    rows = sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in similarity_join.cluster(docs).collect()), key=str)
    assert rows == sorted([(1, 0, 1), (None, 2, 2), (2, 2, 2), (2, 2, 2)], key=str)
    assert similarity_join.cluster(docs.limit(0)).count() == 0


def test_one_of_each(spark):
    rows = _corpus(9)
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    kept = {r["doc_id"] for r in similarity_join.one_of_each(docs).collect()}
    assert kept == {i for i, (_, c) in brute_components(rows, Rule()).items() if i == c}


def test_stars_find_long_chains(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(60)] + [(100, 101), (101, 100), (7, 7)], "a bigint, b bigint")
    roots = {r["node"]: r["root"] for r in components.components(edges).collect()}
    assert roots == {**{k: 0 for k in range(61)}, 100: 100, 101: 100}
    assert components.components(edges.limit(0)).count() == 0


def test_shuffle_files_go_with_their_query(spark):
    """They do not pile up until the driver needs memory; the kept rows and the session's settings stay."""
    blocks = spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager()
    shuffles = lambda: {f.name.split("_")[1] for d in blocks.localDirs() for f in Path(d.getPath()).rglob("shuffle_*.data")}
    before, set_to = shuffles(), spark.conf.get(session.CLEANED)
    counted = spark.range(1000).repartition(3).groupBy((F.col("id") % 7).alias("a")).agg(F.min("id").alias("b"))
    kept = session.durable(counted)
    for _ in range(40):  # files go a moment later
        if left := shuffles() - before:
            time.sleep(0.1)
    assert not left and spark.conf.get(session.CLEANED) == set_to
    assert sorted(map(tuple, kept.collect())) == [(k, k) for k in range(7)] == sorted(map(tuple, counted.collect()))


def _leak_rows(spark, docs, items):
    found = decontamination.find_leaks(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string"))
    return {(r["doc_id"], r["item_id"]): r for r in found.collect()}


def test_leaks(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choices("abcdefgh", k=5))
    items = [(k, " ".join(word() for _ in range(rng.randint(20, 50)))) for k in range(12)] + [(90, "too short"), (91, None)]
    docs = []
    for k in range(40):
        own = [word() for _ in range(200)]
        text = items[k % 12][1].split()
        if k < 12:
            own[50:50] = text
        elif k < 24:
            text[len(text) // 2] = "changed"
            own[0:0] = [w.upper() + "%%%" for w in text] if k % 2 else text
        docs.append((k, " ".join(own)))
    docs += [(100, None), (101, ""), (102, items[3][1]), (103, items[3][1][: len(items[3][1]) // 2])]
    got = _leak_rows(spark, docs, items)
    assert all((k, k) in got and got[k, k]["similarity"] == 1 and got[k, k]["first_word"] == 50 and got[k, k]["distance"] == 0 for k in range(12))
    texts = dict(items)

    def brute(doc, item):
        a, b = doc.lower().replace("%", " ").split(), texts[item].split()
        grams = lambda w: [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        best = 0
        for s in range(max(1, len(a) - len(b) + 1)):
            x, y = set(grams(a[s : s + len(b)])), set(grams(b))
            best = max(best, len(x & y) / max(1, len(x | y)))
        return best

    for k, text in docs:
        for item in range(12):
            assert ((k, item) in got) == (bool(text) and brute(text, item) >= 0.8), (k, item)
    docs_df = spark.createDataFrame(docs, "doc_id bigint, text string")
    left = {r["doc_id"] for r in decontamination.drop_leaking(docs_df, spark.createDataFrame(items, "item_id bigint, text string")).collect()}
    assert left == {k for k, _ in docs} - {k for k, _ in got}
    assert _leak_rows(spark, docs[:2], items[-2:]) == {}


def test_every_near_window_is_a_candidate():
    """What the index misses is beyond the radius; windows at the threshold are within it nearly always."""
    rng = random.Random(8)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    missed = 0
    for trial in range(300):
        text = [word() for _ in range(rng.randint(30, 60))]
        items = decontamination.Items([trial], [" ".join(text)])
        text[rng.choice([0, 1, len(text) - 1])] = word()
        missed += not list(items.within(np_print(items, text), len(text)))
    assert missed <= 1


def test_leaks_do_not_depend_on_the_blocks(spark, monkeypatch):
    """2,001 items make two blocks, the last one of a single item; weights are those of the whole benchmark."""
    rng = random.Random(12)
    some = lambda n: ["".join(rng.choices("abcdefghij", k=7)) for _ in range(n)]
    often, seldom = some(25), some(12)
    items = [(k, " ".join(some(8) + (often if k % 2 else seldom if k % 100 == 0 else []) + some(8))) for k in range(2000)] + [(2000, " ".join(often + some(40)))]
    last, first = items[2000][1].split(), items[101][1].split()
    docs = [(0, " ".join(last)), (1, " ".join([*last[:12], "changed", *last[13:]])), (2, " ".join(seldom[-7:] + last[7:])), (3, " ".join([*last[:45], "changed", *last[46:]])), (4, " ".join([*first[:20], "changed", *first[21:]]))]
    blocked = _leak_rows(spark, docs, items)
    monkeypatch.setattr(decontamination, "ITEMS", 5000)
    assert blocked == _leak_rows(spark, docs, items)
    assert {(0, 2000), (1, 2000), (2, 2000)} <= set(blocked) and blocked[1, 2000]["similarity"] > 56 / 66  # what the often seen shingles weigh is little
    monkeypatch.setattr(decontamination, "ITEMS", 70)
    kept = decontamination.drop_leaking(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items[1900:], "item_id bigint, text string"))
    assert {r["doc_id"] for r in kept.collect()} & {0, 1, 2} == set()


def test_items_that_are_nearly_all_shared():
    """62 shingles that all of 200 items have and one rare one on each side: similar by weight, and candidates."""
    rng = random.Random(14)
    word = lambda: "".join(rng.choices("abcdefghij", k=7))
    missed = 0
    for _ in range(60):
        common = [word() for _ in range(66)]
        texts = [" ".join([word(), *common]) for _ in range(200)]
        items = decontamination.Items(list(range(200)), texts)
        window = [word(), *common]
        _, hashes, _ = next(decontamination._hashes(__import__("pyarrow").array([" ".join(window)])))
        assert items.similarity(decontamination.kernels.shingles(hashes, decontamination.WORDS), 0) >= decontamination.THRESHOLD
        missed += not any(i == 0 for _, i, _ in items.within(np_print(items, window), len(window)))
    assert missed <= 1


def test_windows_around_hits_equal_brute_force():
    rng = random.Random(15)
    words = "abcdefgh"
    items = decontamination.Items([1, 2, 3], [" ".join(rng.choices(words, k=k)) for k in (6, 9, 9)])
    for n in (5, 6, 7, 20, 60):
        import pyarrow as pa

        _, hashes, _ = next(decontamination._hashes(pa.array([" ".join(rng.choices(words, k=n))])))
        shingles = decontamination.kernels.shingles(hashes, decontamination.WORDS)
        known = items.find(shingles)
        hits = [p for p, k in enumerate(known.tolist()) if k >= 0]
        want = {}
        for p in hits:
            for i in items.holders[items.first_holder[known[p]] : items.first_holder[known[p] + 1]].tolist():
                size, total = int(items.sizes[i]), len(hashes)
                want.setdefault(size, set()).update(range(max(0, p - size + decontamination.WORDS), min(p, max(0, total - size)) + 1))
        import numpy as np

        got = {size: set(s.tolist()) for size, s in items.starts(np.array(hits, np.int64), known[hits], len(hashes))}
        assert got == {k: v for k, v in want.items() if v}


def test_long_text_that_repeats_a_common_passage(spark):
    """In linear time, and with clashing column names."""
    rng = random.Random(16)
    item = ["".join(rng.choices("abcdefgh", k=5)) for _ in range(30)]
    docs = spark.createDataFrame([(1, " ".join(item[:12] * 5000)), (2, " ".join(item * 300)), (3, None)], "doc_id bigint, text string")
    docs = docs.selectExpr("doc_id", "text", "'x' AS keep", "'y' AS item_id", "'z' AS row", "'w' AS similarity")
    benchmark = spark.createDataFrame([(1, " ".join(item)), (None, "one two three four five six")], "item_id bigint, text string")
    left = decontamination.drop_leaking(docs, benchmark)
    assert left.columns == docs.columns and {r["doc_id"] for r in left.collect()} == {1, 3}
    assert decontamination.find_leaks(docs, benchmark).filter("doc_id = 2").count() == 1  # one run of overlapping windows
    assert decontamination.drop_leaking(docs.limit(0), benchmark).count() == 0


def np_print(items, text):
    import pyarrow as pa

    _, hashes, _ = next(decontamination._hashes(pa.array([" ".join(text)])))
    s = decontamination.kernels.shingles(hashes, decontamination.WORDS)
    return decontamination._fingerprint(decontamination._pull(s, items.weight).sum(axis=0)[None])
