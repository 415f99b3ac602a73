import math
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from langspan.llm import quality, similarity_join
from tests.llm.test_pairs_and_leaks import _corpus, brute_components

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def _docs(spark, rows):
    """(id, text) or (id, text, source) as documents."""
    full = [(r[0], r[1], "en", r[2] if len(r) > 2 else "s", None if r[1] is None else len(r[1])) for r in rows]
    return spark.createDataFrame(full, DOCS)


def _texts(df):
    return Counter((r["doc_id"], r["text"]) for r in df.collect())


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Small tables with every odd row, and columns that clash with inner names."""
    root = tmp_path_factory.mktemp("tables")
    rng = random.Random(21)
    word = lambda: "".join(rng.choices("abcdefghijkl", k=rng.randint(3, 8)))
    good = [" ".join(word() for _ in range(rng.randint(30, 120))) for _ in range(60)]
    item = " ".join(word() for _ in range(30))
    bad = [" ".join(["$$$ buy!!", *(word() for _ in range(20)), "$$$ ### !!!"] * 3) for _ in range(40)]
    rows = [(k, t, f"s{k % 3}") for k, t in enumerate(good)]
    rows += [(100 + k, t, "junk") for k, t in enumerate(bad)]
    rows += [(200, good[0], "s0"), (0, good[0], "s0"), (1, good[2], "s1"), (201, good[3] + " " + item, "s2"), (202, None, "s0"), (203, "", None), (None, good[5], "s1"), (None, " ".join([*good[9].split()[:-1], "x"]), None)]
    rows += [(204, " ".join(word() for _ in range(40_000)), "s1")]
    docs = _docs(spark, rows)
    docs.write.parquet(f"{root}/documents.parquet")
    labels = [(k, 1, 0) for k in range(60)] + [(100 + k, 0, 0) for k in range(40)]
    spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int").write.parquet(f"{root}/labels.parquet")
    spark.createDataFrame([(1, item), (2, None), (3, "too short")], "item_id bigint, text string").write.parquet(f"{root}/benchmark.parquet")
    return str(root), rows, item


def test_stages_are_named_in_order():
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "decontamination", "mixing", "sharding"]


def test_run_is_its_stages(spark, folder):
    """Each stage on what the one before left, held against brute force."""
    sf, rows, item = folder
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = corpus_pipeline.keep_good(spark, docs, sf)
    assert kept.columns == docs.columns
    judged = quality.assess(docs, spark.read.parquet(f"{sf}/labels.parquet"), *quality.document_sites()).filter("keep")
    assert Counter(r["doc_id"] for r in kept.collect()) == Counter(r["doc_id"] for r in judged.collect())
    left = Counter((i, t) for i, t, *_ in rows if not 100 <= (i or 0) < 140)
    assert _texts(kept.filter("doc_id IS NULL OR doc_id NOT IN (202, 203)")) == left - Counter([(202, None), (203, "")])
    kept = _docs(spark, [(i, t, s) for i, t, s in rows if not 100 <= (i or 0) < 140])  # with the texts without words
    single = corpus_pipeline.keep_one_of_each(spark, kept, sf)
    want = left - Counter([(200, rows[0][1]), (0, rows[0][1]), (2, rows[2][1]), (None, rows[5][1]), (None, next(t for i, t, _ in rows if i is None and t.endswith(" x")))])
    assert _texts(single) == want and single.columns == docs.columns
    clean = corpus_pipeline.keep_unleaked(spark, single, sf)
    want = Counter({k: n for k, n in want.items() if item not in (k[1] or "")})
    assert _texts(clean) == want and clean.columns == docs.columns
    mixed = corpus_pipeline.mix_sources(spark, clean, sf)
    assert mixed.columns == docs.columns and set(want) <= set(_texts(mixed))
    shards = corpus_pipeline.shard(spark, mixed, sf).collect()
    assert len(shards) == mixed.count()
    for s in range(8):
        slots = [r["slot"] for r in shards if r["shard"] == s]
        assert sorted(slots) == list(range(len(slots)))


def test_run_on_odd_and_empty_tables(spark, folder, tmp_path):
    sf, rows, _ = folder
    whole = corpus_pipeline.run(spark, sf)
    assert whole.columns == [*DOCS.replace(" bigint", "").replace(" string", "").split(", "), "shard", "slot"] and whole.count() > 50
    for name, frame in (("documents", _docs(spark, [])), ("labels", spark.createDataFrame([], "doc_id bigint, quality int, toxic int")), ("benchmark", spark.createDataFrame([], "item_id bigint, text string"))):
        frame.write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_survivors_are_rows(spark):
    """Repeated ids: a row goes for its own text's partner alone; of equal rows one stays."""
    t, u = "a b c d e f g h", "i j k l m n o p"
    one = lambda rows: _texts(similarity_join.one_of_each(_docs(spark, rows)))
    assert one([(3, t), (5, t), (5, u)]) == Counter([(3, t), (5, u)])
    assert one([(5, t), (5, t)]) == Counter([(5, t)])
    assert one([(5, t), (5, t), (6, t), (None, t), (None, u), (None, u)]) == Counter([(5, t), (None, u)])
    assert one([(1, ""), (1, ""), (2, None), (None, " ")]) == Counter([(1, ""), (1, ""), (2, None), (None, " ")])
    clash = _docs(spark, [(3, t), (5, t), (5, u), (3, t)]).withColumn("_id", F.lit(1)).withColumn("_hash", F.lit(2)).withColumn("root", F.lit(3))
    found = similarity_join.one_of_each(clash)
    assert found.columns == clash.columns and _texts(found) == Counter([(3, t), (5, u)])


def test_survivors_equal_brute_force(spark):
    rng = random.Random(5)
    rows = [(rng.choice([i, i % 17]), t) for i, t in _corpus(11)]
    keyed = list(enumerate(rows))
    groups = brute_components([(k, t) for k, (_, t) in keyed], similarity_join.Rule())
    want = 0
    by = {}
    for k, (i, t) in keyed:
        by.setdefault(groups[k][1], []).append((i, t))
    got = _texts(similarity_join.one_of_each(_docs(spark, rows)))
    for members in by.values():
        least = min(i for i, _ in members)
        stays = [m for m in got if m in members and m[0] == least]
        assert stays or not (members[0][1] or "").split(), members
        want += 1
    assert sum(got.values()) == want


def test_a_shingle_that_everyone_has(spark, monkeypatch):
    """Heavy shingles go by broadcast: the same components with and without them."""
    rng = random.Random(6)
    words = [f"w{k}" for k in range(200)]
    rows = [(k, "the same five opening words " + " ".join(rng.choices(words, k=rng.randint(6, 30)))) for k in range(150)]
    rows += [(1000 + k, t + " tail") for k, t in rows[:40]] + [(2000 + k, "the same five opening words") for k in range(30)]
    want = brute_components(rows, similarity_join.Rule())
    monkeypatch.setattr(similarity_join, "MEMBERS", 20)
    monkeypatch.setattr(similarity_join, "SAMPLED", 2)
    monkeypatch.setattr(similarity_join, "BLOCK_SHINGLES", 64)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in similarity_join.cluster(_docs(spark, rows)).collect()}
    assert got == want and math.isfinite(len(got))
