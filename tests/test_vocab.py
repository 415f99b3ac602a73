import pytest
from pyspark.sql import functions as F

from langspan.functions import sqlapi
from langspan.operators import lid, vocab
from langspan.operators.vocab import RangeVocab

TWO = RangeVocab.allocate([("en", 1024), ("es", 1024)])


def test_worked_ranges(spark):
    assert TWO.entries == (("en", 0, 1024), ("es", 1024, 1024)) and TWO.total == 2048
    ids = spark.createDataFrame([(i,) for i in (0, 1023, 1024, 2047, 2048, -1, None)], "id int")
    assert [r[0] for r in ids.select(TWO.lang_of(F.col("id"))).collect()] == ["en", "en", "es", "es", None, None, None]


def test_ranges_reject_overlap_and_repeats():
    with pytest.raises(ValueError):
        RangeVocab((("en", 0, 10), ("es", 9, 10)))
    with pytest.raises(ValueError):
        RangeVocab((("en", 0, 10), ("en", 10, 10)))


def test_unequal_extension_and_removal():
    v = RangeVocab.allocate([("a", 13), ("b", 25)]).extend("c", 7)
    assert v.range("c") == (38, 7)
    hole, moves = v.drop("a")
    assert hole.range("b") == (13, 25) and not moves
    packed, moves = v.drop("a", repack=True)
    assert packed.entries == (("b", 0, 25), ("c", 25, 7)) and moves == [(13, 38, -13), (38, 45, -13)]


def test_encoding_round_trip_keeps_languages(spark):
    texts = spark.createDataFrame([(1, "en", "The no, the!"), (2, "es", "no La la?"), (3, "en", "")], "id long, lang string, text string")
    toks = vocab.train_word(texts, 8)
    v = RangeVocab.allocate([("en", 8), ("es", 8)])
    long = vocab.tokens_long(texts, toks, v, "id")
    ids = {r["id"]: r["token_ids"] for r in vocab.encode(texts, toks, v, "id").collect()}
    assert set(ids) == {1, 2} and all(t < 8 for t in ids[1]) and all(t >= 8 for t in ids[2])
    want = {1: "the no the", 2: "no la la"}
    assert {r["id"]: r["text"] for r in vocab.decode_long(long, toks, v, "id").collect()} == want
    assert {r["id"]: r["text"] for r in vocab.decode(vocab.encode(texts, toks, v, "id"), toks, v, "id").collect()} == want


def test_encoding_in_the_row_equals_the_join(spark):
    """Pieces with quotes and backslashes, unknown words, nulls, languages outside the vocabulary, repeated rows, long texts."""
    pieces = [("en", 1, "a"), ("en", 2, "b"), ("en", 3, "it's"), ("en", 4, "\\n"), ("es", 1, "a"), ("es", 2, "ñu"), ("it", 1, "a")]
    toks = spark.createDataFrame(pieces, "lang string, local_id int, piece string")
    v = RangeVocab.allocate([("en", 8), ("es", 8)])
    rows = [(1, "en", "A b c"), (2, "es", "ñu b A"), (3, "it", "a b"), (4, None, "a"), (5, "en", None), (6, "es", ""), (7, "en", "b a zz " * 5000), (8, "en", "b"), (8, "en", "b")]
    texts = spark.createDataFrame(rows, "id long, lang string, text string")
    got = sorted((r["id"], r["token_ids"]) for r in vocab.encode(texts, toks, v, "id").collect())
    assert got == [(1, [1, 2, 0]), (2, [10, 8, 9]), (7, [2, 1, 0] * 5000), (8, [2]), (8, [2])]
    joined = vocab.tokens_long(texts.filter("id <> 8 AND lang IN ('en', 'es')"), toks, v, "id")
    assert {(r["id"], r["pos"], r["token_id"]) for r in joined.collect()} == {(k, i, t) for k, ids in got if k != 8 for i, t in enumerate(ids)}
    ids = spark.createDataFrame([(1, [3, 4, 10, 0, 7, 99, -1, None]), (2, []), (3, None)], "id long, token_ids array<int>")
    assert {r["id"]: r["text"] for r in vocab.decode(ids, toks, v, "id").collect()} == {1: "it's \\n ñu <unk> <unk> <unk> <unk> <unk>", 2: "", 3: None}
    samples = spark.createDataFrame([(1, [(1, "es", "A x"), (0, "en", "b a")]), (2, [(0, "it", "a")]), (3, None)], "sample_id long, segments array<struct<slot int, lang string, text string>>")
    assert {r["sample_id"]: r["token_ids"] for r in vocab.encode_segments(samples, toks, v).collect()} == {1: [2, 1, 9, 8]}
    assert vocab.encode(texts.limit(0), toks.limit(0), v, "id").collect() == []
    with pytest.raises(ValueError):
        vocab.encode(texts, toks, RangeVocab.allocate([("en", 1 << 17)]), "id")


@pytest.mark.parametrize("ids,lang", [([], None), ([5], "en"), ([5, 1030], "en"), ([1030, 1031, 5], "es"), ([2048], None)])
def test_votes_and_ties(spark, ids, lang):
    row = spark.createDataFrame([(1, ids)], "k long, ids array<int>")
    assert row.select(lid.vote_in_row(F.col("ids"), TWO)).first()[0] == lang
    long = row.select("k", F.posexplode("ids").alias("pos", "token_id"))
    found = lid.utterance_lid(long, TWO, "k").collect()
    assert (found[0]["pred_lang"] if found else None) == lang


def test_spans_in_row_equal_long_form_and_table_function(spark):
    sqlapi.register(spark, TWO)
    ids = [1, 2, 1500, 3, 3, 2000, 2001]
    row = spark.createDataFrame([(1, ids)], "k long, ids array<int>")
    array = [(s["lang"], s["first_pos"]) for s in row.select(lid.spans_in_row(F.col("ids"), TWO)).first()[0]]
    long = sorted((r["span"], r["lang"], r["first_pos"]) for r in lid.language_spans(row.select("k", F.posexplode("ids").alias("pos", "token_id")), TWO, "k").collect())
    table = spark.sql(f"SELECT * FROM spans(array({', '.join(map(str, ids))}))").collect()
    assert array == [x[1:] for x in long] == [(r["lang"], r["first_pos"]) for r in table] == [("en", 0), ("es", 2), ("en", 3), ("es", 5)]
    assert spark.sql("SELECT lang_of(1024), shift_id('es', 3)").first()[:] == ("es", 1027)


def test_tags_carry_the_spans(spark):
    long = spark.createDataFrame([(1, p, t) for p, t in enumerate([1, 2, 1500, 3])], "k long, pos int, token_id int")
    tagged = vocab.inject_tags(long, TWO, "k", "span")
    assert [r["token_id"] for r in tagged.orderBy("pos").collect()] == [2050, 1, 2, 2050, 2051, 1500, 2051, 2050, 3, 2050]
    assert [r["token_id"] for r in vocab.strip_tags(tagged, TWO, "k").orderBy("pos").collect()] == [1, 2, 1500, 3]
    assert vocab.lid_from_tags(tagged, TWO, "k").first()["lang"] == "en"


def test_language_predicate_reaches_the_scan(spark, tmp_path):
    spark.range(5000).select(F.col("id").cast("int").alias("token_id")).write.parquet(str(tmp_path / "t"))
    scan = spark.read.parquet(str(tmp_path / "t")).filter(TWO.lang_predicate(F.col("token_id"), ["es"]))
    assert "GreaterThanOrEqual(token_id,1024)" in scan._jdf.queryExecution().executedPlan().toString()
    assert scan.count() == 1024
