import itertools
import math
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from langspan.functions import text as T
from langspan.operators import lid, metrics, recognise, unigram
from langspan.plans import experiments, synth
from langspan.sources import tables
from langspan.queries import measures, studies, switched


def _wer(spark, ref, hyp):
    return metrics.wer(spark.createDataFrame([(ref, hyp)], "ref string, hyp string")).first()


def test_error_rate_cases(spark):
    assert _wer(spark, "a b c", "a b c")["errors"] == 0
    assert _wer(spark, "", "a b")[:] == (2, 0, None)
    assert _wer(spark, None, None)["errors"] == 0
    assert _wer(spark, "a b", "c d e f")["wer"] == 200
    ref = [f"{a}{b}" for a, b in itertools.product("abcdefghijklmnopqrst", "abcdefghijklmno")]
    assert _wer(spark, " ".join(ref), " ".join(ref[1:] + ["zzz"]))["errors"] == 2  # 300 different words
    said = [w for w in "one two three four five six seven eight nine ten eleven twelve".split()] + [w * 2 for w in "ab cd ef gh ij kl mn op qr st uv".split()]
    other = said[:3] + ["x", "y"] + said[5:10] + ["z", "q"] + said[12:22]
    found = _wer(spark, " ".join(said), " ".join(other))
    assert (len(said), len(other), found["errors"]) == (23, 22, 5) and found["wer"] == pytest.approx(21.73913)


def test_distance_equals_alignment(spark):
    rng = random.Random(5)
    rows = [(k, " ".join(rng.choices("abc", k=rng.randint(0, 8))), " ".join(rng.choices("abcd", k=rng.randint(0, 8)))) for k in range(60)]
    pairs = spark.createDataFrame(rows, "k long, ref string, hyp string")
    ops = {r["k"]: r["substitutions"] + r["deletions"] + r["insertions"] for r in metrics.edit_ops(pairs, "k").collect()}
    assert ops == {r["k"]: r["e"] for r in pairs.select("k", metrics.word_errors(F.col("ref"), F.col("hyp")).alias("e")).collect()}


def test_boundaries_and_switch_costs(spark):
    a = spark.createDataFrame([(1, 1, 0), (1, 2, 4), (1, 3, 7)], "k long, span long, first_pos long")
    b = spark.createDataFrame([(1, 1, 0), (1, 2, 4)], "k long, span long, first_pos long")
    assert metrics.boundary_f1(a, b, "k").first()[:] == (0.5, 1.0, pytest.approx(0.666667))


def _segmentations(word):
    if not word:
        yield []
    for k in range(1, len(word) + 1):
        for rest in _segmentations(word[k:]):
            yield [word[:k], *rest]


def test_unigram_lattice_equals_enumeration():
    rng = random.Random(1)
    pieces = {"".join(p): -rng.random() * 5 - 0.1 for n in (1, 2, 3) for p in itertools.product("ab", repeat=n)}
    for word in ("a", "abba", "bababab", "aabbaabb"):
        scored = [(sum(pieces[p] for p in s), s) for s in _segmentations(word) if all(p in pieces for p in s)]
        best, path = unigram.viterbi(word, pieces, 3)
        assert best == pytest.approx(max(s for s, _ in scored)) and "".join(path) == word
        total = math.log(sum(math.exp(s) for s, _ in scored))
        likely, counts = unigram.expected(word, pieces, 3)
        assert likely == pytest.approx(total)
        for p in counts:
            assert counts[p] == pytest.approx(sum(math.exp(s - total) * x.count(p) for s, x in scored), abs=1e-6)


def test_unigram_training(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").filter("lang IN ('en', 'es')")
    log = []
    toks = unigram.train_unigram(docs, size=200, seed_size=400, log=log)
    rows = toks.collect()
    by = {lang: [r for r in rows if r["lang"] == lang] for lang in ("en", "es")}
    assert all(len(v) == 200 and sorted(r["local_id"] for r in v) == list(range(200)) for v in by.values())
    for lang in by:
        mine = [(n, ll) for name, n, ll in log if name == lang]
        assert all(b[1] >= a[1] - 1e-6 * abs(a[1]) for a, b in zip(mine, mine[1:]) if a[0] >= b[0] > 0 and a[0] - b[0] < 5)
    texts = spark.createDataFrame([(1, "en", "the thing"), (2, "es", "de la")], "id long, lang string, text string")
    for r in unigram.encode_unigram(texts, toks, "id", {"en": 0, "es": 1024}).collect():
        assert "".join(r["pieces"]).replace(unigram.MARK, " ").strip() == {1: "the thing", 2: "de la"}[r["id"]]
        assert all((t >= 1024) == (r["lang"] == "es") for t in r["token_ids"])
    mixed = unigram.decode_mixed(texts, toks, "id", {"en": 0, "es": 1024}).collect()
    assert {r["id"]: r["token_ids"][0] >= 1024 for r in mixed} == {1: False, 2: True}


def test_unigram_training_ends_on_any_alphabet(spark):
    """More letters than ids: the rarest go."""
    letters = [chr(0x4E00 + k) for k in range(90)]
    monkey = [(k, "xx", " ".join("".join(letters[(k + j) % 90] for j in range(3)) for _ in range(4))) for k in range(90)]
    docs = spark.createDataFrame(monkey, "doc_id bigint, lang string, text string")
    latin = spark.createDataFrame([(1000 + k, "yy", " ".join(f"{a}{b}" for a in "abcdefghijklmn" for b in "opqrstuvwxyz")) for k in range(4)], docs.schema)
    toks = unigram.train_unigram(docs.union(latin), size=16, seed_size=40).collect()
    sizes = {lang: sum(r["lang"] == lang for r in toks) for lang in {r["lang"] for r in toks}}
    assert sizes and all(n <= 16 for n in sizes.values())


def test_lexicon_paths_equal_brute_force(spark):
    rng = random.Random(2)
    arcs = [(1, p, lang, rng.random() * 5) for p in range(5) for lang in ("a", "b", "c")]
    cost = {(p, lang): c for _, p, lang, c in arcs}
    best = min(sum(cost[p, lang] for p, lang in enumerate(path)) + 1.5 * sum(x != y for x, y in zip(path, path[1:])) for path in itertools.product("abc", repeat=5))
    got = recognise.lexicon_paths(spark.createDataFrame(arcs, "k long, pos int, lang string, cost double"), "k", ["a", "b", "c"], 1.5).first()
    assert got["cost"] == pytest.approx(best, abs=1e-5)


def test_recogniser_orderings(spark, sf):
    pool = T.utterances(spark.read.parquet(f"{sf}/documents.parquet")).filter("lang IN ('en', 'es')").dropDuplicates(["text"])
    rows = recognise.lexicon_rows(pool, 5000)
    rng = random.Random(3)
    by = {lang: [r["text"] for r in pool.filter(F.col("lang") == lang).orderBy("utt_id").limit(40).collect()] for lang in ("en", "es")}
    texts = [(k, f"{rng.choice(by['en'])} {rng.choice(by['es'])}") for k in range(40)]
    models = [recognise.Recogniser("mono_en", "mono", ("en",)), recognise.Recogniser("ml", "con", ("en", "es")), recognise.Recogniser("cs", "con", ("en", "es"), 3.0), recognise.Recogniser("cs", "agg", ("en", "es"), 3.0)]
    heard = recognise.recognise(spark.createDataFrame(texts, "k long, text string"), models, rows, "k").cache()
    rate = {(r["model"], r["tokenizer"]): r["wer"] for r in metrics.wer(heard, ["model", "tokenizer"]).collect()}
    assert rate["cs", "con"] < rate["ml", "con"] and rate["cs", "con"] < rate["mono_en", "mono"]
    assert abs(rate["cs", "con"] - rate["cs", "agg"]) < 5
    assert heard.filter("model = 'ml'").filter(F.size(F.array_distinct("langs")) > 1).count() == 0


def test_word_vote(spark):
    docs = spark.createDataFrame([(1, "en", "the the of"), (2, "es", "la de la")], "doc_id long, lang string, text string")
    model = lid.train_word_vote(docs)
    found = lid.word_vote_lid(spark.createDataFrame([(1, "the la la"), (2, "of")], "k long, text string"), model, "k").collect()
    assert {r["k"]: r["pred"] for r in found} == {1: "es", 2: "en"}


def test_alignments_of_many_equal_those_of_one(monkeypatch):
    rng = random.Random(21)
    draw = lambda: rng.choices("abcd", k=rng.choice([0, 0, 1, 2, 5, 9, 30]))
    refs, hyps = zip(*((draw(), draw()) for _ in range(400)), strict=True)
    want = [metrics.align(r, h) for r, h in zip(refs, hyps, strict=True)]
    for cells in (metrics.CELLS, 3000, 1):
        monkeypatch.setattr(metrics, "CELLS", cells)
        assert list(map(tuple, metrics.align_all(refs, hyps).tolist())) == want
    assert metrics.align_all([], []).shape == (0, 3)


def test_error_rates_take_every_utterance(spark, sf):
    """Brute force over all utterances: long ones, those with letters beyond a-z, and all splits."""
    pairs = measures._pairs(spark, sf).select("lang", "ref", "hyp").collect()
    assert len(pairs) == measures.utts(spark, sf).count()
    assert any(len(r["ref"]) > 150 for r in pairs) and any(set(r["ref"]) & set("éñöü") for r in pairs)
    some = pairs[::7]
    words, chars = {}, {}
    for r in some:
        ops = metrics.align(r["ref"].split(), r["hyp"].split())
        words[r["lang"]] = [a + b for a, b in zip(words.get(r["lang"], [0] * 4), [*ops, len(r["ref"].split())], strict=True)]
    for r in pairs[::101]:
        e = sum(metrics.align(list(r["ref"]), list(r["hyp"])))
        chars[r["lang"]] = [a + b for a, b in zip(chars.get(r["lang"], [0, 0]), [e, len(r["ref"])], strict=True)]
    frame = lambda rows: spark.createDataFrame(rows, "lang string, ref string, hyp string")
    assert {r["lang"]: [r["errors"], r["ref_words"]] for r in metrics.wer(frame(some), ["lang"]).collect()} == {k: [sum(v[:3]), v[3]] for k, v in words.items()}
    assert {r["lang"]: [r["errors"], r["ref_chars"]] for r in metrics.cer(frame(pairs[::101]), ["lang"]).collect()} == chars
    wer = {r["grp"]: r for r in measures.wer_words(spark, sf).collect()}
    cer = {r["grp"]: r for r in measures.cer(spark, sf).collect()}
    ops = {r["lang"]: r for r in measures.edit_ops(spark, sf).collect()}
    for lang in {r["lang"] for r in pairs}:
        own = [r for r in pairs if r["lang"] == lang]
        assert wer[lang]["ref_words"] == sum(len(r["ref"].split()) for r in own) and cer[lang]["ref_chars"] == sum(len(r["ref"]) for r in own)
        assert ops[lang]["substitutions"] + ops[lang]["deletions"] + ops[lang]["insertions"] == wer[lang]["errors"]
        assert tuple(ops[lang])[1:] == tuple(map(sum, zip(*(metrics.align(r["ref"].split(), r["hyp"].split()) for r in own), strict=True)))


def test_studies_use_the_tokenizers_of_the_vocabulary(spark, sf, monkeypatch):
    asked = []
    train = unigram.train_unigram
    monkeypatch.setattr(unigram, "train_unigram", lambda docs, *a, **options: asked.append((a, options)) or train(docs, size=40, seed_size=60, rounds=1))
    for query in (studies.unigram_vocab, studies.unigram_encode, studies.decode_mixed_lid):
        query(spark, sf)
    assert asked == [((), {})] * 3  # the production parameters: 1,024 pieces, 3,000 seeds, two rounds


def test_pieces_across_switches(spark):
    """Pieces of a tokenizer over switched text may straddle switches, those of tokenizers by segment never do."""
    assert unigram.straddles([3, 5], ["▁ab", "▁c▁d"]) == 1 and unigram.straddles([1], ["<unk>", "b"]) == 0
    assert unigram.straddles([], []) == 0
    kind = "sample_id long, segments array<struct<slot int, lang string, text string>>"
    rows = [(k, [(1, "es", "la casa"), (0, "en", "red one")]) for k in range(30)] + [(98, []), (99, None), (97, [(0, "en", "red"), (1, "es", None), (2, "en", "one")])]
    samples = spark.createDataFrame(rows, kind)
    whole = samples.filter("sample_id < 30").select(F.lit("all").alias("lang"), F.lit("red one la casa").alias("text"))
    pairs = {r["piece"]: r["n"] for r in unigram.pair_counts(whole.union(spark.createDataFrame([("all", "one"), ("all", ""), ("all", None)], "lang string, text string"))).collect()}
    assert pairs == {"red▁one": 30, "one▁la": 30, "la▁casa": 30, "one": 1}
    pooled = unigram.train_unigram(whole, size=40, seed_size=60, across=True)
    assert any("▁" in r["piece"][1:] for r in pooled.collect())
    own = unigram.train_unigram(samples.select(F.explode("segments").alias("s")).select("s.lang", "s.text"), size=40, seed_size=60)
    assert not any("▁" in r["piece"][1:] for r in own.collect())
    by = {r["sample_id"]: r for r in unigram.encode_switched(samples, own).collect()}
    assert all(by[k]["n_straddled"] == 0 and by[k]["n_switches"] == 1 for k in range(30))
    assert [tuple(by[k])[1:] for k in (98, 99)] == [(0, 0, 0)] * 2 and by[97]["n_switches"] == 0
    forced = spark.createDataFrame([("all", 0, "<unk>", 0.0), ("all", 1, "e▁l", -0.1), ("all", 2, "<x>", -9.0)], "lang string, local_id int, piece string, score double")
    assert {r["n_straddled"] for r in unigram.encode_switched(samples.filter("sample_id < 30"), forced, "all").collect()} == {1}


def test_straddling_pieces_cleans_texts_once(spark, sf, monkeypatch):
    """They were cleaned for the plans and for the samples of either split."""
    made, train = [], unigram.train_unigram
    monkeypatch.setattr(T, "utterances", lambda docs, f=T.utterances: made.append(docs) or f(docs))
    monkeypatch.setattr(unigram, "train_unigram", lambda docs, across=False, **_: train(docs, size=40, seed_size=60, rounds=1, across=across))
    assert switched.straddling_pieces(spark, sf).count() == 3 and len(made) == 1


def test_pieces_of_many_texts_equal_those_of_one(monkeypatch):
    """Ties, letters that no piece covers, empty texts and cut-up tables among them."""
    rng = random.Random(12)
    for scores, longest in (([-1.0, -2.0, -3.0], 4), ([-0.3, -1.7, -25.0], 3)):
        pieces = {"".join(rng.choices("ab▁é", k=rng.randint(1, longest))): rng.choice(scores) for _ in range(40)}
        texts = ["".join(rng.choices("ab▁éz", k=rng.choice([0, 1, 2, 5, 40]))) for _ in range(300)]
        for cells in (unigram.CELLS, 90):
            monkeypatch.setattr(unigram, "CELLS", cells)
            for have, most in ((pieces, longest), ({}, 1)):
                got = {k: np.flatnonzero(row).tolist() for some, ends in unigram.piece_ends(texts, have, most) for k, row in zip(some, ends, strict=True)}
                for k, text in enumerate(texts):
                    path = unigram.viterbi(text, have, most)[1]
                    assert got[k] == list(itertools.accumulate(1 if p == unigram.UNK else len(p) for p in path))
    assert list(unigram.piece_ends([], {}, 1)) == []


def test_expected_counts_of_many_words_equal_those_of_one(monkeypatch):
    """Pieces that no word uses, words that the pieces can't make, repeats and cut-up tables among them."""
    rng = random.Random(21)
    for longest in (3, 5):
        pieces = {c: -3.0 for c in "ab▁é"} | {"".join(rng.choices("ab▁é", k=rng.randint(1, longest))): rng.choice([-1.0, -2.0, -25.0]) for _ in range(40)}
        words = ["".join(rng.choices("ab▁éz" if k % 5 == 0 else "ab▁é", k=rng.choice([1, 2, 5, 30]))) for k in range(200)]
        counts = np.array([rng.randint(1, 90) for _ in words])
        likelihood, share, cut = 0.0, dict.fromkeys(pieces, 0.0), dict.fromkeys(pieces, 0)
        for word, n in zip(words, counts.tolist(), strict=True):
            likely, found = unigram.expected(word, pieces, longest)
            if likely > -math.inf:
                likelihood += n * likely
                for piece, part in found.items():
                    share[piece] += n * part
                for piece in unigram.viterbi(word, pieces, longest)[1]:
                    cut[piece] += n
        for cells in (unigram.CELLS, 90):
            monkeypatch.setattr(unigram, "CELLS", cells)
            got = unigram.expected_of(words, counts, unigram.Spans(pieces, longest), True)
            assert got[0] == pytest.approx(likelihood) and got[1].tolist() == pytest.approx(list(share.values()), rel=1e-6, abs=1e-6)
            assert got[2].tolist() == list(cut.values())
        assert not unigram.expected_of(words, counts, unigram.Spans(pieces, longest), False)[2].any()
    assert unigram.expected_of(["ab"], np.array([3]), unigram.Spans({}, 1), True)[0] == 0.0


def test_training_uses_all_cores(spark):
    words = spark.createDataFrame([(k, "xx", f"w{chr(97 + k % 9)} v{chr(97 + k % 7)}") for k in range(60)], "doc_id bigint, lang string, text string").coalesce(1)
    counted = unigram.dealt_rows(unigram.durable(unigram.word_counts(words)))
    assert counted.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism and counted.count() == 16


def test_switch_probabilities_are_fitted(spark):
    """Starts come from fitting texts without switches; from each of them fitting ends at the same place."""
    lexicon = [("a", w, 9) for w in ("red", "green", "blue")] + [("b", w, 9) for w in ("uno", "dos", "tres")]
    drawn = spark.createDataFrame([(k, j, "ab"[j % 2], text) for k in range(20) for j, text in enumerate(("red green blue red", "uno dos tres", "green green"))], "sample_id long, slot int, lang string, text string")
    starts = experiments.fitted_starts(drawn, lexicon, ("a", "b"))
    assert starts["scratch"] is None and set(starts) == {"scratch", "mono:a", "mono:b", "ml"}
    assert starts["mono:a"] == pytest.approx(0.5 / (20 * 4 + 1)) and starts["mono:b"] == pytest.approx(0.5 / (20 * 2 + 1))
    assert starts["ml"] == pytest.approx(0.5 / (20 * 6 + 1))
    samples = experiments.joined(drawn)
    ends = {name: recognise.fit_switch(samples, lexicon, ("a", "b"), "sample_id", start) for name, start in starts.items()}
    assert all(p == pytest.approx(40.5 / (20 * 8 + 1)) for p, _ in ends.values())
    assert samples.first()["n_langs"] == 2 and all(r["text"] == "red green blue red uno dos tres green green" for r in samples.collect())


def test_dealing_out_a_small_table_keeps_its_rows(spark, sf, monkeypatch):
    monkeypatch.setattr(tables, "PART_BYTES", 1 << 60)
    whole = tables.read(spark, sf, "documents")
    monkeypatch.setattr(tables, "PART_BYTES", 1 << 10)
    dealt = tables.read(spark, sf, "documents")
    assert dealt.rdd.getNumPartitions() == spark.sparkContext.defaultParallelism
    assert sorted(map(tuple, dealt.collect())) == sorted(map(tuple, whole.collect()))
    same = [sorted(measures.wer_words(spark, sf).collect())]
    monkeypatch.setattr(tables, "DEALT_BYTES", 1)
    assert tables.read(spark, sf, "documents").rdd.getNumPartitions() == whole.rdd.getNumPartitions()
    assert [sorted(measures.wer_words(spark, sf).collect())] == same


def test_distances_of_long_texts(spark, monkeypatch):
    """Against Spark's; the distances of long texts are found in Python, once for models that make the same of a text."""
    rng = random.Random(5)
    pairs = [("".join(rng.choices("abcdĀ", k=rng.choice([0, 1, 2, 9, 63, 64, 65, 130]))), "".join(rng.choices("abcdĀ", k=rng.choice([0, 1, 3, 9, 64, 131])))) for _ in range(200)]
    pairs += [(a, a[: len(a) // 2] + "x" + a[len(a) // 2 + 1 :]) for a, _ in pairs] + [(a, a[1:] + "b") for a, _ in pairs]
    table = spark.createDataFrame(pairs, "a string, b string")
    assert all(recognise.distances(r["a"], [r["b"]]) == [r["d"]] for r in table.select("*", F.levenshtein("a", "b").alias("d")).collect())
    many = ["".join(rng.choices("abcdĀ", k=70)) for _ in range(6)] + ["a" * 70, "z" * 70]
    many += [many[0][:30] + "z" + many[0][31:]]
    assert all(recognise.distances(a, many) == [recognise.distances(a, [b])[0] for b in many] for a, _ in pairs[:40])
    asked = []
    monkeypatch.setattr(F, "levenshtein", lambda a, b, f=F.levenshtein: asked.append(b) or f(F.assert_true(F.length(a) < recognise.LONG).isNull().cast("string"), F.lit("true")) + f(a, b))
    texts = spark.createDataFrame([(0, " ".join(["red"] * 40 + ["blue"] * 80)), (1, "red blue")], "k long, text string")
    lexicon = [("a", "red", 9), ("b", "blue", 9)]
    models = [recognise.Recogniser("mono", "mono", ("a",)), recognise.Recogniser("never", "con", ("a", "b"))]
    got = {r["model"]: (r["errors"], r["ref_words"]) for r in recognise.error_rates(texts, models, lexicon, "k", noise=0.0).collect()}
    assert len(asked) == 2 and got == {"mono": (81, 122), "never": (41, 122)}


def test_error_rates_of_models_equal_those_of_their_words(spark, monkeypatch):
    """Against recognising, writing out and comparing word by word; empty, null, long and cut-up tables among them."""
    rng = random.Random(8)
    en, es = (["".join(rng.choices(letters, k=rng.randint(2, 7))) for _ in range(60)] for letters in ("abcdeé", "cdefgñ"))
    lexicon = [(lang, w, rng.randint(1, 50)) for lang, ws in (("en", en), ("es", es)) for w in dict.fromkeys(ws)]
    texts = [(k, "xy"[k % 2], " ".join(rng.choices(rng.choice([en, es, en + es, ["qqunknown", "zzzz", en[0]]]), k=rng.choice([0, 1, 2, 9, 30])))) for k in range(80)]
    texts += [(100, "x", None), (101, "x", " ".join(rng.choices(en + es, k=700))), (102, None, en[1])]
    table = spark.createDataFrame(texts, "k long, grp string, text string").repartition(3)
    langs = ("en", "es")
    models = [recognise.Recogniser("mono", "mono", ("es",)), *(recognise.Recogniser(f"m{c}", tok, langs, c) for c in (0.0, 2.5) for tok in ("agg", "con")), recognise.Recogniser("never", "con", langs)]
    heard = recognise.recognise(table, models, lexicon, "k", noise=0.2).join(table.select("k", "grp"), "k")
    want = sorted(map(str, metrics.wer(heard, ["grp", "model", "tokenizer"]).collect()))
    for cells, some in ((recognise.CELLS, recognise.SLICE), (64, 50)):
        monkeypatch.setattr(recognise, "CELLS", cells)
        monkeypatch.setattr(recognise, "SLICE", some)
        got = recognise.error_rates(table, models, lexicon, "k", ["grp"], noise=0.2).select("grp", "model", "tokenizer", "errors", "ref_words", "wer")
        assert sorted(map(str, got.collect())) == want
    assert recognise.error_rates(table.limit(0), models, lexicon, "k").count() == 0
    scores = np.array([[[rng.choice([-1.0, -2.0, -3.0]) for _ in range(3)] for _ in range(9)] for _ in range(50)])
    lengths = np.array(sorted((rng.randint(1, 9) for _ in range(50)), reverse=True))
    for cost in (0.0, 1.0, 1.5):
        paths = recognise.best_paths(scores, lengths, cost)
        for row, n, path in zip(scores, lengths, paths, strict=True):
            assert ["abc"[x] for x in path[:n]] == recognise.best_path([[(lang, "", s) for lang, s in zip("abc", at, strict=True)] for at in row[:n]], cost)[1]
    path = recognise.recognise(table, [recognise.Recogniser("fit", "con", langs, recognise.cost_of(0.5))], lexicon, "k").collect()
    s, n = sum(a != b for r in path for a, b in zip(r["langs"], r["langs"][1:])), sum(max(0, len(r["langs"]) - 1) for r in path)
    assert recognise.fit_switch(table, lexicon, langs, "k", 0.5, most=1)[0] == pytest.approx(min(0.5, (s + 0.5) / (n + 1)), rel=1e-12)


def test_studies_clean_texts_once(spark, sf):
    plan = str(experiments._pool(spark, sf)._jdf.queryExecution().optimizedPlan())
    assert "Relation" not in plan and "Generate" not in plan


def test_averages_of_runs_read_a_table(spark, sf):
    assert "event_type" in str(measures.top5_avg(spark, sf)._jdf.queryExecution().optimizedPlan())


def test_listed_letters_are_those_of_the_class(spark):
    """The class that Spark splits by, letter by letter, is that of the SQL, and no range is left in it to be tried."""
    assert "-" not in T._LISTED
    every = "".join(chr(c) for c in range(1, 0x11000) if not 0xD800 <= c < 0xE000)
    assert re.findall(T._LISTED, every) == re.findall(T.NOT_LETTERS, every)
    odd = ["", " ", "--", None, "Ünder ÷ the×sea", "naïve ÿ ß\tÀB  c", "a b 1c", "Straße, İstanbul ΑΒ!", "x" * 40]
    table = spark.createDataFrame([(w,) for w in odd], "text string")
    got = table.select("text", F.lower("text").alias("low"), T.words(F.col("text")).alias("w"), T.normalise(F.col("text")).alias("n")).collect()
    for r in got:
        want = None if r["text"] is None else [w for w in re.split(T.NOT_LETTERS, r["low"]) if w]
        assert r["w"] == want and r["n"] == (None if want is None else " ".join(want))


def test_readings_of_many_models_are_those_of_each_by_itself():
    rng = random.Random(3)
    rows = [(lang, w, rng.randint(1, 99)) for lang in ("de", "en", "es") for w in {"".join(rng.choices("abcé", k=rng.randint(1, 5))) for _ in range(80)}]
    kinds = [(("es",), False), (("es", "en"), True), (("en", "es"), False), (("de",), True), (("en", "de", "es"), True)]
    ear, sounds = recognise._Hearing(rows, kinds, 0.3, 5), ["".join(rng.choices("abcdé", k=rng.randint(1, 6))) for _ in range(300)]
    for _ in range(2):
        for (langs, pooled), got in zip(kinds, ear.readings(sounds), strict=True):
            one = recognise.Lexicons.from_counts(rows, langs, pooled)
            assert got == [one.candidates(w) for w in sounds]
    assert len(ear.memo) == len(set(sounds))
    for key in (7, "a:1", None):
        assert recognise.heard_words(sounds, key, 0.3, 5) == [recognise.heard(w, key, i, 0.3, 5) for i, w in enumerate(sounds)]


@pytest.mark.parametrize(("query", "splits"), [("wer_monolingual", 1), ("init_study", 2)])
def test_studies_count_and_number_once_for_all_pairs(spark, sf, monkeypatch, query, splits):
    done = []
    for where, name in ((experiments, "lexicon_rows"), (synth, "indexed_pool")):
        monkeypatch.setattr(where, name, lambda *a, f=getattr(where, name), name=name: done.append(name) or f(*a))
    monkeypatch.setattr(experiments, "fit_scored", lambda *a: (0.1, 1))
    monkeypatch.setattr(experiments, "fit_switch", lambda *a: (0.1, 1))
    getattr(experiments, query)(spark, sf)
    assert sorted(done) == ["indexed_pool"] * splits + ["lexicon_rows"]
