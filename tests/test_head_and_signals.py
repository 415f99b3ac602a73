import numpy as np
import pytest
from pyspark.sql import functions as F

from langspan.functions import signal as S
from langspan.operators import head
from langspan.operators.vocab import RangeVocab

V = RangeVocab.allocate([("a", 3), ("b", 2)])


@pytest.fixture(scope="module")
def parts(spark):
    rng = np.random.default_rng(0)
    h, w = rng.normal(size=(20, 4)), rng.normal(size=(5, 4))
    states = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(h)], "k long, h array<double>")
    layer = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(w)], "token_id int, w array<double>")
    return h, w, states, layer


def _ids(df):
    return {r["k"]: r["token_id"] for r in df.collect()}


def test_suppression_is_a_masked_argmax(parts):
    h, w, states, layer = parts
    assert _ids(head.project(states, layer, "k")) == dict(enumerate((h @ w.T).argmax(axis=1)))
    masked = h @ w.T
    masked[:, :3] = -np.inf
    assert _ids(head.project(states, layer, "k", V, ["b"])) == dict(enumerate(masked.argmax(axis=1)))
    with pytest.raises(ValueError):
        head.project(states, layer, "k", V, [])
    assert head.scored_ids(V, ["b"]) == 0.4


def test_surgery(spark, parts):
    _, _, states, layer = parts
    grown = head.grow_head(layer, V, V.extend("c", 4), 4)
    old = {r["token_id"]: r["w"] for r in layer.collect()}
    new = {r["token_id"]: r["w"] for r in grown.collect()}
    assert len(new) == 9 and all(new[k] == old[k] for k in old)
    left, smaller = head.drop_language(layer, V, "a", repack=True)
    assert smaller.range("b") == (0, 2) and {r["token_id"]: r["w"] for r in left.collect()} == {0: old[3], 1: old[4]}
    joint = head.project_joint(states, states.select("k", F.transform("h", lambda x: x * 0).alias("context")), layer, "k", V, ["a"])
    assert set(_ids(joint).values()) <= {0, 1, 2}


@pytest.mark.parametrize("ids,out", [([], []), ([9, 9], []), ([1, 1, 2], [1, 2]), ([1, 9, 1], [1, 1]), ([9, 3, 3, 9, 4], [3, 4])])
def test_ctc(spark, ids, out):
    row = spark.createDataFrame([(ids,)], "ids array<int>")
    assert row.select(head.ctc_collapse(F.col("ids"), 9)).first()[0] == out


def _signal(spark, values):
    return spark.createDataFrame([([float(v) for v in values],)], "s array<float>")


@pytest.mark.parametrize(
    "values,out",
    [([0, 0, 0], []), ([0, 5, 0], [5]), ([0.01, -4, 0, 2, 0.01], [-4, 0, 2]), ([], []), ([3], [3])],
)
def test_trim(spark, values, out):
    got = _signal(spark, values).select(S.trim(F.col("s"), 0.1)).first()[0]
    assert got == pytest.approx(out)
    again = _signal(spark, got).select(S.trim(F.col("s"), 0.1)).first()[0]
    assert again == pytest.approx(out)


def test_energy_trim_and_peak(spark):
    quiet, loud = [0.001] * 10, [0.5, -0.5] * 5
    got = _signal(spark, quiet + loud + quiet).select(S.trim(F.col("s"), 0.1, mode="energy", frame=5)).first()[0]
    assert got == pytest.approx(loud)
    scaled = _signal(spark, [0.1, -0.4, 0.2]).select(S.peak_scale(F.col("s"), 0.8)).first()[0]
    assert scaled == pytest.approx([0.2, -0.8, 0.4])
    assert _signal(spark, [0, 0]).select(S.peak_scale(F.col("s"))).first()[0] == [0, 0]


def test_noise_keeps_the_wanted_ratio(spark):
    row = spark.range(1).select(S.noise(20_000, S.noise_level(F.lit(0.5), 10.0), F.lit(3)).alias("n")).first()[0]
    level = 20 * np.log10(0.5 / np.sqrt(np.mean(np.square(row))))
    assert abs(level - 10) < 0.5


def test_arrow_twin(spark, sf):
    vectors = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.col("embedding").alias("signal"))
    by_columns = {r[0]: r[1] for r in vectors.select("vec_id", S.peak_scale(S.trim(F.col("signal"), 0.2), 0.7)).collect()}
    by_arrow = {r["vec_id"]: r["signal"] for r in S.conditioned(vectors, 0.2, 0.7).collect()}
    assert all(by_arrow[k] == pytest.approx(v, abs=1e-5) for k, v in by_columns.items())
