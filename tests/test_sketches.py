"""Invariants of the sketches on small matrices, against numpy."""

import numpy as np
import pytest
from conftest import DATA
from pyspark.sql import functions as F

from colsketch.functions import measures as A
from colsketch.operators import adaptive as K
from colsketch.operators import l1ball as P
from colsketch.operators import oblivious as O
from colsketch.plans import solve as V
from colsketch.sources import matrix as M


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(0)
    x = rng.integers(-3, 4, (30, 24)).astype(float)
    x[:, 5] = x[:, 4]
    x[:, 7] = 0
    x[3] = 0
    rows = [(i, j, float(x[i, j])) for i in range(30) for j in range(24) if x[i, j]]
    fm = M.FeatureMatrix(spark.createDataFrame(rows, M.ENTRIES), spark.range(30).withColumnRenamed("id", "row_id"), 24)
    return x, fm


def dense(df, n, r):
    out = np.zeros((n, r))
    for i, j, v in df.select("row_id", "bucket", "value").collect():
        out[i, j] = v
    return out


def test_worked_projection():
    assert P.project_array([3, -1, 0.5, 0], 2, 0.1) == [2.0625, -0.0625, 0.0, 0.0]
    assert P.project_array([0.5, 0.5], 2, 0.1) == [0.5, 0.5]
    assert np.abs(P.project_array([1.0] * 8, 2, 0.1)).sum() <= 2.2
    with pytest.raises(ValueError):
        P.bisect(np.ones(3), 0, 0.1)


def test_replayed_bisection(spark):
    rng = np.random.default_rng(1)
    c = rng.standard_normal((400, 5)) * [1, 2, 0.01, 5, 1]
    df = spark.createDataFrame([(i, j, float(c[i, j])) for i in range(400) for j in range(5)], O.SKETCH)
    got = {r.bucket: r.theta for r in P.thresholds(df, 20.0, 0.1).collect()}
    for j in range(5):
        assert got[j] == pytest.approx(P.bisect(c[:, j], 20.0, 0.1), abs=1e-9)
    exact = {r.bucket: r.theta for r in P.exact_thresholds(df, 20.0).collect()}
    assert all(exact[j] == pytest.approx(P.exact_threshold(c[:, j], 20.0), abs=1e-9) for j in range(5))
    once = P.project(df, 20.0, 0.1)
    assert A.l1_feasible(once, 20.0, 0.1).first()["outside"] == 0


def test_countsketch_is_linear(small):
    x, fm = small
    got = dense(O.countsketch(fm, 6, 1), 30, 6)
    r = np.zeros((24, 6))
    for f, b, s in O.feature_map(fm.entries.sparkSession.range(24).withColumnRenamed("id", "feature_id"), 6, 1).collect():
        r[f, b] = s
    assert np.allclose(got, x @ r)


def test_hadamard_keeps_lengths(small):
    x, fm = small
    assert np.allclose(O.butterfly(np.eye(8)) @ O.butterfly(np.eye(8)), 8 * np.eye(8))
    got = dense(O.hadamard_rotate(fm, 24, 2), 30, 32)
    assert np.allclose((got**2).sum(axis=1), (x**2).sum(axis=1))
    assert np.allclose(dense(O.hadamard(fm, 24, 8, 2), 30, 8), dense(O.hadamard_pruned(fm, 24, 8, 2), 30, 8))


def test_error_equals_objective(small):
    x, fm = small
    fmap = O.feature_map(fm.features(), 6, 3)
    e = A.reconstruction_error(fm, fmap).first()["error"]
    o = A.kmeans_objective(fm, fmap, O.countsketch(fm, 6, 3, "mean")).first()["objective"]
    assert e == pytest.approx(o, rel=1e-12)


def test_assignment_is_the_full_argmin(small):
    _, fm = small
    m = K.signed(fm, 5)
    centres = P.project(K.init_centres(m, 6, 5), 4.0, 0)
    c, y = dense(centres, 30, 6), np.zeros((30, 24))
    for i, j, v in m.collect():
        y[i, j] = v
    for f, b in K.assign(m, centres, 6).collect():
        dist = (c**2).sum(axis=0) - 2 * y[:, f] @ c
        assert dist[b] == pytest.approx(dist.min())


def test_learned_sketch(small, tmp_path, spark):
    _, fm = small
    base = A.reconstruction_error(fm, O.feature_map(fm.features(), 6, 5)).first()["error"]
    model = K.learn_full(fm, 6, 2, seed=5, init="oblivious_groups")
    assert A.reconstruction_error(fm, model.feature_map).first()["error"] <= base + 1e-9
    shrunk = K.learn_full(fm, 6, 2, lam=10.0, seed=5)
    if shrunk.groups.count() == 6:  # no empty group
        assert np.allclose(dense(shrunk.transform(fm), 30, 6), dense(shrunk.training_sketch(), 30, 6))
    shrunk.save(str(tmp_path / "m"))
    again = K.SketchModel.load(spark, str(tmp_path / "m"))
    assert np.allclose(dense(again.transform(fm), 30, 6), dense(shrunk.transform(fm), 30, 6))
    mini = K.learn_minibatch(fm, 6, 2, 0.5, 10.0, seed=5)
    assert mini.feature_map.count() == 23 and A.group_profile(mini.feature_map, 6).first()["features"] == 23


def test_svm_on_a_sketch(spark):
    docs = M.table(spark, f"{DATA}/sf0.01", "documents", ["doc_id", "text", "lang"])
    fm = M.from_ngrams(docs, "doc_id", F.col("text"), 2, 2000)
    labels = docs.select(F.col("doc_id").alias("row_id"), (F.col("lang") == "en").cast("int").alias("label"))
    got = A.accuracy(V.cross_validate(fm, labels, lambda _: lambda x: O.countsketch(x, 16, 1), 16, 1.0, k=2)).first()
    assert got["mean"] > 75


def test_bad_values(spark):
    df = spark.createDataFrame([(1, 1, 2.0), (1, 1, -2.0), (1, 2, None), (2, 3, float("nan")), (2, 4, 5.0)], "a long, b long, v double")
    assert [tuple(r) for r in M.from_pairs(df, "a", "b", "v", "drop").entries.collect()] == [(2, 4, 5.0)]
    with pytest.raises(Exception, match="null or NaN"):
        M.from_pairs(df, "a", "b", "v").entries.collect()
