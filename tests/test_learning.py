"""The learned sketch against a plain numpy loop, on both ways of looking a map up, and its options."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from colsketch.functions import hashing as H
from colsketch.functions import measures as A
from colsketch.operators import adaptive as K
from colsketch.operators import l1ball as P
from colsketch.operators import oblivious as O
from colsketch.operators import row_kernels
from colsketch.sources import matrix as M

N, D = 40, 26


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(N, D)) * (rng.random((N, D)) < 0.4)
    x[:, 3] = -x[:, 4]
    x[7] = 0
    x[0, :] += rng.normal(size=D)
    fm = M.FeatureMatrix(spark.createDataFrame([(i, j, float(x[i, j])) for i in range(N) for j in range(D) if x[i, j]], M.ENTRIES), spark.range(N).withColumnRenamed("id", "row_id"))
    return x, fm


def dense(df, r):
    out = np.zeros((N, r))
    for i, b, v in df.select("row_id", "bucket", "value").collect():
        out[i, b] = v
    return out


def signs(spark, seed):
    rows = spark.range(D).select("id", H.sign_of(F.col("id"), seed).alias("s")).orderBy("id").collect()
    return np.array([r.s for r in rows], float)


def reference(spark, x, fm, r, iters, lam, eps, seed, fraction=None, learned=False):
    m = x * signs(spark, seed)
    c, count = dense(K.init_centres(K.signed(fm, seed), r, seed), r), np.zeros(r)
    theta = np.zeros(r)

    def nearest(j):
        dots = m[:, j] @ c
        return int(((c**2).sum(axis=0) - 2 * (np.abs(dots) if learned else dots)).argmin())

    for turn in range(1, iters + 1):
        some = np.arange(D) if fraction is None else np.flatnonzero(H.drawn_array(np.arange(D), fraction, seed, f"batch{turn}"))
        at = {j: nearest(j) for j in some}
        flip = {j: -1 if learned and m[:, j] @ c[:, at[j]] < 0 else 1 for j in some}
        for b in set(at.values()):
            mine = [j for j in some if at[j] == b]
            count[b] += len(mine)
            eta = 1 / (2 * (len(mine) if fraction is None else count[b]))
            c[:, b] = c[:, b] - eta * -2 * (sum(m[:, j] * flip[j] for j in mine) - len(mine) * c[:, b])
        if lam:
            theta = np.array([P.bisect(c[:, b], lam, eps) if eps else P.exact_threshold(c[:, b], lam) for b in range(r)])
            c = np.sign(c) * np.maximum(np.abs(c) - theta, 0)
    return c, {j: nearest(j) for j in range(D)} if fraction else at, theta


@pytest.mark.parametrize("bound", [4_000_000, 0])
@pytest.mark.parametrize(("lam", "eps", "learned"), [(None, 0.1, False), (4.0, 0.1, False), (4.0, 0.0, True)])
def test_full_batch(spark, data, monkeypatch, bound, lam, eps, learned):
    x, fm = data
    monkeypatch.setattr(K, "MAX_BROADCAST", bound)
    monkeypatch.setattr(row_kernels, "CELLS", 50)
    want, at, theta = reference(spark, x, fm, 5, 3, lam, eps, 9, learned=learned)
    model = K.learn_full(fm, 5, 3, lam, eps, 9, signs="learned" if learned else "random")
    assert {r.feature_id: r.bucket for r in model.feature_map.collect()} == at
    assert np.allclose(dense(model.training_sketch(), 5), want)
    assert all(r.theta == pytest.approx(theta[r.bucket]) for r in model.groups.collect())
    if not lam or model.groups.count() == 5:
        again = dense(model.transform(fm), 5)
        full = sorted(r.bucket for r in model.groups.collect())
        assert np.allclose(again[:, full], want[:, full])


@pytest.mark.parametrize("bound", [4_000_000, 0])
def test_mini_batch(spark, data, monkeypatch, bound):
    x, fm = data
    monkeypatch.setattr(K, "MAX_BROADCAST", bound)
    want, at, _ = reference(spark, x, fm, 4, 4, 5.0, 0.1, 11, fraction=0.5)
    model = K.learn_minibatch(fm, 4, 4, 0.5, 5.0, 0.1, 11)
    assert np.allclose(dense(model.training_sketch(), 4), want)
    assert {r.feature_id: r.bucket for r in model.feature_map.collect()} == at
    for rate in ("per_batch", ("constant", 1e-3), ("decay", 0.01)):
        assert K.learn_minibatch(fm, 4, 2, 0.5, 5.0, 0.1, 11, rate).feature_map.count() == D


def test_stored_thresholds_repeat_the_training_sketch(spark, data):
    """Every group has members here, so the map of new rows gives the centres themselves."""
    _, fm = data
    model = K.learn_full(fm, 3, 2, 6.0, seed=2, init="oblivious_groups")
    assert model.groups.count() == 3
    assert np.allclose(dense(model.transform(fm), 3), dense(model.training_sketch(), 3))
    assert dense(model.transform(fm, "project"), 3).shape == (N, 3)
    other = M.FeatureMatrix(spark.createDataFrame([(1, 10**6, 2.0)], M.ENTRIES), fm.rows)
    assert model.transform(other).count() == 0 and model.transform(other, "none", "hash").count() == 1


def test_relations_equal_kernels(spark, data):
    _, fm = data
    m = K.signed(fm, 9)
    c = K.init_centres(m, 5, 9)
    one = K.step(m, K.assign(m, c, 5), c)
    assert np.allclose(dense(one, 5), dense(K.learn_full(fm, 5, 1, seed=9).training_sketch(), 5))
    decay = K.learn_full(fm, 5, 3, seed=9, rate=("decay", 0.02))
    assert decay.meta["iters"] == 3
    with pytest.raises(ValueError, match="constant"):
        K.learn_full(fm, 5, 1, seed=9, rate=("constant", 10.0))
    with pytest.raises(ValueError, match="rate"):
        K.learn_full(fm, 5, 1, seed=9, rate=("other", 1.0))


def test_one_step_at_any_constant_rate(spark, data):
    x, fm = data
    m = K.signed(fm, 9)
    c = K.init_centres(m, 5, 9)
    fmap = K.assign(m, c, 5)
    at = {r.feature_id: r.bucket for r in fmap.collect()}
    before, want, s = dense(c, 5), dense(c, 5), signs(spark, 9)
    for b in range(5):
        mine = [j for j in at if at[j] == b]
        want[:, b] = before[:, b] + 2 * 0.5 * ((x * s)[:, mine].sum(axis=1) - len(mine) * before[:, b])
    assert max(np.bincount(list(at.values()))) > 2  # 1 / the largest group's size is below the rate
    assert np.allclose(dense(K.step(m, fmap, c, ("constant", 0.5)), 5), want)


def test_too_few_columns(data):
    with pytest.raises(ValueError, match="fewer"):
        K.learn_full(data[1], D + 1)


def test_inits_and_empty_groups(spark, data):
    x, fm = data
    m = K.signed(fm, 1)
    for init in K.INITS:
        assert K.init_centres(m, 4, 1, init).select("bucket").distinct().count() == 4
    picked = [r.feature_id for r in K.spread_columns(m, 6, 1).orderBy("bucket").collect()]
    assert len(set(picked)) == 6
    same = M.FeatureMatrix(fm.entries.where("feature_id < 2").unionByName(fm.entries.where("feature_id = 0").withColumn("feature_id", F.lit(50).cast("long"))), fm.rows)
    plain = K.learn_full(same, 3, 3, seed=4, signs="identity")
    reseeded = K.learn_full(same, 3, 3, seed=4, signs="identity", reseed_empty=True)
    assert plain.groups.count() <= reseeded.groups.count()
    sizes = {r.feature_id: r.sq for r in K.column_norms(m).collect()}
    assert sizes == pytest.approx({j: (x[:, j] ** 2).sum() for j in range(D) if x[:, j].any()})


def test_empty_matrices(spark):
    none = M.FeatureMatrix(spark.createDataFrame([], M.ENTRIES), spark.range(0).withColumnRenamed("id", "row_id"))
    fmap = O.feature_map(none.features(), 4, 1)
    e = A.reconstruction_error(none, fmap).first()
    assert e["error"] == 0 and e["relative"] is None
    assert A.kmeans_objective(none, fmap, O.countsketch(none, 4, 1)).first()["objective"] == 0
    assert A.sparsity(O.countsketch(none, 4, 1), none.rows, 4).first()["zeros"] is None
    assert A.profile(none).first()["zeros"] is None
