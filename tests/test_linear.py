"""The joint linear solver against dense numpy optimisation, and the projections for large matrices."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from colsketch.operators import oblivious as O
from colsketch.plans import linear, solve
from colsketch.sources import matrix as M

N, D = 90, 7


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(N, D))
    x[5] = 0
    y = (x[:, :3] + 0.3 * rng.normal(size=(N, 3))).argmax(axis=1)
    sketch = spark.createDataFrame([(i, j, float(x[i, j])) for i in range(N) for j in range(D) if x[i, j]], O.SKETCH)
    rows = spark.createDataFrame([(i, int(y[i]) * 10, i % 5) for i in range(N)], "row_id long, label int, fold int")
    return x, y * 10, sketch, rows


def objective(w, x, y, c, loss):
    margin = x @ w[:-1] + w[-1]
    return linear.losses(margin, y, loss)[0].mean() + (w[:-1] ** 2).sum() / (2 * c * len(x))


@pytest.mark.parametrize("loss", linear.LOSSES)
@pytest.mark.parametrize("widest", [8192, 1])
def test_models_reach_their_minimum(data, loss, widest, monkeypatch):
    x, y, sketch, rows = data
    monkeypatch.setattr(linear, "WIDEST", widest)
    models = linear.Models({"one": linear.Sketched(sketch, D), "part": linear.Sketched(sketch.where("bucket < 3"), 3, (2,))}, rows, (0.01, 1.0), loss).fit(150, 1e-7)
    assert len(models.plan[0]) == 5 * 2 * 3 and len(models.plan[1]) == 2 * 3
    rng = np.random.default_rng(0)
    for k, (fold, c, head, n) in enumerate(models.plan[0]):
        inside = np.arange(N) % 5 != fold
        sign = np.where(y[inside] == models.classes[int(head)], 1.0, -1.0)
        w = models.weights[0][k]
        best = objective(w, x[inside], sign, c, loss)
        assert n == inside.sum()
        assert all(objective(w + 1e-3 * rng.normal(size=D + 1), x[inside], sign, c, loss) >= best - 1e-9 for _ in range(20))
    rows_out = models.predictions().where("name = 'one' and c = 1.0").collect()
    assert len(rows_out) == N and {r.label for r in rows_out} == {0, 10, 20}
    for r in rows_out:
        mine = [k for k, p in enumerate(models.plan[0]) if p[0] == r.fold and p[1] == 1.0]
        margins = [x[r.row_id] @ models.weights[0][k][:-1] + models.weights[0][k][-1] for k in mine]
        assert r.predicted == models.classes[int(np.argmax(margins))]
    scores = models.scores()["one", 1.0]
    by = [100 * np.mean([r.label == r.predicted for r in rows_out if r.fold == f]) for f in range(5)]
    assert scores["accuracy"] == pytest.approx(np.mean(by)) and scores["sd"] == pytest.approx(np.std(by, ddof=1))
    assert scores["accuracy"] > 70 and 0 < scores["balanced"] <= 100 and scores["majority"] == pytest.approx(100 * max((y == v).mean() for v in (0, 10, 20)))


def test_cross_validation_protocols(spark, data):
    x, _, sketch, rows = data
    fm = M.FeatureMatrix(sketch.select("row_id", F.col("bucket").cast("long").alias("feature_id"), "value"), spark.range(N).withColumnRenamed("id", "row_id"), D)
    labels = rows.select("row_id", (F.col("label") == 10).cast("int").alias("label"))
    for protocol in ("transductive", "inductive"):
        got = solve.cross_validate(fm, labels, lambda train: lambda z: O.countsketch(z, 6, 1), 6, protocol=protocol)
        assert got.count() == N and got.columns == ["row_id", "fold", "label", "predicted"]
    table = solve.grid(fm, labels, lambda lam: lambda train: lambda z: O.countsketch(z, 6, 1), 6, (0.1, 10.0), (1, 2))
    assert len(table) == 4 and all(0 <= a <= 100 for _, _, a in table)
    model = solve.linear_svm(sketch, labels, D)
    assert solve.predict(model, sketch, labels, D).join(labels, "row_id").where("label = predicted").count() > 0.8 * N
    with pytest.raises(ValueError, match="loss"):
        linear.Models({}, rows, (1.0,), "other")


def test_projections_for_large_matrices(spark, data, monkeypatch):
    x, _, sketch, _ = data
    fm = M.FeatureMatrix(sketch.select("row_id", F.col("bucket").cast("long").alias("feature_id"), "value"), spark.range(N).withColumnRenamed("id", "row_id"), D)

    def dense(df, r):
        out = np.zeros((N, r))
        for i, b, v in df.collect():
            out[i, b] = v
        return out

    f = np.arange(D)
    monkeypatch.setattr(O, "CELLS", 200)
    assert np.allclose(dense(O.gaussian(fm, 12, 4, "per_r", family="hash64"), 12), x @ O.normals(f, 12, 4) / 12**0.5)
    assert np.allclose(dense(O.ternary(fm, 12, 4, family="hash64"), 12), x @ O.trits(f, 12, 4, 1 / 3) * 3**0.5)
    big = np.arange(4000)
    z, t = O.normals(big, 50, 1), O.trits(big, 50, 1, 1 / 3)
    assert abs(z.mean()) < 0.01 and abs(z.var() - 1) < 0.02 and abs((t == 0).mean() - 2 / 3) < 0.01 and abs(t.mean()) < 0.01
    whole = dense(O.hadamard_rotate(fm, D, 3), 8)
    at = O.top_coordinates(fm, D, 3, 3)
    assert np.allclose((whole**2).sum(axis=0)[at], np.sort((whole**2).sum(axis=0))[::-1][:3])
    assert np.allclose(dense(O.hadamard_topr(fm, D, 3, 3), 3), whole[:, at])
    assert dense(O.hadamard(fm, D, 20, 3, replace=True), 20).shape == (N, 20)
    for method in O.METHODS:
        assert O.sketch(fm, method, 4, 1).columns == ["row_id", "bucket", "value"]
    with pytest.raises(ValueError, match="method"):
        O.sketch(fm, "other", 4, 1)
    best = (np.linalg.svd(x, compute_uv=False)[:2] ** 2).sum()
    got = dense(O.approx_svd(fm, 2, 1, 2, power_iters=3), 2)
    basis, _ = np.linalg.qr(got)
    assert 0.9 * best < np.linalg.norm(basis.T @ x) ** 2 < best + 1e-9
    labels = spark.createDataFrame([(i, i % 2) for i in range(N)], "row_id long, label int")
    means = np.array([whole[i::2].mean(axis=0) for i in (0, 1)])
    spread = {r.bucket: r.score for r in O.hadamard_scores(fm, D, 3, "between_class", labels).collect()}
    assert spread == pytest.approx({b: means[:, b].var() for b in range(8)})
    monkeypatch.setattr(O, "MOST_DENSE", 3)
    with pytest.raises(ValueError, match="features"):
        O.pca(fm, D, 2)
