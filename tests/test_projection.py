"""The spread projection against the loop over one vector, on awkward centres."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from colsketch.functions import measures as A
from colsketch.operators import l1ball as P
from colsketch.operators import oblivious as O


def frame(spark, columns):
    rows = [(i, j, float(v)) for j, c in enumerate(columns) for i, v in enumerate(c) if v]
    return spark.createDataFrame(rows, O.SKETCH)


def centres():
    rng = np.random.default_rng(5)
    heavy = np.append(100.0, rng.uniform(0, 0.02, 20_000))
    return [heavy, np.full(700, 0.25), rng.standard_normal(3000) * np.where(rng.random(3000) < 0.01, 1000, 1), rng.standard_cauchy(2000), np.append(1e6, rng.standard_normal(500)), np.append(np.zeros(5), 0.5)]


@pytest.mark.parametrize(("lam", "eps"), [(150.0, 0.1), (20.0, 1e-4), (101.0, 1e-9), (5.0, 0.5)])
def test_zooming_equals_bisection(spark, lam, eps):
    columns = centres()
    df = frame(spark, columns)
    got = {r.bucket: r for r in P.thresholds(df, lam, eps).collect()}
    assert len(got) == len(columns)
    for j, c in enumerate(columns):
        theta = P.bisect(c, lam, eps)
        assert got[j].theta == pytest.approx(theta, rel=1e-9, abs=1e-12)
        if np.abs(c).sum() > lam * (1 + eps):
            left = np.maximum(np.abs(c) - got[j].theta, 0).sum()
            assert lam * (1 - 1e-7) <= left <= lam * (1 + eps) * (1 + 1e-7)
    sq = {r[0]: r[4] for r in P.solved(df, lam, eps)}
    for j, c in enumerate(columns):
        assert sq[j] == pytest.approx((np.maximum(np.abs(c) - got[j].theta, 0) ** 2).sum(), rel=1e-5, abs=1e-6)
    ok = A.l1_feasible(P.project(df, lam, eps), lam, eps, df).first()
    assert ok["outside"] == 0 and ok["below"] == 0


@pytest.mark.parametrize("lam", [0.3, 20.0, 150.0, 1e5])
def test_exact_form(spark, lam):
    columns = centres()
    got = {r.bucket: r.theta for r in P.exact_thresholds(frame(spark, columns), lam).collect()}
    assert all(got[j] == pytest.approx(P.exact_threshold(c, lam), rel=1e-9, abs=1e-9) for j, c in enumerate(columns))


def test_exact_form_on_an_edge(spark):
    """Integers whose threshold is a magnitude, or a cell's edge, itself."""
    columns = [[4, 2, 2, 2], [4, 4, 2, 1], [8] * 5 + [4] * 3, [4096, 1024, 512], [7, 7, 7]]
    for lam in (2.0, 4.0, 8.0, 20.0, 3072.0):
        got = {r.bucket: r.theta for r in P.exact_thresholds(frame(spark, columns), lam).collect()}
        assert {j: got[j] for j in range(5)} == pytest.approx({j: P.exact_threshold(np.array(c, float), lam) for j, c in enumerate(columns)})


def test_no_centres(spark):
    df = spark.createDataFrame([], O.SKETCH)
    assert P.thresholds(df, 1.0).count() == P.exact_thresholds(df, 1.0).count() == P.project(df, 1.0).count() == 0
    with pytest.raises(ValueError, match="positive"):
        P.thresholds(df, 0.0)
    left = P.residual(frame(spark, [[3, -1, 0.5]]), spark.createDataFrame([(0, 0.75)], "bucket int, theta double")).first()["left"]
    assert left == 2.5 and P.stats(df).agg(F.count("*")).first()[0] == 0
