"""Kernels on sparse rows cost by the rows' entries, and experiments on texts store no rows of a fold."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from colsketch.operators import adaptive as K
from colsketch.operators import oblivious as O
from colsketch.operators import row_kernels
from colsketch.plans import workloads
from colsketch.sources import matrix as M

SF = "/root/testdata/sf0.001"


class Sent:
    def __init__(self, value):
        self.value = value


def _sparse(n=50, d=1000, per=12):
    rng = np.random.default_rng(1)
    f = np.concatenate([np.sort(rng.choice(d, per, replace=False)) for _ in range(n)])
    return np.repeat(np.arange(n), per), f, rng.integers(1, 9, len(f)).astype(float)


@pytest.mark.parametrize("pairs", [30, 200, 1_000_000])
def test_energies_of_pairs_are_those_of_the_rotation(monkeypatch, pairs):
    monkeypatch.setattr(O, "PAIRS", pairs)
    row, f, v = _sparse()
    width, rotate = O._rotation(1000, 7)
    x, total = np.zeros((50, 1000)), np.zeros(width)
    x[row, f] = v
    O._add_shifts(total, np.full(50, 12), f, v * O._signs(1000, 7)[f])
    assert np.allclose(O.butterfly(total[None])[0] / width, (rotate(x) ** 2).sum(axis=0))


@pytest.mark.parametrize("sparse,cells", [(8, 4_000_000), (8, 400), (10**6, 400), (0, 400)])
def test_products_with_some_coordinates(monkeypatch, sparse, cells):
    monkeypatch.setattr(O, "SPARSE", sparse)
    monkeypatch.setattr(O, "CELLS", cells)
    row, f, v = _sparse()
    width, rotate = O._rotation(1000, 7)
    x, at = np.zeros((50, 1000)), np.array([5, 900, 0, 1023])
    x[row, f] = v
    got = O._times(50, row, f, v * O._signs(1000, 7)[f], 4, lambda some: O._parities(some, at)) / np.sqrt(width)
    assert np.allclose(got, rotate(x)[:, at])


def test_wide_rows_are_not_rotated_in_full(spark):
    """2,000 rows of three entries among 4,000,000 features; the rotation would make 8,000,000,000 cells."""
    d = 4_000_000
    lists = spark.range(2000).select(F.col("id").alias("row_id"), F.array(F.col("id"), F.col("id") + 5000, F.lit(d - 1)).alias("idx"), F.array(F.lit(1.0), F.lit(2.0), F.lit(3.0)).alias("val"))
    got = O.hadamard(M.FeatureMatrix.of_lists(lists, d), d, 8, 3)
    fm = M.FeatureMatrix.of_lists(lists.where("row_id < 4"), d)
    want = {(x.row_id, x.bucket): x.value for x in O.hadamard_pruned(fm, d, 8, 3).collect()}
    mine = {(x.row_id, x.bucket): x.value for x in got.where("row_id < 4").collect()}
    assert mine == pytest.approx(want) and got.select("row_id").distinct().count() == 2000


@pytest.mark.parametrize("rows,near", [(8192, 250_000), (7, 30)])
def test_products_of_full_centres_come_once_a_group(monkeypatch, rows, near):
    monkeypatch.setattr(row_kernels, "ROWS", rows)
    monkeypatch.setattr(row_kernels, "NEAR", near)
    row, f, v = _sparse()
    bucket, signs = np.random.default_rng(2).integers(0, 8, 1000).astype(np.int32), O._signs(1000, 7)
    replay = row_kernels.Replay(8, Sent(signs), (("move", Sent((bucket, None)), row_kernels.move_table([(k, 0.0, 0.0, 3) for k in range(8)], 8)),))
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(50)), pa.array(f.reshape(50, 12).tolist(), pa.list_(pa.int32())), pa.array(v.reshape(50, 12).tolist(), pa.list_(pa.float64()))], names=["row_id", "idx", "val"])
    x, c, got = np.zeros((50, 1000)), np.zeros((50, 8)), np.zeros((1000, 8))
    x[row, f] = v * signs[f]
    np.add.at(c.T, bucket, x.T / 3)
    met = set()
    for part in row_kernels.products(iter([batch]), None, 3, 8, 7, None, replay):
        for a, b, p in zip(part.column("f"), part.column("b"), part.column("p"), strict=True):
            np.add.at(got, (np.array(a.as_py()), np.array(b.as_py())), np.array(p.as_py()))
            met |= set(a.as_py())
    assert np.allclose(got, x.T @ c) and met == set(f.tolist())


def test_new_rows_of_lists_are_sketched_where_they_are(spark):
    fm, _ = workloads.load(spark, SF, "bow_en")
    model = K.learn_full(fm, 6, 2, ("relative", 0.2), seed=1)
    for shrink in ("theta", "none"):
        got = model.transform(fm, shrink)
        assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()
        plain = K.SketchModel(model.feature_map, model.groups, None, model.meta).transform(fm, shrink)
        a, b = ({(x.row_id, x.bucket): x.value for x in t.collect()} for t in (got, plain))
        assert {k: v for k, v in a.items() if abs(v) > 1e-9} == pytest.approx({k: v for k, v in b.items() if abs(v) > 1e-9})


def test_folds_of_texts_are_not_stored(spark, monkeypatch):
    fm, rows = workloads.load(spark, SF, "bow_en")
    for f in (0, 3):
        part = M.FeatureMatrix.of_lists(fm.lists.where(F.col("fold") != f), fm.d)
        assert workloads._top(fm, workloads.Config("hadamard_topr", 8, 5), f).tolist() == O.top_coordinates(part, fm.d, 8, 5).tolist()
    stored, kept = [], workloads.kept
    monkeypatch.setattr(workloads, "kept", lambda df: stored.append(df.columns) or kept(df))
    configs = [workloads.Config(m, 6) for m in ("hadamard_topr", "learned_full", "learned_minibatch")]
    out = workloads._inductive("bow_en", fm, rows, configs, [], (10.0,))
    assert [x[5] for x in out] == ["accuracy_inductive"] * 3 and all(x[6] > 50 for x in out)
    assert not [c for c in stored if "feature_id" in c]
