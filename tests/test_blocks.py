"""Passes of experiments move blocks of bytes, and give what rows of figures gave."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from colsketch.operators import adaptive as K
from colsketch.operators import oblivious as O
from colsketch.operators import row_kernels as R
from colsketch.plans import linear, workloads
from colsketch.sources import blocks as B
from colsketch.sources import matrix as M

SF = "/root/testdata/sf0.001"


class Sent:
    def __init__(self, value):
        self.value = value


def _rows(n=60, d=40):
    rng = np.random.default_rng(5)
    x = rng.integers(1, 9, (n, d)) * (rng.random((n, d)) < np.linspace(0.02, 0.9, d))
    x[3] = 0
    lists = [np.flatnonzero(r) for r in x]
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(n) * 7 - 50), pa.array(np.arange(n) % 5, pa.int32()), pa.array([r.tolist() for r in lists], pa.list_(pa.int32())), pa.array([x[i, r].tolist() for i, r in enumerate(lists)], pa.list_(pa.int32()))], names=["row_id", "fold", "idx", "val"])
    return x.astype(float), batch


@pytest.mark.parametrize("rows", [8192, 9])
@pytest.mark.parametrize("without", [None, 2])
def test_blocks_give_the_rows_back(monkeypatch, rows, without):
    monkeypatch.setattr(B, "ROWS", rows)
    monkeypatch.setattr(B, "SOME", 4)
    x, batch = _rows()
    got = {}
    for b in B.unpacked(B.pack(iter([batch, batch.slice(0, 0)])), without):
        assert (np.diff(b.f) >= 0).all() and len(b.ids) <= rows
        y = np.zeros((len(b.ids), 40))
        y[b.row, b.f] = b.v
        got |= dict(zip(b.ids.tolist(), y, strict=True))
    want = {int(i): r for i, r, f in zip(np.arange(60) * 7 - 50, x, np.arange(60) % 5, strict=True) if f != without}
    assert got.keys() == want.keys() and all((got[i] == want[i]).all() for i in want)


@pytest.mark.parametrize("packed", [True, False])
@pytest.mark.parametrize("shrink", [0.0, 2.0])
@pytest.mark.parametrize("share", [None, 0.5])
def test_sent_products_give_the_nearest_centres(monkeypatch, packed, shrink, share):
    monkeypatch.setattr(R, "CELLS", 60)
    monkeypatch.setattr(R, "WIDE", 90)
    x, batch = _rows()
    signs, bucket = O._signs(40, 7), np.random.default_rng(2).integers(0, 6, 40).astype(np.int32)
    replay = R.Replay(6, Sent(signs), (("move", Sent((bucket, None)), R.move_table([(k, 0.0, 0.0, 3) for k in range(6)], 6)), ("shrink", np.full(6, shrink))), B.unpacked if packed else None, 1 if packed else None)
    keep = np.arange(60) % 5 != 1 if packed else np.ones(60, bool)
    m = x[keep] * signs
    c = np.zeros((len(m), 6))
    np.add.at(c.T, bucket, m.T / 3)
    c = np.sign(c) * np.maximum(np.abs(c) - shrink, 0)
    norms, per = (c * c).sum(axis=0), 13
    out = pa.Table.from_batches(R.sent_products(B.pack(iter([batch])) if packed else iter([batch]), per, 3, share and (share, "a"), replay))
    got = {}
    for part in set(out.column("part").to_pylist()):
        t = R.nearest_sent(out.filter(pa.compute.equal(out.column("part"), part)), norms, False, per)
        got |= {f: (b, d) for f, b, d in zip(*(t.column(k).to_pylist() for k in ("feature_id", "bucket", "dist")), strict=True)}
    far = norms - 2 * m.T @ c
    some = (R.drawn_array(np.arange(40), share, 3, "a") if share else np.ones(40, bool)) & m.any(axis=0)
    assert got.keys() == set(np.flatnonzero(some).tolist())
    assert all(b == far[f].argmin() and d == pytest.approx(far[f].min()) for f, (b, d) in got.items())


@pytest.mark.parametrize("name", ["bow_en", "bow_multi"])
def test_learners_of_texts_read_blocks(spark, monkeypatch, name):
    """No pass reads lists of figures, and rows are shortened where they are, as by sums of moved entries."""
    fm, rows = workloads.load(spark, SF, name)
    other = M.FeatureMatrix(K.cut(fm.entries), K.cut(fm.rows), fm.d)
    changes = [{"row_sketch": 64}, {"row_sketch": 64, "signs": "learned"}, {"reseed_empty": True}]
    want = [{(r.row_id, r.bucket): r.value for r in K.learn_full(other, 7, 2, 5.0, seed=3, **more).training_sketch().collect()} for more in changes]
    read, columns = K.ReplayedCentres._read, set()
    monkeypatch.setattr(K.ReplayedCentres, "_read", lambda self, *a: columns.update(self.lists.columns) or read(self, *a))
    monkeypatch.setattr(K, "row_sketched", None)
    for more, x in zip(changes, want, strict=True):
        got = {(r.row_id, r.bucket): r.value for r in K.learn_full(fm, 7, 2, 5.0, seed=3, **more).training_sketch().collect()}
        assert got == pytest.approx(x) and len(got) > 50
    assert columns == {x.split()[0] for x in B.PACKED.split(", ")}
    models = linear.Models({"a": linear.Sketched(O.countsketch(fm, 7, 1), 7)}, rows, (1.0,))
    assert not [k for c, k in models.data.dtypes if k.startswith("array")]
    assert models.fit(3).scores()["a", 1.0]["accuracy"] > 0 and models.predictions().count() == rows.where("label is not null").count()
    workloads._done(fm, rows)


def test_squares_are_made_where_rows_are_read(spark, tmp_path):
    """The same matrix, labels and folds as by joined entries; rows that cannot be read so go that way."""
    t = M.table(spark, SF, "embeddings", ["vec_id", "embedding"]).limit(40)
    holes = F.transform("embedding", lambda v, i: F.when((i == 3) & (F.col("vec_id") % 2 == 0) | (i == 20), 0.0).when(i == 30, 2.0).otherwise(v).cast("float"))
    t.select("vec_id", holes.alias("embedding")).write.parquet(str(tmp_path / "embeddings.parquet"))
    fm, rows = workloads.load(spark, str(tmp_path), "embquad")
    given, labels = workloads.DATASETS["embquad"](spark, str(tmp_path))
    slow, _ = M.dense_ids(given)
    want = {(r.row_id, r.feature_id): r.value for r in slow.entries.collect()}
    assert fm.packed is not None and fm.d == slow.d < 2144
    assert {(r.row_id, r.feature_id): r.value for r in fm.entries.collect()} == pytest.approx(want)
    assert sorted(map(tuple, rows.collect())) == sorted(map(tuple, workloads.V.folds(labels, "key").select("row_id", "label", "fold").collect()))
    got = {(r.row_id, r.bucket): r.value for r in K.learn_full(fm, 5, 2, ("relative", 0.2), seed=3).training_sketch().collect()}
    other = K.learn_full(M.FeatureMatrix(K.cut(slow.entries), K.cut(slow.rows), fm.d), 5, 2, ("relative", 0.2), seed=3)
    assert got == pytest.approx({(r.row_id, r.bucket): r.value for r in other.training_sketch().collect()})
    workloads._done(fm, rows)
    for k, change in enumerate((F.array_repeat(F.lit(0.0).cast("float"), 64), F.array_repeat(F.lit(float("nan")).cast("float"), 64))):
        d = tmp_path / str(k)
        t.unionByName(t.limit(1).select((F.col("vec_id") + 10**6).alias("vec_id"), change.alias("embedding"))).write.parquet(str(d / "embeddings.parquet"))
        assert workloads._given_squares(spark, str(d), 5) is None
    t.unionByName(t.limit(1)).write.parquet(str(tmp_path / "twice" / "embeddings.parquet"))
    assert workloads._given_squares(spark, str(tmp_path / "twice"), 5) is None


def test_blocks_of_many_models_stay_small():
    n = 2000
    lists = [pa.array([[0, 1]] * n, pa.list_(pa.int32())), pa.array([[1.0, 2.0]] * n, pa.list_(pa.float64()))]
    batch = pa.RecordBatch.from_arrays([pa.array(np.zeros(n, np.int32)), pa.array(np.arange(n)), *[pa.array(np.zeros(n, np.int32))] * 2, *lists], names=["tag", "row_id", "fold", "label", "idx", "val"])
    sizes = [block.n for _, block, _ in linear._blocks(iter([batch]), [2], [320])]
    assert sum(sizes) == n and max(sizes) * 320 <= linear.NEAR
