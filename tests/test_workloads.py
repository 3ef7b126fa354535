"""Experiments, variants of the learned sketch, serving, formats and streams."""

from pathlib import Path

import numpy as np
import pytest
from conftest import DATA
from pyspark.ml import Pipeline
from pyspark.sql import functions as F

from colsketch.functions import measures as A
from colsketch.operators import adaptive as K
from colsketch.operators import oblivious as O
from colsketch.plans import serving, solve, workloads
from colsketch.session import shared_dir
from colsketch.sources import formats
from colsketch.sources import matrix as M
from colsketch.streaming import sketch_stream as S

SF = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def planted(spark):
    spark.dataSource.register(formats.PlantedSource)
    e = spark.read.format("planted_groups").option("rows", 60).option("groups", 4).option("copies", 5).load()
    e = K.cut(e)
    return M.FeatureMatrix(e, spark.range(60).withColumnRenamed("id", "row_id"), 20)


def test_learned_signs_recover_planted_groups(planted):
    plain = A.reconstruction_error(planted, O.feature_map(planted.features(), 4, 1)).first()["relative"]
    best = min(A.reconstruction_error(planted, K.learn_full(planted, 4, 4, seed=s, signs="learned", tol=0.0).feature_map).first()["relative"] for s in range(4))
    assert best < plain and best < 0.35


def test_options_of_the_learned_sketch(planted):
    model = K.learn_full(planted, 4, 6, ("relative", 0.5), seed=1, tol=1.0)
    assert model.meta["iters"] == 2
    norm = planted.entries.agg(F.sum(F.abs("value"))).first()[0] / 20
    assert model.meta["lam"] == pytest.approx(norm / 2)
    m = K.signed(planted, 1)
    c = K.init_centres(m, 4, 1)
    wide = {(r.feature_id, r.bucket) for r in K.assign(K.row_sketched(m, "feature_id", 1 << 16, 1), K.row_sketched(c, "bucket", 1 << 16, 1), 4).collect()}
    exact = {(r.feature_id, r.bucket) for r in K.assign(m, c, 4).collect()}
    assert len(wide & exact) >= 19
    assert K.kmeans_reference(planted, 4, 1).count() == 20


def test_dense_ids_and_low_rank(planted, spark):
    shifted = M.FeatureMatrix(planted.entries.withColumn("feature_id", F.col("feature_id") * 1000 + 7), planted.rows)
    fm, ids = M.dense_ids(shifted)
    assert {(r.feature_id, r.dense_id) for r in ids.collect()} == {(1000 * i + 7, i) for i in range(20)} and fm.d == 20
    x = np.zeros((60, 20))
    for i, j, v in planted.entries.collect():
        x[i, j] = v
    error, energy = solve.low_rank(planted, 4, 3)
    best = (np.linalg.svd(x, compute_uv=False)[4:] ** 2).sum()
    assert energy == pytest.approx((x**2).sum()) and best - 1e-6 <= error <= 1.5 * best + 1e-6


def test_serving(planted, spark):
    model = K.learn_full(planted, 4, 2, 40.0, seed=2)
    want = {(r.row_id, r.bucket): r.value for r in model.transform(planted).collect()}
    serving.register_table_function(spark, model)
    planted.as_rows().createOrReplaceTempView("given_rows")
    got = {(r.row_id, r.bucket): r.value for r in spark.sql("select row_id, t.bucket, t.value from given_rows, lateral colsketch_transform(idx, val) t").collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)
    scores = {r.row_id: r.score for r in serving.scored(model, planted, [1.0, 2.0, 3.0, 4.0]).collect()}
    assert all(scores[i] == pytest.approx(sum((b + 1) * v for (j, b), v in want.items() if j == i)) for i in range(60))
    vectors = formats.to_vectors(planted, 20)
    out = Pipeline(stages=[serving.ColumnSketch(4, iters=2, lam=40.0, seed=2)]).fit(vectors).transform(vectors)
    assert {(r.row_id, b): v for r in out.collect() for b, v in enumerate(r.sketch) if v} == pytest.approx(want)


def test_formats(planted, spark, tmp_path):
    labels = planted.rows.withColumn("label", F.col("row_id") % 2)
    formats.write_sparse_text(planted, labels, str(tmp_path / "t"))
    back, y = formats.read_sparse_text(spark, str(tmp_path / "t"))
    assert y.groupBy("label").count().orderBy("label").collect() == [(0.0, 30), (1.0, 30)]
    a, b = (sorted(r.value for r in x.entries.collect()) for x in (planted, back))
    assert a == pytest.approx(b)
    page = spark.createDataFrame([("<p>a<b>b</b></p><script>x</script> c", "http://h.org/p?q=1"), (None, None)], "html string, url string")
    assert [tuple(r) for r in page.select(formats.strip_tags(F.col("html")), formats.url_part(F.col("url"), "HOST")).collect()] == [("a b c", "h.org"), (None, None)]


def test_workloads(spark):
    rows = workloads.methods(spark, SF, "bow_en", 8, ["countsketch", "hadamard_topr", "learned_full", "learned_minibatch", "identity"]).collect()
    got = {(r.method, r.metric): r.value for r in rows}
    assert got[("learned_full", "zeros")] > got[("countsketch", "zeros")]
    assert got[("learned_full", "accuracy")] >= got[("learned_full", "majority")] - 5 and got[("identity", "accuracy")] > 80
    assert {"embed_s", "projection_ms", "classification_ms", "theta_gap", "accuracy_inductive", "balanced_accuracy", "error_share"} <= {m for n, m in got if n == "learned_full"}
    assert 0 <= got[("learned_full", "theta_gap")] and got[("learned_full", "error_share")] <= 1


@pytest.mark.parametrize("name", list(workloads.DATASETS))
def test_datasets(spark, name):
    fm, rows = workloads.load(spark, SF, name)
    n, folds, classes = rows.selectExpr("count(*)", "count(distinct fold)", "count(distinct label)").first()
    assert n == fm.rows.count() > 50 and folds == 5
    assert classes > 8 if name in ("emb10", "bigram", "bow_multi") else classes == 2


def test_small_grids(spark):
    grid = workloads.tuning(spark, SF, "emb10", 6, (0.1, 10.0), (10.0, 40.0)).collect()
    assert len(grid) == 4 and all(0 < r.accuracy <= 100 for r in grid)
    runs = {r.method: r for r in workloads.stability(spark, SF, "emb10", 6, range(2)).collect()}
    assert runs["countsketch"].runs == 2 and runs["learned_full"].low <= runs["learned_full"].high
    names = {r.method for r in workloads.ablations(spark, SF, "emb10", 6).collect()}
    assert names == {*workloads.CHANGES, "batch=0.1", "batch=0.2", "batch=0.5"}


def _files(spark):
    """Sizes of what lies in the shared folder."""
    root = Path(shared_dir(spark).removeprefix("file:"))
    return sum(p.stat().st_size for p in root.rglob("*") if p.is_file() and not p.name.startswith("."))


def test_experiments_leave_no_files(spark):
    """Of the stored rows and passes; small tables, as maps and numberings, may stay."""
    before = _files(spark)
    assert workloads.tuning(spark, SF, "bow_en", 6, (0.1,), (10.0, 40.0)).count() == 2
    fm, rows = workloads.load(spark, SF, "bow_en")
    size = sum(p.stat().st_size for t in (fm.entries, rows) for p in Path(t._kept_at.removeprefix("file:")).rglob("*"))
    assert size > 10_000
    workloads._done(fm, rows)
    assert not Path(fm.entries._kept_at.removeprefix("file:")).exists()
    assert _files(spark) - before < 40 * fm.d  # two numberings of the features


def test_learners_share_rows(spark, planted):
    fm = M.FeatureMatrix(planted.entries, planted.rows, 20, shared={})
    alone = [K.learn_full(planted, 4, 2, lam, seed=2).training_sketch().orderBy("row_id", "bucket").collect() for lam in (3.0, 40.0)]
    both = [K.learn_full(fm, 4, 2, lam, seed=2).training_sketch().orderBy("row_id", "bucket").collect() for lam in (3.0, 40.0)]
    assert len(fm.shared) == 1
    for a, b in zip(alone, both, strict=True):
        assert [x[:2] for x in a] == [x[:2] for x in b] and [x.value for x in a] == pytest.approx([x.value for x in b])
    K.learn_full(fm, 4, 1, seed=2, signs="identity")
    assert len(fm.shared) == 2


def test_rows_of_learners_are_narrow_where_exact(spark):
    """4 bytes a figure if ids and values lose nothing by it, else 8; the learner reads the same matrix."""
    whole = [(i, j, float((3 * i + 5 * j) % 7 - 3)) for i in range(12) for j in range(9) if (3 * i + 5 * j) % 7 != 3]
    for shift, factor, kinds in ((0, 1.0, ("int", "float")), (0, 0.1, ("int", "double")), (1 << 40, 1.0, ("bigint", "float")), (-(1 << 31) - 1, 1e60, ("bigint", "double"))):
        given = [(i, j + shift, v * factor) for i, j, v in whole]
        fm = M.FeatureMatrix(spark.createDataFrame(given, M.ENTRIES), spark.range(12).withColumnRenamed("id", "row_id"))
        work = K._Learner(fm, 3, 1, "identity", None, 0.1)
        assert dict(work.rows.dtypes) == {"row_id": "bigint", "idx": f"array<{kinds[0]}>", "val": f"array<{kinds[1]}>"}
        assert sorted(map(tuple, work.entries().collect())) == sorted(given) and work.entries().schema == M.ENTRIES


@pytest.mark.parametrize("most", [K.MAX_CELLS, 0])
def test_lists_store_no_centres(spark, monkeypatch, most):
    """Of a matrix in lists, learners make centres from the rows and leave no files; as by stored centres otherwise."""
    monkeypatch.setattr(K, "MAX_CELLS", most)
    fm, rows = workloads.load(spark, SF, "bow_quality")
    other = M.FeatureMatrix(K.cut(fm.entries), K.cut(fm.rows), fm.d)
    changes = [dict(workloads.CHANGES[x]) for x in ("default", "signs=learned", "init=oblivious_groups", "rate=decay", "eps=0", "reseed_empty")]
    for more in [*changes, {"batch": 0.3}] if most else [changes[0], changes[-1]]:
        learn = (lambda x: K.learn_minibatch(x, 7, 2, 0.3, 5.0, seed=3)) if "batch" in more else lambda x, more=more: K.learn_full(x, 7, 2, 5.0, **({"eps": 0.1, "seed": 3} | more))
        before = _files(spark)
        model = learn(fm)
        assert _files(spark) - before < 40 * fm.d and not model.held
        signs = {(r.feature_id, r.sign) for r in model.feature_map.collect()}
        assert len(signs) == fm.d and {s for _, s in signs} == {-1, 1}
        got, want = ({(r.row_id, r.bucket): r.value for r in x.training_sketch().collect()} for x in (model, learn(other)))
        assert got == pytest.approx(want) and len(got) > 50
    workloads._done(fm, rows)


def test_lists_of_texts(spark, tmp_path):
    """The same matrix as by tokens moved in entries; a repeated doc_id goes that way."""
    fast = {}
    for name in ("bigram", "bow_quality"):
        fm, rows = workloads.load(spark, SF, name)
        docs = M.table(spark, SF, "documents", ["doc_id", "text", "lang"])
        slow, ids = M.dense_ids(workloads.DATASETS[name](spark, SF)[0])
        want = {(r.row_id, r.feature_id): r.value for r in slow.entries.collect()}
        assert fm.lists is not None and fm.d == slow.d
        assert {(r.row_id, r.feature_id): r.value for r in fm.entries.collect()} == pytest.approx(want)
        fast[name] = fm.rows.count()
        workloads._done(fm, rows)
    assert 0 < fast["bow_quality"] < fast["bigram"] == docs.count()
    docs.unionByName(docs.limit(1)).write.parquet(str(tmp_path / "documents.parquet"))
    assert workloads.load(spark, str(tmp_path), "bow_en")[0].lists is None


def test_min_max_of_zeros(spark):
    x = np.array([[0, 5.0, 1, 0], [1, 5.0, -1, 0], [2, 5.0, 0, 0], [0, 5.0, 3, 0]])
    fm = M.FeatureMatrix(spark.createDataFrame([(i, j, float(x[i, j])) for i in range(4) for j in range(4) if x[i, j]], M.ENTRIES), spark.range(4).withColumnRenamed("id", "row_id"))
    got = np.zeros((4, 4))
    for i, j, v in M.min_max(fm).entries.collect():
        got[i, j] = v
    want = np.array([[-1, 0, 0, 0], [0, 0, -1, 0], [1, 0, -0.5, 0], [-1, 0, 1, 0.0]])
    assert np.allclose(got, want)
    empty = M.FeatureMatrix(fm.entries.where("false"), fm.rows.where("false"))
    assert M.min_max(empty).entries.count() == 0


def test_min_max_moves_no_dense_cells(spark, monkeypatch):
    monkeypatch.setattr(M, "CELLS", 7)
    r = np.random.default_rng(3)
    x = r.integers(-2, 4, (9, 11)) * (r.random((9, 11)) < 0.5).astype(float)
    x[:, 4], x[:, 6] = np.arange(1, 10), 3.0
    fm = M.FeatureMatrix(spark.createDataFrame([(i, 5 * j, float(x[i, j])) for i in range(9) for j in range(11) if x[i, j]], M.ENTRIES), spark.range(9).withColumnRenamed("id", "row_id"))
    low, high = x.min(axis=0), x.max(axis=0)
    want = {(i, 5 * j): 2 * (x[i, j] - low[j]) / (high[j] - low[j]) - 1 for i in range(9) for j in range(11) if high[j] > low[j]}
    for most in (M.MAX_BROADCAST, 0):  # sent to the tasks, and joined
        out = M.min_max(fm, most).entries
        assert {(i, j): v for i, j, v in out.collect()} == pytest.approx({k: v for k, v in want.items() if v})
    plan = M.min_max(fm).entries._jdf.queryExecution().optimizedPlan().toString()
    assert "Join Cross" not in plan and "Join Inner\n" not in plan


def test_streams(spark, tmp_path):
    rows = [(i, i % 3, f"2024-01-01 00:{i:02d}:00", i % 5) for i in range(20)]
    df = spark.createDataFrame(rows, "event_id long, user_id long, ts string, feature_id long").withColumn("ts", F.col("ts").cast("timestamp"))
    df.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(df.schema).parquet(str(tmp_path / "in"))
    fm = M.FeatureMatrix(df.groupBy("user_id", "feature_id").agg(F.count("*").cast("double").alias("value")).withColumnRenamed("user_id", "row_id"), df.select(F.col("user_id").alias("row_id")).distinct())
    model = K.learn_full(fm, 3, 1, seed=1)
    S.apply_models(stream(), lambda n: model, str(tmp_path / "out"), str(tmp_path / "c"))
    got = {(r.user_id, r.bucket): r.value for r in spark.read.parquet(str(tmp_path / "out")).groupBy("user_id", "bucket").agg(F.sum("value").alias("value")).collect() if abs(r.value) > 1e-12}
    want = {(r.row_id, r.bucket): r.value for r in model.transform(fm, "none").collect()}
    assert got == pytest.approx(want)
    pairs = S.drain(S.followed_by(stream().where("feature_id = 0"), stream().where("feature_id = 1"), "10 minutes"), "append")
    assert {tuple(r) for r in pairs.collect()} == {(a[1], a[0], b[0]) for a in rows for b in rows if a[3] == 0 and b[3] == 1 and a[1] == b[1] and 0 <= b[0] - a[0] <= 10}
