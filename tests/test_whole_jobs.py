"""Operators and experiments that read the whole input."""

import inspect
import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from colsketch.operators import adaptive
from colsketch.operators import oblivious as O
from colsketch.plans import catalog, relational, solve, workloads
from colsketch.sources import matrix as M


def test_ngrams_of_whole_texts(spark):
    texts = {1: "ab" * 1500 + "é😀z" * 400, 2: "B" * 2500 + "éZ", 3: "a", 4: None, 5: ""}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {(r.row_id, r.feature_id): r.value for r in M.from_ngrams(df, "doc_id", F.col("text"), min_df=1).entries.collect()}
    tf = {i: Counter(t.lower()[k : k + 2] for k in range(len(t) - 1)) for i, t in texts.items() if t}
    names = sorted({g for c in tf.values() for g in c})
    ids = {r.g: r.id for r in spark.createDataFrame([(g,) for g in names], "g string").select("g", M.token_id(F.col("g")).alias("id")).collect()}
    size = {i: math.sqrt(sum((1 + math.log(n)) ** 2 for n in c.values())) for i, c in tf.items()}
    assert got == pytest.approx({(i, ids[g]): (1 + math.log(n)) / size[i] for i, c in tf.items() for g, n in c.items()})


def test_every_row_and_dimension(spark, tmp_path):
    x = np.random.default_rng(1).normal(size=(430, 64)).astype(np.float32)
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    x = x.astype(float)
    got = {(r.row_id, r.feature_id): r.value for r in catalog.quadratic_embeddings(spark, str(tmp_path)).where("row_id % 61 = 0").collect()}
    want = {(i, j): x[i, j] for i in range(0, 430, 61) for j in range(64)}
    want |= {(i, 64 + 64 * j + k): x[i, j] * x[i, k] for i in range(0, 430, 61) for j in range(64) for k in range(j, 64)}
    assert got == pytest.approx(want) and len(got) == 2144 * 8
    sketch = np.zeros((430, catalog.R))
    for r in O.countsketch(M.embeddings(spark, str(tmp_path)), catalog.R, catalog.SEED).collect():
        sketch[r.row_id, r.bucket] = r.value
    ratio = [((sketch[i] - sketch[j]) ** 2).sum() / ((x[i] - x[j]) ** 2).sum() for i in range(430) for j in range(i + 1, min(i + 8, 430))]
    r = catalog.distortion_pairs(spark, str(tmp_path)).first()
    assert r.pairs == len(ratio) and r.mean_ratio == pytest.approx(np.mean(ratio), abs=2e-6) and r.share == pytest.approx(np.mean([0.5 <= q <= 1.5 for q in ratio]))


def test_both_sql_twins(spark):
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    con.execute("create view embeddings as select * from '/root/testdata/sf0.01/embeddings.parquet'")
    for name in ("distortion_pairs", "quadratic_embeddings"):
        got = sorted(tuple(r) for r in catalog.queries()[name](spark, "/root/testdata/sf0.01").collect())
        want = sorted(con.execute(catalog.oracle_sql()[name]).fetchall())
        assert len(got) == len(want) and all(a == pytest.approx(b) for a, b in zip(got, want, strict=True))


def test_registered_experiments_are_the_published_ones(monkeypatch):
    seen = {}
    monkeypatch.setattr(catalog, "ship", lambda s: s)
    for f in ("compare", "methods", "embedding_time", "stability", "tuning", "ablations"):
        whole = inspect.signature(getattr(workloads, f))
        monkeypatch.setattr(workloads, f, lambda *a, whole=whole, **k: whole.bind(*a, **k))
    for name, run in catalog.queries().items():
        if name.startswith("workload_"):
            bound = run(None, "d")
            bound.apply_defaults()
            seen[name] = bound.arguments
            assert not bound.arguments.get("more"), name  # five folds are the default
    assert inspect.signature(workloads.load).parameters["k"].default == 5 == inspect.signature(solve.cross_validate).parameters["k"].default
    for base in ("methods", "embedding_time", "stability", "tuning", "ablations"):
        assert {a["dataset"] for n, a in seen.items() if n.startswith(f"workload_{base}")} == set(workloads.DATASETS)
    assert all(list(a["names"]) == workloads.METHODS for n, a in seen.items() if n.startswith("workload_methods"))
    assert all(list(a["methods"]) == workloads.METHODS for n, a in seen.items() if n.startswith("workload_widths"))
    assert all(a["cs"] == tuple(10.0**k for k in range(-5, 6)) and a["lams"] == (10.0, 20.0, 30.0, 40.0) for n, a in seen.items() if n.startswith("workload_tuning"))


def test_unknown_init_raises(spark):
    m = spark.createDataFrame([(1, 1, 1.0)], "row_id long, feature_id long, value double")
    with pytest.raises(ValueError, match="other"):
        adaptive.init_centres(m, 1, 0, "other")


def test_transform_of_the_features_that_occur(spark, tmp_path):
    spark.createDataFrame([(0, [1.0, 0.0, 2.0]), (1, [0.0, 0.0, 3.0])], "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    assert {tuple(r) for r in catalog.hadamard_matrix(spark, str(tmp_path)).collect()} == {(i, j, 1 - 2 * ((i & j).bit_count() % 2)) for i in (0, 2) for j in (0, 2)}


def test_bisection_of_a_table(spark, tmp_path):
    spark.createDataFrame([(1, 20.0), (2, 16.0), (1, 28.0), (3, 8.0), (4, 0.0)], "l_linenumber int, l_quantity double").write.parquet(str(tmp_path / "lineitem.parquet"))
    # Sums 48, 16, 8, 0 and radius 36; at 12 they leave 36 + 4.
    assert [tuple(r) for r in relational.recursive_bisection(spark, str(tmp_path)).orderBy("k").collect()] == [(0, 0.0, 48.0, 72.0), (1, 0.0, 24.0, 24.0), (2, 12.0, 24.0, 40.0), (3, 12.0, 18.0, 30.0), (4, 12.0, 15.0, 34.0), (5, 13.5, 15.0, 37.0)]
