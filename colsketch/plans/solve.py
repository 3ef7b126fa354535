"""Sketch and solve: folds, linear classifiers, least squares, low rank and k-means on sketches."""

from __future__ import annotations

import numpy as np
from pyspark.ml.classification import LinearSVC, LogisticRegression, OneVsRest
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from ..sources.matrix import FeatureMatrix
from . import linear


def folds(rows: DataFrame, key: str = "row_id", k: int = 5) -> DataFrame:
    """Stable folds by hash; give the digest of a text as key so that exact copies share a fold."""
    h = F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 8), 16, 10).cast("long")
    return rows.withColumn("fold", F.pmod(h, F.lit(k)).cast("int"))


def vectors(sketch: DataFrame, rows: DataFrame, r: int) -> DataFrame:
    """(row_id, ..., features): one vector of r values a row, empty rows too, made in the JVM."""
    held = sketch.groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("bucket").cast("int"), "value"))).alias("p"))
    value = F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda b: F.coalesce(F.try_element_at("p", b), F.lit(0.0)))
    return rows.join(held, "row_id", "left").withColumn("features", array_to_vector(value)).drop("p")


def classifier(loss: str, n: int, c: float, classes: int):
    """Spark's own classifiers: hinge loss, one against the rest for more than two classes, or logistic loss."""
    reg = 1.0 / (n * c)
    if loss == "logistic":
        return LogisticRegression(regParam=reg, standardization=False, maxIter=50)
    svm = LinearSVC(regParam=reg, standardization=False, maxIter=50)
    return svm if classes == 2 else OneVsRest(classifier=svm)


def linear_svm(sketch: DataFrame, labels: DataFrame, r: int, c: float = 1.0, loss: str = "hinge"):
    """A fitted classifier of Spark on all rows of labels (row_id, label); labels run from 0."""
    rows = labels.withColumn("label", F.col("label").cast("double"))
    n, classes = rows.agg(F.count("*"), F.countDistinct("label")).first()
    return classifier(loss, n, c, classes).fit(vectors(sketch, rows, r))


def predict(model, sketch: DataFrame, rows: DataFrame, r: int) -> DataFrame:
    """(row_id, predicted) by a classifier of linear_svm()."""
    return model.transform(vectors(sketch, rows.select("row_id"), r)).select("row_id", F.col("prediction").cast("int").alias("predicted"))


def cross_validate(fm: FeatureMatrix, labels: DataFrame, sketch_of, r: int, c: float = 1.0, k: int = 5, loss: str = "squared_hinge", protocol: str = "transductive", key: str = "row_id") -> DataFrame:
    """(row_id, fold, label, predicted). sketch_of(train fm or all) returns a function from a matrix to its sketch.

    transductive: the sketch is made from all rows, then folds are cut; inductive: learned on the training folds alone.
    """
    rows = cut(folds(fm.rows.join(labels, "row_id"), key, k).select("row_id", "label", "fold"))
    found = sorted(x.fold for x in rows.select("fold").distinct().collect())
    if len(found) < 2:
        raise ValueError("fewer than two folds have rows")
    if protocol == "transductive":
        sketches = {"all": linear.Sketched(sketch_of(fm)(fm), r)}
    else:
        sketches = {}
        for f in found:
            inside = rows.where(F.col("fold") != f).select("row_id")
            apply = sketch_of(FeatureMatrix(fm.entries.join(inside, "row_id", "left_semi"), inside, fm.d))
            sketches[str(f)] = linear.Sketched(apply(fm), r, (f,))
    return linear.Models(sketches, rows, (c,), loss).fit().predictions().drop("name", "c")


def grid(fm, labels, sketch_of_lam, r: int, cs=tuple(10.0**k for k in range(-5, 6)), lams=(10, 20, 30, 40), k: int = 5, loss: str = "squared_hinge") -> list[tuple[float, float, float]]:
    """(lam, C, mean accuracy in percent) over both grids, all models in one loop over the rows."""
    rows = cut(folds(fm.rows.join(labels, "row_id"), "row_id", k).select("row_id", "label", "fold"))
    sketches = {str(lam): linear.Sketched(sketch_of_lam(lam)(fm)(fm), r) for lam in lams}
    scores = linear.Models(sketches, rows, cs, loss).fit().scores()
    return [(lam, c, scores[str(lam), c]["accuracy"]) for lam in lams for c in cs]


def nearest_centroid(sketch: DataFrame, rows: DataFrame, k: int = 5) -> DataFrame:
    """(row_id, fold, label, predicted) with class means of the other folds (extension); rows (row_id, label, fold)."""
    per = rows.join(sketch, "row_id").groupBy("fold", "label", "bucket").agg(F.sum("value").alias("s"))
    n = rows.groupBy("fold", "label").agg(F.count("*").alias("n"))
    every = rows.select(F.col("fold").alias("test")).distinct()
    centre = per.join(F.broadcast(every), F.col("fold") != F.col("test")).groupBy("test", "label", "bucket").agg(F.sum("s").alias("s"))
    size = n.join(F.broadcast(every), F.col("fold") != F.col("test")).groupBy("test", "label").agg(F.sum("n").alias("n"))
    mean = centre.join(size, ["test", "label"]).select("test", F.col("label").alias("guess"), "bucket", (F.col("s") / F.col("n")).alias("c"))
    norm = mean.groupBy("test", "guess").agg(F.sum(F.col("c") * F.col("c")).alias("sq"))
    x = rows.select("row_id", "fold", "label").join(sketch, "row_id")
    dots = x.join(mean, (F.col("fold") == F.col("test")) & (x["bucket"] == mean["bucket"])).groupBy("row_id", "guess").agg(F.sum(F.col("value") * F.col("c")).alias("dot"))
    all_pairs = rows.join(F.broadcast(norm), F.col("fold") == F.col("test")).select("row_id", "fold", "label", "guess", "sq")
    dist = all_pairs.join(dots, ["row_id", "guess"], "left").withColumn("dist", F.round(F.col("sq") - 2 * F.coalesce("dot", F.lit(0.0)), 9))
    return dist.groupBy("row_id", "fold", "label").agg(F.min(F.struct("dist", "guess"))["guess"].alias("predicted"))


def gram(sketch: DataFrame, y: DataFrame) -> DataFrame:
    """(i, j, v) of the sketch's Gram matrix, with j = -1 for the products with y (row_id, y)."""
    a, b = sketch.alias("a"), sketch.alias("b")
    g = a.join(b, "row_id").groupBy(F.col("a.bucket").alias("i"), F.col("b.bucket").alias("j")).agg(F.sum(F.col("a.value") * F.col("b.value")).alias("v"))
    h = sketch.join(y, "row_id").groupBy(F.col("bucket").alias("i"), F.lit(-1).alias("j")).agg(F.sum(F.col("value") * F.col("y")).alias("v"))
    return g.unionByName(h)


def least_squares(sketch: DataFrame, y: DataFrame, r: int, ridge: float = 1e-9) -> np.ndarray:
    a, b = np.zeros((r, r)), np.zeros(r)
    for i, j, v in gram(sketch, y).collect():  # r x (r + 1) figures
        if j < 0:
            b[i] = v
        else:
            a[i, j] = v
    return np.linalg.solve(a + ridge * np.eye(r), b)


def low_rank(fm: FeatureMatrix, k: int, seed: int, oversample: int = 8) -> tuple[float, float]:
    """(error, energy) in squared Frobenius norm of the best rank-k matrix in the range of a Gaussian sketch.

    With Q an orthonormal basis of the sketch, the error is the energy less the k largest eigenvalues of Q'X X'Q; Q and
    Q'X stay tables, and the driver sees two square matrices of k + oversample rows.
    """
    from ..operators.oblivious import gaussian

    m = k + oversample

    def square(a: DataFrame, key: str) -> np.ndarray:
        out, x, y = np.zeros((m, m)), a.alias("x"), a.alias("y")
        for i, j, v in x.join(y, key).groupBy("x.bucket", "y.bucket").agg(F.sum(F.col("x.value") * F.col("y.value"))).collect():
            out[i, j] = v
        return out

    y = cut(gaussian(fm, m, seed, "per_r", family="hash64"))
    values, vectors = np.linalg.eigh(square(y, "row_id"))
    live = values > 1e-12 * max(values.max(), 1e-300)
    turn = vectors[:, live] / np.sqrt(values[live])
    w = F.broadcast(fm.entries.sparkSession.createDataFrame([(i, j, float(turn[i, j])) for i in range(m) for j in range(turn.shape[1])], "bucket int, b int, w double"))
    q = y.join(w, "bucket").groupBy("row_id", F.col("b").alias("bucket")).agg(F.sum(F.col("value") * F.col("w")).alias("q"))
    qx = fm.entries.join(q, "row_id").groupBy("feature_id", "bucket").agg(F.sum(F.col("value") * F.col("q")).alias("value"))
    kept = np.sort(np.linalg.eigvalsh(square(qx, "feature_id")))[::-1][:k].sum()
    energy = fm.entries.agg(F.sum(F.col("value") * F.col("value"))).first()[0] or 0.0
    return max(0.0, energy - float(kept)), energy


def kmeans_rows(sketch: DataFrame, rows: DataFrame, r: int, k: int, seed: int = 0) -> DataFrame:
    data = vectors(sketch, rows, r)
    return KMeans(k=k, seed=seed).fit(data).transform(data).select("row_id", F.col("prediction").alias("cluster"))
