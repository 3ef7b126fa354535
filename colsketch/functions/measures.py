"""Cost and accuracy measures, by norms and counts; nothing is made dense."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.oblivious import group_sizes
from ..sources.matrix import FeatureMatrix


def signed_group_sums(fm: FeatureMatrix, fmap: DataFrame) -> DataFrame:
    e = fm.entries.join(fmap, "feature_id")
    return e.groupBy("row_id", "bucket").agg(F.sum(F.col("value") * F.col("sign")).alias("t"))


def energy(fm: FeatureMatrix) -> DataFrame:
    return fm.entries.agg(F.coalesce(F.sum(F.col("value") * F.col("value")), F.lit(0.0)).alias("energy"))


def reconstruction_error(fm: FeatureMatrix, fmap: DataFrame) -> DataFrame:
    """(error, relative): energy less the sum of squared group sums over group sizes."""
    kept = signed_group_sums(fm, fmap).join(F.broadcast(group_sizes(fmap)), "bucket").agg(F.coalesce(F.sum(F.col("t") * F.col("t") / F.col("size")), F.lit(0.0)).alias("kept"))
    both = energy(fm).crossJoin(kept)  # one row each
    return both.select((F.col("energy") - F.col("kept")).alias("error"), F.try_divide(F.col("energy") - F.col("kept"), F.col("energy")).alias("relative"))


def kmeans_objective(fm: FeatureMatrix, fmap: DataFrame, centres: DataFrame) -> DataFrame:
    """Sum of squared distances of signed columns to their centres: energy - 2 products + sizes x squared norms."""
    sums = signed_group_sums(fm, fmap)
    cross = sums.join(centres.select("row_id", "bucket", F.col("value").alias("c")), ["row_id", "bucket"]).agg(F.coalesce(F.sum(F.col("t") * F.col("c")), F.lit(0.0)).alias("cross"))
    norms = centres.groupBy("bucket").agg(F.sum(F.col("value") * F.col("value")).alias("sq")).join(F.broadcast(group_sizes(fmap)), "bucket").agg(F.coalesce(F.sum(F.col("sq") * F.col("size")), F.lit(0.0)).alias("norms"))
    return energy(fm).crossJoin(cross).crossJoin(norms).select((F.col("energy") - 2 * F.col("cross") + F.col("norms")).alias("objective"))


def sparsity(sketch: DataFrame, rows: DataFrame, r: int) -> DataFrame:
    """Share of zeros among rows x r cells; null without rows."""
    n = rows.agg(F.count("*").alias("n"))
    filled = sketch.where("value != 0").agg(F.count("*").alias("filled"))
    return n.crossJoin(filled).select("n", "filled", (1 - F.try_divide(F.col("filled"), F.col("n") * r)).alias("zeros"))


def group_profile(fmap: DataFrame, r: int) -> DataFrame:
    sizes = group_sizes(fmap)
    return sizes.agg((F.lit(r) - F.count("*")).alias("empty_groups"), F.max("size").alias("largest"), F.sum("size").alias("features"))


def group_entropy(fmap: DataFrame) -> DataFrame:
    """(entropy) in bits of the sizes of groups; null without features."""
    sizes = group_sizes(fmap)
    share = F.col("size") / F.col("features")
    return sizes.crossJoin(sizes.agg(F.sum("size").alias("features"))).agg((-F.sum(share * F.log2(share))).alias("entropy"))  # one row


def balanced_accuracy(predictions: DataFrame) -> DataFrame:
    """(balanced, majority) in percent: the mean recall of the classes, and the share of the largest one."""
    by = predictions.groupBy("label").agg(F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("recall"), F.count("*").alias("n"))
    return by.agg((100 * F.avg("recall")).alias("balanced"), (100 * F.try_divide(F.max("n"), F.sum("n"))).alias("majority"))


def orthonormality(fmap: DataFrame) -> DataFrame:
    """(bucket, gram): the diagonal of the scaled map's Gram matrix, size x (1/sqrt(size))^2; others are 0 by construction."""
    return group_sizes(fmap).select("bucket", "size", (F.col("size") * (1 / F.col("size"))).alias("gram"))


def profile(fm: FeatureMatrix, labels: DataFrame | None = None, d: int | None = None) -> DataFrame:
    one = fm.entries.agg(F.count("*").alias("nnz"), F.countDistinct("feature_id").alias("met"))
    out = fm.rows.agg(F.count("*").alias("n")).crossJoin(one).withColumn("d", F.lit(d).cast("long") if d else F.col("met"))
    out = out.select("n", "d", "nnz", (1 - F.try_divide(F.col("nnz"), F.col("n") * F.col("d"))).alias("zeros"))
    return out.crossJoin(labels.agg(F.countDistinct("label").alias("classes"))) if labels is not None else out


def l1_feasible(centres: DataFrame, lam: float, eps: float, before: DataFrame | None = None) -> DataFrame:
    """(centres, outside, below): projected centres with too large a norm, and, of those that lay outside the ball before, with too small a one."""
    norms = centres.groupBy("bucket").agg(F.sum(F.abs("value")).alias("l1"))
    was = (before if before is not None else centres).groupBy("bucket").agg(F.sum(F.abs("value")).alias("was"))
    both = was.join(norms, "bucket", "full").select(F.coalesce("l1", F.lit(0.0)).alias("l1"), F.coalesce("was", F.lit(0.0)).alias("was"))
    low = (F.col("was") > lam * (1 + eps)) & (F.col("l1") < lam * (1 - 1e-9))
    return both.agg(F.count("*").alias("centres"), F.count_if(F.col("l1") > lam * (1 + eps) * (1 + 1e-9)).alias("outside"), F.count_if(low).alias("below"))


def prediction_ops(fm: FeatureMatrix, sketch: DataFrame | None, method: str, r: int, d: int) -> DataFrame:
    """(row_id, projection, classification): exact operation counts for one prediction."""
    nnz = fm.rows.join(fm.entries.groupBy("row_id").agg(F.count("*").alias("nnz")), "row_id", "left").select("row_id", F.coalesce("nnz", F.lit(0)).alias("nnz"))
    width = 1 << max(0, (d - 1).bit_length())
    dense = {"gaussian": d * r, "ternary": d * r, "hadamard": int(width * math.log2(width)), "hadamard_topr": int(width * math.log2(width))}
    if method in dense:  # whatever the row
        return nnz.select("row_id", F.lit(dense[method]).cast("long").alias("projection"), F.lit(r).cast("long").alias("classification"))
    filled = sketch.groupBy("row_id").agg(F.count("*").alias("f"))
    return nnz.join(filled, "row_id", "left").select("row_id", F.col("nnz").alias("projection"), F.coalesce("f", F.lit(0)).alias("classification"))


def embed_ops(m: DataFrame, centres: DataFrame) -> DataFrame:
    """Products that one assignment pass makes: for each row, its non-zeros times its live centres."""
    a = m.groupBy("row_id").agg(F.count("*").alias("a"))
    b = centres.groupBy("row_id").agg(F.count("*").alias("b"))
    return a.join(b, "row_id").agg(F.sum(F.col("a") * F.col("b")).alias("products"))


def distances(entries: DataFrame, pairs: DataFrame) -> DataFrame:
    """Squared distances of listed pairs (i, j) of rows; entries (row_id, feature, value)."""
    long = pairs.select("i", "j", F.explode(F.array(F.struct(F.col("i").alias("row_id"), F.lit(1.0).alias("s")), F.struct(F.col("j").alias("row_id"), F.lit(-1.0).alias("s")))).alias("p")).select("i", "j", "p.row_id", "p.s")
    diff = long.join(entries.toDF("row_id", "feature", "value"), "row_id").groupBy("i", "j", "feature").agg(F.sum(F.col("s") * F.col("value")).alias("v"))
    return diff.groupBy("i", "j").agg(F.sum(F.col("v") * F.col("v")).alias("sq"))


def distortion(fm: FeatureMatrix, sketch: DataFrame, pairs: DataFrame, eps: float, factor: float = 1.0) -> DataFrame:
    """Ratio of sketched to true squared distances over pairs of rows: mean, and the share within 1 +- eps."""
    true = distances(fm.entries, pairs).withColumnRenamed("sq", "t")
    got = distances(sketch.select("row_id", "bucket", "value"), pairs).withColumnRenamed("sq", "g")
    ratio = true.where("t > 0").join(got, ["i", "j"], "left").select((F.coalesce("g", F.lit(0.0)) * factor / F.col("t")).alias("ratio"))
    return ratio.agg(F.count("*").alias("pairs"), F.avg("ratio").alias("mean_ratio"), F.avg(((F.col("ratio") >= 1 - eps) & (F.col("ratio") <= 1 + eps)).cast("double")).alias("share"))


def jl_width(n: int, eps: float, constant: float = 8.0) -> int:
    return math.ceil(constant * math.log(n) / eps**2)


def accuracy(predictions: DataFrame) -> DataFrame:
    """(mean, sd, folds) of accuracy by fold, in percent."""
    by = predictions.groupBy("fold").agg((100 * F.avg((F.col("label") == F.col("predicted")).cast("double"))).alias("a"))
    return by.agg(F.avg("a").alias("mean"), F.coalesce(F.stddev_samp("a"), F.lit(0.0)).alias("sd"), F.count("*").alias("folds"))


def confusion(predictions: DataFrame) -> DataFrame:
    return predictions.groupBy("label", "predicted").agg(F.count("*").alias("n"))


def timed(df: DataFrame, repeats: int = 3) -> float:
    """Median milliseconds to compute df into no sink."""
    took = []
    for _ in range(repeats):
        start = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took.append(1000 * (time.perf_counter() - start))
    return sorted(took)[len(took) // 2]


def stability(by_seed: DataFrame) -> DataFrame:
    """(method, runs, low, mean, high, sd) of accuracies over seeds; by_seed (method, seed, accuracy)."""
    a = F.col("accuracy")
    return by_seed.groupBy("method").agg(F.count("*").alias("runs"), F.min(a).alias("low"), F.avg(a).alias("mean"), F.max(a).alias("high"), F.coalesce(F.stddev_samp(a), F.lit(0.0)).alias("sd"))
