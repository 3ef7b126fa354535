"""A learned map in use: scores of single rows, a SQL table function, and a stage of an ML pipeline."""

from __future__ import annotations

import pandas as pd
from pyspark.ml import Estimator, Model
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import adaptive as K
from ..sources import formats
from ..sources.matrix import FeatureMatrix

#: Features that a map in the memory of every Python worker may have.
LARGEST_MAP = 2_000_000


def _in_memory(model: K.SketchModel) -> dict[int, tuple[int, float, float]]:
    """feature_id -> (bucket, sign / size, theta), of checked size."""
    if model.meta.get("d", LARGEST_MAP + 1) > LARGEST_MAP:
        raise ValueError("the map is too large for workers' memory; use SketchModel.transform")
    rows = model.feature_map.join(F.broadcast(model.groups), "bucket").select("feature_id", "bucket", (F.col("sign") / F.col("size")).alias("w"), "theta").collect()
    return {x.feature_id: (x.bucket, x.w, x.theta) for x in rows}


def sketch_one(fmap: dict[int, tuple[int, float, float]], idx, val) -> dict[int, float]:
    """The sketch of one row, {bucket: value}; unknown features are left out."""
    sums: dict[int, list[float]] = {}
    for i, v in zip(() if idx is None else idx, () if val is None else val, strict=False):
        if i in fmap and v is not None:
            bucket, w, theta = fmap[i]
            sums.setdefault(bucket, [0.0, theta])[0] += v * w
    return {b: (abs(t) - theta) * (1 if t > 0 else -1) for b, (t, theta) in sorted(sums.items()) if abs(t) > theta}


def score_row(model: K.SketchModel, weights: list[float], bias: float = 0.0):
    """A column function of (idx, val) arrays: the linear score of each row's sketch."""
    sent = model.feature_map.sparkSession.sparkContext.broadcast(_in_memory(model))

    @F.pandas_udf("double")
    def score(idx: pd.Series, val: pd.Series) -> pd.Series:
        fmap = sent.value
        return pd.Series([bias + sum(weights[b] * v for b, v in sketch_one(fmap, i, x).items()) for i, x in zip(idx, val, strict=True)], dtype="float64")

    return score


def register_table_function(spark: SparkSession, model: K.SketchModel, name: str = "colsketch_transform") -> None:
    """SQL: select ... from rows, lateral colsketch_transform(idx, val), which gives (bucket, value)."""
    sent = spark.sparkContext.broadcast(_in_memory(model))

    @F.udtf(returnType="bucket int, value double")
    class Transform:
        def eval(self, idx, val):
            yield from sketch_one(sent.value, idx, val).items()

    spark.udtf.register(name, Transform)


class ColumnSketch(Estimator):
    """Learns a sketch of a vector column; the fitted stage adds a column of sketch vectors."""

    def __init__(self, r: int, input_col: str = "features", output_col: str = "sketch", row_col: str = "row_id", **learning):
        super().__init__()
        self.r, self.input_col, self.output_col, self.row_col, self.learning = r, input_col, output_col, row_col, learning

    def _fit(self, dataset: DataFrame) -> ColumnSketchModel:
        return ColumnSketchModel(K.learn_full(formats.from_vectors(dataset, self.row_col, self.input_col), self.r, **self.learning), self)


class ColumnSketchModel(Model):
    def __init__(self, model: K.SketchModel, made_by: ColumnSketch):
        super().__init__()
        self.model, self.of = model, made_by

    def _transform(self, dataset: DataFrame) -> DataFrame:
        o = self.of
        fm: FeatureMatrix = formats.from_vectors(dataset, o.row_col, o.input_col)
        got = self.model.transform(fm).groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "value"))).alias("_cells"))
        cells = F.transform(F.sequence(F.lit(0), F.lit(o.r - 1)), lambda b: F.coalesce(F.try_element_at("_cells", b), F.lit(0.0)))
        out = dataset.join(got.withColumnRenamed("row_id", "_row"), F.col(o.row_col) == F.col("_row"), "left")
        return out.withColumn(o.output_col, array_to_vector(cells)).drop("_row", "_cells")


def scored(model: K.SketchModel, fm: FeatureMatrix, weights: list[float]) -> DataFrame:
    """(row_id, score) of every row."""
    return fm.as_rows().select("row_id", score_row(model, weights)("idx", "val").alias("score"))


__all__ = ["ColumnSketch", "ColumnSketchModel", "register_table_function", "score_row", "scored", "sketch_one"]
