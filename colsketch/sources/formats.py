"""Other forms of matrices: ML vectors, label and index:value text, bucketed tables, pages, and a source of planted groups."""

from __future__ import annotations

import pyarrow as pa
from pyspark.ml.functions import vector_to_array
from pyspark.ml.linalg import SparseVector, VectorUDT
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .matrix import FeatureMatrix


def from_vectors(df: DataFrame, row: str, vector: str) -> FeatureMatrix:
    """Entries of a column of ML vectors, dense or sparse; null vectors are rows without entries."""
    e = df.select(F.col(row).cast("long").alias("row_id"), F.posexplode(vector_to_array(vector)).alias("feature_id", "value"))
    return FeatureMatrix(e.where("value != 0").select("row_id", F.col("feature_id").cast("long"), "value"), df.select(F.col(row).cast("long").alias("row_id")))


def to_vectors(fm: FeatureMatrix, d: int) -> DataFrame:
    """(row_id, features): one sparse vector a row; feature ids must be below d."""
    make = F.udf(lambda i, v: SparseVector(d, i, v), VectorUDT())
    return fm.as_rows().select("row_id", make("idx", "val").alias("features"))


def write_sparse_text(fm: FeatureMatrix, labels: DataFrame, path: str) -> None:
    """Lines of a label and index:value pairs, indices from 1 and ascending; rows without a label get 0."""
    pairs = F.transform(F.arrays_zip("idx", "val"), lambda p: F.concat((p["idx"] + 1).cast("string"), F.lit(":"), p["val"].cast("string")))
    lines = fm.as_rows().join(labels, "row_id", "left").select(F.rtrim(F.concat_ws(" ", F.coalesce("label", F.lit(0)).cast("string"), F.array_join(pairs, " "))).alias("value"))
    lines.write.mode("overwrite").text(path)


def read_sparse_text(spark: SparkSession, path: str) -> tuple[FeatureMatrix, DataFrame]:
    """The matrix and labels of such lines, rows numbered by hash of file, split and place; the numbers agree between reads only while files are split alike."""
    lines = spark.read.text(path).select(F.split(F.trim("value"), " +").alias("p"), F.xxhash64(F.col("_metadata.file_path"), F.col("_metadata.file_block_start"), F.monotonically_increasing_id()).alias("row_id"))
    pair = F.split(F.col("pair"), ":")
    e = lines.select("row_id", F.explode(F.slice("p", 2, F.greatest(F.size("p") - 1, F.lit(0)))).alias("pair")).select("row_id", (pair[0].cast("long") - 1).alias("feature_id"), pair[1].cast("double").alias("value"))
    return FeatureMatrix(e.where("value != 0"), lines.select("row_id")), lines.select("row_id", F.col("p")[0].cast("double").alias("label"))


def write_bucketed(fm: FeatureMatrix, table: str, buckets: int = 1024, by: str = "row_id") -> None:
    """A bucketed table of the entries: joins on `by` then need no shuffle."""
    fm.entries.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def _part(buckets: int) -> Column:
    return F.pmod(F.xxhash64("feature_id"), F.lit(buckets)).cast("int")


def write_by_feature(fm: FeatureMatrix, path: str, buckets: int = 1024, files: int = 8) -> None:
    """Entries in folders by the hash of their feature, each of some files, as a feature may hold many of the rows."""
    fm.entries.withColumn("part", _part(buckets)).repartition("part", F.pmod(F.xxhash64("row_id"), F.lit(files))).write.mode("overwrite").partitionBy("part").parquet(path)


def read_features(spark: SparkSession, path: str, features: DataFrame, buckets: int = 1024) -> DataFrame:
    """The entries of the given features (feature_id); only their folders are read."""
    parts = [r.part for r in features.where("feature_id is not null").select(_part(buckets).alias("part")).distinct().collect()]  # at most `buckets`
    entries = spark.read.schema("row_id long, feature_id long, value double, part int").parquet(path).where(F.col("part").isin(parts))
    return entries.join(features.select("feature_id").distinct(), "feature_id", "left_semi").select("row_id", "feature_id", "value")


def strip_tags(html: Column) -> Column:
    """Page text without scripts, styles, comments and tags, white space made one space; a plain strip, not the page template."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>", " ")
    return F.trim(F.regexp_replace(bare, r"[ \t\r\n]+", " "))


def url_part(url: Column, part: str) -> Column:
    return F.try_parse_url(url, F.lit(part))


class PlantedReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.groups = int(options.get("rows", 200)), int(options.get("groups", 6))
        self.copies, self.parts = int(options.get("copies", 10)), int(options.get("partitions", 4))
        self.seed, self.noise = int(options.get("seed", 0)), float(options.get("noise", 0.05))

    def partitions(self):
        return [InputPartition(p) for p in range(self.parts)]

    def read(self, partition):
        import numpy as np

        for row in range(partition.value, self.rows, self.parts):
            rng = np.random.default_rng((self.seed, row))
            base = rng.integers(-4, 5, self.groups).astype(float)
            d = self.groups * self.copies
            values = np.repeat(base, self.copies) * np.where(np.arange(d) % 2, -1, 1) + self.noise * rng.standard_normal(d)
            yield pa.RecordBatch.from_arrays([pa.array([row] * d, pa.int64()), pa.array(np.arange(d), pa.int64()), pa.array(values)], names=["row_id", "feature_id", "value"])


class PlantedSource(DataSource):
    """format('planted_groups'): groups of columns that are one column with both signs and noise; rows come from their number alone."""

    @classmethod
    def name(cls):
        return "planted_groups"

    def schema(self):
        return "row_id bigint, feature_id bigint, value double"

    def reader(self, schema):
        return PlantedReader(self.options)
