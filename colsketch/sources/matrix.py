"""Feature matrices in coordinate form, and builders from tables, arrays and texts.

entries (row_id LONG, feature_id LONG, value DOUBLE) has no zeros and one row for each pair; rows (row_id LONG) has all
rows, those without entries too, so that the number of rows is right.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import cut, drop, kept
from . import blocks

ENTRIES = T.StructType([T.StructField("row_id", T.LongType()), T.StructField("feature_id", T.LongType()), T.StructField("value", T.DoubleType())])
SEPARATORS = "[ \\t\\r\\n]+"
_SPLIT = re.compile(SEPARATORS)


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: str) -> DataFrame:
    """CSV, JSON, ORC, Parquet or text, with a declared schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write(df: DataFrame, fmt: str, path: str, partition_by: list[str] | None = None) -> None:
    w = df.write.mode("overwrite")
    w = w.partitionBy(*partition_by) if partition_by else w
    w.option("header", "true").format(fmt).save(path)


def require_schema(df: DataFrame, schema: T.StructType) -> DataFrame:
    found = {f.name: f.dataType for f in df.schema}
    wrong = [f.name for f in schema if found.get(f.name) != f.dataType]
    if wrong:
        raise TypeError(f"columns {wrong} are missing or have other types than {schema.simpleString()}")
    return df.select(*[f.name for f in schema])


@dataclass
class FeatureMatrix:
    entries: DataFrame
    rows: DataFrame
    d: int | None = None  # declared number of features, for dense matrices
    held: list[DataFrame] = field(default_factory=list)  # stored tables that entries are read from
    shared: dict | None = None  # forms of the matrix that learners have in common; only where entries are stored
    lists: DataFrame | None = None  # the rows as in as_rows(), each once, of figures of any width; features are numbered from 0 to d - 1
    energies: dict = field(default_factory=dict)  # stored energies of rotated coordinates by fold, of lists with folds, by seed
    profile: tuple | None = None  # of the lists: the features that are met, the sum of magnitudes, the number of tasks
    packed: DataFrame | None = None  # the lists of stored rows in blocks, of which the matrix has all rows
    opened: object = None  # what makes blocks of packed rows where they are read
    without: int | None = None  # but those of this fold

    @staticmethod
    def of_lists(lists: DataFrame, d: int) -> FeatureMatrix:
        pairs = lists.select("row_id", F.explode(F.arrays_zip("idx", "val")).alias("x"))
        return FeatureMatrix(pairs.select("row_id", F.col("x.idx").cast("long").alias("feature_id"), F.col("x.val").cast("double").alias("value")), lists.select("row_id"), d, lists=lists)

    def outside(self, fold: int) -> FeatureMatrix:
        """The rows outside a fold, of a matrix in lists, of which nothing is stored."""
        out = FeatureMatrix.of_lists(self.lists.where(F.col("fold") != fold), self.d)
        out.packed, out.opened, out.without, out.shared = self.packed, self.opened, fold, {}
        return out

    def features(self) -> DataFrame:
        return self.entries.select("feature_id").distinct()

    def as_rows(self) -> DataFrame:
        """(row_id, idx, val), sorted by idx; rows without entries have empty arrays."""
        if self.lists is not None:
            return self.lists.select("row_id", F.col("idx").cast("array<bigint>"), F.col("val").cast("array<double>"))
        lists = self.entries.groupBy("row_id").agg(F.array_sort(F.collect_list(F.struct("feature_id", "value"))).alias("p"))
        out = self.rows.join(lists, "row_id", "left")
        empty = F.array().cast("array<struct<feature_id:bigint,value:double>>")
        p = F.coalesce("p", empty)
        return out.select("row_id", F.transform(p, lambda x: x["feature_id"]).alias("idx"), F.transform(p, lambda x: x["value"]).alias("val"))


def sanitised(entries: DataFrame, on_bad: str = "error") -> DataFrame:
    """Sums repeated pairs and drops zeros; nulls and NaN raise, or are dropped or zero."""
    e = entries.select(F.col("row_id").cast("long"), F.col("feature_id").cast("long"), F.col("value").cast("double"))
    bad = F.col("value").isNull() | F.isnan("value") | F.col("row_id").isNull() | F.col("feature_id").isNull()
    if on_bad == "error":
        e = e.withColumn("value", F.when(bad, F.raise_error(F.lit("null or NaN in a feature matrix")).cast("double")).otherwise(F.col("value")))
    else:
        e = e.where(~bad)
    return e.groupBy("row_id", "feature_id").agg(F.sum("value").alias("value")).where("value != 0")


def from_pairs(df: DataFrame, row: str, feature: str, value: Column | str, on_bad: str = "error") -> FeatureMatrix:
    """Interactions: values of equal (row, feature) are summed."""
    v = F.col(value) if isinstance(value, str) else value
    e = sanitised(df.select(F.col(row).alias("row_id"), F.col(feature).alias("feature_id"), v.alias("value")), on_bad)
    return FeatureMatrix(e, df.select(F.col(row).cast("long").alias("row_id")).distinct())


def from_arrays(df: DataFrame, row: str, array: str) -> FeatureMatrix:
    """Dense arrays; floats become doubles before any arithmetic."""
    e = df.select(F.col(row).cast("long").alias("row_id"), F.posexplode(array).alias("feature_id", "value"))
    e = e.select("row_id", F.col("feature_id").cast("long"), F.col("value").cast("double")).where("value != 0")
    return FeatureMatrix(e, df.select(F.col(row).cast("long").alias("row_id")))


def token_id(token: Column) -> Column:
    """52 bits of the MD5: exact as a double, no global dictionary."""
    return F.conv(F.substring(F.md5(token), 1, 13), 16, 10).cast("long")


def from_tokens(df: DataFrame, row: str, text: str, min_df: int = 1, weight: str = "count", norm: str | None = None) -> FeatureMatrix:
    """Bag of lower-case tokens; weight count, log (1 + ln tf) or tfidf; norm l2 or none."""
    tokens = df.select(F.col(row).cast("long").alias("row_id"), F.explode(F.split(F.lower(text), SEPARATORS)).alias("token")).where("token != ''")
    counts = tokens.groupBy("row_id", "token").agg(F.count("*").alias("tf"))
    if min_df > 1 or weight == "tfidf":
        frequent = counts.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
        counts = counts.join(frequent, "token")
    value = F.col("tf").cast("double") if weight == "count" else 1 + F.log("tf")
    if weight == "tfidf":
        value = value * F.log(F.lit(float(max(1, df.count()))) / F.col("df"))
    e = counts.select("row_id", token_id(F.col("token")).alias("feature_id"), value.alias("value")).where("value != 0")
    if norm == "l2":
        size = e.groupBy("row_id").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("size"))
        e = e.join(size, "row_id").select("row_id", "feature_id", (F.col("value") / F.col("size")).alias("value"))
    return FeatureMatrix(e, df.select(F.col(row).cast("long").alias("row_id")))


def _gram_counts(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    """(row_id, g, tf) of the n-grams of each text, in time n log n in its length."""
    for batch in batches:
        rows, grams, counts = [], [], []
        for row, text in zip(batch.column("row_id"), batch.column("t"), strict=True):
            points = np.frombuffer((text.as_py() or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
            if len(points) < n:
                continue
            wins = np.lib.stride_tricks.sliding_window_view(points, n)
            if n <= 3:  # 21 bits a character
                keys = sum(wins[:, k].astype(np.uint64) << np.uint64(21 * (n - 1 - k)) for k in range(n))
                met, first, tf = np.unique(keys, return_index=True, return_counts=True)
            else:
                met, first, tf = np.unique(wins, axis=0, return_index=True, return_counts=True)
            rows.append(np.full(len(tf), row.as_py()))
            grams += [w.tobytes().decode("utf-32-le", "surrogatepass") for w in wins[first]]
            counts.append(tf)
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(rows)), pa.array(grams, pa.string()), pa.array(np.concatenate(counts))], names=["row_id", "g", "tf"])


def from_ngrams(df: DataFrame, row: str, text: str, n: int = 2, limit: int | None = None, min_df: int = 3) -> FeatureMatrix:
    """Character n-grams of whole texts, or of their first `limit` characters, 1 + ln tf, rows of unit length."""
    t = F.col(text) if isinstance(text, str) else text
    given = df.select(F.col(row).cast("long").alias("row_id"), (t if limit is None else F.substring(t, 1, limit)).alias("t")).where("row_id is not null")
    stored = counts = kept(given.mapInArrow(lambda it: _gram_counts(it, n), "row_id long, g string, tf long"))
    counts = counts.join(counts.groupBy("g").agg(F.count("*").alias("df")).where(F.col("df") >= min_df), "g")
    e = counts.select("row_id", token_id(F.col("g")).alias("feature_id"), (1 + F.log("tf")).alias("value"))
    size = e.groupBy("row_id").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("size"))
    return FeatureMatrix(e.join(size, "row_id").select("row_id", "feature_id", (F.col("value") / F.col("size")).alias("value")), df.select(F.col(row).cast("long").alias("row_id")), held=[stored])


class _Ids:
    """token_id() of strings, each computed once while MOST of them are held."""

    MOST = 200_000

    def __init__(self):
        self.held: dict[str, int] = {}

    def __call__(self, words: Iterable[str]) -> np.ndarray:
        if len(self.held) > self.MOST:
            self.held.clear()
        out, held = [], self.held
        for w in words:
            i = held.get(w)
            if i is None:
                i = held[w] = int(hashlib.md5(w.encode("utf-8", "surrogatepass")).hexdigest()[:13], 16)
            out.append(i)
        return np.array(out, np.int64)


def _lists(values: list[np.ndarray], kind) -> pa.Array:
    ends = np.append(0, np.cumsum([len(x) for x in values])).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*values, np.zeros(0, kind)]).astype(kind)))


def _counted(batches: Iterator[pa.RecordBatch], n: int | None) -> Iterator[pa.RecordBatch]:
    """The columns of a batch but for the lower-case text t, and the ids and counts of its tokens, or of its n-grams."""
    ids = _Ids()
    for batch in batches:
        idx, tf = [], []
        for text in batch.column("t"):
            text = text.as_py() or ""
            if n is None:
                counts = Counter(_SPLIT.split(text))
            else:
                counts = Counter(text[i : i + n] for i in range(len(text) - n + 1))
            counts.pop("", None)
            idx.append(ids(counts))
            tf.append(np.fromiter(counts.values(), np.int32, len(counts)))
        kept = [c for c in batch.schema.names if c != "t"]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), _lists(idx, np.int64), _lists(tf, np.int32)], names=[*kept, "idx", "val"])


def _numbered(batches: Iterator[pa.RecordBatch], sent, unit: bool) -> Iterator[pa.RecordBatch]:
    """Rows of _counted() with the places of their ids in sent, which is sorted; other ids go. unit: 1 + ln tf, rows of unit length."""
    known = sent.value
    for batch in batches:
        sizes, f = np.asarray(batch.column("idx").value_lengths()), np.asarray(batch.column("idx").flatten())
        row, tf = np.repeat(np.arange(len(sizes)), sizes), np.asarray(batch.column("val").flatten())
        at = np.searchsorted(known, f)
        keep = np.flatnonzero(known[np.minimum(at, len(known) - 1)] == f) if len(known) else np.zeros(0, int)
        keep = keep[np.lexsort((at[keep], row[keep]))]
        row, at, tf = row[keep], at[keep], tf[keep]
        if unit:
            v = 1 + np.log(tf)
            v /= np.sqrt(np.bincount(row, v * v, minlength=len(sizes)))[row]
        else:
            v = tf
        ends = pa.array(np.append(0, np.cumsum(np.bincount(row, minlength=len(sizes)))).astype(np.int32))
        names = [c for c in batch.schema.names if c not in ("idx", "val")]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.ListArray.from_arrays(ends, pa.array(at.astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(v))], names=[*names, "idx", "val"])


def text_lists(docs: DataFrame, n: int | None = None, min_df: int = 3, most: int = 4_000_000) -> tuple[DataFrame, int] | None:
    """(row_id, ..., idx, val) and the number of features of docs (row_id, ..., t, wanted), each row_id once, t in lower case:
    counts of tokens, or of n-grams as in from_ngrams(), that min_df rows have, numbered in the order of their ids.

    Rows that are not wanted count for min_df alone, and their tokens' features have numbers only if a wanted row has them.
    Entries stay where their text is. None if there are over `most` features, whose numbers would go to every task.
    """
    spark, own = docs.sparkSession, [c for c in docs.columns if c not in ("t", "wanted")]
    head = ", ".join(f"{c} {t}" for c, t in docs.dtypes if c != "t")
    counts = kept(docs.select(*own, "wanted", "t").mapInArrow(lambda it: _counted(it, n), f"{head}, idx array<long>, val array<int>"))
    frequent = counts.select("wanted", F.explode("idx").alias("f")).groupBy("f").agg(F.count("*").alias("df"), F.max("wanted").alias("wanted"))
    found = np.sort(np.asarray(frequent.where((F.col("df") >= min_df) & F.col("wanted")).select("f").limit(most + 1).toArrow().column("f"), dtype=np.int64))
    out = None
    if len(found) <= most:
        sent = spark.sparkContext.broadcast(found)
        head = ", ".join(f"{c} {t}" for c, t in docs.dtypes if c in own)
        out = kept(counts.where("wanted").drop("wanted").mapInArrow(lambda it: _numbered(it, sent, n is not None), f"{head}, idx array<int>, val array<{'int' if n is None else 'double'}>")), len(found)
    drop(counts)
    return out


def from_columns(df: DataFrame, row: str, numeric: list[str], categorical: list[str]) -> FeatureMatrix:
    """Numeric columns as they are and categories one-hot, both hashed by name."""
    parts = [F.struct(token_id(F.lit(c)).alias("feature_id"), F.col(c).cast("double").alias("value")) for c in numeric]
    parts += [F.struct(token_id(F.concat(F.lit(c + "="), F.col(c).cast("string"))).alias("feature_id"), F.lit(1.0).alias("value")) for c in categorical]
    e = df.select(F.col(row).cast("long").alias("row_id"), F.explode(F.array(*parts)).alias("p")).select("row_id", "p.feature_id", "p.value")
    return FeatureMatrix(e.where("feature_id is not null and value != 0"), df.select(F.col(row).cast("long").alias("row_id")))


def quadratic(fm: FeatureMatrix, d: int) -> FeatureMatrix:
    """Linear features and all products i <= j of a dense matrix of d features, numbered d + i d + j."""
    a, b = fm.entries.alias("a"), fm.entries.alias("b")
    pairs = a.join(b, F.expr("a.row_id = b.row_id and a.feature_id <= b.feature_id")).select("a.row_id", (F.lit(d) + F.col("a.feature_id") * d + F.col("b.feature_id")).alias("feature_id"), (F.col("a.value") * F.col("b.value")).alias("value"))
    return FeatureMatrix(fm.entries.unionByName(pairs), fm.rows)


#: Rows whose products squared() holds at a time.
SQUARED = 1_000


def _squared(batches: Iterator[pa.RecordBatch], d: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
    """(rows, their linear features and all products i <= j in the order of quadratic()'s ids); cells that are missing are 0."""
    i, j = np.triu_indices(d)
    for batch in batches:
        for a in range(0, batch.num_rows, SQUARED):
            part = batch.slice(a, SQUARED)
            sizes, v = np.asarray(part.column("x").value_lengths()), np.asarray(part.column("x").flatten().fill_null(0)).astype(float)
            x, row = np.zeros((len(sizes), d)), np.repeat(np.arange(len(sizes)), sizes)
            x[row, np.arange(len(v)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = v
            yield part, np.concatenate([x, x[:, i] * x[:, j]], axis=1)


def _spans(batches: Iterator[pa.RecordBatch], d: int) -> Iterator[pa.RecordBatch]:
    low = high = None
    for _, x in _squared(batches, d):
        a, z = x.min(axis=0), x.max(axis=0)
        low, high = (a, z) if low is None else (np.minimum(low, a), np.maximum(high, z))
    if low is not None:
        yield pa.RecordBatch.from_arrays([pa.array([y.tobytes()], pa.binary()) for y in (low, high)], names=["low", "high"])


def _scaled_squares(batches: Iterator[pa.RecordBatch], d: int, sent) -> Iterator[pa.RecordBatch]:
    """The columns of a batch but for x, and idx and val: columns scaled to [-1, 1] and numbered, constant ones left out."""
    low, high = sent.value
    at = np.flatnonzero(high > low)
    low, size = low[at], (high - low)[at]
    for part, x in _squared(batches, d):
        x = 2 * (x[:, at] - low) / size - 1
        i, f = np.nonzero(x)
        ends = pa.array(np.append(0, np.cumsum(np.bincount(i, minlength=len(x)))).astype(np.int32))
        own = [c for c in part.schema.names if c != "x"]
        yield pa.RecordBatch.from_arrays([*(part.column(c) for c in own), pa.ListArray.from_arrays(ends, pa.array(f.astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(x[i, f]))], names=[*own, "idx", "val"])


def _square_blocks(batches: Iterator[pa.RecordBatch], d: int, sent, without: int | None) -> Iterator[blocks.Block]:
    """The blocks of _scaled_squares()."""
    low, high = sent.value
    at = np.flatnonzero(high > low)
    low, size = low[at], (high - low)[at]
    for part, x in _squared(batches, d):
        ids = np.asarray(part.column("row_id"))
        if without is not None:
            keep = np.asarray(part.column("fold")) != without
            ids, x = ids[keep], x[keep]
        x = np.ascontiguousarray((2 * (x[:, at] - low) / size - 1).T)
        row, f, v = np.tile(np.arange(len(ids)), len(at)), np.repeat(np.arange(len(at)), len(ids)), x.ravel()
        if not v.all():
            met = np.flatnonzero(v)
            row, f, v = row[met], f[met], v[met]
        yield blocks.Block(ids, row, f, v)


def scaled_squares(base: DataFrame, d: int) -> FeatureMatrix:
    """As min_max(quadratic()) with dense_ids(), of stored rows (row_id, ..., x), each row_id once, with arrays of up to d finite
    figures: rows are squared where they are read, and nothing is stored."""
    spark, head = base.sparkSession, ", ".join(f"{c} {t}" for c, t in base.dtypes if c != "x")
    bounds = base.select("x").mapInArrow(lambda it: _spans(it, d), "low binary, high binary").collect()  # figures by column from each task
    low, high = (f([np.frombuffer(r[k], float) for r in bounds] or [np.zeros(d + d * (d + 1) // 2)], axis=0) for k, f in enumerate((np.min, np.max)))
    sent = spark.sparkContext.broadcast((low, high))
    made = lambda it: _scaled_squares(it, d, sent)
    out = FeatureMatrix.of_lists(base.mapInArrow(made, f"{head}, idx array<int>, val array<double>"), int((high > low).sum()))
    out.rows = base.select("row_id")
    out.packed, out.opened = base.select("row_id", "fold", "x"), lambda it, without: _square_blocks(it, d, sent, without)
    return out


#: Columns with holes whose bounds go to every task, 32 bytes each; more are joined.
MAX_BROADCAST = 4_000_000
#: Cells of a batch and, about, of a task that min_max() makes.
CELLS, TASK_CELLS = 500_000, 50_000_000


def min_max(fm: FeatureMatrix, max_broadcast: int = MAX_BROADCAST) -> FeatureMatrix:
    """Columns to [-1, 1] over all rows, a cell without an entry being 0; a constant column becomes 0.

    For dense matrices: where 0 lies inside a column's span, each of its cells gets its image, so rows x such columns
    entries are made, where the row is, without moving them; without rows there are none. A column without entries stays without.
    """
    n = fm.rows.agg(F.count("*").alias("n"))
    span = fm.entries.groupBy("feature_id").agg(F.min("value").alias("low"), F.max("value").alias("high"), F.count("*").alias("met")).crossJoin(F.broadcast(n))  # one row
    holes = F.col("met") < F.col("n")
    span = cut(span.select("feature_id", F.when(holes, F.least("low", F.lit(0.0))).otherwise(F.col("low")).alias("low"), F.when(holes, F.greatest("high", F.lit(0.0))).otherwise(F.col("high")).alias("high"), holes.alias("holes")))
    v = F.when(F.col("high") > F.col("low"), 2 * (F.col("value") - F.col("low")) / (F.col("high") - F.col("low")) - 1).otherwise(0.0)
    # Only columns with holes meet all rows; the cells that are there keep their value.
    open_ = span.where("holes and high > low").select("feature_id", "low", "high")
    whole = fm.entries.join(span.where("not holes"), "feature_id").select("row_id", "feature_id", v.alias("value")).where("value != 0")
    count = open_.count()
    if not count:
        return FeatureMatrix(whole, fm.rows, fm.d)
    if count <= max_broadcast:
        t = open_.toArrow()
        order = np.argsort(np.asarray(t.column("feature_id")))
        sent = fm.entries.sparkSession.sparkContext.broadcast(tuple(np.asarray(t.column(c))[order] for c in ("feature_id", "low", "high")))
        own = FeatureMatrix(fm.entries.join(span.where("not holes").select("feature_id"), "feature_id", "left_anti"), fm.rows.select("row_id").distinct())
        parts = max(int(own.rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-count * own.rows.count() // TASK_CELLS))
        full = own.as_rows().repartition(parts, "row_id").mapInArrow(lambda it: _spread(it, sent), ENTRIES)
    else:
        zero = fm.rows.select("row_id").distinct().crossJoin(open_.select("feature_id")).select("row_id", "feature_id", F.lit(0.0).alias("value"))
        full = fm.entries.unionByName(zero).groupBy("row_id", "feature_id").agg(F.sum("value").alias("value"))
        full = full.join(open_, "feature_id").select("row_id", "feature_id", v.alias("value")).where("value != 0")
    return FeatureMatrix(whole.unionByName(full), fm.rows, fm.d)


def _spread(batches: Iterator[pa.RecordBatch], sent) -> Iterator[pa.RecordBatch]:
    """(row_id, feature_id, value) of all the columns in `sent` for each of as_rows(), in blocks of CELLS cells, without zeros."""
    ids, low, high = sent.value
    size = high - low
    for batch in batches:
        idx, val = batch.column("idx"), batch.column("val")
        starts = np.concatenate([[0], np.cumsum(np.asarray(idx.value_lengths()))])
        met, given, rows = np.asarray(idx.flatten()), np.asarray(val.flatten()), np.asarray(batch.column("row_id"))
        at = np.searchsorted(ids, met)
        known = ids[np.minimum(at, len(ids) - 1)] == met
        for a in range(0, len(ids), CELLS):
            z = min(len(ids), a + CELLS)
            many = max(1, CELLS // (z - a))
            for i in range(0, len(rows), many):
                j = min(len(rows), i + many)
                x = np.zeros((j - i, z - a))
                here = np.arange(starts[i], starts[j])
                row = np.repeat(np.arange(j - i), np.diff(starts[i : j + 1]))
                mine = known[here] & (at[here] >= a) & (at[here] < z)
                x[row[mine], at[here][mine] - a] = given[here][mine]
                x = (2 * (x - low[a:z]) / size[a:z] - 1).ravel()
                kept = np.flatnonzero(x)
                if len(kept) < len(x):
                    yield pa.RecordBatch.from_arrays([pa.array(rows[i + kept // (z - a)]), pa.array(ids[a + kept % (z - a)]), pa.array(x[kept])], names=["row_id", "feature_id", "value"])
                else:
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(rows[i:j], z - a)), pa.array(np.tile(ids[a:z], j - i)), pa.array(x)], names=["row_id", "feature_id", "value"])


def dense_ids(fm: FeatureMatrix) -> tuple[FeatureMatrix, DataFrame]:
    """The matrix with features numbered from 0 in the order of their ids, and (feature_id, dense_id).

    Ranks come from range partitions and the partitions' sizes; no partition holds all features.
    """
    placed = cut(fm.features().repartitionByRange("feature_id").select("feature_id", F.spark_partition_id().alias("part")))
    sizes, start, offsets = {x.part: x.n for x in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}, 0, []  # one figure a partition
    for part in sorted(sizes):
        offsets.append((part, start))
        start += sizes[part]
    at = F.broadcast(fm.entries.sparkSession.createDataFrame(offsets, "part int, start long"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy("feature_id")) - 1
    ids = placed.join(at, "part").select("feature_id", (F.col("start") + rank).alias("dense_id"))
    e = fm.entries.join(ids, "feature_id").select("row_id", F.col("dense_id").alias("feature_id"), "value")
    return FeatureMatrix(e, fm.rows, start), ids


def custpart(spark: SparkSession, sf_dir: str) -> FeatureMatrix:
    """Customers x parts, summed quantities: exact integers."""
    o, li = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    return from_pairs(o.join(li, o.o_orderkey == li.l_orderkey), "o_custkey", "l_partkey", "l_quantity")


def suppart(spark: SparkSession, sf_dir: str) -> FeatureMatrix:
    return from_pairs(table(spark, sf_dir, "lineitem", ["l_suppkey", "l_partkey"]), "l_suppkey", "l_partkey", F.lit(1.0))


def embeddings(spark: SparkSession, sf_dir: str) -> FeatureMatrix:
    return from_arrays(table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding")
