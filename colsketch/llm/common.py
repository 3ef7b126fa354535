"""Helpers of the corpus operators: reading, checkpoints, class labels of linked rows, fixed-size bit maps."""

from __future__ import annotations

import atexit
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut, shared_dir


#: Rows of small tables (a row for each source, label) that are broadcast; larger ones are joined.
BROADCAST_ROWS = 100_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stored(df: DataFrame) -> DataFrame:
    """As cut(), for large results: a Parquet table in the shared folder, read again. It stays until the process ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    atexit.register(_delete, jvm, conf, path)
    return spark.read.schema(df.schema).parquet(path)


def _delete(jvm, conf, path: str) -> None:
    try:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
    except Exception:  # noqa: BLE001, the session may have ended before the process
        return


def components(edges: DataFrame) -> DataFrame:
    """Columns (id, component) for each end of edges (a, b): the smallest id that the links reach.

    Alternates two contractions of the edge list (neighbours to the smallest neighbour, larger and then smaller
    ones) until nothing changes; the number of edges never grows, and no vertex gathers its neighbours in memory.
    """
    now = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b").distinct())
    before = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a != b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        now = cut(small.select(F.col("a"), F.col("m").alias("b")).unionByName(small.where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))).where("a != b").distinct())
        state = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % 1_000_003)).first()
        if state == before:
            break
        before = state
    ends = now.select(F.col("a").alias("id"), F.col("b").alias("component"))
    return ends.unionByName(ends.select(F.col("component").alias("id"), "component")).groupBy("id").agg(F.min("component").alias("component"))


def bit_map(ids: DataFrame, column: str, bits: int = 1 << 24) -> np.ndarray:
    """A bit map of fixed size with the hashed ids set; at most bits / 64 rows reach the driver, however many ids there are.

    A row whose bit is unset is surely not among the ids; others need an exact check afterwards.
    """
    h = F.pmod(F.xxhash64(column), F.lit(bits))
    words = ids.select((h / 64).cast("long").alias("w"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64({column}), 64) as int))").alias("v")).groupBy("w").agg(F.bit_or("v").alias("v"))
    out = np.zeros(bits // 64, np.int64)
    for w, v in words.collect():
        out[w] = v
    return out


def found_in(bits: np.ndarray, hashes) -> np.ndarray:
    """Which of xxhash64 values (no nulls) are set in a bit_map()."""
    x = np.mod(np.asarray(hashes), len(bits) * 64)
    return ((bits[x >> 6] >> (x & 63)) & 1).astype(bool)


def in_bit_map(column: str, sent):
    """A Boolean column that looks `column` up in a broadcast bit_map()."""

    @F.arrow_udf("boolean")  # pandas would take 28 MB of each Python worker
    def found(h: pa.Array) -> pa.Array:
        return pa.array(found_in(sent.value, h))

    return found(F.xxhash64(column))


def label_sample(docs: DataFrame, labels: DataFrame, wanted: str, train, limit: int) -> DataFrame:
    """Documents with a label, `limit` at most (the smallest hashes of doc_id), for fitting: (doc_id, text, label).

    The sample of labels is bounded, so its broadcast is. Null ids and labels are left out.
    """
    some = labels.where(F.col("doc_id").isNotNull() & F.col(wanted).isNotNull() & train)
    some = some.groupBy("doc_id").agg(F.max(wanted).alias("label"))
    some = some.orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit)
    return docs.select("doc_id", "text").join(F.broadcast(some), "doc_id")


def sample_of_each(docs: DataFrame, wanted: str, train, limit: int) -> DataFrame:
    """As label_sample() for a label in docs itself, with about the same number of documents of each label, and all of those
    of rare ones; about `limit` in all, by hash of doc_id."""
    some = docs.where(F.col("doc_id").isNotNull() & F.col(wanted).isNotNull() & train).select("doc_id", "text", F.col(wanted).alias("label"))
    sizes = cut(some.groupBy("label").agg(F.count("*").alias("n")))
    labels = sizes.count()
    share = sizes.select(F.col("label").alias("of"), (F.lit(max(1.0, limit / max(1, labels))) / F.col("n")).alias("share"))
    drawn = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < F.col("share") * (1 << 30)
    joined = some.join(F.broadcast(share) if labels <= BROADCAST_ROWS else share, F.col("label") == F.col("of"))
    return joined.where(drawn).select("doc_id", "text", "label")


def fresh(columns: list[str], *names: str) -> list[str]:
    """The names, each with underscores after it until no column has it (in any case)."""
    taken, out = {c.lower() for c in columns}, []
    for n in names:
        while n.lower() in taken:
            n += "_"
        taken.add(n.lower())
        out.append(n)
    return out
