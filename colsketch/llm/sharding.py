"""Sharding by extendible hashing.

A directory is indexed by the leading bits of a row's hash. A bucket whose bytes exceed the limit is split on its next
bit, and no other; so a row's shard is the shortest prefix of its hash whose rows fit. The levels are taken some bits at
a time, and only rows of buckets that are still too large go on to the next.

A null text has 0 bytes. Rows with equal hashes (repeated doc_id) cannot be parted by bits: a bucket that still exceeds
the limit when the bits end keeps all of them, marked `oversize`. An empty table has no shards.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

LIMIT_BYTES = 1 << 20
HASH_BITS = 60
STEP_BITS = 10


def hash_bits(column) -> F.Column:
    """60 bits of the MD5 of the id's decimal form, as a string of 0 and 1."""
    return F.lpad(F.conv(F.substring(F.md5(F.coalesce(column.cast("string"), F.lit(""))), 1, HASH_BITS // 4), 16, 2), HASH_BITS, "0")


def shards(docs: DataFrame, limit: int = LIMIT_BYTES, step: int = STEP_BITS) -> DataFrame:
    """(doc_id, bytes, shard, depth, shard_bytes, oversize) for each row; shard is the prefix, a string of `depth` bits."""
    rows = cut(docs.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("bytes"), hash_bits(F.col("doc_id")).alias("bits")))
    left, directory, done = rows, None, 0
    while done <= HASH_BITS:
        top = min(done + step, HASH_BITS)
        fine = left.groupBy(F.substring("bits", 1, top).alias("prefix")).agg(F.sum("bytes").alias("b"))
        depths = F.sequence(F.lit(done), F.lit(top))
        sums = fine.select(F.explode(depths).alias("depth"), "prefix", "b").groupBy("depth", F.expr("substring(prefix, 1, depth)").alias("shard")).agg(F.sum("b").alias("shard_bytes"))
        sums = cut(sums.where((F.col("shard_bytes") <= limit) | (F.col("depth") == top)))
        fits = sums.where(F.col("shard_bytes") <= limit)
        # The shortest prefix that fits: one whose parent, if it is in this level, does not.
        parent = fits.select((F.col("depth") + 1).alias("depth"), F.col("shard").alias("p"))
        leaf = fits.withColumn("p", F.expr("substring(shard, 1, depth - 1)")).join(parent, ["depth", "p"], "left_anti").drop("p").withColumn("oversize", F.lit(False))
        large = sums.where((F.col("shard_bytes") > limit) & (F.col("depth") == top))
        if top == HASH_BITS:
            leaf = leaf.unionByName(large.withColumn("oversize", F.lit(True)))
        directory = leaf if directory is None else directory.unionByName(leaf)
        directory = cut(directory)
        if top == HASH_BITS or large.isEmpty():
            break
        left = cut(left.withColumn("prefix", F.substring("bits", 1, top)).join(large.select(F.col("shard").alias("prefix")), "prefix", "left_semi").drop("prefix"))
        done = top + 1
    # A row looks its prefixes up at the depths that occur, one equi-join with the directory.
    depths = [r.depth for r in directory.select("depth").distinct().orderBy("depth").collect()]  # HASH_BITS + 1 at most
    wide = rows.select("doc_id", "bytes", F.explode(F.array(*[F.substring("bits", 1, d) if d else F.lit("") for d in depths])).alias("shard")) if depths else rows.select("doc_id", "bytes", F.lit("").alias("shard"))
    return wide.join(directory, "shard").select("doc_id", "bytes", "shard", "depth", "shard_bytes", "oversize")


def write_shards(docs: DataFrame, assigned: DataFrame, path: str) -> None:
    """Writes docs as Parquet, one folder for each shard; doc_id must be a key of both."""
    docs.join(assigned.select("doc_id", "shard"), "doc_id").repartition("shard").sortWithinPartitions("shard").write.partitionBy("shard").mode("overwrite").parquet(path)
