"""Mixing sources to target weights: exact budgets of words, cut on one random order inside each source.

Every row gets a random key from a hash of its doc_id, rows are range-partitioned and sorted by (source, key, doc_id),
and prefix sums of sizes come from the partitions' totals. Sources, of any number, stay a table. A source's budget takes whole epochs of it and then the
first rows of the order, to the very word; the row on the cut gives the words that are still wanted.

A null or empty text has size 0 and is taken 0 words. A null source is a source of its own and the last one. Repeated
rows are distinct rows; ties of key and doc_id lie next to each other, in no matter what order, as they are alike. An
empty table gives no rows, and very long texts are one size more.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, cut, fresh

WEIGHTS = (5, 2, 1)
MOST_EPOCHS = 3


def word_count(text) -> F.Column:
    """Number of runs of characters other than space and U+0009 to U+000D."""
    one = F.translate(text, "\t\n\x0b\x0c\r", "     ")
    return F.coalesce(F.size(F.filter(F.split(one, " "), lambda w: w != "")), F.lit(0)).cast("long")


def _ranked(sources: DataFrame) -> DataFrame:
    """(source, n, rank): sources in code point order, null last, numbered from 0, by range partitions and their sizes."""
    order = F.col("source").asc_nulls_last()
    placed = cut(sources.repartitionByRange(order).withColumn("part", F.spark_partition_id()))
    sizes = sorted((r.part, r.n) for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect())  # a figure a partition
    start = np.cumsum([0, *(n for _, n in sizes)])[:-1]
    # From Arrow, as rows of Python objects would start Python workers.
    offsets = pa.table({"part": pa.array([p for p, _ in sizes], pa.int32()), "start": pa.array(start, pa.int64())})
    at = F.broadcast(sources.sparkSession.createDataFrame(offsets))
    return placed.join(at, "part").selectExpr("source", "n", "start + row_number() over (partition by part order by source nulls last) - 1 as rank")


def targets(sources: DataFrame, most: int = MOST_EPOCHS) -> DataFrame:
    """sources (source, n, weight) with target: shares of all n by weight, none above most x n; the excess goes to the others.

    Sources whose limit lies below the level that all others share are capped, until none is: the level only rises, so a
    few sums over the sources are enough.
    """
    long = "decimal(38,0)"
    total, weights, limits = sources.select(F.col("n").cast(long).alias("n"), F.col("weight").cast(long).alias("w")).agg(F.sum("n"), F.sum("w"), F.sum(F.col("n") * most)).first()
    left, share = int(total or 0), int(weights or 0)
    while share:
        capped = F.col("n").cast(long) * most * F.lit(share).cast(long) <= F.lit(left).cast(long) * F.col("weight").cast(long)
        taken, used = sources.where(capped).agg(F.sum(F.col("n").cast(long) * most), F.sum("weight")).first()
        now = (int(total) - int(taken or 0), int(weights) - int(used or 0))
        if now == (left, share):
            break
        left, share = now
    if not share:
        return sources.withColumn("target", (F.col("n") * most).cast("double"))
    capped = F.col("n").cast(long) * most * F.lit(share).cast(long) <= F.lit(left).cast(long) * F.col("weight").cast(long)
    return sources.withColumn("target", F.when(capped, (F.col("n") * most).cast("double")).otherwise((F.col("weight") * F.lit(left)).cast("double") / share))


def _running(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of a partition in order, with `at`: the sizes of the rows of the same source before them in the partition."""
    last, so_far = None, 0
    for batch in batches:
        if not batch.num_rows:
            continue
        source, size = batch.column("source").dictionary_encode(), np.asarray(batch.column("size"))
        code = np.asarray(source.indices.fill_null(-1))
        cuts = [0, *(np.flatnonzero(code[1:] != code[:-1]) + 1).tolist(), len(code)]
        at = np.cumsum(size) - size
        for a, z in zip(cuts, cuts[1:], strict=False):
            name = ("", None) if code[a] < 0 else ("s", source.dictionary[int(code[a])].as_py())
            if name != last:
                last, so_far = name, 0
            n = int(size[a:z].sum())
            at[a:z] += so_far - at[a]
            so_far += n
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "source", "key", "size", "part")), pa.array(at)], names=["doc_id", "source", "key", "size", "part", "at"])


def random_key(doc_id, seed: int):
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(doc_id.cast("string"), F.lit(""))))


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def mix(docs: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_EPOCHS, seed: int = 7) -> DataFrame:
    """(doc_id, source, key, size, source_size, target, taken, copies) for each row.

    taken: words the mixture takes of the row, repeats counted; copies: how many times the row is then to be written.
    """
    sized = cut(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), random_key(F.col("doc_id"), seed).alias("key")))
    ranked = _ranked(sized.groupBy("source").agg(F.sum("size").alias("n")))
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod("rank", F.lit(len(weights))) + 1).cast("int")).cast("long")
    plan = cut(targets(cut(ranked.select("source", "n", weight.alias("weight"))), most))
    count = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = sized.repartitionByRange(count, "source", "key", "doc_id").sortWithinPartitions("source", "key", "doc_id").withColumn("part", F.spark_partition_id())
    dealt = cut(dealt.mapInArrow(_running, "doc_id long, source string, key string, size long, part int, at long"))
    # What earlier partitions hold of a source: a row for each source and partition that has some of it.
    sums = dealt.groupBy("part", "source").agg(F.sum("size").alias("n")).selectExpr("part as p", "source as s", "sum(n) over (partition by source order by part) - n as before")
    budget = plan.selectExpr("source as t", "n as source_size", "target", "if(n > 0, cast(floor(target) as bigint) div n, 0) as whole", "if(n > 0, cast(floor(target) as bigint) % n, 0) as rest")
    parts = cut(sums.join(budget, F.col("s").eqNullSafe(F.col("t"))).drop("t"))
    out = dealt.join(_small(parts), (F.col("part") == F.col("p")) & F.col("source").eqNullSafe(F.col("s")))
    last = F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("before") - F.col("at")))
    out = out.select("*", last.alias("last"))
    return out.select("doc_id", "source", "key", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("last")).alias("taken"), (F.col("whole") + (F.col("last") > 0).cast("long")).alias("copies"))


def mixed_rows(docs: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_EPOCHS, seed: int = 7) -> DataFrame:
    """The mixture itself: whole rows of docs, each as many times as its source's epochs and cut say.

    The cuts are one key for each source, so rows are taken where they lie, without moving a text.
    """
    of, whole, top, key, at, copy = fresh(docs.columns, "cut_source", "whole", "top", "cut_key", "cut_id", "copy_")
    cuts = mix(docs, weights, most, seed).where("size > 0").groupBy("source").agg(F.min("copies").alias("whole"), F.max("copies").alias("top"), F.max(F.struct("copies", "key", F.coalesce("doc_id", F.lit(-(1 << 63))).alias("id"))).alias("at"))
    small = _small(cut(cuts.select(F.col("source").alias(of), F.col("whole").alias(whole), F.col("top").alias(top), F.col("at.key").alias(key), F.col("at.id").alias(at))))
    first = F.struct(random_key(F.col("doc_id"), seed), F.coalesce("doc_id", F.lit(-(1 << 63)))) <= F.struct(F.col(key), F.col(at))
    copies = F.when(first, F.col(top)).otherwise(F.col(whole))
    copies = F.when(word_count(F.col("text")) > 0, F.coalesce(copies, F.lit(0))).otherwise(F.lit(1))
    joined = docs.join(small, F.col("source").eqNullSafe(F.col(of)), "left").where(copies > 0)
    return joined.select(*docs.columns, F.explode(F.array_repeat(F.lit(1), copies.cast("int"))).alias(copy)).drop(copy)
