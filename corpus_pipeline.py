"""The corpus pipeline: documents without toxic texts, near copies and benchmark passages, mixed and dealt to shards.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from colsketch.llm import contamination, mixing, near, registry, sharding, toxicity
from colsketch.llm.common import fresh, shared_dir, stored, table
from colsketch.session import ship, small_batches


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity operator does not reject."""
    small_batches(ship(spark))
    return toxicity.toxic_flags(docs, registry.toxicity_model(spark, docs, sf_dir))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest doc_id; documents with a null doc_id stay."""
    small_batches(ship(spark))
    (other,) = fresh(docs.columns, "copy_of_other")
    groups = near.near_duplicates(docs).where("doc_id != component_id").select(F.col("doc_id").alias(other)).distinct()
    return docs.join(groups, F.col("doc_id") == F.col(other), "left_anti")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not contaminated by benchmark items."""
    (hit,) = fresh(docs.columns, "found_id")
    found = contamination.contamination(docs, table(spark, sf_dir, "benchmark")).where("contaminated").select(F.col("doc_id").alias(hit)).distinct()
    return docs.join(found, F.col("doc_id") == F.col(hit), "left_anti")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture by source: rows repeated or left out as the sources' weights say."""
    small_batches(ship(spark))
    return mixing.mixed_rows(docs)


def deal_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, bytes, shard, depth, shard_bytes, oversize) for each row of the mixture."""
    return sharding.shards(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard_join", drop_near_copies),
    ("benchmark_decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", deal_shards),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    shared_dir(spark)
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = stored(docs)
    return docs


#: Toxicity learns a lexicon and near copies are joined components, which SQL cannot express.
ORACLE_SQL = None
