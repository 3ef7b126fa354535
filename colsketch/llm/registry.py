"""Queries op1 to op10 and the pipeline, with production parameters over whole tables, and SQL where it can express them."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship
from . import contamination, extraction, language, lm, mixing, near, quality, sharding, substrings, toxicity
from .common import bit_map, in_bit_map, label_sample, sample_of_each, table


def _remainder(column: str, by: int) -> F.Column:
    return F.pmod(F.crc32(F.col(column).cast("string")), F.lit(by))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def toxicity_model(spark: SparkSession, docs: DataFrame, sf_dir: str) -> toxicity.Model:
    sample = label_sample(docs, table(spark, sf_dir, "labels"), "toxic", _remainder("doc_id", 5) != 0, toxicity.MAX_LABELLED)
    return toxicity.fit(sample)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = toxicity.toxicity(docs, toxicity_model(spark, docs, sf_dir))
    return scored.select("doc_id", F.coalesce(_remainder("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "score", "predicted", "n_hits")


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near.near_duplicates(table(spark, sf_dir, "documents"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.remove_repeats(table(spark, sf_dir, "documents"), digest=True).withColumnRenamed("kept_text", "kept_sha256")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = contamination.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", F.col("n_hit").cast("long").alias("n_hit"), F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), "contaminated")


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shards(table(spark, sf_dir, "documents"))


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extraction.extract(table(spark, sf_dir, "pages"))


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.backoff_scores(table(spark, sf_dir, "documents"), order=3)


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(_remainder("doc_id", 4) == 2, F.lit(False))
    sample = sample_of_each(docs, "lang", _remainder("doc_id", 4) != 2, language.MAX_LABELLED)
    return language.identify(docs, language.fit(sample)).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def quality_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, label) of all documents with a quality label."""
    given = labels.where("doc_id is not null and quality is not null")
    return given.groupBy("doc_id").agg(F.max("quality").alias("label"))


def trusted_texts(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The texts of all documents with quality label 1; a bit map rules most others out before texts are moved."""
    ids = quality_labels(labels).where("label = 1").select("doc_id")
    sent = docs.sparkSession.sparkContext.broadcast(bit_map(ids, "doc_id"))
    return docs.select("doc_id", "text").where(in_bit_map("doc_id", sent)).join(ids, "doc_id", "left_semi").select("text")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    labels = table(spark, sf_dir, "labels")
    known = quality_labels(labels)
    sent = spark.sparkContext.broadcast(bit_map(known, "doc_id"))
    labelled = docs.select("doc_id", "text").where(in_bit_map("doc_id", sent))
    return quality.quality(docs, quality.fit(docs, labelled, trusted_texts(docs, labels), labels=known))


def quality_base_figures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rule figures of op10 alone, which SQL can express."""
    return quality.quality(table(spark, sf_dir, "documents")).drop("kept", "score")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def _shipped(f):
    @functools.wraps(f)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return f(ship(spark), sf_dir)

    return run


def queries() -> dict:
    return {f.__name__: _shipped(f) for f in (op1_mixing, op2_toxicity, op3_jaccard_join, op4_substring_dedup, op5_decontamination, op6_sharding, op7_html_extraction, op8_lm_scoring, op9_language_id, op10_quality_rules, quality_base_figures, pipeline)}


def oracle_sql() -> dict[str, str]:
    from .oracles import SQL

    return dict(SQL)
