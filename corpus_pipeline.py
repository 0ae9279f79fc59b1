"""Corpus pipeline: quality, near duplicates, benchmark leaks, secrets, packing; each stage reads what the one before wrote."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenloom.llm import decontaminate, packing, quality_model, secrets, simhash
from eigenloom.llm.common import shared_dir, stored, table

LEAST_QUALITY = 0.5


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose probability of grade 1 or better is at least LEAST_QUALITY."""
    return quality_model.selected(docs, table(spark, sf_dir, "labels"), LEAST_QUALITY)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group: the one with the smallest id, then the least digest of its text. Of rows equal in both, one stays; ids may be null (last in order) or repeated."""
    digest = F.md5("text")
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), digest.alias("digest"))
    found = stored(simhash.near_duplicates(docs.select(key.alias("key"), "text"), "key"), "components")
    dropped = found.filter(F.col("doc_id") != F.col("component_id")).select("doc_id.*").distinct()
    same = F.col("doc_id").eqNullSafe(F.col("id")) & digest.eqNullSafe(F.col("digest"))
    kept = docs.join(dropped, same, "left_anti").select(*docs.columns)
    if found.groupBy("doc_id").count().filter("count > 1").isEmpty():
        return kept
    return kept.withColumn("_digest", digest).dropDuplicates(["doc_id", "_digest"]).select(*docs.columns)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a window of a benchmark item. The text decides, so a text is named by its digest and ids may be null or repeated."""
    found = decontaminate.contamination(docs.select(F.md5("text").alias("digest"), "text"), table(spark, sf_dir, "benchmark"), id_col="digest")
    leaks = found.filter("n_hit > 0").select(F.col("doc_id").alias("digest")).distinct()
    return docs.join(leaks, F.md5("text") == F.col("digest"), "left_anti").select(*docs.columns)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces secrets in the texts; every document stays."""
    return secrets.redacted(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs)


STAGES = [("quality classifier", quality), ("SimHash near-dedup", near_duplicates), ("benchmark decontamination", benchmark_leaks), ("secret scans", secret_scan), ("packing", pack)]
#: Trained weights, fingerprints and byte-pair merges have no SQL form; tests hold the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    at = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{at}/{k}")
        docs = spark.read.parquet(f"{at}/{k}")
    return docs
