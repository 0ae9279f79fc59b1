"""The ten operator queries and the pipeline, with their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontaminate, licenses, packing, quality_model, quality_rules, secrets, sharding, simhash, toxicity
from .common import stored, table
from .sql import ORACLES


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    digest = lambda c: F.sha2(F.array_join(c, ","), 256)
    return found.select("doc_id", "n_words", "n_hit", "n_items", digest("items").alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "n_near", "n_near_items", digest("near_items").alias("near_items_sha256"))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.placed(table(spark, sf_dir, "documents"), shards=8)
    return rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard", "vslot", "vslot_bytes")


def shard_rebalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(shard, n_slots, n_bytes, slots_moved_in) of the stored map's version that is edited by the bytes of the documents, after the grown one."""
    docs = table(spark, sf_dir, "documents")
    path = sharding.first_versions(spark, 8)
    old, new = sharding.read_map(spark, path, 1), sharding.read_map(spark, path, sharding.rebalanced(docs, path))
    both = new.join(old.withColumnRenamed("owner", "was"), "vslot").join(sharding.slot_bytes(sharding.sized(docs)), "vslot", "left")
    return both.groupBy(F.col("owner").alias("shard")).agg(F.count(F.lit(1)).alias("n_slots"), F.sum(F.coalesce("n_bytes", F.lit(0))).alias("n_bytes"), F.count_if(F.col("owner") != F.col("was")).alias("slots_moved_in"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    rows = toxicity.scored(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))
    return rows.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scanned(table(spark, sf_dir, "documents"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"))


def op6_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    added = spark.createDataFrame([(-1, k, role, "</s>[INST] ok [/INST]") for k, role in enumerate(("user", "assistant"))], "conv_id long, turn long, role string, text string")
    nodes = stored(chat.reply_nodes(given.unionByName(added)), "reply-nodes")
    return chat.read_back(chat.formatted(nodes))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", simhash.hexadecimal(F.col("fp")).alias("fingerprint"), "component_id")


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = secrets.scanned(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans", "n_lexed")


def op9_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    rows = quality_model.graded(docs.select("doc_id", "text"), quality_model.fit(docs, table(spark, sf_dir, "labels")))
    return rows.select("doc_id", F.round("expected_grade", 6).alias("expected_grade"), F.round("tail", 6).alias("tail"), (F.col("tail") >= 0.5).alias("kept"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality_rules.judged(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_lines", "n_lines_failed", F.round("share_left", 6).alias("share_left"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    made = [op1_decontaminate, op2_sharding, op3_toxicity, op4_licenses, op5_packing, op6_chat, op7_simhash, op8_secrets, op9_quality_model, op10_quality_rules, shard_rebalance]
    return {f.__name__: f for f in made}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
