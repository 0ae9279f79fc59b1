"""Streams over the events table, replayed as files and run to completion with availableNow."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parque[t]")


def finished(stream: DataFrame, mode: str) -> DataFrame:
    """The stream's output as files: in append mode a folder for each batch, so a repeated batch replaces itself; in complete mode the last batch's whole result."""
    from eigenloom.sources.stores import shared_dir

    root = f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/out" if mode == "complete" else f"{root}/out/batch={number}")

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    names = [f.name for f in stream.schema]
    return stream.sparkSession.read.option("basePath", f"{root}/out").schema(stream.schema).parquet(f"{root}/out").select(*names)


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges per hour and type."""
    events = source(spark, sf_dir).withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 day")
    counted = events.groupBy(F.window("at", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return finished(counted, "complete").select("event_type", F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("slot"), "n")


def complete(spark: SparkSession, sf_dir: str) -> DataFrame:
    return finished(source(spark, sf_dir).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")), "complete")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event arrives twice; repeats within the watermark are dropped."""
    events = source(spark, sf_dir).withColumn("at", F.col("ts").cast("timestamp"))
    twice = events.unionByName(events).withWatermark("at", "31 days")
    return finished(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append")


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keyed state holds each user's last event type; every micro-batch turns successive types into counted edges."""

    def step(key, frames, state):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        kinds = rows["event_type"].tolist()
        before = [last, *kinds[:-1]]
        state.update((kinds[-1],))
        pairs = [(a, b) for a, b in zip(before, kinds) if a is not None]
        yield pd.DataFrame(pairs, columns=["i", "j"])

    stream = source(spark, sf_dir).select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(step, "i string, j string", "last string", "append", "NoTimeout")
    return finished(stream, "append").groupBy("i", "j").agg(F.count(F.lit(1)).alias("n"))


def _timed(spark: SparkSession, sf_dir: str, delay: str = "1 day") -> DataFrame:
    return source(spark, sf_dir).withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)


def _text(column: str):
    return F.date_format(column, "yyyy-MM-dd HH:mm:ss")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges per two hours, begun every hour, and type."""
    counted = _timed(spark, sf_dir).groupBy(F.window("at", "2 hours", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return finished(counted, "complete").select("event_type", _text("window.start").alias("slot"), "n")


def sessions(spark: SparkSession, sf_dir: str, gap: str = "6 hours") -> DataFrame:
    """Runs of a user's events with no pause as long as the gap."""
    counted = _timed(spark, sf_dir).groupBy(F.session_window("at", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return finished(counted, "complete").select("user_id", _text("session_window.start").alias("began"), "n")


def late_dropped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts per day of a stream that comes in three runs: days 11 to 20, days 21 on, then days 1 to 10, which the one-day watermark rejects.

    The runs share a checkpoint, as restarts of one job do; days still open at the end are not emitted.
    """
    from eigenloom.sources.stores import shared_dir

    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("at"))
    root = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    day = F.dayofmonth("at") + 31 * (F.month("at") - 1)
    for chosen in (day.between(11, 20), day > 20, day <= 10):
        events.filter(chosen).write.mode("append").parquet(f"{root}/in")
        arriving = spark.readStream.schema(events.schema).parquet(f"{root}/in").withWatermark("at", "1 day")
        counted = arriving.groupBy(F.window("at", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        counted.writeStream.outputMode("append").format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{root}/out").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


def with_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of users that are customers, counted by nation: a stream beside a dimension."""
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    counted = source(spark, sf_dir).join(customers, "user_id").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))
    return finished(counted, "complete")


def click_then_purchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a click and a purchase of one user within the six hours after it: two streams with watermarks, whose state is bounded by the interval."""
    side = lambda kind, key, at: _timed(spark, sf_dir, "1 hour").filter(F.col("event_type") == kind).select("user_id", F.col("event_id").alias(key), F.col("at").alias(at))
    clicks, purchases = side("click", "click", "clicked"), side("purchase", "purchase", "bought").withColumnRenamed("user_id", "buyer")
    within = (F.col("user_id") == F.col("buyer")) & (F.col("bought") > F.col("clicked")) & (F.col("bought") <= F.col("clicked") + F.expr("interval 6 hours"))
    return finished(clicks.join(purchases, within).select("user_id", "click", "purchase"), "append")


def merged_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, event_type, n): each micro-batch writes its counted edges under its own number, so a repeated batch replaces itself; readers add the parts."""
    from eigenloom.sources.stores import shared_dir

    root = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"

    def merge(batch: DataFrame, number: int) -> None:
        batch.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{root}/batch={number}")

    source(spark, sf_dir).select("user_id", "event_type").writeStream.foreachBatch(merge).option("checkpointLocation", f"{root}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("user_id long, event_type string, n long, batch int").parquet(root).groupBy("user_id", "event_type").agg(F.sum("n").alias("n"))
