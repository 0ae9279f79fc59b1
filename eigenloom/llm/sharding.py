"""Sharding over fixed virtual slots.

A record's key is hashed once into one of `slots` virtual slots. A stored map leads from slots to shards; each version is a table of its own that is never written again, and a new
version is an edit of the last one, so records are never hashed anew. `grow` hands slots to a new shard by the slot numbers alone, so that
key and shard count decide and rows move only into it; `rebalance` edits by the bytes aggregated per slot. Equal keys share a slot, and rows of one key are ordered by their text's checksum
(rows equal in both have interchangeable places); null keys share the slot of the empty string; null texts weigh one byte, texts of any length their own; an empty table has no
placed row and an empty folder; `write_shards` keeps all columns, and a given column of the name `shard` as `shard_given`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import _folder, stored

SLOTS, FINE = 4096, 4096


def slot_of(key, slots: int = SLOTS):
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 12), 16, 10).cast("long"), F.lit(slots)).cast("int")


def first_map(shards: int, slots: int = SLOTS) -> list[int]:
    """Version 0: contiguous runs of slots."""
    return [s * shards // slots for s in range(slots)]


def grow(owners: list[int]) -> list[int]:
    """The next version for one more shard: every old shard gives up its highest slots beyond the new even share."""
    shards = max(owners) + 1
    owners, room = list(owners), len(owners) // (shards + 1)
    held = {k: [s for s, o in enumerate(owners) if o == k] for k in range(shards)}
    for _ in range(room):
        giver = max(held, key=lambda k: (len(held[k]), -k))
        owners[held[giver].pop()] = shards
    return owners


def rebalance(owners: list[int], weights: dict[int, int], slack: float = 0.02) -> list[int]:
    """The next version by measured bytes: moves slots from the heaviest to the lightest shard while that narrows their gap."""
    owners, shards = list(owners), max(owners) + 1
    load = [0] * shards
    for slot, owner in enumerate(owners):
        load[owner] += weights.get(slot, 0)
    for _ in range(len(owners)):
        high, low = max(range(shards), key=load.__getitem__), min(range(shards), key=load.__getitem__)
        gap = load[high] - load[low]
        if gap <= slack * max(1, sum(load) / shards):
            break
        fit = [(abs(gap / 2 - w), s) for s, o in enumerate(owners) if o == high and 0 < (w := weights.get(s, 0)) < gap]
        if not fit:
            break
        slot = min(fit)[1]
        owners[slot] = low
        load[high] -= weights[slot]
        load[low] += weights[slot]
    return owners


def publish(spark: SparkSession, path: str, owners: list[int], version: int) -> None:
    """Writes one version of the map; a version that exists is an error, never overwritten."""
    rows = spark.createDataFrame(list(enumerate(owners)), "vslot int, owner int")
    rows.coalesce(1).write.parquet(f"{path}/version={version}")


def versions(spark: SparkSession, path: str) -> list[int]:
    """The versions of the stored map in order; none where there is no map."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [f.getPath().getName() for f in files.listStatus(where)] if files.exists(where) else []
    return sorted(int(n.split("=")[1]) for n in names if n.startswith("version="))


def read_map(spark: SparkSession, path: str, version: int) -> DataFrame:
    """(vslot, owner) of one version: as many rows as slots, whatever the data."""
    return spark.read.schema("vslot int, owner int").parquet(f"{path}/version={version}")


def edited(spark: SparkSession, path: str, edit) -> int:
    """Publishes edit(owners of the newest version) as the next version and returns its number."""
    last = versions(spark, path)[-1]
    owners = [r["owner"] for r in read_map(spark, path, last).orderBy("vslot").collect()]
    publish(spark, path, edit(owners), last + 1)
    return last + 1


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slots: int = SLOTS) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(
        F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), slot_of(F.col(id_col), slots).alias("vslot")
    )


def slot_bytes(rows: DataFrame) -> DataFrame:
    """(vslot, n_rows, n_bytes): what `rebalance` needs; at most one row per slot."""
    return rows.groupBy("vslot").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("size").alias("n_bytes"))


def rebalanced(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", slots: int = SLOTS) -> int:
    """Publishes the newest version edited by the bytes per slot of docs, and returns its number."""
    weights = {r["vslot"]: r["n_bytes"] for r in slot_bytes(sized(docs, id_col, text_col, slots)).collect()}  # at most `slots` rows
    return edited(docs.sparkSession, path, lambda owners: rebalance(owners, weights))


def first_versions(spark: SparkSession, shards: int, slots: int = SLOTS, path: str | None = None) -> str:
    """The folder of a map with version 0 of `shards` shards and version 1, grown by one."""
    path = path or _folder(spark, "shard-map")
    if not versions(spark, path):
        publish(spark, path, first_map(shards, slots), 0)
        edited(spark, path, grow)
    return path


def placed(docs: DataFrame, shards: int = 8, slots: int = SLOTS, id_col: str = "doc_id", text_col: str = "text", fine: int = FINE, path: str | None = None) -> DataFrame:
    """Shard and gapless place of every row under version 0 of the stored map, and its shard under version 1 (one more shard).

    Rows equal in key, checksum and size that came in one partition are one counted cell; places add up from counts of slots before it in the shard, bins (checksum mod `fine`) before
    it in the slot and cells before it in the bin. So no task ranks more than the cells of a bin, and rows come from cells that are dealt anew.
    """
    spark = docs.sparkSession
    path = first_versions(spark, shards, slots, path)
    old, new = (read_map(spark, path, v).withColumnRenamed("owner", name) for v, name in ((0, "shard"), (1, "grown_shard")))
    owners = old.join(F.broadcast(new), "vslot")
    rows = sized(docs, id_col, text_col, slots).withColumns({"bin": F.pmod("text_crc32", F.lit(fine)).cast("int"), "part": F.spark_partition_id()})
    key = ["doc_id", "text_crc32", "size", "part"]
    cells = stored(rows.groupBy("vslot", "bin", *key).agg(F.count(F.lit(1)).alias("n")), "shard-cells")
    before = lambda by, *order: F.coalesce(F.sum("n").over(Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    bins = cells.groupBy("vslot", "bin").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("size")).alias("bytes"))
    all_slots = bins.groupBy("vslot").agg(F.sum("n").alias("n"), F.sum("bytes").alias("vslot_bytes")).join(F.broadcast(owners), "vslot")
    all_slots = all_slots.select("vslot", "shard", "grown_shard", "vslot_bytes", before(["shard"], "vslot").alias("in_shard"))  # at most `slots` rows
    begins = bins.select("vslot", "bin", before(["vslot"], "bin").alias("in_slot")).join(F.broadcast(all_slots), "vslot")
    ranked = cells.select("vslot", "bin", *key, "n", before(["vslot", "bin"], *key).alias("in_bin")).join(begins, ["vslot", "bin"])
    spread = ranked.repartition(F.xxhash64("vslot", *key)).withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)))
    return spread.select("doc_id", "size", "text_crc32", "shard", (F.col("in_shard") + F.col("in_slot") + F.col("in_bin") + F.col("k")).cast("long").alias("slot"), "grown_shard", "vslot", "vslot_bytes")


def write_shards(docs: DataFrame, map_path: str, version: int, path: str, id_col: str = "doc_id", slots: int = SLOTS) -> None:
    """Writes the rows of docs in one folder per shard of a version; the shard follows from the key alone, so no row is matched with another."""
    given = docs.withColumnRenamed("shard", "shard_given")
    routed = given.withColumn("_vslot", slot_of(F.col("shard_given" if id_col == "shard" else id_col), slots))
    owners = read_map(docs.sparkSession, map_path, version).select(F.col("vslot").alias("_vslot"), F.col("owner").alias("shard"))
    routed.join(F.broadcast(owners), "_vslot").drop("_vslot").write.partitionBy("shard").parquet(path)
