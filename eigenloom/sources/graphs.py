"""Edge frames (i, j, w) from the given tables, and generators of graphs with known spectra."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


#: Bytes in files of one shuffle partition of the orders' keys up to which they are hashed in memory.
HASHED_BYTES = 8 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def coalesced(rows: DataFrame, i, j, w=None, summed: bool = True) -> DataFrame:
    """One edge per (i, j), weights added, or without summed an edge per row, for readers that add repeats themselves; rows with a null or negative endpoint or a null, infinite or undefined weight are errors of the caller and dropped here."""
    weight = F.lit(1.0) if w is None else w.cast("double")
    kept = rows.select(i.cast("long").alias("i"), j.cast("long").alias("j"), weight.alias("w")).filter((F.col("i") >= 0) & (F.col("j") >= 0) & (F.abs("w") < float("inf")))
    return kept.groupBy("i", "j").agg(F.sum("w").alias("w")) if summed else kept


def symmetrised(edges: DataFrame, combine: str = "sum") -> DataFrame:
    """combine: sum, max or any (weight 1)."""
    both = edges.select("i", "j", "w").union(edges.select("j", "i", "w"))
    how = {"sum": F.sum("w"), "max": F.max("w"), "any": F.lit(1.0)}[combine]
    return both.groupBy("i", "j").agg(how.alias("w"))


def transposed(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("j").alias("i"), F.col("i").alias("j"), "w")


def without_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("i <> j")


def _ordered_items(spark, sf_dir):
    """Line items with their orders' customers. While the orders' keys of a shuffle partition are few bytes they are hashed, so the items are not sorted; beyond, Spark's own join sorts and spills."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    each = int(str(orders._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) / int(spark.conf.get("spark.sql.shuffle.partitions"))
    return table(spark, sf_dir, "lineitem").join(orders.hint("shuffle_hash") if each <= HASHED_BYTES else orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_part(spark, sf_dir, summed: bool = True):
    return coalesced(_ordered_items(spark, sf_dir), F.col("o_custkey"), F.col("l_partkey"), None, summed)


def supplier_part(spark, sf_dir):
    return coalesced(table(spark, sf_dir, "lineitem"), F.col("l_suppkey"), F.col("l_partkey"))


def nation_trade(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    rows = rows.join(table(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(table(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return symmetrised(coalesced(rows, F.col("s_nationkey"), F.col("c_nationkey")))


def user_transitions(spark, sf_dir):
    """Edges from one event's user to the next event's. The order is global, so events are first bounded to days and the seams between days are joined apart."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", F.to_date("ts").alias("day"))
    order = Window.partitionBy("day").orderBy("ts", "event_id")
    inner = events.withColumn("next", F.lead("user_id").over(order)).filter("next is not null").select("user_id", "next")
    ends = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    seams = ends.withColumn("next", F.lead("first").over(Window.orderBy("day"))).filter("next is not null").select(F.col("last").alias("user_id"), "next")  # one row per day
    return without_loops(coalesced(inner.union(seams), F.col("user_id"), F.col("next")))


def user_adjacency(spark, sf_dir):
    return symmetrised(user_transitions(spark, sf_dir), "any")


def user_type(spark, sf_dir):
    kinds = table(spark, sf_dir, "events").select("event_type").distinct().orderBy("event_type")
    ids = kinds.withColumn("j", F.row_number().over(Window.orderBy("event_type")) - 1)  # a handful of types
    return coalesced(table(spark, sf_dir, "events").join(F.broadcast(ids), "event_type"), F.col("user_id"), F.col("j"))


def dense_ids(values: DataFrame, key: str) -> DataFrame:
    """(key, id): ids from 0 in key order, from counts per range partition and an order inside each; no window over all rows."""
    dealt = values.select(key).filter(F.col(key).isNotNull()).distinct().repartitionByRange(key).withColumn("part", F.spark_partition_id()).persist()
    counts = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    begins = counts.withColumn("begin", F.sum("n").over(Window.orderBy("part")) - F.col("n")).drop("n")  # one row per partition
    inside = F.row_number().over(Window.partitionBy("part").orderBy(key))
    return dealt.withColumn("inside", inside - 1).join(F.broadcast(begins), "part").select(key, (F.col("begin") + F.col("inside")).alias("id"))


def page_links(spark, sf_dir, host_rows: bool = False):
    """Pages (or hosts) by the paths their anchors name; columns are dense ids of paths."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("path"))
    rows = pages.join(dense_ids(pages, "path").withColumnRenamed("id", "j"), "path")
    if host_rows:
        rows = rows.join(dense_ids(pages, "host").withColumnRenamed("id", "h"), "host")
    return coalesced(rows, F.col("h" if host_rows else "page_id"), F.col("j"))


def doc_terms(spark, sf_dir):
    tokens = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), r"\s+")).alias("term")).filter("term <> ''")
    return coalesced(tokens.join(dense_ids(tokens, "term"), "term"), F.col("doc_id"), F.col("id"))


def nearest(rows: DataFrame, asked: DataFrame, k: int, block: int = 1024, digits: int = 9) -> DataFrame:
    """(i, j, s, rank): the k rows nearest to each asked row by cosine rounded to `digits`, ties by id. Blocks of queries meet blocks of rows as matrix products and keep k each."""
    import numpy as np
    import pandas as pd

    def dealt(frame, number, held):
        return frame.select("vec_id", "embedding").withColumn(number, F.floor(F.col("vec_id") / block)).groupBy(number).agg(F.sort_array(F.collect_list(F.struct("vec_id", "embedding"))).alias(held))

    def unit(vectors):
        x = np.array([v["embedding"] for v in vectors], float)
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)

    def run(batches):
        for pdf in batches:
            out = []
            for queries, held in zip(pdf["queries"], pdf["held"]):
                qi, hi = np.array([x["vec_id"] for x in queries]), np.array([x["vec_id"] for x in held])
                s = np.round(unit(queries) @ unit(held).T, digits)
                s[qi[:, None] == hi[None, :]] = -np.inf
                best = np.argsort(-s, axis=1, kind="stable")[:, :k]
                out.append(pd.DataFrame({"i": np.repeat(qi, best.shape[1]), "j": hi[best].ravel(), "s": np.take_along_axis(s, best, 1).ravel()}))
            yield pd.concat(out) if out else pd.DataFrame({"i": [], "j": [], "s": []})

    near = dealt(asked, "block", "queries").crossJoin(dealt(rows, "chunk", "held")).mapInPandas(run, "i long, j long, s double").filter("not isnan(s) and s > -2")
    return near.withColumn("rank", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("s"), "j"))).filter(F.col("rank") <= k)


def vector_neighbours(spark, sf_dir, k: int = 10, weight: str = "distance", block: int = 1024):
    """Each vector's k nearest by cosine, symmetrised by maximum; weight 'distance' or 'similarity'."""
    rows = table(spark, sf_dir, "embeddings")
    w = F.col("s") if weight == "similarity" else 1 - F.col("s")
    return symmetrised(nearest(rows, rows, k, block).select("i", "j", w.alias("w")), "max")


def turn_graph(spark, sf_dir):
    rows = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("node"), "conv_id", "turn")
    nxt = F.lead("node").over(Window.partitionBy("conv_id").orderBy("turn"))
    return symmetrised(coalesced(rows.withColumn("next", nxt).filter("next is not null"), F.col("node"), F.col("next")), "any")


def star(spark, sf_dir, child: str, key: str, parent_key: str, weight: str | None = None):
    """One entry per child row: its singular values are the roots of the parents' sums of squares."""
    rows = table(spark, sf_dir, child)
    return coalesced(rows, F.col(parent_key), F.col(key), None if weight is None else F.col(weight))


def ring(spark: SparkSession, n: int, keys: DataFrame | None = None):
    """keys: a frame whose column `id` holds the vertices, 0 to n - 1."""
    rows = spark.range(n) if keys is None else keys.select(F.col("id").cast("long").alias("id"))
    return symmetrised(rows.select(F.col("id").alias("i"), ((F.col("id") + 1) % n).alias("j"), F.lit(1.0).alias("w")), "any")


def path(spark: SparkSession, n: int):
    return symmetrised(spark.range(n - 1).select(F.col("id").alias("i"), (F.col("id") + 1).alias("j"), F.lit(1.0).alias("w")), "any")


def recursive_matrix(spark: SparkSession, scale: int, edge_factor: int = 40, seed: int = 1, shares=(57, 19, 19, 5), keys: DataFrame | None = None):
    """Power-law edges from an arithmetic generator that SQL can repeat: each level takes one quadrant. keys: a frame whose column `id` starts the generator, a key an edge, instead of ordinals."""
    a, b, c = shares[0], shares[0] + shares[1], sum(shares[:3])
    edges = (spark.range(edge_factor << scale) if keys is None else keys.select(F.col("id").cast("long").alias("id"))).select(((F.col("id") * 69621 + seed) % 2147483647 + 1).alias("x"), F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"))
    for _ in range(scale):
        edges = edges.select(((F.col("x") * 48271) % 2147483647).alias("x"), "i", "j")
        pick = F.col("x") % 100
        edges = edges.select("x", (F.col("i") * 2 + (pick >= b).cast("long")).alias("i"), (F.col("j") * 2 + (((pick >= a) & (pick < b)) | (pick >= c)).cast("long")).alias("j"))
    return edges.select("i", "j").distinct().withColumn("w", F.lit(1.0))


def degree_profile(edges: DataFrame) -> DataFrame:
    return edges.groupBy("i").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))
