"""Uses of the spectrum: clustering, triangle counts, low-rank error; and measures of a clustering."""

from __future__ import annotations

import numpy as np
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenloom.operators import dense, solver, spmm


def spectral_clusters(spark: SparkSession, edges: DataFrame, n: int, k: int, storage: str = "arrays", seed: int = 7, **options) -> DataFrame:
    """(i, cluster): rows of the k leading vectors of D^-1/2 A D^-1/2, set to length 1, by k-means. A vertex without edges is a row of zeros."""
    options = {"b": min(k, 4), "blocks": 12, "tol": 1e-7, "kernel": "relational"} | options
    found = solver.eigen(spark, spmm.normalised(edges), n, k, storage=storage, which="LA", want_vectors=True, **options)
    if storage == "arrays":
        rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(found.vectors)], "i long, x array<double>")
    else:
        rows = dense.to_rows(found.vectors, dense.interval_bits(4, edge=1024))
    length = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v))
    unit = rows.withColumn("_l", length).select("i", array_to_vector(F.transform("x", lambda v: F.when(F.col("_l") > 1e-12, v / F.col("_l")).otherwise(0.0))).alias("features")).persist()
    return KMeans(k=k, seed=seed, initSteps=5, maxIter=50).fit(unit).transform(unit).select("i", F.col("prediction").alias("cluster"))


def purity(assigned: DataFrame, truth: DataFrame, label: str = "label") -> DataFrame:
    """One row: share of vertices whose label is the commonest of their cluster, and the adjusted Rand index."""
    cells = assigned.join(truth, "i").groupBy("cluster", label).agg(F.count(F.lit(1)).alias("n"))
    pairs = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2)
    inside = cells.agg(pairs("n").alias("both"), F.sum("n").alias("total"))
    by_cluster = cells.groupBy("cluster").agg(F.sum("n").alias("s"), F.max("n").alias("best")).agg(pairs("s").alias("own"), F.sum("best").alias("hit"))
    by_label = cells.groupBy(label).agg(F.sum("n").alias("s")).agg(pairs("s").alias("true"))
    one = inside.crossJoin(by_cluster).crossJoin(by_label)  # one row each
    expected = F.col("own") * F.col("true") / (F.col("total") * (F.col("total") - 1) / 2)
    return one.select((F.col("hit") / F.col("total")).alias("purity"), ((F.col("both") - expected) / ((F.col("own") + F.col("true")) / 2 - expected)).alias("adjusted_rand"))


def triangles(values: np.ndarray) -> float:
    """Triangles of a simple undirected graph from its eigenvalues; the leading ones give an estimate."""
    return float((np.asarray(values) ** 3).sum() / 6)


def low_rank_errors(edges: DataFrame, singular_values: np.ndarray) -> list[float]:
    """Relative Frobenius error of the best approximation of each rank 1, 2, ..."""
    whole = edges.agg(F.sum(F.col("w") * F.col("w"))).first()[0] or 0.0
    left = np.maximum(whole - np.cumsum(np.asarray(singular_values) ** 2), 0)
    return [float(x) for x in np.sqrt(left / whole)] if whole else [0.0] * len(singular_values)
