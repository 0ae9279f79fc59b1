"""User functions over edge lists, tiles, vectors and pages: scalar, vectorised, aggregating, grouped, cogrouped and table functions.

Built-in functions are faster wherever they express the same; these are for what they do not, and for users' own code.
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, Row, StringType

from .tables import HtmlLinks, TileCells


@F.udf(StringType())
def host_of(url):
    found = re.match(r"[a-z]+://([^/]+)", url or "")
    return found.group(1) if found else ""


@F.pandas_udf(DoubleType())
def norm(vectors: pd.Series) -> pd.Series:
    return vectors.map(lambda v: float(np.linalg.norm(np.asarray(v, float))) if v is not None else None)


@F.pandas_udf(DoubleType())
def cosine(left: pd.Series, right: pd.Series) -> pd.Series:
    def one(a, b):
        a, b = np.asarray(a, float), np.asarray(b, float)
        return float(a @ b / (np.linalg.norm(a) * np.linalg.norm(b)))

    return pd.Series([one(a, b) for a, b in zip(left, right)])


@F.pandas_udf(DoubleType())
def square_sum(weights: pd.Series) -> float:
    return float((weights * weights).sum())


def row_profile(edges: DataFrame) -> DataFrame:
    """(i, degree, last): one Arrow table per row of the matrix."""

    def run(key, cells):
        j = cells.column("j").to_numpy()
        return pa.table({"i": pa.array([key[0].as_py()], pa.int64()), "degree": pa.array([len(j)], pa.int64()), "last": pa.array([int(j.max())], pa.int64())})

    return edges.select("i", "j").groupBy("i").applyInArrow(run, "i long, degree long, last long")


def side_counts(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """(key, n_left, n_right) of two frames cogrouped by a column of one name; both arrive counted, so no group is large."""
    counted = lambda frame: frame.groupBy(key).agg(F.count(F.lit(1)).alias("n"))

    def run(k, a, b):
        return pd.DataFrame({key: [k[0]], "n_left": [int(a["n"].sum())], "n_right": [int(b["n"].sum())]})

    return counted(left).groupBy(key).cogroup(counted(right).groupBy(key)).applyInPandas(run, f"{key} long, n_left long, n_right long")


def tile_keys(edges: DataFrame, edge: int) -> DataFrame:
    """(tr, tc, cells) by Arrow batches, counted inside each batch before the shuffle."""

    def run(batches):
        for batch in batches:
            keys = np.stack([batch.column(0).to_numpy() // edge, batch.column(1).to_numpy() // edge], 1)
            found, n = np.unique(keys, axis=0, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1]), pa.array(n)], ["tr", "tc", "n"])

    return edges.select("i", "j").mapInArrow(run, "tr long, tc long, n long").groupBy("tr", "tc").agg(F.sum("n").alias("cells"))


def register(spark: SparkSession) -> None:
    """SQL names: tile_cells, html_links (table functions), host_of, vector_norm, and tile_of, which stays inside generated code."""
    spark.udtf.register("tile_cells", F.udtf(TileCells, returnType="i long, j long, w double"))
    spark.udtf.register("html_links", F.udtf(HtmlLinks, returnType="place int, target string"))
    spark.udf.register("host_of", host_of)
    spark.udf.register("vector_norm", norm)
    spark.sql("create or replace temporary function tile_of(x bigint, edge bigint) returns bigint return x div edge")


def register_spectral(spark: SparkSession) -> None:
    """spectral_values(cells, k): the k eigenvalues of largest magnitude of a small symmetric matrix given as an array of (i, j, w)."""

    class SpectralValues:
        def eval(self, cells: list[Row], k: int):
            ids = sorted({x for c in cells for x in (c["i"], c["j"])})
            at = {v: n for n, v in enumerate(ids)}
            a = np.zeros((len(ids), len(ids)))
            for c in cells:
                a[at[c["i"]], at[c["j"]]] += c["w"]
            values = np.linalg.eigvalsh((a + a.T) / 2)
            for rank, v in enumerate(sorted(values, key=lambda v: -abs(v))[:k]):
                yield rank, float(v)

    spark.udtf.register("spectral_values", F.udtf(SpectralValues, returnType="rank int, value double"))
