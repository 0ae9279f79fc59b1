"""Edge lists written to and read back from file formats, a partitioned store, and the generator as a Python data source."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGES = "i long, j long, w double"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, one made here, but only under a local master: a machine-local folder loses data on a cluster."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="eigenloom-"))
    return context._jsc.sc().getCheckpointDir().get()


def copied(edges: DataFrame) -> DataFrame:
    """The edge list as files that are read again: unlike persisted partitions, of which there are as many as the last exchange had, they are as few as their size asks for."""
    path = f"{shared_dir(edges.sparkSession)}/edges-{uuid.uuid4().hex}"
    edges.select("i", "j", "w").write.parquet(path)
    return edges.sparkSession.read.schema(EDGES).parquet(path)


def roundtrip(edges: DataFrame, kind: str) -> DataFrame:
    """The edge list as csv, json, orc or parquet files, read again with its schema stated (no inference pass)."""
    spark = edges.sparkSession
    path = f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"
    edges.select("i", "j", "w").write.format(kind).save(path)
    return spark.read.format(kind).schema(EDGES).load(path)


def partitioned(edges: DataFrame, rows_per_band: int) -> DataFrame:
    """The edge list in a folder per band of rows; a filter on `band` reads only its folders."""
    spark = edges.sparkSession
    path = f"{shared_dir(spark)}/bands-{uuid.uuid4().hex}"
    banded = edges.withColumn("band", F.floor(F.col("i") / rows_per_band))
    banded.repartition("band").sortWithinPartitions("band", "i", "j").write.partitionBy("band").parquet(path)
    return spark.read.schema(EDGES + ", band long").parquet(path)


class Span(InputPartition):
    def __init__(self, first: int, end: int):
        super().__init__((first, end))


class RecursiveReader(DataSourceReader):
    """Each partition generates a span of edge ordinals, so partitions need nothing from one another."""

    def __init__(self, options):
        self.scale, self.seed = int(options.get("scale", 6)), int(options.get("seed", 1))
        self.total = int(options.get("edges", int(options.get("edgeFactor", 40)) << min(self.scale, 20)))
        self.pieces = int(options.get("partitions", 8))
        if not 1 <= self.scale <= 20:
            raise ValueError("scale is 1 to 20")

    def partitions(self):
        total = self.total
        step = max(1, -(-total // self.pieces))
        return [Span(s, min(total, s + step)) for s in range(0, total, step)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        first, end = partition.value
        for at in range(first, end, 1 << 16):
            ordinal = np.arange(at, min(end, at + (1 << 16)), dtype=np.int64)
            x = (ordinal * 69621 + self.seed) % 2147483647 + 1
            i = j = np.zeros(len(x), np.int64)
            for _ in range(self.scale):
                x = x * 48271 % 2147483647
                quadrant = np.searchsorted([57, 76, 95], x % 100, side="right")
                i, j = i * 2 + quadrant // 2, j * 2 + quadrant % 2
            yield pa.RecordBatch.from_arrays([pa.array(ordinal), pa.array(i), pa.array(j)], ["id", "i", "j"])


class RecursiveMatrix(DataSource):
    """spark.read.format("recursive_matrix").option("scale", s).load(): power-law edges, repeats included, each with its ordinal."""

    @classmethod
    def name(cls):
        return "recursive_matrix"

    def schema(self):
        return "id long, i long, j long"

    def reader(self, schema):
        return RecursiveReader(self.options)


def generated(spark: SparkSession, scale: int, edge_factor: int = 40, seed: int = 1, keys: DataFrame | None = None) -> DataFrame:
    """Different edges of the data source; keys: a frame whose column `id` holds the ordinals wanted, of which the greatest bounds what is generated."""
    spark.dataSource.register(RecursiveMatrix)
    made = spark.read.format("recursive_matrix").option("scale", scale).option("edgeFactor", edge_factor).option("seed", seed)
    made = made.load() if keys is None else made.option("edges", (keys.agg(F.max("id")).first()[0] or 0) + 1).load().join(keys, "id", "left_semi")
    return made.select("i", "j").distinct().withColumn("w", F.lit(1.0))
