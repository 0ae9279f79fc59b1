"""Shared folder, table access and text helpers of the training-data operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space as the result contracts define it.
SPACE = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


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


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/llm-{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str, *split_by: str) -> DataFrame:
    """df written once as Parquet (in a folder per value of split_by) in the shared folder and read again: lost executors cost no recomputation above it."""
    path = _folder(df.sparkSession, name)
    df.write.partitionBy(*split_by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucket_count(df: DataFrame, size: int, target: int) -> int:
    """Buckets of `target` bytes for `size` bytes, at least the session's shuffle partitions, at most what Spark allows."""
    conf = df.sparkSession.conf
    return min(max(int(conf.get("spark.sql.shuffle.partitions")), -(-size // target)), int(conf.get("spark.sql.sources.bucketing.maxBuckets", "100000")))


#: A task of `bucketed` has so many files open at once, so it need not first sort its rows by bucket in memory; rows of further buckets are sorted.
WRITERS, BUCKET_WRITERS = "spark.sql.maxConcurrentOutputFileWriters", 16


def bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """df as a table in the shared folder, bucketed by key: aggregates on key and joins on it with tables of as many buckets need no exchange. Deal df by `repartition(buckets, key)` first."""
    table_name, conf = f"{name}_{uuid.uuid4().hex}", df.sparkSession.conf
    before = conf.get(WRITERS, None)
    conf.set(WRITERS, BUCKET_WRITERS)
    try:
        df.write.option("compression", "zstd").bucketBy(buckets, key).option("path", _folder(df.sparkSession, name)).saveAsTable(table_name)
    finally:
        conf.unset(WRITERS) if before is None else conf.set(WRITERS, before)
    return df.sparkSession.table(table_name)


def swept(spark: SparkSession) -> None:
    """Deletes all tables that `stored` and `bucketed` of this application wrote; call it when their results have been written elsewhere."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/llm-{spark.sparkContext.applicationId}")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def cut(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


#: Keys with more rows than this are joined apart from the others.
HOT_ROWS = 100_000


def joined_hot(left: DataFrame, right: DataFrame, key: str, n: str = "n", hot: int = HOT_ROWS) -> DataFrame:
    """Inner join on key where right has one row a key and, in `n`, how many rows left has of it. Rows of hot keys stay where they are and meet a broadcast table instead of one task.

    That table has at most rows / hot keys; its count is checked, and where it is too long for a broadcast `hot` is doubled, which halves it.
    """
    heavy = right.filter(F.col(n) > hot)
    count = heavy.count()
    if not count:
        return left.join(right.drop(n), key)
    if count > BROADCAST_ROWS:
        return joined_hot(left, right, key, n, 2 * hot)
    heavy = F.broadcast(heavy.drop(n))
    return left.join(heavy, key).unionByName(left.join(heavy.select(key), key, "left_anti").join(right.filter(F.col(n) <= hot).drop(n), key))


#: Tables of at most so many rows are broadcast; the count is checked first, and larger ones are joined by shuffle.
BROADCAST_ROWS = 500_000
