"""Tall dense blocks as chunk frames (iv, rows, data: columns one after another) and the operations a block eigensolver needs.

Operands of one run share interval boundaries, so operations join on iv alone; blocks dealt alike (`dealt`) meet without an exchange. Small
matrices are NumPy arrays that travel inside the task. `group` is how many tall operands a task multiplies at a time. Stored blocks are in `subspace`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CHUNK = "iv int, rows int, data array<double>"


def interval_bits(width: int, target_bytes: int = 8 << 20, edge: int = 1) -> int:
    """p such that 2^p rows of `width` doubles come near the target and are a multiple of the tile edge, which must be a power of two."""
    if edge & (edge - 1):
        raise ValueError("a tile edge that intervals are a multiple of is a power of two")
    return max(edge.bit_length() - 1, max(1, target_bytes // (8 * width)).bit_length() - 1)


def _batch(iv, rows, datas) -> pa.RecordBatch:
    """datas: flat arrays of doubles."""
    ends = np.cumsum([0, *map(len, datas)], dtype=np.int32)
    lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0), *datas])))
    return pa.RecordBatch.from_arrays([pa.array(iv, pa.int32()), pa.array(rows, pa.int32()), lists], ["iv", "rows", "data"])


def _matrices(column: pa.Array, rows: list[int]) -> list[np.ndarray]:
    """(rows, width) views of a column of chunks, lists or bytes, without a copy."""
    if pa.types.is_binary(column.type):
        return [np.frombuffer(d.as_buffer(), "<f8").reshape(-1, n).T for d, n in zip(column, rows)]
    at, flat = column.offsets.to_numpy(), column.values.to_numpy()
    return [flat[at[t] : at[t + 1]].reshape(-1, n).T for t, n in enumerate(rows)]


def _mapped(frame: DataFrame, columns: list[str], f) -> DataFrame:
    """f(matrices...) -> matrix, for each interval."""

    def run(batches):
        for batch in batches:
            iv, rows = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            held = [_matrices(batch.column(2 + k), rows) for k in range(len(columns))]
            yield _batch(iv, rows, [f(*(h[t] for h in held)).ravel(order="F") for t in range(len(rows))])

    return frame.select("iv", "rows", *columns).mapInArrow(run, CHUNK)


def packed(chunks: DataFrame) -> DataFrame:
    """Chunks with their doubles as bytes, the form they are stored in; chunks of bytes come back as they are."""
    if dict(chunks.dtypes)["data"] == "binary":
        return chunks.select("iv", "rows", "data")

    def run(batches):
        for batch in batches:
            at, flat = batch.column(2).offsets.to_numpy(), batch.column(2).values.to_numpy()
            data = pa.array([flat[at[t] : at[t + 1]].tobytes() for t in range(batch.num_rows)], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), data], ["iv", "rows", "data"])

    return chunks.select("iv", "rows", "data").mapInArrow(run, "iv int, rows int, data binary")


def unpacked(chunks: DataFrame) -> DataFrame:
    """Chunks with their doubles as an array, which column expressions can read."""
    if dict(chunks.dtypes)["data"] != "binary":
        return chunks

    def run(batches):
        for batch in batches:
            rows = batch.column(1).to_pylist()
            yield _batch(batch.column(0).to_pylist(), rows, [np.frombuffer(d.as_buffer(), "<f8") for d in batch.column(2)])

    return chunks.select("iv", "rows", "data").mapInArrow(run, CHUNK)


def from_rows(block: DataFrame, bits: int, n: int, width: int) -> DataFrame:
    """Row block -> chunk block; absent rows are zero, repeated ones are added."""

    def run(key, rows):
        iv = key[0].as_py()
        size = min(1 << bits, n - (iv << bits))
        x = np.zeros((size, width))
        rows = rows.combine_chunks()
        np.add.at(x, rows.column("i").to_numpy() - (iv << bits), rows.column("x").combine_chunks().flatten().to_numpy().reshape(-1, width))
        return pa.Table.from_batches([_batch([iv], [size], [x.ravel(order="F")])])

    some = block.select(F.shiftright("i", bits).cast("int").alias("iv"), "i", "x")
    every = block.sparkSession.range(((n - 1) >> bits) + 1).select(F.col("id").cast("int").alias("iv"), (F.col("id") * (1 << bits)).alias("i"), F.array(*(F.lit(0.0) for _ in range(width))).alias("x"))
    return some.unionByName(every).groupBy("iv").applyInArrow(run, CHUNK)


def to_rows(chunks: DataFrame, bits: int) -> DataFrame:
    """Chunk block -> row block; chunks of an array without Python, chunks of bytes, which need it to be read, in one pass of it."""
    if dict(chunks.dtypes)["data"] == "binary":
        return chunks.select("iv", "rows", "data").mapInArrow(lambda batches: _rows_of(batches, bits), "i long, x array<double>")
    columns = F.size("data") / F.col("rows")
    x = F.transform(F.sequence(F.lit(0), columns.cast("int") - 1), lambda c: F.get("data", c * F.col("rows") + F.col("r")))
    spread = chunks.select("iv", "rows", "data", F.explode(F.sequence(F.lit(0), F.col("rows") - 1)).alias("r"))
    return spread.select((F.col("iv").cast("long") * (1 << bits) + F.col("r")).alias("i"), x.alias("x"))


def _rows_of(batches, bits: int):
    for batch in batches:
        rows = batch.column(1).to_pylist()
        for iv, x in zip(batch.column(0).to_pylist(), _matrices(batch.column(2), rows)):
            ends = pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1])
            yield pa.RecordBatch.from_arrays([pa.array((iv << bits) + np.arange(len(x))), pa.ListArray.from_arrays(ends, pa.array(x.ravel()))], ["i", "x"])


def from_array(spark: SparkSession, x: np.ndarray, bits: int) -> DataFrame:
    size = 1 << bits
    return spark.createDataFrame([(k, len(x[s : s + size]), x[s : s + size].ravel(order="F").tolist()) for k, s in enumerate(range(0, len(x), size))], CHUNK)


def to_array(chunks: DataFrame) -> np.ndarray:
    """The resident form on the driver: 8 x rows x columns bytes."""
    table = chunks.select("iv", "rows", "data").toArrow().sort_by("iv").combine_chunks()
    return np.concatenate(_matrices(table.column("data").combine_chunks(), table.column("rows").to_pylist()))


def random(spark: SparkSession, n: int, width: int, seed: int, bits: int) -> DataFrame:
    """Counter-based: the value of (row, column) depends on them and the seed, not on the partitioning."""
    value = lambda i, c: F.pmod(F.xxhash64(i, c, F.lit(seed)), F.lit(2000003)).cast("double") / 1000001.5 - 1
    heads = spark.range(((n - 1) >> bits) + 1).select(F.col("id").cast("int").alias("iv"), F.least(F.lit(1 << bits), F.lit(n) - F.col("id") * (1 << bits)).cast("int").alias("rows"))
    cells = F.transform(F.sequence(F.lit(0), F.col("rows") * width - 1), lambda k: value(F.col("iv").cast("long") * (1 << bits) + k % F.col("rows"), F.floor(k / F.col("rows"))))
    return heads.select("iv", "rows", cells.alias("data"))


def aligned(blocks: list[DataFrame]) -> DataFrame:
    """(iv, rows, d0, d1, ...): joins on iv alone."""
    out = blocks[0].select("iv", "rows", F.col("data").alias("d0"))
    for k, block in enumerate(blocks[1:], 1):
        out = out.join(block.select("iv", F.col("data").alias(f"d{k}")), "iv")
    return out


def dealt(block: DataFrame, parts: int) -> DataFrame:
    """The block persisted and hash-partitioned by interval: joins of blocks dealt into as many parts need no exchange."""
    out = block.repartition(parts, "iv").persist()
    out.columns_held = getattr(block, "columns_held", None)
    return out


def _groups(blocks: list, group: int | None) -> list[list]:
    size = group or len(blocks) or 1
    return [blocks[s : s + size] for s in range(0, len(blocks), size)]


def combine(alpha: float, blocks: list[DataFrame], small: np.ndarray, beta: float = 0.0, other: DataFrame | None = None, group: int | None = None) -> DataFrame:
    """alpha * [blocks] small + beta * other in one plan. A task cuts the small matrix along its rows by groups of blocks and adds their parts into one buffer, so no partial result is stored."""
    widths = _widths(blocks)
    starts = np.cumsum([0, *widths])
    size, more = group or len(blocks), other is not None

    def f(*xs):
        tall = xs[1:] if more else xs
        out = beta * xs[0] if more else np.zeros((len(tall[0]), small.shape[1]))
        for s in range(0, len(tall), size):
            part = tall[s : s + size]
            out = out + alpha * (np.hstack(part) @ small[starts[s] : starts[s + len(part)]])
        return out

    frames = blocks if other is None else [other, *blocks]
    return _mapped(aligned(frames), [f"d{k}" for k in range(len(frames))], f)


def _widths(blocks: list[DataFrame]) -> list[int]:
    """Columns of each block, remembered on the frame."""
    return [getattr(b, "columns_held", None) or _measure(b) for b in blocks]


def _measure(block: DataFrame) -> int:
    row = block.select((F.size("data") / F.col("rows")).cast("int").alias("w")).first()
    block.columns_held = row["w"] if row else 0
    return block.columns_held


def gram(alpha: float, blocks: list[DataFrame], right: DataFrame, group: int | None = None, share_right: bool = True) -> np.ndarray:
    """alpha * [blocks]^T right: sums over a task's intervals, then one small sum. Blocks are multiplied in groups; the right operand's interval is read once for all of them, or,
    without share_right, once for each group (the form that sharing is measured against)."""
    if not share_right:
        return np.vstack([gram(alpha, part, right, None) for part in _groups(blocks, group)])
    parts = _gram_plan(blocks, right, group or len(blocks))
    summed = parts.select("width", F.posexplode("v").alias("at", "v")).groupBy("width", "at").agg(F.sum("v").alias("v")).toArrow()
    values = np.zeros(summed.num_rows)
    values[summed.column("at").to_numpy()] = summed.column("v").to_numpy()
    return alpha * values.reshape(-1, summed.column("width")[0].as_py())


def _gram_plan(blocks: list[DataFrame], right: DataFrame, size: int) -> DataFrame:
    count = len(blocks)

    def run(batches):
        total = None
        for batch in batches:
            rows = batch.column(1).to_pylist()
            held = [_matrices(batch.column(2 + k), rows) for k in range(count + 1)]
            for t in range(len(rows)):
                made = np.vstack([np.hstack([h[t] for h in held[1 + s : 1 + s + size]]).T @ held[0][t] for s in range(0, count, size)])
                total = made if total is None else total + made
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.shape[1]], pa.int32()), pa.array([total.ravel()], pa.list_(pa.float64()))], ["width", "v"])

    return aligned([right, *blocks]).mapInArrow(run, "width int, v array<double>")


def tsqr(block: DataFrame) -> np.ndarray:
    """R of a tall block's QR factors: a QR of each interval, then one of the stacked small factors on the driver (width x width doubles an interval)."""

    def run(batches):
        for batch in batches:
            for x in _matrices(batch.column(1), batch.column(0).to_pylist()):
                r = np.linalg.qr(x, mode="r")
                yield pa.RecordBatch.from_arrays([pa.array([x.shape[1]], pa.int32()), pa.array([r.ravel()], pa.list_(pa.float64()))], ["width", "v"])

    made = block.select("rows", "data").mapInArrow(run, "width int, v array<double>").collect()
    return np.linalg.qr(np.vstack([np.array(m["v"]).reshape(-1, m["width"]) for m in made]), mode="r")


def scale(alpha: float, block: DataFrame) -> DataFrame:
    return block.select("iv", "rows", F.transform("data", lambda v: v * F.lit(float(alpha))).alias("data"))


def scale_columns(block: DataFrame, vec) -> DataFrame:
    by = F.array(*(F.lit(float(v)) for v in vec))
    return block.select("iv", "rows", F.transform("data", lambda v, k: v * F.get(by, F.floor(k / F.col("rows")).cast("int"))).alias("data"))


def add(alpha: float, left: DataFrame, beta: float, right: DataFrame) -> DataFrame:
    both = aligned([left, right])
    return both.select("iv", "rows", F.zip_with("d0", "d1", lambda a, b: a * F.lit(float(alpha)) + b * F.lit(float(beta))).alias("data"))


def column_dots(left: DataFrame, right: DataFrame) -> DataFrame:
    """(c, v): dot products of columns of one index."""
    product = aligned([left, right]).select("rows", F.posexplode(F.zip_with("d0", "d1", lambda a, b: a * b)).alias("k", "v"))
    return product.groupBy(F.floor(F.col("k") / F.col("rows")).cast("int").alias("c")).agg(F.sum("v").alias("v"))


def column_norms(block: DataFrame) -> DataFrame:
    squares = block.select("rows", F.posexplode("data").alias("k", "v"))
    return squares.groupBy(F.floor(F.col("k") / F.col("rows")).cast("int").alias("c")).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("v"))


def view(block: DataFrame, columns: list[int]) -> DataFrame:
    """Chosen columns; a slice per column, no copy until it is used."""
    return block.select("iv", "rows", F.concat(*(F.slice("data", F.col("rows") * c + 1, F.col("rows")) for c in columns)).alias("data"))


def set_columns(block: DataFrame, columns: list[int], other: DataFrame, width: int) -> DataFrame:
    both = aligned([block, other])
    cut = lambda d, c: F.slice(d, F.col("rows") * c + 1, F.col("rows"))
    return both.select("iv", "rows", F.concat(*(cut("d1", columns.index(c)) if c in columns else cut("d0", c) for c in range(width))).alias("data"))
