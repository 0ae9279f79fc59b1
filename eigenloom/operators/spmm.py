"""Sparse times dense in the variants of the survey. A dense block at rest is a row block (i, x array<double>) or a chunk block (iv, rows, data), column by column."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eigenloom.functions import codec, resident as residency
from eigenloom.operators import tiles as tiling

CHUNK = "iv int, rows int, data array<double>"


def relational(edges: DataFrame, block: DataFrame, width: int, hint: str | None = None) -> DataFrame:
    """Both operands on disk: one join and one partially aggregated sum, all inside generated code."""
    right = block.select(F.col("i").alias("j"), "x")
    joined = edges.join(right.hint(hint) if hint else right, "j")
    sums = [F.sum(F.col("w") * F.get("x", F.lit(k))).alias(f"_{k}") for k in range(width)]
    return joined.groupBy("i").agg(*sums).select("i", F.array(*(F.col(f"_{k}") for k in range(width))).alias("x"))


def resident(tiles: DataFrame, dense: np.ndarray, edge: int, vectorised: bool = True, super_tile: bool = True) -> DataFrame:
    """The matrix streams from storage while the dense block is resident once per executor process; (i, x) partial sums by tile row, no join.

    A task adds into local buffers of tile rows; tile rows split over tasks are added by `added`. Every row with a cell is in the product, whatever its sum.
    """
    held = tiles.sparkSession.sparkContext.broadcast(dense)

    def run(batches):
        x, sums = held.value, _Sums(edge, dense.shape[1], vectorised)
        for batch in batches:
            rows = list(zip(*(batch.column(k).to_pylist() for k in ("tr", "tc", "n_single", "code", "vals"))))
            for run in tiling.grouped(sorted(rows, key=lambda t: t[:2]) if super_tile else rows):
                tr, tc, single, code, vals = zip(*run)
                place, r, c, w = codec.decode_many(code, vals, single)
                yield from sums.add(np.array(tr, np.int64)[place], r, w, x, np.array(tc, np.int64)[place] * edge + c)
        yield from sums.rest()

    return tiles.select("tr", "tc", "n_single", "code", "vals").mapInArrow(run, "i long, x array<double>")


#: Bytes of a core's cache that a super tile fills, and the greatest block that is broadcast; beyond it the striped multiply runs.
CACHE_BYTES, RESIDENT_BYTES = 1 << 20, 4 << 30
#: Bytes of a task's buffers of tile rows.
HELD_BYTES = 32 << 20


def semi_external(store, dense: np.ndarray, spread: bool = True, super_tile: bool = True, vectorised: bool = True, local_buffer: bool = True, buffer_reuse: bool = True, rows: bool = False) -> DataFrame:
    """Stored tiles times a resident block, as chunks (iv, rows, data binary) of the store's row intervals, or with `rows` as rows (i, x) without another pass of Python; no exchange. Each
    switch off gives the same product.

    spread: workers of an executor share one mapped copy of the block; off: each unpickles its own. super_tile: a batch's tiles are visited by super tiles whose dense rows fit the
    cache; off: as they come. vectorised: sorted sums; off: a loop over cells. local_buffer: a part's rows are added up in one buffer and emitted once; off: each tile emits
    its rows, which a second stage adds. buffer_reuse: the buffer outlives the part; off: each part allocates its own.
    """
    width, edge, bits, n = dense.shape[1], store.edge, store.bits, store.n_rows
    if 8 * dense.size > RESIDENT_BYTES:
        raise ValueError("the block is too large to be resident; use striped")
    padded = np.zeros((-(-dense.shape[0] // edge) * edge, width))
    padded[: len(dense)] = dense
    held, side, parts = store.spark.sparkContext.broadcast(padded), tiling.plan_super(width, CACHE_BYTES, 1, edge), store.parts
    name = f"{store.table}-{held._jbroadcast.id()}"

    def ordered(batch):
        rows = [r for r in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("tr", "tc", "n_single", "code", "vals"))) if r[0] >= 0]
        return sorted(rows, key=lambda r: (r[0] // side, r[1] // side, r[0], r[1])) if super_tile else rows

    def by_part(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = residency.mapped(held, name) if spread else held.value
        first, last = parts[key[0].as_py()]
        begin, end = first << bits, min(n, (last + 1) << bits)
        out = residency.zeros(-(-(end - begin) // edge) * edge, width, buffer_reuse)
        for batch in batches:
            for run in tiling.grouped(ordered(batch)):
                tr, tc, single, code, vals = zip(*run)
                place, r, c, w = codec.decode_many(code, vals, single)
                codec.multiply_into(out, np.array(tr, np.int64)[place] * edge - begin + r, np.array(tc, np.int64)[place] * edge + c, w, x, vectorised)
        if rows:
            yield _rows(np.arange(begin, end), out[: end - begin].copy())
            return
        for iv in range(first, last + 1):
            piece = out[(iv << bits) - begin : min(end, (iv + 1) << bits) - begin]
            yield pa.RecordBatch.from_arrays([pa.array([iv], pa.int32()), pa.array([len(piece)], pa.int32()), pa.array([piece.tobytes(order="F")], pa.binary())], ["iv", "rows", "data"])

    def by_tile(batches):
        x = residency.mapped(held, name) if spread else held.value
        for batch in batches:
            for run in tiling.grouped(ordered(batch)):
                tr, tc, single, code, vals = zip(*run)
                place, r, c, w = codec.decode_many(code, vals, single)
                lines, of = np.unique(place * edge + r, return_inverse=True)
                out = residency.zeros(len(lines), width, buffer_reuse)
                codec.multiply_into(out, of, np.array(tc, np.int64)[place] * edge + c, w, x, vectorised)
                yield _rows(np.array(tr, np.int64)[lines // edge] * edge + lines % edge, out)

    if local_buffer:
        made = store.frame.groupBy("part").applyInArrow(by_part, "i long, x array<double>" if rows else "iv int, rows int, data binary")
    else:
        from eigenloom.operators import dense as blocks

        partial = store.frame.select("tr", "tc", "n_single", "code", "vals").mapInArrow(by_tile, "i long, x array<double>")
        made = blocks.from_rows(added(partial, width), bits, n, width)
        made = blocks.to_rows(made, bits) if rows else blocks.packed(made)
    made.resident = held  # destroyed by whoever has used the product
    return made


def _rows(i: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
    lists = pa.ListArray.from_arrays(tiling.column_of(np.arange(len(i) + 1, dtype=np.int32) * x.shape[1]), tiling.column_of(x.ravel()))
    return pa.RecordBatch.from_arrays([tiling.column_of(i), lists], ["i", "x"])


class _Sums:
    """A task's sums by row in buffers of tile rows, of HELD_BYTES in all; they are emitted when they need the room, and at the end."""

    def __init__(self, edge: int, width: int, vectorised: bool = True):
        self.edge, self.vectorised, self.slots = edge, vectorised, max(1, HELD_BYTES // (8 * edge * width))
        self.at: dict[int, int] = {}
        self.out, self.seen = np.zeros((self.slots * edge, width)), np.zeros(self.slots * edge, bool)

    def add(self, tr: np.ndarray, r: np.ndarray, w: np.ndarray, dense: np.ndarray, c: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Adds w * dense[c] to the rows r of the tile rows tr."""
        kinds, of = np.unique(tr, return_inverse=True)
        for begin in range(0, len(kinds), self.slots):
            new = kinds[begin : begin + self.slots].tolist()
            if len(self.at) + sum(k not in self.at for k in new) > self.slots:
                yield from self.rest()
            slot = np.array([self.at.setdefault(k, len(self.at)) for k in new], np.int64)
            mine = slice(None) if len(kinds) <= self.slots else (of >= begin) & (of < begin + self.slots)
            rows = slot[of[mine] - begin] * self.edge + r[mine]
            self.seen[rows] = True
            codec.multiply_into(self.out, rows, c[mine], w[mine], dense, self.vectorised)

    def rest(self) -> Iterator[pa.RecordBatch]:
        used = np.flatnonzero(self.seen)
        if len(used):
            begins = np.fromiter(self.at, np.int64, len(self.at)) * self.edge
            yield _rows(begins[used // self.edge] + used % self.edge, self.out[used])
            self.out[used], self.seen[used] = 0.0, False
        self.at = {}


def added(parts: DataFrame, width: int) -> DataFrame:
    """Sums of partial rows of one i."""
    return parts.groupBy("i").agg(*(F.sum(F.get("x", F.lit(k))).alias(f"_{k}") for k in range(width))).select("i", F.array(*(F.col(f"_{k}") for k in range(width))).alias("x"))


def striped(tiles: DataFrame, block: DataFrame, edge: int, width: int, splits: int = 1) -> DataFrame:
    """For dense blocks too large to be resident: tiles meet the chunk of their tile column (interval = tile edge), then partial rows are added.

    block: chunk block with iv = tile column. splits: tiles of one column are dealt by tile row into so many groups, each with a copy of the chunk, so a hub column is no single
    task's work. A task adds into buffers of tile rows, and emits them when they need the room.
    """

    def run(batches):
        sums = _Sums(edge, width)
        for batch in batches:
            tr, data, size = batch.column(0).to_numpy(), batch.column(5), batch.column(4).to_numpy().astype(np.int64)
            flat, begins, count = data.values.to_numpy(), data.offsets.to_numpy()[:-1].astype(np.int64), 0
            for run in tiling.grouped(zip(*[[None] * batch.num_rows] * 2, *(batch.column(k).to_pylist() for k in (1, 2, 3)))):
                _tr, _tc, single, code, vals = zip(*run)
                place, r, c, w = codec.decode_many(code, vals, single)
                place, count = place + count, count + len(run)
                cells = (begins[place] + c)[:, None] + size[place][:, None] * np.arange(width)
                yield from sums.add(tr[place], r, w, flat[cells], np.arange(len(r)))
        yield from sums.rest()

    left = tiles.withColumn("split", F.pmod("tr", F.lit(splits)))
    right = block.select(F.col("iv").alias("tc"), "rows", "data", F.explode(F.sequence(F.lit(0), F.lit(splits - 1))).alias("split"))
    joined = left.join(right, ["tc", "split"]).select("tr", "n_single", "code", "vals", "rows", "data")
    return added(joined.mapInArrow(run, "i long, x array<double>"), width)


def row_listed(lists: DataFrame, dense: np.ndarray) -> DataFrame:
    """Compressed-row baseline with random gathers into a resident block."""
    held = lists.sparkSession.sparkContext.broadcast(dense)

    def run(batches):
        for batch in batches:
            at, cols, vals = batch.column(1).offsets.to_numpy(), batch.column(1).values.to_numpy(), batch.column(2).values.to_numpy()
            made = np.array([vals[a:b] @ held.value[cols[a:b]] for a, b in zip(at, at[1:])]).reshape(batch.num_rows, -1)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(made) + 1, dtype=np.int32) * held.value.shape[1]), pa.array(made.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], ["i", "x"])

    return lists.select("i", "cols", "vals").mapInArrow(run, "i long, x array<double>")


def column_at_a_time(edges: DataFrame, block: DataFrame, width: int) -> DataFrame:
    """Baseline kernel tuned for one column: as many sparse-vector products as columns."""
    out = None
    for k in range(width):
        one = relational(edges, block.select("i", F.array(F.get("x", F.lit(k))).alias("x")), 1).select("i", F.get("x", F.lit(0)).alias(f"_{k}"))
        out = one if out is None else out.join(one, "i")
    return out.select("i", F.array(*(F.col(f"_{k}") for k in range(width))).alias("x"))


def normal(edges: DataFrame, block: DataFrame, width: int) -> DataFrame:
    """A^T (A X), the operator behind singular values."""
    inner = relational(edges, block, width)
    return relational(edges.select(F.col("j").alias("i"), F.col("i").alias("j"), "w"), inner, width)


def laplacian(edges: DataFrame, block: DataFrame, width: int) -> DataFrame:
    """(D - A) X for a symmetric edge frame."""
    degree = edges.groupBy("i").agg(F.sum("w").alias("d"))
    loops = degree.select("i", F.col("i").alias("j"), F.col("d").alias("w"))
    signed = edges.select("i", "j", (-F.col("w")).alias("w")).unionByName(loops).groupBy("i", "j").agg(F.sum("w").alias("w"))
    return relational(signed, block, width)


def normalised(edges: DataFrame) -> DataFrame:
    """D^-1/2 A D^-1/2."""
    degree = edges.groupBy("i").agg(F.sum("w").alias("d"))
    rows = edges.join(degree, "i").join(degree.select(F.col("i").alias("j"), F.col("d").alias("e")), "j")
    return rows.select("i", "j", (F.col("w") / F.sqrt(F.col("d") * F.col("e"))).alias("w"))


def shifted(edges: DataFrame, n: int, sigma: float) -> DataFrame:
    """A - sigma I as an edge frame."""
    loops = edges.sparkSession.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(-float(sigma)).alias("w"))
    return edges.select("i", "j", "w").unionByName(loops).groupBy("i", "j").agg(F.sum("w").alias("w"))


def bordered(edges: DataFrame, n_rows: int) -> DataFrame:
    """[0 A; A' 0] as an edge frame; columns of A follow its rows."""
    moved = edges.select("i", (F.col("j") + n_rows).alias("j"), "w")
    return moved.unionByName(moved.select(F.col("j").alias("i"), F.col("i").alias("j"), "w"))


def choose(n: int, width: int, cells: int, budget_bytes: int = RESIDENT_BYTES, tiled: bool = True) -> str:
    """resident if the block fits an executor's budget; striped if tiles exist; else relational."""
    return "resident" if 8 * n * width <= budget_bytes and tiled else "striped" if tiled and cells > n else "relational"
