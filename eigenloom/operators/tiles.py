"""Two-dimensional tiles of a sparse matrix: encoding, index, storage accounting and run-time grouping."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eigenloom.functions import codec
from eigenloom.sources.stores import shared_dir

TILE = "tr int, tc int, nnz int, n_multi_rows int, n_single int, code binary, vals binary"
LISTS = "group long, cells binary, weights binary"


def assigned(edges: DataFrame, edge: int) -> DataFrame:
    if edge > codec.MAX_EDGE:
        raise ValueError(f"a tile edge is at most {codec.MAX_EDGE}")
    at = lambda c: F.floor(F.col(c) / edge).cast("int")
    return edges.select(at("i").alias("tr"), at("j").alias("tc"), (F.col("i") % edge).cast("int").alias("r"), (F.col("j") % edge).cast("int").alias("c"), "w")


#: Columns of a tile row that one task encodes together, cells that are encoded in one pass, and cells (as a power of 2) that a list of them holds at most.
SPAN, PASS_CELLS, LIST_BITS = 1 << 15, 1 << 18, 14
#: Cells that a task sorts by group before it writes lists of them.
DEAL_CELLS = 1 << 20
#: The setting whose limit Spark compares with a batch's size at each of its rows.
BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


def encoded(edges: DataFrame, edge: int = 16384, hybrid: bool = True) -> DataFrame:
    """Tile frame; one row per tile, of at most edge x edge cells; one shuffle of the edges, once per matrix; edges that repeat are added. Cells of neighbouring tiles of a row lie in one task and
    reach Python as lists of at most 2^LIST_BITS, since a row for each cell costs more to hand over than to encode. Lists sorted by their tiles are encoded some at a time, whatever the tiles' number
    and size: only cells of the same neighbours wait for one another, and those that repeat are added meanwhile."""
    per = _per(edge)
    local = f"((j % {per * edge}) div {edge} * {edge} + i % {edge}) * {edge} + j % {edge}"
    group = F.shiftleft(F.expr(f"i div {edge}"), 32).bitwiseOR(F.expr(f"j div {per * edge}"))
    keyed = edges.select(group.alias("group"), F.expr(f"cast({local} as int)").alias("cell"), "w")
    # Sorted before they are listed, so that lists are few and an aggregate holds few cells at a time.
    dealt = keyed.repartition("group").sortWithinPartitions("group").withColumn("list", F.shiftright(F.monotonically_increasing_id(), LIST_BITS))
    one = F.col("w").eqNullSafe(F.lit(1.0))
    lists = dealt.groupBy("group", "list").agg(F.collect_list(F.when(one, F.col("cell"))).alias("ones"), F.collect_list(F.when(~one, F.struct("cell", F.col("w").cast("double").alias("w")))).alias("others"))
    return lists.select("group", "ones", "others").sortWithinPartitions("group").mapInArrow(_encoder(_of_arrays, edge, hybrid), TILE)


def encoded_lists(lists: DataFrame, edge: int, hybrid: bool = True) -> DataFrame:
    """The tile frame of the files of `listed`; one shuffle, of the lists."""
    return lists.repartition("group").sortWithinPartitions("group").mapInArrow(_encoder(_of_bytes, edge, hybrid), TILE)


def listed(edges: DataFrame, edge: int, path: str) -> DataFrame | None:
    """Edges as files of lists (group, cells, weights) of at most 2^LIST_BITS cells of a group, which each task sorts some at a time, so that neither a shuffle nor a sort meets a row for each cell.

    While they are written, Spark does not compare a batch's bytes with its limit at each row, which costs more than the rows do: three numbers each, they are bounded by their count. None if
    that is not so: where batches are not bounded by a count, or where the edges themselves come through Python, whose rows may be long.
    """
    per, deal, most, spark = _per(edge), DEAL_CELLS, 1 << LIST_BITS, edges.sparkSession
    plan = edges._jdf.queryExecution().optimizedPlan().toString()
    if any(name in plan for name in ("Python", "Arrow", "Pandas")) or int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) <= 0:
        return None

    def run(batches):
        held, count = [], 0
        for batch in batches:
            held.append([_numbers(batch.column(k), dtype) for k, dtype in enumerate(("<i8", "<i8", "<f8"))])
            count += batch.num_rows
            if count >= deal:
                yield from _lists(*map(np.concatenate, zip(*held)), per, edge, most)
                held, count = [], 0
        if count:
            yield from _lists(*map(np.concatenate, zip(*held)), per, edge, most)

    lists = edges.select(F.col("i").cast("long"), F.col("j").cast("long"), F.col("w").cast("double")).mapInArrow(run, LISTS)
    before = spark.conf.get(BATCH_BYTES)
    spark.conf.set(BATCH_BYTES, str((1 << 31) - 1))
    try:
        lists.write.option("parquet.enable.dictionary", "false").parquet(path)
    finally:
        spark.conf.set(BATCH_BYTES, before)
    return spark.read.schema(LISTS).parquet(path)


def _per(edge: int) -> int:
    """Tiles of a group: neighbours in a tile row."""
    if edge > codec.MAX_EDGE:
        raise ValueError(f"a tile edge is at most {codec.MAX_EDGE}")
    return max(1, SPAN // edge)


def _encoder(read, edge: int, hybrid: bool):
    """The function that encodes batches sorted by group; read(batch) gives each row's group and its cells as (cells, weights), where weights of None are 1."""
    per = _per(edge)
    most, size = PASS_CELLS, per * edge * edge

    def run(batches):
        held, groups, count, least = [], [], 0, 0
        for batch in batches:
            for group, parts in read(batch):
                if count >= most and group != groups[-1]:
                    yield _coded(*_added(held), groups, per, edge, hybrid)
                    held, groups, count, least = [], [], 0, 0
                elif count >= most and count >= 2 * least:
                    held = [_added(held)]
                    count = least = len(held[0][0])
                if not groups or group != groups[-1]:
                    groups.append(group)
                begin = np.int64((len(groups) - 1) * size)
                for cells, w in parts:
                    held.append((cells + begin, w))
                    count += len(cells)
        if held:
            yield _coded(*_added(held), groups, per, edge, hybrid)

    return run


def _of_arrays(batch: pa.RecordBatch):
    ones, others = batch.column(1), batch.column(2)
    one_ends, other_ends = ones.offsets.to_numpy(), others.offsets.to_numpy()
    one_cells, other_cells, weights = ones.values.to_numpy(), others.values.field(0).to_numpy(), others.values.field(1).to_numpy()
    for k, group in enumerate(batch.column(0).to_pylist()):
        mine, more = slice(one_ends[k], one_ends[k + 1]), slice(other_ends[k], other_ends[k + 1])
        yield group, [(one_cells[mine], None)] + ([(other_cells[more], weights[more])] if more.start < more.stop else [])


def _of_bytes(batch: pa.RecordBatch):
    (cells, ends), (weights, weight_ends) = _flat(batch.column(1), "<i4"), _flat(batch.column(2), "<f8")
    ends, weight_ends = ends.tolist(), weight_ends.tolist()
    for k, group in enumerate(batch.column(0).to_pylist()):
        given = weights[weight_ends[k] : weight_ends[k + 1]]
        yield group, [(cells[ends[k] : ends[k + 1]], given if len(given) else None)]


def _split(x: np.ndarray, by: int) -> tuple[np.ndarray, np.ndarray]:
    """(quotients, remainders) of numbers that are not negative."""
    if by & (by - 1):
        quotient = x // by
        return quotient, x - quotient * by
    return x >> (by.bit_length() - 1), x & (by - 1)


def _lists(i: np.ndarray, j: np.ndarray, w: np.ndarray, per: int, edge: int, most: int) -> Iterator[pa.RecordBatch]:
    """Edges as lists (group, cells, weights) of at most `most` cells, those that repeat added; lists without weights are of ones. A cell is numbered within its group."""
    if min(i.min(), j.min()) < 0 or i.max() // edge >= 1 << 31:
        raise ValueError("an edge lies outside the matrix")
    (row, r), (column, c), size = _split(i, edge), _split(j, edge), per * edge * edge
    span, tile = _split(column, per)
    group, cell = (row << 32) | span, (tile * edge + r) * edge + c
    row -= (first_row := row.min())
    span -= (first_span := span.min())
    spans = int(span.max()) + 1
    if (int(row.max()) + 1) * spans * size < 1 << 63:
        place, names = row * spans + span, None
    else:
        names, place = np.unique(group, return_inverse=True)
    cells, w = _added([(place * size + cell, None if (w == 1).all() else w)])
    ones = w == 1
    for mine, given in ((cells[ones], None), (cells[~ones], w[~ones])):
        if not len(mine):
            continue
        place, cell = _split(mine, size)
        firsts = np.flatnonzero(np.diff(place, prepend=-1))
        ends = np.append(firsts, len(place))
        pieces = -(-np.diff(ends) // most)
        begins = np.repeat(firsts, pieces) + most * (np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces))
        at, bounds = place[begins], np.append(begins, len(place))
        group = names[at] if names is not None else ((at // spans + first_row) << 32) | (at % spans + first_span)
        binary = lambda x, dtype: _bytes(bounds * np.dtype(dtype).itemsize, x.astype(dtype), None)
        yield pa.RecordBatch.from_arrays([column_of(group), binary(cell, "<i4"), pa.nulls(len(begins), pa.binary()) if given is None else binary(given, "<f8")], ["group", "cells", "weights"])


def _flat(column: pa.Array, dtype: str) -> tuple[np.ndarray, np.ndarray]:
    """(all numbers of a column of bytes, where each value's begin and the last's end); nulls have none."""
    large, size = pa.types.is_large_binary(column.type), np.dtype(dtype).itemsize
    _valid, ends, data = column.buffers()
    if not len(column):
        return np.zeros(0, dtype), np.zeros(1, np.int64)
    ends = np.frombuffer(ends, "<i8" if large else "<i4")[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return np.frombuffer(data, np.uint8)[: ends[-1]].view(dtype) if data is not None and ends[-1] else np.zeros(0, dtype), ends // size


def _added(held: list[tuple[np.ndarray, np.ndarray | None]]) -> tuple[np.ndarray, np.ndarray]:
    """(cells in order, weights): those of equal cells are added; weights of None are 1."""
    cells = np.concatenate([c for c, _ in held])
    if all(w is None for _, w in held):
        cells.sort()
        first = np.flatnonzero(np.diff(cells, prepend=-1))
        return cells[first], np.diff(first, append=len(cells)).astype(float)
    weights = np.concatenate([np.ones(len(c)) if w is None else w for c, w in held])
    order = np.argsort(cells, kind="stable")
    cells = cells[order]
    first = np.flatnonzero(np.diff(cells, prepend=-1))
    return cells[first], np.add.reduceat(weights[order], first)


def _coded(cells: np.ndarray, w: np.ndarray, groups: list[int], per: int, edge: int, hybrid: bool) -> pa.RecordBatch:
    """The tiles of different cells in order; a group has `per` tiles, one after another."""
    tile, at = _split(cells, edge * edge)
    begins = np.flatnonzero(np.diff(tile, prepend=-1))
    bounds, (group, column) = np.append(begins, len(tile)), np.divmod(tile[begins], per)
    of = np.array(groups, np.int64)[group]
    words, word_ends, stored, value_ends, multi, single = codec.encode_many(bounds, *_split(at, edge), w, edge, hybrid)
    binary = lambda ends, size, data, none: _bytes(np.append(0, ends * size), data, none)
    weighted = np.packbits(np.diff(value_ends, prepend=0) > 0, bitorder="little")
    columns = [column_of(x.astype(np.int32)) for x in (of >> 32, (of & 0xFFFFFFFF) * per + column, np.diff(bounds), multi, single)]
    return pa.RecordBatch.from_arrays([*columns, binary(word_ends, 2, words.tobytes(), None), binary(value_ends, 8, stored.tobytes(), pa.py_buffer(weighted))], ["tr", "tc", "nnz", "n_multi_rows", "n_single", "code", "vals"])


def column_of(x: np.ndarray) -> pa.Array:
    """The array's numbers as a column. Unlike `pa.array` (and `to_numpy`) it does not make a new worker import pandas, which takes longer than its first cells."""
    return pa.Array.from_buffers(pa.from_numpy_dtype(x.dtype), len(x), [None, pa.py_buffer(np.ascontiguousarray(x))])


def _numbers(column: pa.Array, dtype: str) -> np.ndarray:
    """The column's numbers, without a copy, nulls as undefined ones."""
    if column.null_count:
        return column.to_numpy(zero_copy_only=False)
    held = np.frombuffer(column.buffers()[1], dtype) if len(column) else np.zeros(0, dtype)
    return held[column.offset : column.offset + len(column)]


def _bytes(ends: np.ndarray, data: bytes, valid: pa.Buffer | None) -> pa.Array:
    """A column of bytes; cast only from more than its offsets take, since a worker's first cast imports what takes longer than to encode many tiles."""
    large = ends[-1] >= 1 << 31
    made = pa.Array.from_buffers(pa.large_binary() if large else pa.binary(), len(ends) - 1, [valid, pa.py_buffer(ends.astype(np.int64 if large else np.int32)), pa.py_buffer(data)])
    return made.cast(pa.binary()) if large else made


def grouped(rows, most_bytes: int = 1 << 19):
    """Runs of consecutive tiles (tr, tc, n_single, code, vals) of about most_bytes of code, to be decoded in one pass."""
    run, held = [], 0
    for row in rows:
        run.append(row)
        held += len(row[3])
        if held >= most_bytes:
            yield run
            run, held = [], 0
    if run:
        yield run


def decoded(tiles: DataFrame, edge: int) -> DataFrame:
    """Edge frame of a tile frame."""

    def run(batches):
        for batch in batches:
            for rows in grouped(zip(*(batch.column(k).to_pylist() for k in ("tr", "tc", "n_single", "code", "vals")))):
                tr, tc, single, code, vals = zip(*rows)
                at, r, c, w = codec.decode_many(code, vals, single)
                yield pa.RecordBatch.from_arrays([pa.array(r + np.array(tr, np.int64)[at] * edge), pa.array(c + np.array(tc, np.int64)[at] * edge), pa.array(w)], ["i", "j", "w"])

    return tiles.mapInArrow(run, "i long, j long, w double")


def index_of(tiles: DataFrame) -> DataFrame:
    """Per tile row: tiles, cells and bytes; the planner's only statistics."""
    size = F.octet_length("code") + F.coalesce(F.octet_length("vals"), F.lit(0))
    return tiles.groupBy("tr").agg(F.count(F.lit(1)).alias("tiles"), F.sum("nnz").alias("nnz"), F.sum(size).alias("bytes"))


def storage_report(edges: DataFrame, edge: int) -> DataFrame:
    """One row: bytes of the 0/1 pattern as tile code, as per-tile and as global compressed rows. Two aggregates, no encoding."""
    rows = assigned(edges, edge).groupBy("tr", "tc", "r").agg(F.count(F.lit(1)).alias("cells"))
    tiles = rows.groupBy("tr", "tc").agg(F.sum("cells").alias("nnz"), F.count(F.lit(1)).alias("n_rows"), F.sum((F.col("cells") == 1).cast("long")).alias("n_single"))
    tiled = tiles.agg(
        F.count(F.lit(1)).alias("tiles"),
        F.sum("nnz").alias("nnz"),
        F.sum("n_rows").alias("tile_rows"),
        F.sum("n_single").alias("single_rows"),
        F.sum(2 * F.col("n_rows") + 2 * F.col("nnz")).alias("code_bytes"),
        F.sum(2 * (edge + 1) + 2 * F.col("nnz")).alias("tile_csr_bytes"),
    )
    return tiled.crossJoin(edges.agg((8 * F.count(F.lit(1)) + 8 * (F.max("i") + 2)).alias("csr_bytes")))  # one row each


def plan_super(width: int, cache_bytes: int, sharers: int, edge: int) -> int:
    """Tiles along the side of a super tile: as many as keep its dense rows, read and written, within a thread's share of the cache."""
    return max(1, cache_bytes // (sharers * 2 * 8 * width) // edge)


def plan_partitions(index: list[tuple[int, int]], width: int, target_bytes: int) -> list[tuple[int, int]]:
    """Contiguous ranges [first, last] of tile rows or row intervals whose bytes plus dense output stay near a target; wider blocks give more ranges."""
    ranges, first, held = [], None, 0
    for row, size in index:
        cost = size * max(1, width // 4)
        if first is not None and held + cost > target_bytes:
            ranges.append((first, last))
            first, held = None, 0
        first = row if first is None else first
        last, held = row, held + cost
    return ranges + ([(first, last)] if first is not None else [])


def best_edge(edges: DataFrame, most_cells: int = 1 << 22, choices=(16384, 4096, 1024, 256)) -> int:
    """The largest tile edge of which no tile holds more cells than a task should encode at once."""
    fine = choices[-1]
    counts = edges.groupBy(F.floor(F.col("i") / fine).alias("a"), F.floor(F.col("j") / fine).alias("b")).agg(F.count(F.lit(1)).alias("n")).persist()
    for edge in choices:
        by = edge // fine
        if (counts.groupBy(F.floor(F.col("a") / by), F.floor(F.col("b") / by)).agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0) <= most_cells:
            break
    counts.unpersist()
    return edge


class TileStore:
    """A matrix of n_rows x n_cols as tiles in a table, bucketed by parts: contiguous row intervals of 2^bits rows, as many as `plan_partitions` makes for blocks of `width` columns.

    A part's tiles meet in one task without an exchange and give the chunks of its intervals, so a multiply reads the stored matrix once and shuffles nothing.
    dynamic: parts of near equal bytes, of which the scheduler hands the next to whichever core is free; without it, parts of equally many intervals.
    """

    def __init__(self, edges: DataFrame, n_rows: int, n_cols: int, bits: int, edge: int | None = None, width: int = 4, target_bytes: int = 16 << 20, hybrid: bool = True, codec: str = "zstd", dynamic: bool = True):
        self.spark, self.n_rows, self.n_cols, self.bits, self.width = edges.sparkSession, n_rows, n_cols, bits, width
        self.edge = min(edge or best_edge(edges), 1 << bits)
        if (1 << bits) % self.edge:
            raise ValueError("a row interval holds whole tiles")
        self.root = f"{shared_dir(self.spark)}/tiles-{uuid.uuid4().hex}"
        # Encoded once, whatever the edges cost, into files of their own; the parts are planned from the tiles.
        draft, sorted_cells = f"{self.root}-draft", f"{self.root}-lists"
        lists = listed(edges, self.edge, sorted_cells)
        (encoded(edges, self.edge, hybrid) if lists is None else encoded_lists(lists, self.edge, hybrid)).write.parquet(draft)
        self._delete(sorted_cells)
        coded = self.spark.read.schema(TILE).parquet(draft).withColumn("iv", F.shiftright(F.col("tr") * self.edge, bits).cast("int"))
        size = F.octet_length("code") + F.coalesce(F.octet_length("vals"), F.lit(0))
        per = coded.groupBy("iv").agg(F.sum("nnz").alias("n"), F.max(F.col("vals").isNotNull()).alias("weighted"), F.sum(size).alias("bytes")).collect()  # a row for each interval
        cells = {r["iv"]: r["n"] * (12 if r["weighted"] else 4) for r in per}
        self.cells, self.bytes, intervals = sum(r["n"] for r in per), sum(r["bytes"] for r in per), ((n_rows - 1) >> bits) + 1
        index = [(iv, cells.get(iv, 0) + 8 * width * min(1 << bits, n_rows - (iv << bits))) for iv in range(intervals)]
        if dynamic:
            least = max(1, min(target_bytes, sum(c for _, c in index) // self.spark.sparkContext.defaultParallelism))
            self.parts = plan_partitions(index, width, least)
        else:
            step = max(1, -(-intervals // self.spark.sparkContext.defaultParallelism))
            self.parts = [(s, min(s + step, intervals) - 1) for s in range(0, intervals, step)]
        # From Arrow, so that no Python worker makes these rows.
        sizes = [b + 1 - a for a, b in self.parts]
        of = self.spark.createDataFrame(pa.table({"iv": pa.array(np.arange(sum(sizes)) + self.parts[0][0], pa.int32()), "part": pa.array(np.repeat(np.arange(len(sizes)), sizes), pa.int32())}))
        self.buckets = min(4 * len(self.parts), int(self.spark.conf.get("spark.sql.sources.bucketing.maxBuckets", "100000")))
        # An empty row for each part, so that rows without cells give zeros.
        empty = of.groupBy("part").agg(F.min("iv").alias("iv")).selectExpr("iv", "-1 as tr", "0 as tc", "0 as nnz", "0 as n_multi_rows", "0 as n_single", "cast('' as binary) as code", "cast(null as binary) as vals", "part")
        rows = coded.join(F.broadcast(of), "iv").unionByName(empty).repartition(self.buckets, "part")
        self.table = "tiles_" + uuid.uuid4().hex
        rows.write.bucketBy(self.buckets, "part").sortBy("part", "tr", "tc").option("compression", codec).option("path", self.root).saveAsTable(self.table)
        self._delete(draft)

    @property
    def frame(self) -> DataFrame:
        return self.spark.table(self.table)

    def close(self) -> None:
        self.spark.sql(f"drop table if exists {self.table}")
        self._delete(self.root)

    def _delete(self, folder: str) -> None:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def row_lists(edges: DataFrame, by: str = "i") -> DataFrame:
    """Compressed rows (or columns, by='j'): (i, cols, vals) sorted; the format of the baselines."""
    other = "j" if by == "i" else "i"
    lists = edges.groupBy(by).agg(F.sort_array(F.collect_list(F.struct(F.col(other).alias("c"), F.col("w").alias("v")))).alias("e"))
    return lists.select(F.col(by).alias("i"), F.col("e.c").alias("cols"), F.col("e.v").alias("vals"))
