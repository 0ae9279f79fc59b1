"""Storage of a growing subspace: tall blocks in one table of column-major chunks, partitioned by block and bucketed by row interval.

All blocks of a run share interval boundaries and buckets, so a scan of any of them already holds an interval's chunks in one task: products of blocks group
by interval without an exchange. A block is committed by a manifest that is renamed into place after the write, so a retried write never shows half a block.
"""

from __future__ import annotations

import json
import time
import uuid

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from eigenloom.functions import resident as residency
from eigenloom.sources.stores import shared_dir

#: A chunk at rest: the doubles of an interval, column after column.
PACKED = "iv int, rows int, data binary"
PARTIAL = "width int, v array<double>"
#: Buckets of which each may send the driver a small matrix of its own.
GATHERED = 1024


class Ledger:
    """Logical bytes, bytes of files and seconds by phase."""

    def __init__(self):
        self.rows: list[tuple[int, str, str, int, int, float, int]] = []
        self.step = 0

    def note(self, phase: str, op: str, read: int = 0, written: int = 0, seconds: float = 0.0, files: int = 0) -> None:
        self.rows.append((self.step, phase, op, int(read), int(written), seconds, int(files)))

    def total(self, column: str, op: str | None = None):
        at = {"read": 3, "written": 4, "seconds": 5, "files": 6}[column]
        return sum(r[at] for r in self.rows if op in (None, r[2]))

    def share(self, phase: str) -> float:
        spent = self.total("seconds")
        return sum(r[5] for r in self.rows if r[1] == phase) / spent if spent else 0.0

    def device_writes_per_day(self, capacity_bytes: int, days: float) -> float:
        return self.total("written") / (capacity_bytes * days)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "step int, phase string, op string, bytes_read long, bytes_written long, seconds double, file_bytes long")


class Block:
    """A tall block: stored under its number, or, with number 0, held in memory only, as a persisted frame or as an array with its broadcast."""

    def __init__(self, number: int, width: int, frame: DataFrame | None, array: np.ndarray | None = None, shared=None):
        self.number, self.width, self.frame, self.array, self.shared = number, width, frame, array, shared


def _chunk(data, rows: int) -> np.ndarray:
    """(width, rows) view of a chunk's bytes."""
    return np.frombuffer(data, "<f8").reshape(-1, rows)


def _pieces(table: pa.Table) -> dict[int, np.ndarray]:
    rows = table.column("rows")[0].as_py() if table.num_rows else 0
    return {b: _chunk(d.as_buffer(), rows) for b, d in zip(table.column("blk").to_pylist(), table.column("data"))}


def _partial(made: np.ndarray) -> pa.Table:
    return pa.table({"width": pa.array([made.shape[1]], pa.int32()), "v": pa.array([made.ravel()], pa.list_(pa.float64()))})


def _whole(batches):
    """Rows of whole intervals from batches sorted by interval; rows of a batch's last interval wait for the next batch."""
    waiting = []
    for batch in batches:
        if not batch.num_rows:
            continue
        iv = batch.column(0).to_numpy()
        cut = int(np.searchsorted(iv, iv[-1]))
        if cut or waiting and waiting[-1].column(0)[0].as_py() != iv[0]:
            yield pa.Table.from_batches([*waiting, batch.slice(0, cut)]).combine_chunks()
            waiting = []
        waiting.append(batch.slice(cut))
    if waiting:
        yield pa.Table.from_batches(waiting).combine_chunks()


def _stacks(table: pa.Table, per: int):
    """(intervals, array (interval, columns, rows)) of whole intervals with `per` blocks each, sorted by interval and block; intervals of equal rows are one array, without a copy."""
    iv, rows = (table.column(c).to_numpy()[::per] for c in ("iv", "rows"))
    data = table.column("data").combine_chunks()
    data = data.chunk(0) if isinstance(data, pa.ChunkedArray) else data
    ends = np.frombuffer(data.buffers()[1], "<i4")[data.offset : data.offset + len(data) + 1]
    flat = np.frombuffer(data.buffers()[2], "u1")
    cuts = np.append(np.flatnonzero(np.diff(rows, prepend=-1)), len(rows))
    for a, b in zip(cuts, cuts[1:]):
        piece = flat[ends[a * per] : ends[b * per]]
        piece = piece if piece.ctypes.data % 8 == 0 else piece.copy()
        yield iv[a:b].astype(np.int64), piece.view("<f8").reshape(b - a, -1, rows[a])


def _chunks(iv: np.ndarray, made: np.ndarray, numbers: list[int] | None = None, cuts: list[int] | None = None) -> pa.RecordBatch:
    """Chunks from an array (interval, columns, rows); with numbers, of the blocks whose columns begin at the cuts."""
    cuts = np.array(cuts or [0, made.shape[1]])
    per, rows = len(cuts) - 1, made.shape[2]
    ends = np.append((np.arange(len(iv))[:, None] * cuts[-1] + cuts[:-1]).ravel(), len(iv) * cuts[-1]) * 8 * rows
    data = pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype("<i4")), pa.py_buffer(np.ascontiguousarray(made, "<f8"))])
    columns = [pa.array(np.repeat(iv, per).astype(np.int32)), pa.array(np.full(len(iv) * per, rows, np.int32)), data]
    return pa.RecordBatch.from_arrays(columns + ([pa.array(np.tile(np.array(numbers, np.int32), len(iv)))] if numbers else []), ["iv", "rows", "data"] + (["blk"] if numbers else []))


def _packed(iv: int, made: np.ndarray) -> pa.Table:
    """One chunk from a (rows, width) matrix."""
    return pa.table({"iv": pa.array([iv], pa.int32()), "rows": pa.array([len(made)], pa.int32()), "data": pa.array([np.asarray(made, "<f8").tobytes(order="F")], pa.binary())})


class Subspace:
    """Blocks of n rows in intervals of 2^bits. cache_recent keeps the most recent block, the product that is being projected, in memory until it is stored in its final form;
    without it that block is written to files too, and read from them."""

    def __init__(self, spark: SparkSession, n: int, bits: int, root: str | None = None, cache_recent: bool = True, ledger: Ledger | None = None, width: int = 4, bucket_bytes: int = 64 << 20):
        self.spark, self.n, self.bits, self.cache_recent, self.ledger = spark, n, bits, cache_recent, ledger or Ledger()
        self.root = root or f"{shared_dir(spark)}/subspace-{uuid.uuid4().hex}"
        self.intervals = ((n - 1) >> bits) + 1
        wanted = max(spark.sparkContext.defaultParallelism, 8 * n * width // bucket_bytes)
        self.buckets = max(1, min(self.intervals, wanted, int(spark.conf.get("spark.sql.sources.bucketing.maxBuckets", "100000"))))
        self.table, self.blocks, self.commits, self.made = "subspace_" + uuid.uuid4().hex, {}, 0, 0

    def _path(self, name: str):
        return self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")

    def _files(self, path):
        return path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def commit(self) -> None:
        """Writes the list of blocks beside the last one and renames it into place."""
        self.commits += 1
        draft, final = self._path(f"manifest-{self.commits:08d}.draft"), self._path(f"manifest-{self.commits:08d}.json")
        files = self._files(draft)
        out = files.create(draft, True)
        out.write(bytearray(json.dumps({"n": self.n, "bits": self.bits, "buckets": self.buckets, "blocks": [[b.number, b.width] for b in self.blocks.values()]}).encode()))
        out.close()
        files.rename(draft, final)
        if self.commits > 1:
            files.delete(self._path(f"manifest-{self.commits - 1:08d}.json"), False)

    @classmethod
    def resumed(cls, spark: SparkSession, root: str, **options) -> Subspace:
        """The store that the newest manifest under root describes."""
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
        files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        last = max(f.getPath().getName() for f in files.listStatus(path) if f.getPath().getName().endswith(".json"))
        held = json.loads(spark.read.text(f"{root}/{last}", wholetext=True).first()[0])
        made = cls(spark, held["n"], held["bits"], root, **options)
        made.buckets, made.commits = held["buckets"], int(last[9:17])
        spark.sql(f"create table {made.table} (iv int, rows int, data binary, blk int) using parquet partitioned by (blk) clustered by (iv) sorted by (iv) into {made.buckets} buckets location '{root}/blocks'")
        for number, width in held["blocks"]:
            spark.sql(f"alter table {made.table} add if not exists partition (blk={number})")
            made.blocks[number] = Block(number, width, made.scan([number]).drop("blk"))
            made.made = max(made.made, number)
        return made

    def scan(self, numbers: list[int]) -> DataFrame:
        return self.spark.table(self.table).where(F.col("blk").isin(numbers)).select("iv", "blk", "rows", "data")

    def put(self, frame: DataFrame, width: int) -> Block:
        """Writes one block; frame has PACKED rows."""
        began = time.time()
        self.made += 1
        number = self.made
        rows = frame.select("iv", "rows", "data").withColumn("blk", F.lit(number))
        rows.write.mode("append").partitionBy("blk").bucketBy(self.buckets, "iv").sortBy("iv").option("compression", "uncompressed").option("path", f"{self.root}/blocks").saveAsTable(self.table)
        block = Block(number, width, self.scan([number]).drop("blk"))
        self.blocks[number] = block
        self.commit()
        size = self._files(self._path("blocks")).getContentSummary(self._path(f"blocks/blk={number}")).getLength()
        self.ledger.note("store", "write", written=8 * self.n * width, seconds=time.time() - began, files=size)
        return block

    def put_many(self, blocks: list[Block], small: np.ndarray, widths: list[int]) -> list[Block]:
        """The columns of [blocks] small as blocks of the given widths, from one scan and in one write."""
        began, cuts = time.time(), np.cumsum([0, *widths])
        numbers = list(range(self.made + 1, self.made + 1 + len(widths)))
        self.made += len(widths)

        of = self._turned(blocks, small)

        def run(iv, v, w):
            return _chunks(iv, np.matmul(of.T, v), numbers, cuts.tolist())

        rows = self.swept(blocks, None, run, PACKED + ", blk int")
        rows.write.mode("append").partitionBy("blk").bucketBy(self.buckets, "iv").sortBy("iv").option("compression", "uncompressed").option("path", f"{self.root}/blocks").saveAsTable(self.table)
        made = [Block(k, w, self.scan([k]).drop("blk")) for k, w in zip(numbers, widths)]
        self.blocks |= {b.number: b for b in made}
        self.commit()
        size = sum(self._files(self._path("blocks")).getContentSummary(self._path(f"blocks/blk={k}")).getLength() for k in numbers)
        self.ledger.note("store", "write", written=8 * self.n * sum(widths), seconds=time.time() - began, files=size)
        return made

    def hold(self, frame: DataFrame | None, width: int, array: np.ndarray | None = None) -> Block:
        """A block that is used once: kept in memory, as a shared copy of the array or as a frame dealt like the buckets, if cache_recent; else written."""
        if not self.cache_recent:
            return self.put(frame, width)
        if array is not None:
            return Block(0, width, None, array, self.spark.sparkContext.broadcast(array))
        kept = frame.select("iv", "rows", "data").repartition(self.buckets, "iv").persist(StorageLevel.MEMORY_AND_DISK)
        return Block(0, width, kept)

    def drop(self, blocks: list[Block]) -> None:
        """Forgets blocks, commits that, and deletes their files."""
        for b in blocks:
            if b.shared is not None:
                b.shared.destroy()
                b.array = b.shared = None
            elif not b.number:
                b.frame.unpersist()
            self.blocks.pop(b.number, None)
        gone = [b.number for b in blocks if b.number]
        if gone:
            self.commit()
            self.spark.sql(f"alter table {self.table} drop if exists " + ", ".join(f"partition (blk={k})" for k in gone))
            for k in gone:
                self._files(self._path("blocks")).delete(self._path(f"blocks/blk={k}"), True)

    def close(self) -> None:
        """Deletes the table and all its files."""
        self.spark.sql(f"drop table if exists {self.table}")
        self._files(self._path("")).delete(self._path(""), True)

    def grouped(self, blocks: list[Block], other: Block | None, run, schema: str) -> DataFrame:
        """run(iv, matrices of blocks, matrix of other or None) -> Arrow table, for each interval; matrices are (width, rows). No exchange."""
        order = [b.number for b in blocks]

        def alone(key, table):
            held = _pieces(table)
            return run(key[0].as_py(), [held[k] for k in order], None if last is None else held[last])

        def beside(key, left, right):
            held = _pieces(left)
            return run(key[0].as_py(), [held[k] for k in order], _chunk(right.column("data")[0].as_buffer(), right.column("rows")[0].as_py()))

        last = None if other is None else other.number
        if other is not None and not other.number:
            if not blocks:
                return other.frame.groupBy("iv").applyInArrow(lambda key, t: run(key[0].as_py(), [], _chunk(t.column("data")[0].as_buffer(), t.column("rows")[0].as_py())), schema)
            return self.scan(order).groupBy("iv").cogroup(other.frame.groupBy("iv")).applyInArrow(beside, schema)
        return self.scan(order if last is None else sorted({*order, last})).groupBy("iv").applyInArrow(alone, schema)

    def _turned(self, blocks: list[Block], small: np.ndarray) -> np.ndarray:
        """The rows of small, given in the order of the blocks, in that of their numbers, in which they are scanned."""
        return small[self._places(blocks)]

    @staticmethod
    def _places(blocks: list[Block]) -> np.ndarray:
        begins = np.cumsum([0, *(b.width for b in blocks)])
        order = sorted(range(len(blocks)), key=lambda k: blocks[k].number)
        return np.concatenate([np.zeros(0, np.int64), *(np.arange(begins[k], begins[k + 1]) for k in order)]).astype(np.int64)

    def swept(self, blocks: list[Block], other: Block | None, run, schema: str) -> DataFrame:
        """run(intervals, array (interval, columns of blocks by number, rows), array (interval, rows, columns) of other or None) -> record batch, or, with schema PARTIAL, a matrix of which a task
        emits the sum. Many intervals at once, sorted, without an exchange; a task holds a batch of chunks, and other only where it is stored or an array."""
        numbers = sorted({b.number for b in blocks} | ({other.number} if other is not None and other.number else set()))
        mine, at, seen = {b.number: b.width for b in blocks}, [], 0
        last, found = None, {b.number: b.width for b in [*blocks, *([other] if other is not None else [])]}
        for k in numbers:
            span = np.arange(seen, seen + found[k])
            seen += found[k]
            at.append(span if k in mine else span[:0])
            last = span if other is not None and k == other.number else last
        columns, per, bits = np.concatenate(at) if at else np.zeros(0, np.int64), len(numbers), self.bits
        every, shared = len(columns) == seen, None if other is None else other.shared
        name, summing = f"{self.table}-{shared._jbroadcast.id()}" if shared is not None else "", schema == PARTIAL

        def task(batches):
            total = None
            x = residency.mapped(shared, name) if shared is not None else None
            for table in _whole(batches):
                for iv, v in _stacks(table, per):
                    if x is not None:
                        w = x[(iv[:, None] << bits) + np.arange(v.shape[2])]
                    else:
                        w = None if last is None else v[:, last].transpose(0, 2, 1)
                    made = run(iv, v if every else v[:, columns], w)
                    if not summing:
                        yield made
                    else:
                        total = made if total is None else total + made
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([total.shape[1]], pa.int32()), pa.array([total.ravel()], pa.list_(pa.float64()))], ["width", "v"])

        # The window sorts, and as it needs an interval's chunks in one task, the scan stays one of buckets.
        place = F.row_number().over(Window.partitionBy("iv").orderBy("blk"))
        return self.scan(numbers).select("iv", "blk", "rows", "data", place.alias("place")).mapInArrow(task, schema)

    def _sweeps(self, blocks: list[Block], other: Block | None) -> bool:
        """A frame that is held meets the blocks in a join of groups; all else is swept."""
        return other is None or other.number > 0 or other.array is not None and len(blocks) > 0

    def summed(self, partials: DataFrame) -> np.ndarray:
        """Second phase of products with a small result: a task adds its intervals' partial matrices. A matrix for each bucket reaches the driver, or, of more than GATHERED buckets, one that the
        cluster has added up."""

        def run(batches):
            total, width = None, 0
            for batch in batches:
                if batch.num_rows:
                    made = batch.column(1).flatten().to_numpy().reshape(batch.num_rows, -1).sum(axis=0)
                    total, width = made if total is None else total + made, batch.column(0)[0].as_py()
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([width], pa.int32()), pa.array([total], pa.list_(pa.float64()))], ["width", "v"])

        added = partials.mapInArrow(run, PARTIAL)
        if self.buckets <= GATHERED:
            parts = added.toArrow()
            return np.sum([v.values.to_numpy() for v in parts.column("v")], axis=0).reshape(-1, parts.column("width")[0].as_py())
        rows = added.select("width", F.posexplode("v").alias("at", "v")).groupBy("width", "at").agg(F.sum("v").alias("v")).toArrow()
        values = np.zeros(rows.num_rows)
        values[rows.column("at").to_numpy()] = rows.column("v").to_numpy()
        return values.reshape(-1, rows.column("width")[0].as_py())

    def gram_plan(self, blocks: list[Block], other: Block) -> DataFrame:
        if self._sweeps(blocks, other):
            return self.swept(blocks, other, lambda iv, v, w: np.vstack([np.matmul(v, w).sum(axis=0), np.matmul(w.transpose(0, 2, 1), w).sum(axis=0)]), PARTIAL)
        return self.grouped(blocks, other, lambda iv, held, w: _partial(np.vstack([v @ w.T for v in [*held, w]])), PARTIAL)

    def _parts(self, made: np.ndarray, blocks: list[Block], other: Block) -> tuple[np.ndarray, np.ndarray]:
        upper = made[: -other.width]
        if self._sweeps(blocks, other):
            upper = upper[np.argsort(self._places(blocks))]
        return upper, made[-other.width :]

    def gram(self, blocks: list[Block], other: Block) -> tuple[np.ndarray, np.ndarray]:
        """([blocks]' other, other' other) in one scan."""
        if not blocks and other.array is not None:
            return np.zeros((0, other.width)), other.array.T @ other.array
        return self._parts(self.summed(self.gram_plan(blocks, other)), blocks, other)

    def second_gram(self, blocks: list[Block], other: Block, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for other - [blocks] h, which is made chunk by chunk and stored nowhere."""
        of = self._turned(blocks, h)

        def many(iv, v, w):
            rest = w - np.matmul(v.transpose(0, 2, 1), of)
            return np.vstack([np.matmul(v, rest).sum(axis=0), np.matmul(rest.transpose(0, 2, 1), rest).sum(axis=0)])

        def run(iv, held, w):
            rest, at = w.copy(), 0
            for v in held:
                rest -= h[at : at + len(v)].T @ v
                at += len(v)
            return _partial(np.vstack([v @ rest.T for v in [*held, rest]]))

        plan = self.swept(blocks, other, many, PARTIAL) if self._sweeps(blocks, other) else self.grouped(blocks, other, run, PARTIAL)
        return self._parts(self.summed(plan), blocks, other)

    def combine_plan(self, blocks: list[Block], small: np.ndarray, other: Block | None = None, by: np.ndarray | None = None) -> DataFrame:
        """[blocks] small + other by, as PACKED rows."""
        of = self._turned(blocks, small)

        def many(iv, v, w):
            made = np.matmul(of.T, v)
            return _chunks(iv, made if w is None else made + np.matmul(by.T, w.transpose(0, 2, 1)))

        def run(iv, held, w):
            out, at = (np.zeros((small.shape[1], held[0].shape[1])) if w is None else by.T @ w), 0
            for v in held:
                out += small[at : at + len(v)].T @ v
                at += len(v)
            return _packed(iv, out.T)

        return self.swept(blocks, other, many, PACKED) if self._sweeps(blocks, other) else self.grouped(blocks, other, run, PACKED)
