"""Restarted block Krylov solvers for a few eigenvalues or singular values.

The loop keeps A V = V T + F C with F the newest block: each step multiplies F, projects the product against all of V (twice, against rounding), and
normalises the rest to the next F. A full subspace is compressed to the wanted invariant part of T, an orthonormal basis Q of it giving
V <- V Q, T <- Q' T Q, C <- C Q. Everything tall sits behind a backend; only T, C and Gram matrices reach the driver.
"""

from __future__ import annotations

import os
import time
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenloom.functions import codec
from eigenloom.sources.stores import shared_dir

from . import dense, spmm, tiles
from .subspace import Block, Ledger, Subspace


#: Bytes of a basis in memory up to which its blocks are also kept side by side, so that a product with all of them is one call of the library.
JOINED_BYTES = 256 << 20


class MemoryBackend:
    """Tall blocks are NumPy arrays: the in-memory variant, and the exact comparison for small orders."""

    def __init__(self, apply, n: int, cells: int = 0):
        self.product, self.n, self.cells, self.ledger, self.held = apply, n, cells, Ledger(), []
        self.side = None

    def joined(self, blocks):
        """The blocks' columns as rows of one array, to which blocks that follow are appended; None where they would be more than JOINED_BYTES."""
        width = sum(b.shape[1] for b in blocks)
        if not blocks or 8 * self.n * width > JOINED_BYTES:
            return None
        known = len(self.held)
        if known > len(blocks) or any(a is not b for a, b in zip(self.held, blocks)):
            known, self.held = 0, []
        if self.side is None or len(self.side) < width:
            known, self.held, self.side = 0, [], np.empty((min(2 * width, JOINED_BYTES // (8 * self.n)), self.n))
        at = sum(b.shape[1] for b in self.held)
        for b in blocks[known:]:
            self.side[at : at + b.shape[1]] = b.T
            at += b.shape[1]
            self.held.append(b)
        return self.side[:width]

    def random(self, width, seed):
        return np.asfortranarray(np.random.default_rng(seed).standard_normal((self.n, width)))

    def apply(self, x):
        return self.product(x)

    def gram(self, blocks, w):
        if len(blocks) > 1 and (v := self.joined(blocks)) is not None:
            return v @ w
        return np.vstack([b.T @ w for b in blocks]) if blocks else np.zeros((0, w.shape[1]))

    def combine(self, alpha, blocks, small, beta=0.0, other=None):
        if len(blocks) > 1 and (v := self.joined(blocks)) is not None:
            made = ((alpha * small).T @ v).T
            return made if other is None else np.add(made, beta * other, out=made)
        made, at = (np.zeros((self.n, small.shape[1])) if other is None else beta * other), 0
        for b in blocks:  # one after another, so that no copy of all of them is made
            made += b @ (alpha * small[at : at + b.shape[1]])
            at += b.shape[1]
        return made

    def keep(self, w):
        return w

    def drop(self, blocks):
        pass

    def array(self, w):
        return w


class FrameBackend:
    """Tall blocks are persisted chunk frames, dealt alike so that their joins need no exchange; a written copy only cuts their lineage. product(frame, width) -> frame is any multiply of `spmm`."""

    def __init__(self, spark: SparkSession, product, n: int, bits: int = 12, group: int | None = None):
        self.spark, self.product, self.n, self.bits, self.group, self.ledger = spark, product, n, bits, group, Ledger()
        self.root, self.parts = f"{shared_dir(spark)}/frames-{uuid.uuid4().hex}", max(1, min(spark.sparkContext.defaultParallelism, ((n - 1) >> bits) + 1))

    def _kept(self, frame, width):
        path = f"{self.root}/{uuid.uuid4().hex}"
        dense.packed(frame).write.parquet(path)
        held = dense.dealt(self.spark.read.schema("iv int, rows int, data binary").parquet(path), self.parts)
        held.columns_held = width
        return held

    def random(self, width, seed):
        return self._kept(dense.random(self.spark, self.n, width, seed, self.bits), width)

    def apply(self, x):
        w = dense._widths([x])[0]
        return self._kept(self.product(x, w), w)

    def gram(self, blocks, w):
        return dense.gram(1.0, blocks, w, self.group) if blocks else np.zeros((0, dense._widths([w])[0]))

    def combine(self, alpha, blocks, small, beta=0.0, other=None):
        return self._kept(dense.combine(alpha, blocks, small, beta, other, self.group), small.shape[1])

    def keep(self, w):
        return w

    def drop(self, blocks):
        for b in blocks:
            b.unpersist()

    def array(self, w):
        return dense.to_array(w)

    def columns(self, blocks):
        return sum(dense._widths(blocks))


class Pending:
    """A product less its parts along a basis, not yet made: rest = w - [blocks] h, with its Gram matrix."""

    def __init__(self, blocks: list[Block], w: Block, h: np.ndarray, gram: np.ndarray):
        self.blocks, self.w, self.h, self.gram, self.width = blocks, w, h, gram, w.width


class StoreBackend:
    """Tall blocks are in a bucketed `Subspace`: the external variant. A step scans the subspace three times and writes one block: the first scan gives V'w, the second V' and the Gram
    matrix of w - V h without storing it, the third writes the normalised rest. The product w itself stays in memory, or, without cache_recent, in files until then. A resident multiply has the
    newest block on the driver; its product is then an array too, and of a symmetric operator V'w is known but for the newest block's own part, so that the first scan is left out."""

    def __init__(self, spark: SparkSession, product, n: int, bits: int, matrix_bytes: int = 0, cache_recent: bool = True, width: int = 4, root: str | None = None):
        self.product, self.n, self.matrix_bytes, self.ledger = product, n, matrix_bytes, Ledger()
        self.store = Subspace(spark, n, bits, root, cache_recent, self.ledger, width)
        self.bits, self.peak_bytes, self.clock, self.newest = bits, 0, False, None
        self.held_before = sum(i.memSize() + i.diskSize() for i in spark.sparkContext._jsc.sc().getRDDStorageInfo())

    def _bytes(self, *widths) -> int:
        return 8 * self.n * sum(widths)

    def _size(self, block: Block) -> int:
        """Bytes that a scan of the block reads from files."""
        return self._bytes(block.width) if block.number else 0

    def random(self, width, seed):
        return self.store.put(dense.packed(dense.random(self.store.spark, self.n, width, seed, self.bits)), width)

    def apply(self, x):
        x = self._made(x)
        self.ledger.note("multiply", "spmm", read=self.matrix_bytes + self._size(x))
        if getattr(self.product, "gathers", False) and self.store.cache_recent:
            self.newest = dense.to_array(x.frame)
            return self.store.hold(None, x.width, dense.to_array(self.product(self.newest, x.width)))
        held = self.store.hold(dense.packed(self.product(x.frame, x.width)), x.width)
        if self.clock and not held.number:
            held.frame.count()  # so that the multiply's time is not counted with the first scan's
        return held

    def project(self, blocks, w, passes=2, known=None):
        """known: [all blocks but the newest]' w, where the operator's symmetry gives it; what rounding or a block set aside adds to it is found by the second scan."""
        if known is not None and w.array is not None:
            h = np.vstack([known, self.newest.T @ w.array])
        else:
            h, _g = self.store.gram(blocks, w)
            self.ledger.note("reorthogonalise", "gram", read=self._bytes(*(b.width for b in blocks)) + self._size(w))
        if not w.number:  # what is held beside the files while the subspace is read: the product and the resident block
            context = self.store.spark.sparkContext._jsc.sc()
            kept = sum(i.memSize() + i.diskSize() for i in context.getRDDStorageInfo()) - self.held_before
            self.peak_bytes = max(self.peak_bytes, int(kept) + self._bytes(w.width) + (0 if w.array is None else 2 * w.array.nbytes))
        while True:
            more, g = self.store.second_gram(blocks, w, h)
            self.ledger.note("reorthogonalise", "second gram", read=self._bytes(*(b.width for b in blocks)) + self._size(w))
            h, wrong = h + more, np.abs(more).max() > 0.01 * np.abs(h).max()
            if known is None or not wrong:
                return Pending(list(blocks), w, h, g - more.T @ more), h
            known = None

    def _made(self, w):
        if not isinstance(w, Pending):
            return w
        return self.combine(1.0, [w], np.eye(w.width))

    def gram(self, blocks, w):
        if len(blocks) == 1 and blocks[0] is w:
            return w.gram if isinstance(w, Pending) else self.store.gram([], w)[1]
        made, w = [self._made(b) for b in blocks], self._made(w)
        self.ledger.note("reorthogonalise", "gram", read=self._bytes(*(b.width for b in made)) + self._size(w))
        return self.store.gram(made, w)[0]

    def combine(self, alpha, blocks, small, beta=0.0, other=None):
        if len(blocks) == 1 and isinstance(blocks[0], Pending):
            p = blocks[0]
            if p.w is None:
                raise ValueError("a pending block is made once")
            self.ledger.note("reorthogonalise", "combine", read=self._bytes(*(b.width for b in p.blocks)) + self._size(p.w))
            out = self.store.put(self.store.combine_plan(p.blocks, -alpha * p.h @ small, p.w, alpha * small), small.shape[1])
            self.release(p)
            return out
        made = [self._made(b) for b in blocks]
        self.ledger.note("reorthogonalise", "combine", read=self._bytes(*(b.width for b in made)) + (self._size(other) if other is not None else 0))
        return self.store.put(self.store.combine_plan(made, alpha * small, other, None if other is None else beta * np.eye(small.shape[1])), small.shape[1])

    def compress(self, blocks, q, b):
        """Blocks of [blocks] q, all from one scan."""
        self.ledger.note("restart", "combine", read=self._bytes(*(x.width for x in blocks)))
        return self.store.put_many(blocks, q, [min(b, q.shape[1] - s) for s in range(0, q.shape[1], b)])

    def release(self, w):
        if isinstance(w, Pending) and w.w is not None:
            self.store.drop([w.w])
            w.w = None

    def keep(self, w):
        return self._made(w)

    def drop(self, blocks):
        self.store.drop(blocks)

    def sweep(self, keep):
        """Drops all blocks but these."""
        kept = {b.number for b in keep if isinstance(b, Block)}
        self.store.drop([b for k, b in list(self.store.blocks.items()) if k not in kept])

    def array(self, w):
        return dense.to_array(self._made(w).frame)

    def columns(self, blocks):
        return sum(b.width for b in blocks)


def relational_product(edges: DataFrame, n: int, bits: int):
    """Multiply of a chunk frame by joins and sums alone."""
    return lambda x, width: dense.from_rows(spmm.relational(edges, dense.to_rows(dense.unpacked(x), bits), width), bits, n, width)


class resident_product:
    """Semi-external multiply by stored tiles: the matrix streams, the newest block is resident; the last multiply's broadcast leaves the executors at the next (a lost
    part of its product can still be made again). gathers: the newest block is an array on the driver."""

    def __init__(self, store, **switches):
        self.store, self.switches, self.last, self.gathers = store, switches, None, True

    def __call__(self, x, width):
        if self.last is not None:
            self.last.unpersist()
        made = spmm.semi_external(self.store, x if isinstance(x, np.ndarray) else dense.to_array(x), **self.switches)
        self.last = made.resident
        return made


class chained:
    """The second multiply of the first one's product."""

    def __init__(self, first, second):
        self.first, self.second, self.gathers = first, second, getattr(first, "gathers", False)

    def __call__(self, x, width):
        return self.second(self.first(x, width), width)


def striped_product(store, n_cols: int, bits: int, splits: int = 1):
    """Multiply for blocks beyond the resident budget: chunks of the block are cut to tile columns and meet the tiles there."""
    edge = store.edge

    def product(x, width):
        columns = dense.from_rows(dense.to_rows(dense.unpacked(x), bits), edge.bit_length() - 1, n_cols, width)
        return dense.from_rows(spmm.striped(store.frame.filter("tr >= 0"), columns, edge, width, splits), store.bits, store.n_rows, width)

    return product


def array_product(edges: DataFrame, n_rows: int, n_cols: int, most: int = 20_000_000, packed: str | None = None):
    """Compressed rows on the driver for orders that fit; refuses more than `most` cells. packed: the side, 'i' or 'j', whose empty rows or columns are left out."""
    cells = edges.select("i", "j", "w").limit(most + 1).toArrow()
    if cells.num_rows > most:
        raise ValueError("too many cells for the in-memory variant")
    i, j, w = (cells.column(c).to_numpy() for c in ("i", "j", "w"))
    if packed == "i":
        kinds, i = np.unique(i, return_inverse=True)
        n_rows = len(kinds)
    if packed == "j":
        kinds, j = np.unique(j, return_inverse=True)
        n_cols = len(kinds)
    order = np.lexsort((j, i))
    i, j, w = i[order], j[order], w[order]
    first = np.flatnonzero((np.diff(i, prepend=-1) != 0) | (np.diff(j, prepend=-1) != 0))
    if len(first) < len(i):  # edges that repeat are added
        i, j, w = i[first], j[first], np.add.reduceat(w, first)
    starts = np.flatnonzero(np.diff(i, prepend=-1))
    by_col = np.argsort(j, kind="stable")
    col_starts = np.flatnonzero(np.diff(j[by_col], prepend=-1))

    ones = bool((w == 1).all())
    rows, cols, turned = i[starts], j[by_col[col_starts]], i[by_col]
    w_turned = None if ones else w[by_col]
    pool = ThreadPoolExecutor(os.cpu_count())

    def product(x, size, places, at, begins, weights):
        """Column by column, each in a thread: the library's loops release the interpreter."""
        out = np.zeros((x.shape[1], size))

        def column(c):
            seen = np.ascontiguousarray(x[:, c]).take(at)
            out[c, places] = np.add.reduceat(seen if ones else np.multiply(seen, weights, out=seen), begins)

        if len(at):
            list(pool.map(column, range(x.shape[1])))
        return out.T

    def forward(x):
        return product(np.asarray(x, float), n_rows, rows, j, starts, w)

    def backward(x):
        return product(np.asarray(x, float), n_cols, cols, turned, col_starts, w_turned)

    return forward, backward, len(i)


class SpreadProduct:
    """A and A' times blocks on the driver, of a matrix with too many cells for it: cells lie in the store's parts, sorted once by row and once by column, and both products of a part are made in one
    task. A task sends the rows that it has a sum for, so the driver gets at most as many blocks as there are tasks, of which there are no more than cores."""

    def __init__(self, store):
        spark, self.n_rows, self.n_cols, self.cells = store.spark, store.n_rows, store.n_cols, store.cells
        edge, self.tasks = store.edge, spark.sparkContext.defaultParallelism

        def sides(table):
            rows = [r for r in zip(*(table.column(c).to_pylist() for c in ("tr", "tc", "n_single", "code", "vals"))) if r[0] >= 0]
            found = []
            for run in tiles.grouped(rows):
                tr, tc, single, code, vals = zip(*run)
                place, r, c, w = codec.decode_many(code, vals, single)
                found.append((np.array(tr, np.int64)[place] * edge + r, np.array(tc, np.int64)[place] * edge + c, w))
            made = []
            if found:
                i, j, w = map(np.concatenate, zip(*found))
                kind = next(k for k in ("u1", "<f4", "<f8") if k == "<f8" or _same(w, k))
                order = np.argsort(i, kind="stable")
                i, j, w = i[order], j[order], w[order].astype(kind)
                starts = np.flatnonzero(np.diff(i, prepend=-1))
                local, turn = np.repeat(np.arange(len(starts)), np.diff(starts, append=len(i))), np.argsort(j, kind="stable")
                col_starts = np.flatnonzero(np.diff(j[turn], prepend=-1))
                made = [x.tobytes() for x in (i[starts], starts, j.astype("<i4"), w, j[turn][col_starts], col_starts, local[turn].astype("<i4"), w[turn])] + [kind]
            return pa.table([pa.array([x] if made else [], t) for x, t in zip(made or [None] * 9, [pa.binary()] * 8 + [pa.string()])], names=[*SpreadProduct.PARTS, "kind"])

        path = f"{shared_dir(spark)}/spread-{uuid.uuid4().hex}"
        schema = ", ".join(f"{c} binary" for c in self.PARTS) + ", kind string"
        store.frame.groupBy("part").applyInArrow(sides, schema).repartition(self.tasks).write.option("compression", "uncompressed").parquet(path)
        self.spark, self.frame = spark, spark.read.schema(schema).parquet(path).coalesce(self.tasks)

    #: Rows that have cells, their begins, columns and weights by row; columns that have cells, their begins, places of rows and weights by column.
    PARTS = ("rows", "starts", "j", "w", "cols", "col_starts", "at", "turned")

    def _run(self, x: np.ndarray, forward: bool, backward: bool) -> np.ndarray:
        held, size, width = self.spark.sparkContext.broadcast(np.ascontiguousarray(x.T)), self.n_cols if backward else self.n_rows, x.shape[1]

        def sums(x, at, starts, w):
            return np.stack([np.add.reduceat(column.take(at) * w, starts) for column in x])

        def run(batches):
            out, seen = np.zeros((width, size)), np.zeros(size, bool)
            for batch in batches:
                for row in zip(*(batch.column(k) for k in range(9))):
                    kind = row[8].as_py()
                    rows, starts, j, w, cols, col_starts, at, turned = (np.frombuffer(v.as_buffer(), t) for v, t in zip(row, ("<i8", "<i8", "<i4", kind, "<i8", "<i8", "<i4", kind)))
                    made = sums(held.value, j, starts, w) if forward else held.value[:, rows]
                    if backward:
                        made, rows = sums(made, at, col_starts, turned), cols
                    out[:, rows] += made
                    seen[rows] = True
            some = np.flatnonzero(seen)
            if len(some):
                yield pa.RecordBatch.from_arrays([pa.array([some.tobytes()], pa.binary()), pa.array([np.ascontiguousarray(out[:, some]).tobytes()], pa.binary())], ["at", "data"])

        out = np.zeros((size, width))
        for at, data in zip(*self.frame.mapInArrow(run, "at binary, data binary").toArrow().columns):
            at = np.frombuffer(at.as_buffer(), "<i8")
            out[at] += np.frombuffer(data.as_buffer(), "<f8").reshape(width, -1).T
        held.destroy()
        return out

    def there(self, x):
        return self._run(x, True, False)

    def back(self, x):
        return self._run(x, False, True)

    def both(self, x):
        """A'(A x)."""
        return self._run(x, True, True)


def _same(w: np.ndarray, kind: str) -> bool:
    with np.errstate(invalid="ignore", over="ignore"):
        return bool((w.astype(kind) == w).all())


def cubed_trace(edges: DataFrame) -> DataFrame:
    """(trace) of A^3, the sum of the cubed eigenvalues, of a symmetric 0/1 edge frame without loops. Each edge is led from its end of smaller degree to the other, so that a hub leads few, and a
    triangle, which the trace counts six times, is met once."""
    degree = edges.groupBy("i").agg(F.count(F.lit(1)).alias("d"))
    both = edges.select("i", "j").join(degree, "i").join(degree.select(F.col("i").alias("j"), F.col("d").alias("e")), "j")
    led = both.filter((F.col("d") < F.col("e")) | (F.col("d") == F.col("e")) & (F.col("i") < F.col("j"))).select("i", "j").persist()
    wedges = led.join(led.select("i", F.col("j").alias("k")), "i").filter("j <> k").select("j", "k")
    return wedges.join(led.select(F.col("i").alias("j"), F.col("j").alias("k")), ["j", "k"]).agg((6 * F.count(F.lit(1))).alias("trace"))


def refined(a: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Rayleigh quotients of a symmetric array in extended precision: their error is the square of the vectors'."""
    a, x = a.astype(np.longdouble), vectors.astype(np.longdouble)
    return (x * (a @ x)).sum(axis=0) / (x * x).sum(axis=0)


@dataclass
class Result:
    values: np.ndarray
    residuals: np.ndarray
    converged: np.ndarray
    vectors: object = None
    expansions: int = 0
    restarts: int = 0
    products: int = 0
    orthogonality: float = 0.0
    locked: int = 0
    left: object = None
    forward: object = None
    backward: object = None
    cells: int = 0
    steps: list = field(default_factory=list)
    ledger: Ledger = field(default_factory=Ledger)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(k, float(v), float(r), bool(c)) for k, (v, r, c) in enumerate(zip(np.real(self.values), self.residuals, self.converged))]
        return spark.createDataFrame(rows, "rank int, value double, residual double, converged boolean")


#: Order of wanted values.
WHICH = {
    "LM": lambda t: np.lexsort((-np.real(t), -np.round(np.abs(t), 10))),
    "SM": lambda t: np.argsort(np.abs(t), kind="stable"),
    "LA": lambda t: np.argsort(-np.real(t), kind="stable"),
    "SA": lambda t: np.argsort(np.real(t), kind="stable"),
    "LR": lambda t: np.argsort(-np.real(t), kind="stable"),
    "SR": lambda t: np.argsort(np.real(t), kind="stable"),
    "LI": lambda t: np.argsort(-np.abs(np.imag(t)), kind="stable"),
}


def preset(k: int, profile: str = "external") -> tuple[int, int]:
    """(block width, number of blocks)."""
    if profile == "baseline" or profile == "external" and k <= 16:
        return 1, 2 * k
    if profile == "clustered":
        return (1, 8 * k) if k <= 16 else (4, 4 * k)
    if profile == "web":
        return 2, 2 * k
    return 4, k


def project_out(backend, blocks: list, w, passes: int = 2, known: np.ndarray | None = None):
    """(w without its parts along the blocks, coefficients). known: the coefficients of all blocks but the last, which a backend may take instead of a scan."""
    if hasattr(backend, "project"):
        return backend.project(blocks, w, passes, known)
    total = None
    for _ in range(passes):
        h = backend.gram(blocks, w)
        w = backend.combine(-1.0, blocks, h, 1.0, w)
        total = h if total is None else total + h
    return w, total


def normalise(backend, w, seed: int, blocks: list, floor: float, method: str = "svqb"):
    """(orthonormal w, R, number of replaced columns) with old w = new w R; columns without a direction of their own are replaced by random ones (their part of R is 0)."""
    g = backend.gram([w], w)
    size = len(g)
    values, vectors = np.linalg.eigh((g + g.T) / 2)
    good = values > max(floor * floor, 1e-26 * max(values[-1], 0))
    if not good.any() and backend.n < _columns(backend, blocks) + size:
        return None, np.zeros((0, size)), size
    if method == "cholesky" and good.all() and values[0] > 1e-8 * values[-1]:
        r = np.linalg.cholesky((g + g.T) / 2).T
        out = backend.combine(1.0, [w], np.linalg.inv(r))
    else:
        inverse = np.where(good, 1 / np.sqrt(np.where(good, values, 1)), 0)
        out = backend.combine(1.0, [w], vectors * inverse)
        r = (vectors * np.where(good, np.sqrt(np.abs(values)), 0)).T
    missing = int((~good).sum())
    if missing and backend.n < _columns(backend, blocks) + size:
        # fewer directions are left than the block has columns: go on with a narrower block
        return backend.combine(1.0, [out], np.eye(size)[:, good]), r[good], missing
    if missing:
        fresh = backend.combine(1.0, [backend.random(size, seed)], np.diag((~good).astype(float)), 1.0, out)
        for _ in range(2):
            fresh = project_out(backend, blocks, fresh, 1)[0] if blocks else fresh
            turned = backend.gram([fresh], fresh)
            fresh = backend.combine(1.0, [fresh], np.linalg.inv(np.linalg.cholesky((turned + turned.T) / 2).T))
        return fresh, backend.gram([fresh], out) @ r, missing
    if size == 1 or values[0] > 1e-4 * values[-1]:
        return out, r, 0
    second = backend.gram([out], out)  # a second pass of the same kind takes out rounding
    c = np.linalg.cholesky((second + second.T) / 2).T
    return backend.combine(1.0, [out], np.linalg.inv(c)), c @ r, 0


#: A solve from files ends within a sweep once its residuals are within this share of the tolerance.
EARLY = 0.01


def _settled(t: np.ndarray, coupling: np.ndarray, k: int, which: str, tol: float, symmetric: bool) -> bool:
    values, vectors = projected(t, None, symmetric)
    order = WHICH[which](values)[:k]
    scale = np.finfo(float).eps ** (2 / 3) * max(np.abs(values).max(), 1e-300)
    return bool((np.linalg.norm(coupling @ vectors[:, order], axis=0) <= tol * np.maximum(np.abs(values[order]), scale)).all())


def _columns(backend, blocks) -> int:
    return backend.columns(blocks) if hasattr(backend, "columns") else sum(b.shape[1] for b in blocks)


def projected(t: np.ndarray, gram: np.ndarray | None = None, symmetric: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Values and vectors of the projected problem T y = theta G y; G = V'V is given when the basis has lost orthogonality, and is reduced by its Cholesky factor."""
    if gram is not None:
        inverse = np.linalg.inv(np.linalg.cholesky((gram + gram.T) / 2))
        values, vectors = projected(inverse @ t @ inverse.T, None, symmetric)
        return values, inverse.T @ vectors
    return np.linalg.eigh((t + t.T) / 2) if symmetric else np.linalg.eig(t)


def krylov_schur(backend, k: int, b: int = 1, blocks: int | None = None, which: str = "LM", tol: float = 1e-8, max_restarts: int = 200, symmetric: bool = True, passes: int = 2, seed: int = 7, want_vectors: bool = False, lock: bool = True) -> Result:
    """k wanted eigenvalues of the backend's operator with blocks of width b and at most `blocks` blocks. lock: at a restart, converged wanted vectors are uncoupled from the rest, so
    later steps change them no more; unwanted directions of the tail are dropped."""
    n = backend.n
    if k < 1 or n < 1:
        raise ValueError("k and the order must be at least 1")
    k, b = min(k, n), min(b, n)
    limit = min(n, b * (blocks or max(2 * k // b, 2) + 2))
    limit = min(n, max(limit, k + 2 * b))
    limit = n if n - limit < b else limit
    began = {}

    def timed(phase, f, *args, **kw):
        t = time.time()
        out = f(*args, **kw)
        began[phase] = began.get(phase, 0.0) + time.time() - t
        return out

    result = Result(np.array([]), np.array([]), np.array([]), ledger=backend.ledger)
    basis: list = []
    size = 0
    t = np.zeros((0, 0))
    coupling = np.zeros((b, 0))
    front, _r, _m = normalise(backend, backend.random(b, seed), seed + 1, [], 0.0)
    full = False  # no direction is left outside the subspace
    for restart in range(max_restarts + 1):
        while not full and size + (wide := len(coupling)) <= limit:
            front = backend.keep(front)
            basis.append(front)
            result.steps.append(("expand", size + wide, wide))
            w = timed("multiply", backend.apply, front)
            result.products += wide
            result.expansions += 1
            w, h = timed("reorthogonalise", project_out, backend, basis, w, passes, coupling.T if symmetric else None)
            grown = np.zeros((size + wide, size + wide))
            grown[:size, :size], grown[size:, :size] = t, coupling
            grown[:, size:] = h
            if symmetric:
                grown[size:, :] = h.T
                grown[size:, size:] = (h[size:] + h[size:].T) / 2
            t, size = grown, size + wide
            if size >= n:
                full, coupling = True, np.zeros((1, size))
                break
            front, r, _missing = timed("reorthogonalise", normalise, backend, w, seed + 1000 + result.expansions, basis, 1e-12 * max(1e-300, np.abs(t).max()))
            full = front is None
            coupling = np.hstack([np.zeros((len(r), size - wide)), r]) if not full else np.zeros((1, size))
            if hasattr(backend, "project") and size >= k and not full and _settled(t, coupling, k, which, EARLY * tol, symmetric):
                break
        values, vectors = projected(t, None, symmetric)
        order = WHICH[which](values)
        values, vectors = values[order], vectors[:, order]
        residuals = np.linalg.norm(coupling @ vectors, axis=0)
        scale = max(np.abs(values).max(), 1e-300)
        done = residuals[:k] <= tol * np.maximum(np.abs(values[:k]), np.finfo(float).eps ** (2 / 3) * scale)
        if done.all() or restart == max_restarts or full:
            break
        # half of what is not wanted is kept too: a clustered edge of the spectrum then takes about half as many steps as with k more
        kept = max(min(size - b, k + max(b, (size - k) // 2)), min(k, size - 1))
        if symmetric:
            q = vectors[:, :kept]
        else:
            chosen = vectors[:, :kept]
            if np.iscomplexobj(chosen) and abs(values[kept - 1].imag) > 0 and not np.isclose(values[kept - 2], values[kept - 1].conj()):
                chosen = vectors[:, : kept + 1]
            u, s, _v = np.linalg.svd(np.hstack([chosen.real, chosen.imag]), full_matrices=False)
            q = u[:, s > 1e-10 * s[0]]
        result.steps.append(("restart", size, q.shape[1]))
        if hasattr(backend, "compress"):
            front, basis = backend.keep(front), timed("restart", backend.compress, basis, q, b)
            backend.sweep([*basis, front])
        else:
            old, basis = basis, [timed("reorthogonalise", backend.combine, 1.0, basis, q[:, s : s + b]) for s in range(0, q.shape[1], b)]
            backend.drop(old)
        t, coupling, size = q.T @ t @ q, coupling @ q, q.shape[1]
        if lock and symmetric:
            fixed = np.flatnonzero(done)
            coupling[:, fixed] = 0.0
            result.locked = len(fixed)
        result.restarts += 1
    result.values, result.residuals, result.converged = values[:k], residuals[:k], done
    if want_vectors:
        result.vectors = backend.combine(1.0, basis, np.real(vectors[:, :k]))
        g = backend.gram([result.vectors], result.vectors)
        result.orthogonality = float(np.abs(g - np.eye(len(g))).max())
    if hasattr(backend, "sweep"):
        backend.release(w)
        backend.sweep([*basis, result.vectors])
    for phase, seconds in began.items():
        backend.ledger.note(phase, "time", seconds=seconds)
    return result


#: Matrices of more cells are solved from stored tiles and files; fewer are gathered to the driver when storage is 'auto'.
ARRAY_CELLS = 20_000_000


def _place(edges: DataFrame, storage: str) -> str:
    if storage != "auto":
        return storage
    return "arrays" if edges.limit(ARRAY_CELLS + 1).count() <= ARRAY_CELLS else "external"


def folded(edges: DataFrame, by: str) -> tuple[DataFrame, int]:
    """(edges, cells) of a matrix B with B B' = A A' where `by` is 'j', or B'B = A'A where it is 'i': columns (rows) whose only cells lie in the same row (column) are one, with the root of the sum
    of their squares, so a matrix mostly of such columns shrinks to its shorter side. Other matrices come back as they are."""
    other = "i" if by == "j" else "j"
    lines = edges.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.min(other).alias("at"), F.sum(F.col("w") * F.col("w")).alias("q")).persist()
    cells, single, last = lines.agg(F.sum("n"), F.sum((F.col("n") == 1).cast("long")), F.max(by)).first()
    if not cells or 2 * single < cells:
        lines.unpersist()
        return edges, cells or 0
    alone = lines.filter("n = 1").groupBy("at").agg(F.sqrt(F.sum("q")).alias("w"))
    made = alone.select(F.col("at").alias(other), (F.col("at") + last + 1).alias(by), "w").select("i", "j", "w")
    if single < cells:
        made = made.unionByName(edges.join(lines.filter("n > 1").select(by), by, "left_semi").select("i", "j", "w"))
    made = made.persist()
    cells = made.count()
    lines.unpersist()
    return made, cells


def _limit(n: int, k: int, options: dict) -> int:
    b = options.get("b", 1)
    return min(n, max(b * ((options.get("blocks") or max(2 * k // b, 2)) + 2), k + 2 * b))


def _product(spark, edges, n_rows, n_cols, b, bits, kernel, edge, switches):
    """(multiply, bytes of the matrix that it reads) by the planner's choice, or by the one asked for."""
    if kernel == "relational":
        held = edges.persist()
        return relational_product(held, n_rows, bits), 16 * held.count()
    store = tiles.TileStore(edges, n_rows, n_cols, bits, edge, b)
    chosen = spmm.choose(n_cols, b, store.cells) if kernel == "auto" else kernel
    return (resident_product(store, **switches) if chosen == "resident" else striped_product(store, n_cols, bits)), store.bytes


def eigen(spark: SparkSession, edges: DataFrame, n: int, k: int, storage: str = "auto", edge: int | None = None, kernel: str = "auto", cache_recent: bool = True, bits: int | None = None, switches: dict | None = None, **options) -> Result:
    """Eigenvalues of a square edge frame.

    storage: 'arrays' (in-memory variant on the driver), 'memory' (persisted chunk frames), 'external' (bucketed files), or 'auto': arrays up to ARRAY_CELLS cells, files beyond.
    kernel: 'resident', 'striped', 'relational', or 'auto' by the size of a block.
    """
    storage = _place(edges, storage)
    if storage == "arrays":
        forward, _b, cells = array_product(edges, n, n)
        return krylov_schur(MemoryBackend(forward, n, cells), k, **options)
    bits = bits or dense.interval_bits(_limit(n, k, options), 64 << 20, edge or 256)
    product, size = _product(spark, edges, n, n, options.get("b", 1), bits, kernel, edge, switches or {})
    if storage == "memory":
        return krylov_schur(FrameBackend(spark, product, n, bits), k, **options)
    backend = StoreBackend(spark, product, n, bits, size, cache_recent, options.get("b", 1))
    found = krylov_schur(backend, k, **options)
    found.backend = backend
    return found


def singular(spark: SparkSession, edges: DataFrame, n_rows: int, n_cols: int, k: int, via: str = "normal", storage: str = "auto", edge: int | None = None, kernel: str = "auto", cache_recent: bool = True, bits: int | None = None, **options) -> Result:
    """Singular values, and with want_vectors both sides' vectors (`left`, `vectors`).

    storage: as for `eigen`, or 'spread': cells in files, dealt to tasks that make both products at once, and the blocks of the shorter side in arrays on the driver.
    via: 'normal' works on A'A or AA', whichever is smaller (squares values); 'bordered' on [0 A; A' 0] (order n_rows + n_cols, pairs of signs).
    """
    k = min(k, n_rows, n_cols)
    options.setdefault("b", 2)
    options.setdefault("blocks", max(2 * k // options["b"], 2) + 4)
    flipped, fold = n_cols > n_rows, None
    if storage == "auto" and via == "normal" and not options.get("want_vectors"):
        fold = "j" if flipped else "i"
        smaller, cells = folded(edges, fold)
        storage = "arrays" if cells <= ARRAY_CELLS else "external"
        edges, fold = (smaller, fold) if storage == "arrays" else (edges, None)
    storage = _place(edges, storage)
    if via == "bordered":
        found = eigen(spark, spmm.bordered(edges, n_rows), n_rows + n_cols, k, storage, edge, kernel, cache_recent, bits, which="LA", **options)
        if found.vectors is not None and isinstance(found.vectors, np.ndarray):
            found.left, found.vectors = (np.sqrt(2) * x for x in np.split(found.vectors, [n_rows]))
        return found
    if storage == "arrays":
        forward, backward, cells = array_product(edges, n_rows, n_cols, packed=fold)
        there, back = (backward, forward) if flipped else (forward, backward)
        found = krylov_schur(MemoryBackend(lambda x: back(there(x)), min(n_rows, n_cols), cells), k, which="LA", **options)
        found.values = np.sqrt(np.maximum(found.values, 0))
        if found.vectors is not None:
            found.left = there(found.vectors) / np.maximum(found.values, 1e-300)
        found.forward, found.cells = forward, cells
    elif storage == "spread":
        turned = edges.select(F.col("j").alias("i"), F.col("i").alias("j"), "w") if flipped else edges
        tall, order = max(n_rows, n_cols), min(n_rows, n_cols)
        store = tiles.TileStore(turned, tall, order, 9, edge or 256, options["b"])
        matrix = SpreadProduct(store)
        store.close()
        found = krylov_schur(MemoryBackend(matrix.both, order, matrix.cells), k, which="LA", **options)
        found.values = np.sqrt(np.maximum(found.values, 0))
        if found.vectors is not None:
            found.left = matrix.there(found.vectors) / np.maximum(found.values, 1e-300)
        found.forward, found.cells = matrix.back if flipped else matrix.there, matrix.cells
    else:
        turned = edges.select(F.col("j").alias("i"), F.col("i").alias("j"), "w")
        edges, turned, n_rows, n_cols = (turned, edges, n_cols, n_rows) if flipped else (edges, turned, n_rows, n_cols)
        bits = bits or dense.interval_bits(_limit(n_cols, k, options), 64 << 20, edge or 256)
        there, size = _product(spark, edges, n_rows, n_cols, options["b"], bits, kernel, edge, {})
        back, more = _product(spark, turned, n_cols, n_rows, options["b"], bits, kernel, edge, {})
        product = chained(there, back)
        if storage == "memory":
            backend = FrameBackend(spark, product, n_cols, bits)
        else:
            backend = StoreBackend(spark, product, n_cols, bits, size + more, cache_recent, options["b"])
        found = krylov_schur(backend, k, which="LA", **options)
        found.values = np.sqrt(np.maximum(found.values, 0))
        if getattr(there, "gathers", False) and getattr(back, "gathers", False):
            found.forward, found.backward = ((lambda x, f=f: dense.to_array(f(x, x.shape[1]))) for f in ((back, there) if flipped else (there, back)))
        if found.vectors is not None:
            chunks = found.vectors.frame if isinstance(found.vectors, Block) else found.vectors
            found.left = dense.scale_columns(dense.unpacked(there(chunks, k)), 1 / np.maximum(found.values, 1e-300))
    if flipped:
        found.left, found.vectors = found.vectors, found.left
    return found
