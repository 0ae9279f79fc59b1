"""The reference's experiments on the given tables. `python -m eigenloom.experiments NAME [SF_DIR]` prints one as rows; timings are medians of `repeats` after one warm run.

Relative performance is the in-memory time over the variant's; a ladder's gain is the time of the step before over its own.
"""

from __future__ import annotations

import sys
import time
from statistics import median

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenloom.operators import baselines, dense, solver, spmm, tiles
from eigenloom.operators.subspace import Subspace
from eigenloom.plans import costs
from eigenloom.sources import graphs, stores

WIDTHS = (1, 2, 4, 8, 16)
#: Greatest order of a dense decomposition on the driver.
DENSE_ORDER = 4096


def seconds(run, repeats: int = 3) -> float:
    run()
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        run()
        took.append(time.perf_counter() - began)
    return median(took)


def _drain(frame: DataFrame) -> None:
    frame.write.format("noop").mode("overwrite").save()


def _block(n: int, width: int) -> np.ndarray:
    return np.random.default_rng(11).standard_normal((n, width))


def _stored(frame: DataFrame, codec: str = "zstd") -> DataFrame:
    path = f"{stores.shared_dir(frame.sparkSession)}/exp-{time.time_ns()}"
    frame.write.option("compression", codec).parquet(path)
    return frame.sparkSession.read.schema(frame.schema).parquet(path)


def workloads(spark: SparkSession, sf_dir: str, names: tuple[str, ...] | None = None) -> dict[str, tuple[DataFrame, int]]:
    """Square graphs by stand-in: two recursive matrices, neighbour graph, undirected and directed user graphs; only those of `names` are made."""
    users = graphs.table(spark, sf_dir, "events").agg(F.max("user_id")).first()[0] + 1
    vectors = graphs.table(spark, sf_dir, "embeddings").agg(F.max("vec_id")).first()[0] + 1
    made = {
        "recursive_40": (graphs.symmetrised(graphs.recursive_matrix(spark, 10, 40), "any"), 1 << 10),
        "recursive_160": (graphs.symmetrised(graphs.recursive_matrix(spark, 10, 160), "any"), 1 << 10),
        "neighbours": (graphs.vector_neighbours(spark, sf_dir, 100), vectors),
        "undirected": (graphs.user_adjacency(spark, sf_dir), users),
        "directed": (graphs.user_transitions(spark, sf_dir), users),
    }
    return {name: (_stored(edges), n) for name, (edges, n) in made.items() if names is None or name in names}


def with_relative(frame: DataFrame, base: str, *keys: str) -> DataFrame:
    """Adds `relative`: seconds of the variant `base` over a row's own, within equal keys."""
    other = frame.filter(F.col("variant") == base).select(*keys, F.col("seconds").alias("_base"))
    return frame.join(other, list(keys), "left").withColumn("relative", F.round(F.col("_base") / F.col("seconds"), 3)).drop("_base")


def spmm_ladder(spark: SparkSession, sf_dir: str, widths=WIDTHS, edge: int = 1024, repeats: int = 3) -> DataFrame:
    """Switches of the resident multiply added one at a time over compressed rows; each row has the gain over the step before and over the first."""
    rows = []
    for name in ("undirected", "directed"):
        edges, n = workloads(spark, sf_dir)[name]
        lists, plain, hybrid = _stored(tiles.row_lists(edges)), _stored(tiles.encoded(edges, edge, hybrid=False)), _stored(tiles.encoded(edges, edge))
        for b in widths:
            x = _block(-(-n // edge) * edge, b)
            steps = [
                ("compressed rows", lambda: spmm.row_listed(lists, x)),
                ("tiled", lambda: spmm.resident(plain, x, edge, vectorised=False, super_tile=False)),
                ("super tile", lambda: spmm.resident(plain, x, edge, vectorised=False)),
                ("vectorised", lambda: spmm.resident(plain, x, edge)),
                ("hybrid code", lambda: spmm.resident(hybrid, x, edge)),
                ("in memory", lambda kept=hybrid.persist(): spmm.resident(kept, x, edge)),
            ]
            took = [seconds(lambda f=f: _drain(f()), repeats) for _, f in steps]
            rows += [(name, b, k, step, t, (took[k - 1] / t if k else 1.0), took[0] / t) for k, ((step, _), t) in enumerate(zip(steps, took))]
    return spark.createDataFrame(rows, "graph string, b int, step int, variant string, seconds double, gain double, total double")


def spmm_variants(spark: SparkSession, sf_dir: str, widths=WIDTHS, edge: int = 1024, repeats: int = 3, names=None) -> DataFrame:
    """In-memory, semi-external, relational, striped and baseline multiplies over graphs and widths."""
    rows = []
    for name, (edges, n) in workloads(spark, sf_dir).items():
        if names and name not in names:
            continue
        coded, lists = _stored(tiles.encoded(edges, edge)), _stored(tiles.row_lists(edges))
        kept = tiles.encoded(edges, edge).persist()
        bits = int(np.log2(edge))
        for b in widths:
            x = _block(-(-n // edge) * edge, b)
            frame = _stored(dense.to_rows(dense.from_array(spark, x[:n], bits), bits))
            chunks = _stored(dense.from_array(spark, x[:n], bits))
            runs = {
                "in memory": lambda: spmm.resident(kept, x, edge),
                "semi-external": lambda: spmm.resident(coded, x, edge),
                "relational": lambda: spmm.relational(edges, frame, b),
                "striped": lambda: spmm.striped(coded, chunks, edge, b),
                "one column at a time": lambda: spmm.column_at_a_time(edges, frame, b),
                "compressed rows": lambda: spmm.row_listed(lists, x),
            }
            rows += [(name, b, variant, seconds(lambda f=f: _drain(f()), repeats)) for variant, f in runs.items()]
    return with_relative(spark.createDataFrame(rows, "graph string, b int, variant string, seconds double"), "in memory", "graph", "b")


def dense_sweep(spark: SparkSession, sf_dir: str, columns=(4, 8, 16, 32, 64, 128, 256, 512), b: int = 4, bits: int = 12, group: int = 16, repeats: int = 1) -> DataFrame:
    """Both dense multiplies over m: persisted, from a bucketed store, and NumPy on the driver; with throughput in 2^30 bytes a second."""
    n = graphs.table(spark, sf_dir, "orders").count()
    store = Subspace(spark, n, bits, width=b)
    external = [store.put(dense.packed(dense.random(spark, n, b, 100 + k, bits)), b) for k in range(max(columns) // b)]
    arrays = [dense.to_array(e.frame) for e in external]
    inside = [dense.dealt(e.frame, store.buckets) for e in external]
    for e in inside:
        e.columns_held = b
    rows = []
    for m in columns:
        count = m // b
        small = _block(m, b)
        for form, size in (("combine", n * (m + b) * 8), ("gram", n * (m + b) * 8)):
            persisted = (lambda: _drain(dense.combine(1.0, inside[:count], small, group=group))) if form == "combine" else (lambda: dense.gram(1.0, inside[:count], inside[0], group))
            stored = (lambda: _drain(store.combine_plan(external[:count], small))) if form == "combine" else (lambda: store.gram(external[:count], external[0]))
            if m <= 64:  # a join of more persisted blocks takes the planner longer than the product
                rows.append((form, m, "in memory", seconds(persisted, repeats), size))
            rows.append((form, m, "external", seconds(stored, repeats), size))
            serial = (lambda: np.hstack(arrays[:count]) @ small) if form == "combine" else (lambda: np.hstack(arrays[:count]).T @ arrays[0])
            rows.append((form, m, "one machine's library", seconds(serial, repeats), size))
    made = spark.createDataFrame(rows, "form string, m int, variant string, seconds double, bytes long")
    return with_relative(made, "in memory", "form", "m").withColumn("gib_per_second", F.round(F.col("bytes") / F.col("seconds") / (1 << 30), 4))


def dense_ladder(spark: SparkSession, sf_dir: str, columns=(16, 64), b: int = 4, repeats: int = 1) -> DataFrame:
    """External Gram products as storage switches are added: small chunks gzipped, then zstd, then grouped reads, then large chunks, then the newest block kept."""
    n = graphs.table(spark, sf_dir, "orders").count()
    rows = []
    for m in columns:
        steps = [("gzip, small chunks", "gzip", 10, 1, False), ("zstd", "zstd", 10, 1, False), ("grouped", "zstd", 10, 16, False), ("large chunks", "zstd", 15, 16, False), ("recent block kept", "zstd", 15, 16, True)]
        took = []
        for _, codec, bits, group, keep in steps:
            blocks = [_stored(dense.random(spark, n, b, 100 + k, bits), codec) for k in range(m // b)]
            for e in blocks:
                e.columns_held = b
            right = blocks[-1].persist() if keep else blocks[-1]
            took.append(seconds(lambda bl=blocks, r=right, g=group: dense.gram(1.0, bl, r, g), repeats))
            right.unpersist()
        rows += [(m, k, steps[k][0], t, took[k - 1] / t if k else 1.0, took[0] / t) for k, t in enumerate(took)]
    return spark.createDataFrame(rows, "m int, step int, variant string, seconds double, gain double, total double")


def eigen_relative(spark: SparkSession, sf_dir: str, counts=(8, 32), names=None) -> DataFrame:
    """In-memory solver by preset against the baseline of one column at a time, over graphs; restarts, products and modelled bytes beside the seconds."""
    rows = []
    for name, (edges, n) in workloads(spark, sf_dir).items():
        if name == "directed" or names and name not in names:
            continue
        forward, _back, cells = solver.array_product(edges, n, n)
        single = lambda x: np.hstack([forward(x[:, c : c + 1]) for c in range(x.shape[1])])
        for k in counts:
            profile = "clustered" if name == "neighbours" else "external"
            for variant, product, chosen in (("in memory", forward, profile), ("baseline", single, "baseline")):
                b, blocks = solver.preset(k, chosen)
                began = time.perf_counter()
                found = solver.krylov_schur(solver.MemoryBackend(product, n, cells), k, b=b, blocks=blocks, tol=1e-6)
                took = time.perf_counter() - began
                read, written = costs.solve(n, b, min(n, b * blocks), k + b, 16 * cells, found.restarts)
                rows.append((name, k, variant, b, blocks, took, found.restarts, found.products, bool(found.converged.all()), read, written))
    made = spark.createDataFrame(rows, "graph string, k int, variant string, b int, blocks int, seconds double, restarts int, products int, converged boolean, bytes_read long, bytes_written long")
    return with_relative(made, "in memory", "graph", "k")


def timed_external(spark: SparkSession, edges: DataFrame, n: int, k: int, **options):
    """An external solve without restarts whose multiplies are clocked apart from the scans."""
    b, blocks = solver.preset(k)
    store = tiles.TileStore(edges, n, n, 5, 32, b)
    backend = solver.StoreBackend(spark, solver.resident_product(store), n, 5, store.bytes, True, b)
    backend.clock = True
    return solver.krylov_schur(backend, k, **({"b": b, "blocks": blocks, "max_restarts": 0} | options))


def external_relative(spark: SparkSession, sf_dir: str, counts=(8, 32), names=("undirected",), tol: float = 1e-4, max_restarts: int = 3) -> DataFrame:
    """Solves by presets with persisted frames, with files, and with files without the cache of the recent block: seconds, bytes by the ledger and in files, share of reorthogonalisation."""
    rows = []
    graphs_ = workloads(spark, sf_dir)
    for name in names:
        edges, n = graphs_[name]
        for k in counts:
            b, blocks = solver.preset(k, "clustered" if name == "neighbours" else "external")
            for variant, storage, cached in (("in memory", "memory", True), ("external", "external", True), ("external, no cache", "external", False)):
                began = time.perf_counter()
                found = solver.eigen(spark, edges, n, k, storage=storage, cache_recent=cached, b=b, blocks=blocks, tol=tol, max_restarts=max_restarts, bits=8, edge=256)
                ledger = found.ledger
                rows.append((name, k, variant, time.perf_counter() - began, ledger.total("read"), ledger.total("written"), ledger.total("files"), ledger.share("reorthogonalise"), found.restarts, found.expansions))
    made = spark.createDataFrame(rows, "graph string, k int, variant string, seconds double, bytes_read long, bytes_written long, file_bytes long, reorthogonalise_share double, restarts int, expansions int")
    return with_relative(made, "in memory", "graph", "k")


def parameter_study(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """Restarts, products and modelled bytes over block width and subspace size: larger subspaces restart less; wider blocks read the matrix less often."""
    edges, n = graphs.vector_neighbours(spark, sf_dir), graphs.table(spark, sf_dir, "embeddings").agg(F.max("vec_id")).first()[0] + 1
    forward, _back, cells = solver.array_product(edges, n, n)
    rows = []
    for b in (1, 2, 4):
        for times in (1, 2, 4):
            blocks = max(2, k * times * 2 // b)
            found = solver.krylov_schur(solver.MemoryBackend(forward, n, cells), k, b=b, blocks=blocks, tol=1e-6)
            read, written = costs.solve(n, b, b * blocks, k + b, 16 * cells, found.restarts)
            rows.append((b, blocks, found.restarts, found.expansions, found.products, bool(found.converged.all()), read, written))
    return spark.createDataFrame(rows, "b int, blocks int, restarts int, expansions int, products int, converged boolean, bytes_read long, bytes_written long")


def phase_share(spark: SparkSession, sf_dir: str, counts=(4, 32, 128)) -> DataFrame:
    """Flops of reorthogonalisation and of the multiply for k wanted values, from counted steps: the share of the former grows towards 1."""
    edges, n = workloads(spark, sf_dir)["recursive_40"]
    forward, _back, cells = solver.array_product(edges, n, n)
    rows = []
    for k in counts:
        b, blocks = solver.preset(k)
        found = solver.krylov_schur(solver.MemoryBackend(forward, n, cells), k, b=b, blocks=blocks, tol=1e-6)
        seen = found.ledger.share("reorthogonalise")
        flops = 8 * n * found.products * (b * blocks) * 0.75
        rows.append((k, found.products, float(flops / (flops + 2 * cells * found.products)), seen))
    return spark.createDataFrame(rows, "k int, products int, modelled_share double, measured_share double")


def solver_family(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """The block Krylov solver and the other solvers on the undirected graph: products with the matrix, seconds, error against the dense decomposition, or beyond its order against a solve to rounding."""
    edges, n = workloads(spark, sf_dir, ("undirected",))["undirected"]
    forward, _back, cells = solver.array_product(edges, n, n)
    if n <= DENSE_ORDER:
        values = baselines.dense_exact(edges, n)
        exact, by_size = np.sort(values)[::-1][:k], values[:k]
    else:  # a dense matrix of this order is too large: a wide subspace and a tolerance near rounding stand for it
        exact, by_size = (np.real(solver.krylov_schur(solver.MemoryBackend(forward, n, cells), k, b=k, blocks=10, which=w, tol=1e-12).values) for w in ("LA", "LM"))
    make = lambda: solver.MemoryBackend(forward, n, cells)
    runs = {
        "block Krylov-Schur": lambda: solver.krylov_schur(make(), k, b=2, blocks=8, which="LA"),
        "single vector": lambda: baselines.single_vector(make(), k, which="LA"),
        "block Davidson": lambda: baselines.block_davidson(make(), k),
        "locally optimal": lambda: baselines.locally_optimal(make(), k),
        "subspace iteration": lambda: baselines.subspace_iteration(make(), k),
    }
    rows = []
    for method, run in runs.items():
        began = time.perf_counter()
        found = run()
        want = by_size if method == "subspace iteration" else exact
        rows.append((method, found.products, time.perf_counter() - began, float(np.abs(np.sort(np.real(found.values)) - np.sort(want)).max())))
    return spark.createDataFrame(rows, "method string, products int, seconds double, error double")


def web_svd(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Singular values of directed and rectangular graphs by the web preset: seconds, products, modelled bytes."""
    rows = []
    for name, edges in (("page links", graphs.page_links(spark, sf_dir)), ("customer by part", graphs.customer_part(spark, sf_dir, False))):
        edges = stores.copied(edges)
        size = edges.agg(F.max("i") + 1, F.max("j") + 1).first()
        b, blocks = solver.preset(k, "web")
        storage = "arrays" if edges.count() <= solver.ARRAY_CELLS else "spread"
        began = time.perf_counter()
        found = solver.singular(spark, edges, *size, k, b=b, blocks=blocks, tol=1e-6, storage=storage, want_vectors=True)
        rest = float(np.abs(found.forward(found.vectors) - found.left * found.values).max())
        order = min(size)
        read, written = costs.solve(order, b, b * blocks, k + b, 16 * found.cells, found.restarts, 2)
        rows.append((name, *size, time.perf_counter() - began, found.restarts, found.products, bool(found.converged.all()), costs.resident(order, b), read, written, rest))
    return spark.createDataFrame(rows, "graph string, n_rows long, n_cols long, seconds double, restarts int, products int, converged boolean, resident long, bytes_read long, bytes_written long, residual double")


def scaling(spark: SparkSession, sf_dir: str, repeats: int = 1) -> DataFrame:
    """Relational multiply and Gram product at the scale factors beside sf_dir, with the growth exponent from one to the next."""
    root, rows = sf_dir.rstrip("/").rsplit("/", 1)[0], []
    for sf in ("sf0.001", "sf0.01", "sf0.1"):
        edges = _stored(graphs.customer_part(spark, f"{root}/{sf}"))
        n = edges.agg(F.max("j") + 1).first()[0]
        x = _stored(dense.to_rows(dense.random(spark, n, 4, 3, 10), 10))
        rows.append((sf, edges.count(), seconds(lambda: _drain(spmm.relational(edges, x, 4)), repeats)))
    return spark.createDataFrame([(s, e, t, float(np.log(t / rows[k - 1][2]) / np.log(e / rows[k - 1][1])) if k else 0.0) for k, (s, e, t) in enumerate(rows)], "sf string, edges long, seconds double, exponent double")


ALL = {f.__name__: f for f in (spmm_ladder, spmm_variants, dense_sweep, dense_ladder, eigen_relative, external_relative, parameter_study, phase_share, solver_family, web_svd, scaling)}


def main() -> None:
    name, sf_dir = sys.argv[1], sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    for chosen in ALL if name == "all" else [name]:
        frame = ALL[chosen](spark, sf_dir)
        print(chosen)
        frame.show(200, truncate=False)
    spark.stop()


if __name__ == "__main__":
    main()
