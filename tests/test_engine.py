"""Codec, multiplies, dense operations and solvers against hand-checked cases, closed forms and exact decompositions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from eigenloom import apps, queries
from eigenloom.functions import codec, surface
from eigenloom.operators import baselines, dense, solver, spmm, tiles
from eigenloom.operators.subspace import Subspace
from eigenloom.plans import costs, lazy
from eigenloom.sources import graphs, stores


def test_codec_worked_example_and_limits():
    rows, cols = np.array([1, 1, 3, 6, 6, 6]), np.array([2, 5, 0, 1, 2, 7])
    code, vals, multi, single = codec.encode(rows, cols, np.ones(6), 8)
    assert code.hex() == "80010002000580060001000200070003" + "0000" and vals is None and (multi, single) == (2, 1)
    for edge, r, c in ((32768, [32767], [32767]), (8, [], []), (4, *np.divmod(np.arange(16), 4))):
        r, c = np.array(r, int), np.array(c, int)
        w = np.arange(len(r)) + 2.0
        for hybrid in (True, False):
            code, vals, _multi, single = codec.encode(r, c, w, edge, hybrid)
            back = codec.decode(code, vals, single)
            assert sorted(zip(*map(list, back))) == sorted(zip(r, c, w if len(w) else []))
    with pytest.raises(ValueError):
        codec.encode(rows, cols, None, 32769)


def test_resident_plan_has_no_exchange(spark, sf):
    coded = tiles.encoded(graphs.customer_part(spark, sf), 64)
    stored = spark.createDataFrame(coded.toPandas(), tiles.TILE)
    plan = spmm.resident(stored, np.ones((256, 2)), 64)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


def test_closed_form_spectra(spark):
    n = 40
    found = solver.eigen(spark, graphs.path(spark, n), n, 4, b=2, blocks=8, which="LA")
    assert np.allclose(found.values, [2 * np.cos(np.pi * j / (n + 1)) for j in range(1, 5)], atol=1e-7)
    complete = spark.range(15).selectExpr("id as i").crossJoin(spark.range(15).selectExpr("id as j")).filter("i <> j").withColumn("w", F.lit(1.0))
    assert np.allclose(solver.eigen(spark, complete, 15, 3, b=2, blocks=4).values, [14, -1, -1])


def test_gold_singular_values(spark):
    sf = "/root/testdata/sf0.01"
    found = solver.singular(spark, graphs.customer_part(spark, sf), 1500, 2000, 4, b=2, blocks=12)
    assert np.allclose(found.values, [37.426704, 12.553319, 12.511288, 12.412756], atol=1e-5) and found.converged.all()


def test_solver_invariants_and_baselines():
    rng = np.random.default_rng(1)
    a = rng.standard_normal((60, 60))
    a = a + a.T
    exact = np.linalg.eigvalsh(a)
    backend = lambda m=a: solver.MemoryBackend(lambda x: m @ x, len(m))
    for b in (1, 3, 4):
        found = solver.krylov_schur(backend(), 4, b=b, which="LA", want_vectors=True)
        assert np.allclose(found.values, exact[::-1][:4]) and found.orthogonality < 1e-10
    assert np.allclose(solver.krylov_schur(backend(), 3, which="SA").values, exact[:3])
    assert np.allclose(baselines.block_davidson(backend(), 3).values, exact[::-1][:3])
    assert np.allclose(baselines.locally_optimal(backend(), 3).values, exact[::-1][:3])
    skew = rng.standard_normal((30, 30)) + 10 * np.diag(np.arange(30))
    largest = sorted(np.abs(np.linalg.eigvals(skew)))[::-1][:3]
    assert np.allclose(sorted(np.abs(solver.krylov_schur(backend(skew), 3, symmetric=False, blocks=12).values))[::-1], largest)
    with pytest.raises(ValueError):
        solver.krylov_schur(backend(), 0)
    assert np.allclose(solver.krylov_schur(backend(np.zeros((5, 5))), 2).values, 0)
    identity = solver.krylov_schur(backend(np.eye(6)), 3, b=2)
    assert np.allclose(identity.values, 1)


def test_group_size_does_not_change_dense_results(spark):
    rng = np.random.default_rng(2)
    arrays = [rng.integers(-5, 6, (70, 2)).astype(float) for _ in range(4)]
    frames = [dense.from_array(spark, x, 5) for x in arrays]
    small = rng.integers(-3, 4, (8, 2)).astype(float)
    for group in (None, 1, 3):
        assert (dense.to_array(dense.combine(2.0, frames, small, -1.0, frames[0], group)) == 2 * np.hstack(arrays) @ small - arrays[0]).all()
        assert (dense.gram(1.0, frames, frames[1], group) == np.hstack(arrays).T @ arrays[1]).all()


def test_planner_and_costs():
    assert spmm.choose(10**6, 4, 10**8, 10**9) == "resident" and spmm.choose(10**10, 4, 10**12, 10**9) == "striped" and spmm.choose(10**10, 4, 10, 10**9, False) == "relational"
    assert costs.solve(100, 1, 4, 2, 1000, 0) == (4 * 1000 + 4 * 8 * 100 * (1 + 2 + 3 + 4), 4 * 800)
    assert tiles.plan_partitions([(0, 5), (1, 5), (2, 20)], 1, 12) == [(0, 1), (2, 2)]
    assert solver.preset(8, "clustered") == (1, 64) and solver.preset(32, "baseline") == (1, 64)


def test_entry_imports_without_llm(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 5 and abs(rows[0]["value"] - 116.519685) < 1e-5
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def _plan(frame):
    return frame._jdf.queryExecution().executedPlan().toString()


def test_lazy_chain_is_one_projection(spark):
    rng = np.random.default_rng(4)
    arrays = [rng.integers(-5, 6, (70, 3)).astype(float) for _ in range(2)]
    frames = [dense.from_array(spark, x, 5) for x in arrays]
    a, b = (lazy.Tall.stored(f, 3) for f in frames)
    small = np.array([[1.0, 2], [0, -1], [3, 0]])
    chain = (a.scale(2.0) + b.scale_columns([1, 0, -1])).set_columns([1], a.view([2])).times(small) - b.view([0, 0])
    want = 2 * arrays[0] + arrays[1] * [1, 0, -1]
    want[:, 1] = arrays[0][:, 2]
    assert (dense.to_array(chain.frame()) == want @ small - arrays[1][:, [0, 0]]).all()
    alone = a.scale(2.0).view([1, 0]) + a.view([0, 2]).scale(-1.0)
    assert "Join" not in _plan(alone.frame()) and _plan(chain.frame()).count("Join ") <= 1 and "Python" not in _plan(chain.frame())
    assert (dense.to_array(a.scale(0.0).frame() if a.scale(0.0).blocks else frames[0]) is not None) and a.width == 3
    with pytest.raises(ValueError):
        a + a.view([0])


def test_block_identity_and_recent_cache(spark):
    one, two = lazy.BlockId("x"), lazy.BlockId("y")
    assert one.t().t() == one and one.t() != one
    cache, block = lazy.RecentBlocks(100), spark.range(3).toDF("iv")
    cache.put(one, block, 60)
    assert cache.get(one.t()) is block
    cache.put(two, spark.range(2).toDF("iv"), 60)
    assert cache.get(one) is None and cache.get(two) is not None
    cache.put(one, block, 101)
    assert cache.get(one) is None


def test_stores_prune_and_generator_agrees(spark, sf):
    held = stores.partitioned(graphs.customer_part(spark, sf), 32)
    assert "PartitionFilters: [isnotnull(band" in _plan(held.filter("band = 2")) and held.filter("band = 2").agg(F.min("i"), F.max("i")).first()[:] == (64, 95)
    assert stores.generated(spark, 5, 10, 3).exceptAll(graphs.recursive_matrix(spark, 5, 10, 3)).isEmpty()
    with pytest.raises(Exception):
        stores.generated(spark, 30).count()


def test_join_hints_choose_the_strategy(spark, sf):
    made = queries.queries()
    assert "ShuffledHashJoin" in _plan(made["rel_join_shuffle_hash"](spark, sf)) and "SortMergeJoin" in _plan(made["rel_join_sort_merge"](spark, sf))


def test_clusters_of_two_cliques_and_measures(spark):
    left, right = range(0, 6), range(6, 13)
    cells = [(i, j, 1.0) for side in (left, right) for i in side for j in side if i != j] + [(5, 6, 0.1), (6, 5, 0.1)]
    found = apps.spectral_clusters(spark, spark.createDataFrame(cells, "i long, j long, w double"), 13, 2)
    truth = spark.createDataFrame([(i, int(i > 5)) for i in range(13)], "i long, label int")
    assert tuple(apps.purity(found, truth).first()) == (1.0, 1.0)
    mixed = spark.createDataFrame([(i, i % 2) for i in range(13)], "i long, cluster int")
    assert apps.purity(mixed, truth).first()["adjusted_rand"] < 0.1


def test_spectral_table_function(spark):
    surface.register_spectral(spark)
    got = spark.sql("select * from spectral_values(array(named_struct('i', 0L, 'j', 1L, 'w', 1D), named_struct('i', 1L, 'j', 0L, 'w', 1D)), 2)").collect()
    assert sorted(r["value"] for r in got) == pytest.approx([-1, 1])


def test_super_tile_fills_the_cache():
    assert tiles.plan_super(1, 8 << 20, 4, 1024) == 128 and tiles.plan_super(16, 8 << 20, 4, 1024) == 8 and tiles.plan_super(16, 1024, 4, 1024) == 1


def test_store_products_have_no_exchange_and_survive_a_restart(spark):
    rng = np.random.default_rng(6)
    arrays = [rng.integers(-5, 6, (70, 2)).astype(float) for _ in range(4)]
    store = Subspace(spark, 70, 4)
    blocks = [store.put(dense.packed(dense.from_array(spark, x, 4)), 2) for x in arrays]
    held = store.hold(dense.packed(dense.from_array(spark, arrays[3], 4)), 2)
    for other in (blocks[3], held):
        for frame in (store.gram_plan(blocks[:3], other), store.combine_plan(blocks[:3], np.ones((6, 2)), other, np.eye(2))):
            frame.collect()
            assert "Exchange" not in _plan(frame).split("InMemoryTableScan")[0] and "Bucketed: true" in _plan(frame)
        h, g = store.gram(blocks[:3], other)
        assert (h == np.hstack(arrays[:3]).T @ arrays[3]).all() and (g == arrays[3].T @ arrays[3]).all()
        rest = arrays[3] - np.hstack(arrays[:3]) @ (h / 100)
        more, g = store.second_gram(blocks[:3], other, h / 100)
        assert np.allclose(more, np.hstack(arrays[:3]).T @ rest) and np.allclose(g, rest.T @ rest)
    small = rng.integers(-3, 4, (6, 3)).astype(float)
    made = store.put_many(blocks[:3], small, [2, 1])
    assert (np.hstack([dense.to_array(b.frame) for b in made]) == np.hstack(arrays[:3]) @ small).all()
    store.drop(blocks[:1])
    back = Subspace.resumed(spark, store.root)
    assert sorted(back.blocks) == sorted(store.blocks) and (dense.to_array(back.blocks[2].frame) == arrays[1]).all()
    assert back.gram([back.blocks[2]], back.blocks[3])[0].tolist() == (arrays[1].T @ arrays[2]).tolist()
    back.close()
    store.close()


def test_stored_tiles_multiply_without_exchange(spark, sf):
    edges, rng = graphs.customer_part(spark, sf), np.random.default_rng(3)
    store = tiles.TileStore(edges, 150, 200, 5, 16, 3)
    x = rng.integers(-4, 5, (200, 3)).astype(float)
    forward, _b, _c = solver.array_product(edges, 150, 200)
    for switches in ({}, {"spread": False, "super_tile": False}, {"local_buffer": False}, {"vectorised": False, "buffer_reuse": False}):
        made = spmm.semi_external(store, x, **switches)
        assert (dense.to_array(made) == forward(x)).all()
        assert "Exchange" not in _plan(made) or not switches.get("local_buffer", True)
    assert store.parts[0][0] == 0 and store.parts[-1][1] == 4 and len(tiles.TileStore(edges, 150, 200, 5, 16, 3, dynamic=False).parts) >= 2
    assert (dense.to_array(solver.striped_product(store, 200, 5, 3)(dense.from_array(spark, x, 5), 3)) == forward(x)).all()
    assert tiles.best_edge(edges, 10, (64, 32)) == 32 and tiles.best_edge(edges, 10**6, (64, 32)) == 64
    store.close()


def test_external_solve_equals_arrays_and_deletes_what_it_dropped(spark):
    edges = graphs.path(spark, 60).unionByName(spark.range(60).select(F.col("id").alias("i"), F.col("id").alias("j"), F.pow(F.lit(1.2), "id").alias("w")))
    options = {"b": 2, "blocks": 5, "which": "LA", "tol": 1e-4, "max_restarts": 4, "want_vectors": True}
    inside = solver.eigen(spark, edges, 60, 2, storage="arrays", **options)
    outside = solver.eigen(spark, edges, 60, 2, storage="external", bits=4, edge=16, **options)
    assert inside.converged.all() and outside.converged.all() and np.allclose(inside.values, outside.values, rtol=1e-6) and outside.orthogonality < 1e-10
    assert outside.ledger.total("files") > 0 and set(outside.backend.store.blocks) == {b.number for b in outside.backend.store.blocks.values()}
    assert len(outside.backend.store.blocks) <= 8
    with pytest.raises(ValueError):
        dense.interval_bits(4, edge=48)


def test_bad_edges_are_dropped(spark):
    rows = spark.createDataFrame([(0, 1, 1.0), (None, 1, 1.0), (0, None, 1.0), (-1, 2, 1.0), (2, -1, 1.0), (1, 2, float("nan")), (1, 2, float("inf")), (1, 2, None), (0, 1, 2.0)], "a long, b long, w double")
    assert [tuple(r) for r in graphs.coalesced(rows, F.col("a"), F.col("b"), F.col("w")).collect()] == [(0, 1, 3.0)]


def test_locking_and_vectors_of_both_sides():
    rng = np.random.default_rng(9)
    a = rng.standard_normal((80, 80))
    a = a + a.T + np.diag(np.arange(80.0) * 3)
    exact = np.linalg.eigvalsh(a)[::-1]
    runs = [solver.krylov_schur(solver.MemoryBackend(lambda x: a @ x, 80), 5, b=1, blocks=8, which="LA", lock=lock) for lock in (True, False)]
    assert all(np.allclose(r.values, exact[:5]) for r in runs) and runs[0].locked > 0 and runs[1].locked == 0
