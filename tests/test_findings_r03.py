"""Cases of the third round's findings; each fails on the code before its fix."""

import numpy as np

from eigenloom import queries
from eigenloom.operators import baselines, dense, solver, subspace


def test_stored_blocks_are_swept_many_intervals_at_once(spark):
    rng = np.random.default_rng(2)
    arrays = [rng.integers(-5, 6, (299, w)).astype(float) for w in (2, 3, 2)]
    store = subspace.Subspace(spark, 299, 3)
    blocks = [store.put(dense.packed(dense.from_array(spark, x, 3)), x.shape[1]) for x in arrays]
    turned, held = [blocks[1], blocks[0]], store.hold(None, 2, arrays[2])
    v, small = np.hstack([arrays[1], arrays[0]]), rng.integers(-3, 4, (5, 2)).astype(float)
    for other in (blocks[2], held):
        plan = store.gram_plan(turned, other)._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "Groups" not in plan and "Exchange" not in plan and "Bucketed: true" in plan
        h, g = store.gram(turned, other)
        assert (h == v.T @ arrays[2]).all() and (g == arrays[2].T @ arrays[2]).all()
        rest = arrays[2] - v @ (h / 1000)
        assert np.allclose(store.second_gram(turned, other, h / 1000)[0], v.T @ rest)
        made = store.put(store.combine_plan(turned, small, other, np.eye(2)), 2)
        assert (dense.to_array(made.frame) == v @ small + arrays[2]).all()
    assert (np.hstack([dense.to_array(b.frame) for b in store.put_many(turned, small, [1, 1])]) == v @ small).all()
    store.drop([held])
    store.close()


def test_a_symmetric_solve_from_files_scans_twice_and_ends_when_it_has_converged(spark):
    a = np.diag([50.0, -40.0, *np.linspace(0, 1, 58)])
    a[3, 7] = a[7, 3] = 0.5
    edges = spark.createDataFrame([(int(i), int(j), float(a[i, j])) for i, j in zip(*np.nonzero(a))], "i long, j long, w double")
    found = solver.eigen(spark, edges, 60, 2, storage="external", b=2, blocks=12, tol=1e-4, bits=4, edge=16)
    assert np.allclose(found.values, [50, -40]) and found.converged.all() and found.expansions < 8
    ops = [r[2] for r in found.ledger.rows]
    assert ops.count("second gram") == found.expansions and ops.count("gram") <= 1


def test_triples_of_more_cells_than_the_arrays_take(spark, sf, monkeypatch):
    def refuse(*_a, **_k):
        raise ValueError("too many cells for the in-memory variant")

    want = queries.queries()["external_customer_part_k8"](spark, sf).collect()
    monkeypatch.setattr(solver, "ARRAY_CELLS", 10)
    monkeypatch.setattr(solver, "array_product", refuse)
    assert queries.queries()["external_customer_part_k8"](spark, sf).collect() == want and all(want[0][1:])


def test_tall_blocks_are_not_decomposed_and_are_normalised_seldom(monkeypatch):
    rng = np.random.default_rng(4)
    a = rng.standard_normal((500, 500)) + np.diag(np.linspace(0, 200, 500))
    a = (a + a.T) / 2
    exact, svd, calls = np.linalg.eigvalsh(a), np.linalg.svd, []
    monkeypatch.setattr(np.linalg, "svd", lambda x, **k: calls.append(max(x.shape)) or svd(x, **k))
    assert np.allclose(np.sort(baselines.locally_optimal(solver.MemoryBackend(lambda x: a @ x, 500), 3, steps=200).values), exact[-3:]) and max(calls) <= 9
    normal, made = baselines.normalise, []
    monkeypatch.setattr(baselines, "normalise", lambda *x, **k: made.append(1) or normal(*x, **k))
    found = baselines.subspace_iteration(solver.MemoryBackend(lambda x: a @ x, 500), 3)
    assert np.allclose(np.sort(found.values), exact[-3:]) and len(made) < found.expansions / 2
    assert np.allclose(np.sort(baselines.block_davidson(solver.MemoryBackend(lambda x: a @ x, 500), 3).values), exact[-3:])
