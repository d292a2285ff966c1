"""Distributed products, panels, and solves over blocks."""

from __future__ import annotations

import numpy as np
import pytest

from eigenlake import types
from eigenlake.build import dense, spectra
from eigenlake.linalg import blocks as layout
from eigenlake.linalg.small import gaussian
from eigenlake.linalg.space import LocalSpace, SparkSpace
from eigenlake.solve import driver, sequence


def operator(n: int, dtype: str, seed: int = 1) -> np.ndarray:
    a = gaussian(np.arange(n), n, seed, dtype)
    return a + a.conj().T


def coo(spark, a: np.ndarray):
    i, j = (x.ravel().tolist() for x in np.indices(a.shape))
    if np.iscomplexobj(a):
        return spark.createDataFrame(list(zip(i, j, a.real.ravel().tolist(), a.imag.ravel().tolist())), types.COO_COMPLEX)
    return spark.createDataFrame(list(zip(i, j, a.ravel().tolist())), types.COO)


@pytest.mark.parametrize("dtype", ["f8", "c16"])
@pytest.mark.parametrize(
    "more", [{"strategy": "grid"}, {"strategy": "broadcast"}, {"strategy": "grid", "half": True}, {"strategy": "broadcast", "half": True, "sub_grid": (2, 2)}, {"strategy": "grid", "shift": "materialised"}, {"strategy": "auto", "sign": -1.0}, {"strategy": "coo"}, {"strategy": "coo", "half": True}, {"strategy": "grid", "relayout": True, "sub_grid": (2, 1)}]
)
def test_step_equals_dense_arithmetic(spark, dtype, more):
    n, a = 11, operator(11, dtype)
    v, before = gaussian(np.arange(n), 3, 2, dtype), gaussian(np.arange(n), 3, 3, dtype)
    space = SparkSpace(layout.to_blocks(coo(spark, a), n, 4), n, 4, dtype, **more)
    got = space.gather(space.step(space.load(v), space.load(before), 0.5, -0.3, 1.7))
    sign = more.get("sign", 1.0)
    assert np.allclose(got, 0.5 * (sign * a @ v - 1.7 * v) - 0.3 * before, atol=1e-12)


@pytest.mark.parametrize("dtype", ["f8", "c16"])
def test_paired_steps_and_transposed_blocks(spark, dtype):
    n, a = 10, operator(10, dtype)
    v, before = gaussian(np.arange(n), 2, 2, dtype), gaussian(np.arange(n), 2, 3, dtype)
    space = SparkSpace(layout.to_blocks(coo(spark, a), n, 4), n, 4, dtype, "paired")
    one, two = (0.5, -0.3, 1.7), (1.1, 0.2, 1.7)
    first, second = space.pair(space.load(v), space.load(before), one, two)
    w = 0.5 * (a @ v - 1.7 * v) - 0.3 * before
    assert np.allclose(space.gather(first), w, atol=1e-12)
    assert np.allclose(space.gather(second), 1.1 * (a @ w - 1.7 * w) + 0.2 * v, atol=1e-12)
    grid = SparkSpace(layout.to_blocks(coo(spark, a), n, 4), n, 4, dtype, "grid")
    assert np.allclose(grid.gather(grid.product(grid.load(v), "col")), a @ v, atol=1e-12)


def between(plan: str, leaf: str) -> list[str]:
    """The operators above the first leaf of that name, up to its join."""
    lines = [x for x in plan.splitlines() if x.strip()]
    depth = lambda x: len(x) - len(x.lstrip(" :+-"))
    k = next(i for i, x in enumerate(lines) if leaf in x)
    out, level = [], depth(lines[k])
    for x in reversed(lines[:k]):
        if depth(x) < level:
            level = depth(x)
            out.append(x.strip(" :+-*"))
            if "Join" in x:
                return out
    return out


@pytest.mark.parametrize("half", [False, True])
def test_the_operator_stays_where_it_is(spark, half):
    n, a = 12, operator(12, "f8")
    space = SparkSpace(layout.to_blocks(coo(spark, a), n, 3), n, 3, strategy="grid", half=half).pin()
    panel = space.load(gaussian(np.arange(n), 2, 2))
    for role in ("row", "col"):
        parts = space._partials(panel, 1.0, 2, role)
        plan = parts._jdf.queryExecution().executedPlan().toString()
        above = between(plan, "InMemoryTableScan [bi")
        assert "SortMergeJoin" in above[-1] and not any(x.startswith(("Exchange", "Sort ")) for x in above), plan
        assert np.allclose(space.gather(space.product(panel, role)), a @ space.gather(panel))
    # Every cell has a partition of its own, the same in both tables.
    cells = space.blocks.select("cell", spark_partition()).distinct().collect()
    assert len({r[0] for r in cells}) == len({r[1] for r in cells}) == len(cells) == (3 if half else 4)
    space.unpin()


def spark_partition():
    from pyspark.sql import functions as F

    return F.spark_partition_id()


def test_alternating_steps_and_low_precision(spark):
    n, a = 11, operator(11, "c16")
    v = gaussian(np.arange(n), 3, 2, "c16")
    steps = [(0.1, 0.0, 0.4), (0.2, -0.3, 0.4), (0.2, -0.1, 0.4), (0.3, -0.2, 0.4)]
    want = LocalSpace(a).filter(v, np.array([2, 4, 4]), steps)
    for more in ({"alternate": True}, {"alternate": True, "half": True}, {"every": 3}):
        space = SparkSpace(layout.to_blocks(coo(spark, a), n, 4), n, 4, "c16", "grid", **more)
        assert np.allclose(space.gather(space.filter(space.load(v), np.array([2, 4, 4]), steps)), want)
    low = space.filter_low(space.load(v), np.array([2, 4, 4]), steps)
    got = space.gather(low)
    assert got.dtype == np.complex128 and 1e-12 < np.abs(got - want).max() < 1e-4 * np.abs(want).max()
    space.unpin()


def test_unknown_words_and_large_panels_are_refused(spark, monkeypatch):
    blocks = spark.createDataFrame([], types.BLOCK)
    for more in ({"strategy": "ring"}, {"shift": "sideways"}):
        with pytest.raises(ValueError, match="unknown"):
            SparkSpace(blocks, 8, 4, **more)
    monkeypatch.setattr("eigenlake.linalg.space.broadcast_limit", lambda spark: 8)
    space = SparkSpace(blocks, 13, 4, strategy="broadcast")
    panel = space.load(gaussian(np.arange(13), 4, 2))
    for f in (space.gather, lambda p: space.step(p, None, 1.0, 0.0, 0.0)):
        with pytest.raises(types.DoesNotFit):
            f(panel)


def test_panel_arithmetic(spark):
    n = 13
    space = SparkSpace(spark.createDataFrame([], types.BLOCK), n, 4)
    v, w = gaussian(np.arange(n), 4, 2), gaussian(np.arange(n), 2, 3)
    p, q = space.load(v), space.load(w)
    assert np.allclose(space.gather(space.random(4, 2)), v)
    assert np.allclose(space.gram(p, q), v.T @ w) and np.allclose(space.gram(p, p), v.T @ v)
    assert np.allclose(space.gather(space.columns(space.beside(p, q), [5, 0, 2])), np.concatenate([v, w], 1)[:, [5, 0, 2]])
    assert np.allclose(space.gather(space.minus(p, q, np.ones((2, 4)))), v - w @ np.ones((2, 4)))
    for method in ("local", "cholqr2", "tsqr"):
        got = space.gather(space.orthonormalise(q, p, method))
        basis = np.linalg.qr(w)[0]
        assert np.abs(got.T @ got - np.eye(4)).max() < 1e-10
        if method == "local":
            assert np.abs(basis.T @ got).max() < 1e-10
    orth = space.load(np.linalg.qr(w)[0])
    assert np.abs(np.linalg.qr(w)[0].T @ space.gather(space.orthonormalise(orth, p))).max() < 1e-10
    long = layout.from_panel(p, 4)
    assert np.allclose(space.gather(layout.to_panel(long, n, 4, 4)), v)


def test_blocks_round_trip_and_checks(spark):
    a = operator(7, "f8")
    df = coo(spark, a)
    back = layout.from_blocks(layout.to_blocks(df, 7, 3), 3)
    assert sorted((r.i, r.j, round(r.v, 12)) for r in back.collect()) == sorted((r.i, r.j, round(r.v, 12)) for r in df.collect())
    layout.validate_operator(df, 7, full_index=True)
    layout.validate_operator(coo(spark, operator(4, "c16")), 4)
    extra = lambda *row: df.unionByName(spark.createDataFrame([row], types.COO))
    with pytest.raises(types.DuplicateCoordinate):
        layout.validate_operator(extra(1, 1, 1.0), 7)
    with pytest.raises(types.MissingIndex):
        layout.validate_operator(extra(8, 8, 1.0), 7)
    with pytest.raises(types.NonFinite):
        layout.validate_operator(extra(1, 1, float("nan")), 7)
    with pytest.raises(types.NotSelfAdjoint):
        layout.validate_operator(spark.createDataFrame([(0, 1, 1.0), (1, 0, 2.0)], types.COO), 2)
    with pytest.raises(types.NotSelfAdjoint):
        layout.validate_operator(spark.createDataFrame([(0, 1, 1.0), (0, 0, 2.0)], types.COO), 2)
    assert layout.grid_shape(12) == (3, 4) and layout.grid_shape(7) == (1, 7)


@pytest.mark.parametrize("strategy", ["grid", "paired"])
def test_distributed_solve_equals_one_task(spark, strategy):
    a = operator(16, "f8")
    df = coo(spark, a)
    more = {"deg": 6, "max_deg": 8, "lanczos_steps": 6, "lanczos_runs": 2, "end": "high"}
    far = driver.eigs(df, 16, 1, 3, tol=1e-6, strategy=strategy, bs=6, **more)
    near = driver.eigs(df, 16, 1, 3, tol=1e-6, strategy="single_task", **more)
    assert (far.iterations, far.matvecs) == (near.iterations, near.matvecs)
    exact = np.linalg.eigvalsh(a)[-1]
    assert abs(far.solution.values[0] - exact) < 1e-8
    v = np.array([r.v for r in far.vectors().orderBy("i").collect()])
    assert np.abs(a @ v - exact * v).max() < 1e-5
    if strategy == "paired":
        assert far.sweeps < near.sweeps


def test_input_order_and_partitions_do_not_matter(spark):
    df = coo(spark, operator(20, "f8"))
    runs = [driver.eigs(x, 20, 3, 3) for x in (df, df.repartition(7), df.orderBy("v").coalesce(1))]
    assert len({(r.iterations, r.matvecs) for r in runs}) == 1
    assert np.allclose(runs[0].solution.values, runs[1].solution.values, atol=1e-12)
    assert runs[0].trace.where("phase = 'Filter'").count() == runs[0].iterations and "single_task" in runs[0].explain()


def test_warm_start_needs_fewer_products(spark):
    base = operator(60, "f8")
    change = operator(60, "f8", 9)
    problems = [coo(spark, base + t * 1e-4 * change) for t in range(3)]
    warm = sequence.eigs_sequence(problems, 60, 4, 6)
    cold = sequence.eigs_sequence(problems, 60, 4, 6, warm=False)
    assert sum(r.matvecs for r in warm[1:]) < sum(r.matvecs for r in cold[1:])
    for r, c in zip(warm, cold):
        assert np.allclose(r.solution.values, c.solution.values, atol=1e-8)


def test_dense_generators_have_their_spectra(spark):
    lams = spectra.values("geometric", 21, eps=1e-2)
    for method in ("reflectors", "gaussian_qr"):
        a = np.zeros((21, 21))
        for r in layout.from_blocks(dense.dense_from_spectrum(spark, lams, method, bs=8), 8).collect():
            a[r.i, r.j] = r.v
        assert np.allclose(a, a.T, atol=1e-12) and np.allclose(np.linalg.eigvalsh(a), np.sort(lams), atol=1e-10)
        assert np.abs(a - np.diag(np.diag(a))).max() > 1e-3


def test_operator_without_entries(spark):
    result = driver.eigs(spark.createDataFrame([], types.COO), 5, 2, 2)
    assert np.allclose(result.solution.values, 0) and LocalSpace(np.zeros((2, 2))).n == 2


def test_implicit_laplacian_and_stage_totals(spark):
    from eigenlake.build import graph
    from eigenlake.cost.stages import measured
    from eigenlake.solve.driver import Options, solve

    n = 12
    w = np.abs(gaussian(np.arange(n), n, 4))
    w = w + w.T
    np.fill_diagonal(w, 0)
    lap = np.diag(w.sum(1)) - w
    edges = coo(spark, w).where("i != j")
    space = graph.LaplacianOperator(edges, n)
    assert np.allclose(space.apply(np.eye(n)), lap, atol=1e-12)
    s = solve(space, Options(2, 4, tol=1e-7, deg=8, max_deg=8, lanczos_steps=6, lanczos_runs=1))
    assert np.allclose(s.values, np.linalg.eigvalsh(lap)[:2], atol=1e-6)
    count, got = measured(spark, lambda: spark.range(1000).repartition(3).count())
    assert count == 1000 and got["shuffle_rows_written"] >= 1000 and got["jobs"] >= 1 and 0 <= got["communication_share"]


def test_pairs_of_a_hot_group_are_spread(spark):
    from eigenlake.build.graph import cooccurrence

    rows = [(1, k) for k in range(300)] + [(2, k) for k in range(0, 300, 2)] + [(2, 0), (None, 1), (3, None), (4, 9)]
    got = {(r.i, r.j): r.v for r in cooccurrence(spark.createDataFrame(rows, "g long, item long"), "g", "item").collect()}
    assert len(got) == 300 * 299 and all(v == (2.0 if i % 2 == 0 and j % 2 == 0 else 1.0) for (i, j), v in got.items())
