"""What is asked of larger tables than those at hand."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from eigenlake.baseline import krylov
from eigenlake.build import dense, graph, spectra
from eigenlake.build import tridiag as bands
from eigenlake.linalg import blocks as layout
from eigenlake.linalg.operators import Banded, TridiagonalInverse
from eigenlake.linalg.small import gaussian
from eigenlake.linalg.space import LocalSpace, SparkSpace, orthonormalise
from eigenlake.queries import QUERIES, methods
from eigenlake.queries.base import nearest

SF = "/root/testdata/sf0.001"


def low_four(n: int) -> np.ndarray:
    return 2 - 2 * np.cos(np.pi * np.arange(1, 5) / (n + 1))


@pytest.mark.parametrize("n", [1, 2, 3, 40])
@pytest.mark.parametrize("shift", [0.25, 0.25 + 0.5j])
def test_tridiagonal_inverse(n, shift):
    below, diagonal, above = np.random.default_rng(n).normal(size=(3, n))
    a, y = Banded({-1: below, 0: diagonal, 1: above}), np.random.default_rng(9).normal(size=(n, 3))
    x = TridiagonalInverse(*a.tridiagonal(), shift) @ y
    assert np.allclose((a.dense() - shift * np.eye(n)) @ x, y, atol=1e-9)


def test_factorised_shifts_beyond_a_dense_matrix(spark):
    n = 9000
    coo = bands.tridiag_121(spark.range(n).select(F.col("id").alias("k")), "k")
    edge = 2 - 2 * np.cos(np.pi * 4.5 / (n + 1))
    values, _ = krylov.rational_rows(coo, n, -0.1 * edge, edge, 10)
    assert np.allclose(np.sort(values), low_four(n), rtol=1e-6, atol=0)
    found = krylov.slice_rows(coo, n, np.array([0.0, 0.4 * edge, edge])).toPandas()
    assert np.allclose(np.sort(found.eigenvalue), low_four(n), rtol=1e-6, atol=0)


@pytest.mark.parametrize("solve", [krylov.lanczos_eigs, lambda space, nev: krylov.subspace_eigs(space, nev, 16)], ids=["lanczos", "subspace"])
@pytest.mark.parametrize("sign", [1.0, -1.0])
def test_solvers_without_a_filter_converge_where_the_spectrum_is_dense(solve, sign):
    n = 9000
    s = solve(LocalSpace(Banded({o: np.full(n, 2.0 if o == 0 else 1.0) for o in (-1, 0, 1)}), sign), 4)
    want = low_four(n) if sign > 0 else 4 - low_four(n)
    assert s.converged and np.allclose(s.values, want, rtol=1e-6, atol=0)


def test_the_inverse_of_an_operator_with_a_zero_value():
    n = 3000
    d = np.full(n, 2.0)
    d[0] = d[-1] = 1.0
    s = krylov.lanczos_eigs(LocalSpace(Banded({-1: -np.ones(n), 0: d, 1: -np.ones(n)})), 4)
    assert s.converged and np.allclose(s.values, 4 * np.sin(np.pi * np.arange(4) / (2 * n)) ** 2, atol=1e-12)


@pytest.mark.parametrize("own", [True, False])
def test_factored_block(own):
    rng = np.random.default_rng(3)
    left, right = rng.normal(size=(9, 2)), rng.normal(size=(9 if own else 7, 2))
    a = layout.Factored(left, right, rng.normal(size=9) if own else None)
    data = a.tobytes("f8")
    b, x, y = layout.block(data, *a.shape, "f8"), rng.normal(size=(a.shape[1], 3)), rng.normal(size=(9, 3))
    assert len(data) < 8 * 9 * a.shape[1]
    assert np.allclose(b @ x, a.dense() @ x) and np.allclose(b.conj().T @ y, a.dense().T @ y)
    assert not own or np.allclose(b.minus(0.5).dense(), a.dense() - 0.5 * np.eye(9))


def test_grid_of_factored_blocks(spark):
    """Two by two blocks of 20,000 rows: dense ones would take 12.8 GB."""
    n, bs = 40_000, 20_000
    lam = spectra.values("geometric", n, eps=1e-60)
    space = SparkSpace(dense.reflector_blocks(spark, lam, bs=bs), n, bs, strategy="grid").pin()
    x = space.random(2, 5)
    got, v = space.gather(space.product(x)), space.gather(x)
    u = np.linalg.qr(gaussian(np.arange(n), 2, 3))[0]
    turn = lambda y: y - 2 * u @ (u.T @ y)
    assert np.allclose(got, turn(lam[:, None] * turn(v)), atol=1e-10)
    assert np.allclose(space.gather(space.product(x, "col")), got, atol=1e-10)
    space.unpin()


def test_small_blocks_of_a_large_operator(spark, monkeypatch):
    """Blocks that do not line up with the three by three parts give the same facts."""
    assert methods._rows(1000, 3) == 334 and methods._rows(60_000, 3) <= 512
    key = lambda df: sorted(tuple(r) for r in df.select("bi", "bj", "n", "total", "squares").collect())
    want = key(QUERIES["block_layout"](spark, SF))
    monkeypatch.setattr(methods, "_rows", lambda n, parts: 3)
    assert key(QUERIES["block_layout"](spark, SF)) == want


def test_cooccurrence_of_small_and_large_groups(spark, monkeypatch):
    monkeypatch.setattr(graph, "WHOLE", 6)
    rows = [(g, (7 * g + k * k) % 23) for g in range(12) for k in range(g)] + [(3, None), (None, 4)]
    got = {(r.i, r.j): r.v for r in graph.cooccurrence(spark.createDataFrame(rows, "g int, x int"), "g", "x").collect()}
    sets = [{x for h, x in rows if h == g and x is not None} for g in range(12)]
    want = {(a, b): n for a in range(23) for b in range(23) if a != b and (n := sum(a in s and b in s for s in sets))}
    assert got == want


def test_entries_of_a_dense_operator_are_dealt_to_tasks(spark, monkeypatch):
    """One file of suppliers is one partition, but their pairs are the work of many tasks."""
    df = QUERIES["dense_reflector"](spark, SF)
    assert df.rdd.getNumPartitions() >= 4
    want = sorted(map(tuple, df.collect()))
    monkeypatch.setattr(methods, "ENTRIES", 10)
    df = QUERIES["dense_reflector"](spark, SF)
    assert df.rdd.getNumPartitions() == -(-len(want) // 10) > 4
    assert sorted(map(tuple, df.collect())) == want


def test_nearest_is_the_rounding_of_the_sql(spark):
    duckdb = pytest.importorskip("duckdb")
    x = np.concatenate([np.random.default_rng(2).normal(size=3000), (np.arange(-200, 200) + 0.5) / 1e6, np.arange(-8, 9) / 16, [0.0, -0.0, -1e-9, 4.9999999e-7, 0.49999999999999994e-6]])
    rows = spark.createDataFrame([(k, float(v)) for k, v in enumerate(x)], "k long, x double")
    got = {r.k: repr(r.v) for r in rows.select("k", nearest("x").alias("v")).collect()}
    c = duckdb.connect()
    c.execute("CREATE TABLE t(k BIGINT, x DOUBLE)")
    c.executemany("INSERT INTO t VALUES (?, ?)", [(k, float(v)) for k, v in enumerate(x)])
    assert got == {k: repr(v) for k, v in c.sql("SELECT k, round(x, 6) + 0.0 FROM t").fetchall()}


@pytest.mark.parametrize("seed", [0, 1, 2])
def test_two_directions_and_noise_end_orthonormal(seed):
    """What a filter leaves where one value, held twice, stands far from all others."""
    rng = np.random.default_rng(seed)
    panel = rng.standard_normal((50, 2)) @ rng.standard_normal((2, 10)) + 1e-14 * rng.standard_normal((50, 10))
    q = orthonormalise(LocalSpace(np.eye(50)), None, panel)
    assert np.abs(q.T @ q - np.eye(10)).max() < 1e-13


@pytest.mark.parametrize("dtype", ["f8", "c16"])
def test_blocks_by_their_entries(dtype):
    rng = np.random.default_rng(5)
    a = np.where(rng.random((60, 60)) < 0.03, rng.integers(-9, 9, (60, 60)), 0).astype(dtype)
    a[7] = 0
    a += 0.1j * a if dtype == "c16" else 0
    i, j = (np.concatenate([x, x[:5]]) for x in np.nonzero(a))
    twice = a.copy()
    twice[i[:5], j[:5]] *= 2
    data = layout.Sparse.of(a.shape, i, j, a[i, j]).tobytes(dtype)
    b, x = layout.block(data, 60, 60, dtype), rng.normal(size=(60, 3))
    assert isinstance(b, layout.Sparse) and len(data) < a.nbytes / 2
    assert np.allclose(b.dense(), twice) and np.allclose(b @ x, twice @ x) and np.allclose(b.conj().T @ x, twice.conj().T @ x)
    assert np.allclose(b.minus(0.5).dense(), twice - 0.5 * np.eye(60))
    full = np.arange(16.0).reshape(4, 4)
    assert np.array_equal(layout.block(layout.Sparse.of((4, 4), *np.indices((4, 4)).reshape(2, -1), full.ravel()).tobytes("f8"), 4, 4, "f8"), full)


def test_few_entries_take_few_bytes_in_blocks(spark, monkeypatch):
    """An operator with an entry in every block is stored by its entries, whichever packs they came in."""
    monkeypatch.setattr(layout, "PACK", 100)
    n = 600
    coo = spark.range(3 * n).select((F.col("id") * 7919 % n).alias("i"), (F.col("id") * 104729 % n).alias("j"), F.lit(1.0).alias("v"))
    held = layout.to_blocks(coo, n, 100)
    assert held.agg(F.sum(F.octet_length("data"))).first()[0] < n * n * 8 / 10
    assert sorted(map(tuple, layout.from_blocks(held, 100).collect())) == sorted(map(tuple, coo.groupBy("i", "j").agg(F.sum("v")).collect()))


def test_products_of_blocks_stored_by_their_entries(spark):
    rng = np.random.default_rng(8)
    a = np.triu(np.where(rng.random((90, 90)) < 0.04, rng.integers(1, 9, (90, 90)), 0), 1).astype(float)
    a += a.T
    i, j = np.nonzero(a)
    held = layout.to_blocks(spark.createDataFrame([(int(x), int(y), float(a[x, y])) for x, y in zip(i, j)], "i long, j long, v double"), 90, 30).cache()
    assert held.agg(F.max(F.octet_length("data"))).first()[0] < 30 * 30 * 8 / 2
    x = rng.normal(size=(90, 2))
    for more in ({"strategy": "paired"}, {"strategy": "broadcast", "half": True}, {"strategy": "grid"}):
        space = SparkSpace(held, 90, 30, **more)
        assert np.allclose(space.gather(space.product(space.load(x))), a @ x)
        if more["strategy"] == "paired":
            two = space.pair(space.load(x), None, (1.0, 0.0, 0.5), (1.0, 0.0, 0.0))[1]
            assert np.allclose(space.gather(two), a @ (a @ x - 0.5 * x))
    moved = space.shifted(0.5)
    assert np.allclose(moved.gather(moved.product(moved.load(x))), a @ x - 0.5 * x)
