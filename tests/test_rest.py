"""Baselines, cost models, sources and sinks, streams, SQL, and the shape of the package."""

from __future__ import annotations

import re
import subprocess
import sys
from pathlib import Path

import numpy as np
import pytest

from eigenlake import types
from eigenlake.baseline import direct, krylov, tridiag
from eigenlake.build import gram
from eigenlake.cost import measures, memory
from eigenlake.io import sinks, sources, spectral_source
from eigenlake.linalg.small import gaussian
from eigenlake.linalg.space import LocalSpace
from eigenlake.solve.driver import Options, eigs, solve

ROOT = Path(__file__).resolve().parent.parent


@pytest.mark.parametrize("method", ["ql", "dc", "bisect", "mrrr"])
@pytest.mark.parametrize("family", ["onetwoone", "wilkinson", "split"])
def test_tridiagonal_solvers(method, family):
    n = 61
    d = {"onetwoone": np.full(n, 2.0), "wilkinson": np.abs(np.arange(n) - 30.0), "split": np.arange(n, dtype=float)}[family]
    e = np.ones(n - 1)
    if family == "split":
        e[20] = e[40] = 0
    a = np.diag(d) + np.diag(e, 1) + np.diag(e, -1)
    w, v = tridiag.tridiag_eigs(d, e, method, 20)
    assert np.allclose(w, np.linalg.eigvalsh(a)[:20], atol=1e-10)
    assert np.abs(a @ v - v * w).max() < 1e-7 and np.abs(v.T @ v - np.eye(20)).max() < 1e-7


@pytest.mark.parametrize("dtype", ["f8", "c16"])
@pytest.mark.parametrize("method", ["dense", "householder", "band"])
def test_direct_solvers(dtype, method):
    a = gaussian(np.arange(40), 40, 3, dtype)
    a = a + a.conj().T
    w, v = direct.direct(a, 5, method)
    assert np.allclose(w, np.linalg.eigvalsh(a)[:5], atol=1e-10) and np.abs(a @ v - v * w).max() < 1e-9
    assert np.allclose(direct.direct(a, 5, method, vectors=False)[0], w, atol=1e-9)


def test_distributed_reduction(spark):
    a = gaussian(np.arange(6), 6, 4)
    a = a + a.T
    rows = [(int(i), int(j), float(a[i, j])) for i in range(6) for j in range(6)]
    got = np.zeros((6, 6))
    for r in direct.householder_distributed(spark.createDataFrame(rows, types.COO), 6).collect():
        got[r.i, r.j] = r.v
    assert np.abs(np.triu(got, 2)).max() < 1e-10 and np.allclose(np.linalg.eigvalsh(got), np.linalg.eigvalsh(a), atol=1e-10)
    with pytest.raises(types.DoesNotFit):
        direct.direct_eigs(spark.createDataFrame(rows, types.COO), 10_000, 2)


def test_iterative_baselines_and_who_wins():
    a = gaussian(np.arange(80), 80, 3)
    a = a + a.T
    exact = np.linalg.eigvalsh(a)
    plain, kry = krylov.subspace_eigs(LocalSpace(a), 4, 8), krylov.lanczos_eigs(LocalSpace(a), 4)
    ours = solve(LocalSpace(a), Options(4, 8, 1e-8))
    for s in (plain, kry, ours):
        assert np.allclose(s.values, exact[:4], atol=1e-8)
    assert ours.sweeps < plain.sweeps
    low, high = exact[3] - 1e-3, exact[9] + 1e-3
    assert np.allclose(np.sort(krylov.rational_eigs(a, low, high, 14)[0]), exact[3:10], atol=1e-8)
    assert np.allclose(krylov.slice_eigs(a, np.linspace(low, high, 4)), exact[3:10], atol=1e-8)


@pytest.mark.parametrize("phase", [0.0, 0.3])
def test_nodes_and_slices_as_tasks(spark, phase):
    a = gaussian(np.arange(40), 40, 5)
    b = gaussian(np.arange(40), 40, 6)
    a = a + a.T + 1j * phase * (b - b.T) if phase else a + a.T
    exact = np.linalg.eigvalsh(a)
    rows = [(i, j, float(a[i, j].real), float(a[i, j].imag)) for i in range(40) for j in range(40)]
    coo = spark.createDataFrame(rows, "i long, j long, v double, im double")
    coo = coo if phase else coo.drop("im")
    low, high = (exact[2] + exact[3]) / 2, (exact[8] + exact[9]) / 2
    values, res = krylov.rational_rows(coo, 40, low, high, 12, nodes=6)
    assert np.allclose(np.sort(values), exact[3:9], atol=1e-8) and res.max() < 1e-8
    found = krylov.slice_rows(coo, 40, np.linspace(low, high, 4)).toPandas()
    assert np.allclose(np.sort(found.eigenvalue), exact[3:9], atol=1e-8) and found["slice"].nunique() > 1
    with pytest.raises(types.DoesNotFit):
        krylov.slice_rows(coo, 10_000, np.linspace(low, high, 4))


def test_memory_models(spark):
    assert memory.host_elements(20_000, 2000, 1, 1) == 5.6e8
    assert memory.device_elements(20_000, 2000, 1, 1, 1, 1) == 6.04e8
    fits = memory.plan(spark, 120_000, 2250, 750, 512e9, 40e9).first()
    assert fits.fits and fits.bytes_device <= 40e9
    smaller = fits.r - 1
    assert smaller == 0 or memory.device_elements(120_000, 3000, smaller, smaller, 2, 2) * 8 > 40e9
    with pytest.raises(types.DoesNotFit):
        memory.require_fit(spark, 10**9, 2250, 750, 1e9, 1e9)
    n = memory.largest_n(3000, 4, 4, 40e9)
    assert memory.device_elements(n, 3000, 4, 4, 2, 2) * 8 <= 40e9 < memory.device_elements(n + 1, 3000, 4, 4, 2, 2) * 8
    full, half = (memory.spark_bytes(100_000, 3000, 2048, 10, 4, h)["executor"] for h in (False, True))
    assert half < full


def test_measures(spark):
    rows = [(k, k, 1.0) for k in range(30)] + [(k, k + 1, 0.2) for k in range(29)] + [(k + 1, k, 0.2) for k in range(29)]
    result = eigs(spark.createDataFrame(rows, types.COO), 30, 3, 3)
    assert measures.matvecs(result.trace).first().matvecs == result.matvecs
    assert measures.phase_seconds(result.trace).first().All > 0
    assert all(r.same for r in measures.compare_runs(result.trace, result.trace).collect())
    v = result.solution.vectors
    assert measures.orthogonality(LocalSpace(np.eye(30)), v) < 1e-9 and measures.subspace_angle(v, v) < 1e-6
    assert measures.tflops(1000, 1000, 1.0) == 0.002 and measures.tflops(1000, 1000, 1.0, complex_=True) == 0.008
    runs = spark.createDataFrame([("a", 1, 8.0), ("a", 4, 4.0)], "case string, nodes int, seconds double")
    assert [r.speedup for r in measures.strong_scaling(runs, "case").orderBy("nodes").collect()] == [1.0, 2.0]
    assert measures.speedup(runs, runs, ["case", "nodes"]).first().speedup == 1


def test_implicit_gram_never_forms_the_matrix(spark):
    x = gaussian(np.arange(50), 6, 2)
    df = spark.createDataFrame([(k, r.tolist()) for k, r in enumerate(x)], "k long, x array<double>")
    space = gram.GramOperator(df.repartition(3), "x", center=True, sign=-1.0, divide=49)
    s = solve(space, Options(2, 3, 1e-8, deg=6, max_deg=8, lanczos_steps=4, lanczos_runs=2))
    assert np.allclose(s.values, np.linalg.eigvalsh(np.cov(x.T))[::-1][:2], atol=1e-8)


def test_sources_and_sinks(spark, tmp_path):
    upper = spark.createDataFrame([(0, 0, 1.0), (0, 1, 2.5), (1, 2, -1.0)], types.COO)
    for fmt in ("parquet", "orc", "json", "csv"):
        upper.write.format(fmt).option("header", True).save(f"{tmp_path}/{fmt}")
        got = sources.read_coo(spark, f"{tmp_path}/{fmt}", fmt, symmetric=True)
        assert sorted(map(tuple, got.collect())) == [(0, 0, 1.0), (0, 1, 2.5), (1, 0, 2.5), (1, 2, -1.0), (2, 1, -1.0)]
    (tmp_path / "m.txt").write_text("%%header\n% 3 3 2\n1 1 4.0\n2 3 0.5\n")
    assert sorted(map(tuple, sources.read_coord_text(spark, str(tmp_path / "m.txt")).collect())) == [(0, 0, 4.0), (1, 2, 0.5)]
    sinks.write_coord_text(upper, f"{tmp_path}/text")
    assert sources.read_coord_text(spark, f"{tmp_path}/text").count() == 3
    result = eigs(sources.mirrored(upper), 3, 1, 1)
    for fmt in ("parquet", "csv"):
        sinks.write_result(result, f"{tmp_path}/result-{fmt}", fmt)
    assert spark.read.parquet(f"{tmp_path}/result-parquet/values").count() == 1
    sinks.noop(upper)
    spectral_source.register(spark)
    for kind in ("onetwoone", "wilkinson", "uniform", "geometric"):
        df = spark.read.format("spectral").option("kind", kind).option("n", 9).option("partitions", 2).load()
        assert df.where("i = j").count() == 9


def test_stream_of_solves_starts_warm_and_runs_again(spark, tmp_path):
    from eigenlake.streaming import warm

    rng = np.random.default_rng(0)
    base = rng.normal(size=(40, 5)) * np.array([5, 2, 1, 1, 1])
    for k in range(3):
        part = spark.createDataFrame([(r.tolist(),) for r in base + 0.01 * k], "x array<double>")
        part.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("x array<double>").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = warm.solve_batches(stream, lambda b: gram.gram(b, "x"), 5, 1, 3, f"{tmp_path}/out", f"{tmp_path}/state", end="high", tol=1e-8)
    q.awaitTermination(120)
    got = spark.read.option("basePath", f"{tmp_path}/out/spectrum").parquet(f"{tmp_path}/out/spectrum").orderBy("batch").collect()
    assert len(got) == 3 and got[0].eigenvalue < got[1].eigenvalue < got[2].eigenvalue
    whole = np.concatenate([base + 0.01 * k for k in range(3)])
    assert abs(got[-1].eigenvalue - np.linalg.eigvalsh(whole.T @ whole)[-1]) < 1e-6


def test_late_and_repeated_rows(spark, tmp_path):
    from pyspark.sql import functions as F

    from eigenlake.streaming import windows

    early = [("a", 1, "2024-01-01 00:00:00"), ("a", 1, "2024-01-01 00:00:00"), ("a", 2, "2024-01-01 03:00:00")]
    late = [("a", 3, "2023-12-01 00:00:00"), ("a", 4, "2024-03-01 00:00:00")]
    for k, rows in enumerate((early, [("a", 5, "2024-01-01 04:00:00")], late, [("z", 9, "2030-01-01 00:00:00")])):
        spark.createDataFrame(rows, "kind string, id int, t string").select("kind", "id", F.to_timestamp("t").alias("ts")).coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
    stream = spark.readStream.schema("kind string, id int, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    counts = windows.tumbling_counts(windows.deduplicated(stream, "ts", "id"), "ts", "kind", watermark=None)
    q = counts.writeStream.outputMode("append").format("memory").queryName("late_rows").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(r.n for r in spark.table("late_rows").collect()) == [1, 3]


def test_entry_and_names(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 5
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_the_rest_does_not_need_the_text_operators(tmp_path):
    for path in (ROOT / "eigenlake").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert not re.search(r"^\s*(from|import) .*llm", path.read_text(), re.M), path
    copy = tmp_path / "copy"
    copy.mkdir()
    (copy / "__spark_entry__.py").write_text((ROOT / "__spark_entry__.py").read_text())
    (copy / "eigenlake").mkdir()
    for path in (ROOT / "eigenlake").rglob("*.py"):
        part = path.relative_to(ROOT)
        if "llm" not in part.parts:
            (copy / part).parent.mkdir(parents=True, exist_ok=True)
            (copy / part).write_text(path.read_text())
    code = "import __spark_entry__ as e; assert len(e.queries()) > 100 and not any(q.startswith('op') or q == 'pipeline' for q in e.queries())"
    assert subprocess.run([sys.executable, "-c", code], cwd=copy, timeout=120).returncode == 0


def test_a_stream_goes_on_from_its_checkpoint(spark, tmp_path):
    from pyspark.sql import functions as F

    from eigenlake.streaming import state

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")

    def add(k: int, rows: list) -> None:
        spark.createDataFrame(rows, "kind string, x double").coalesce(1).write.parquet(f"{tmp_path}/in/{k}")

    def run(name: str) -> dict:
        out: dict = {}
        stream = spark.readStream.schema("kind string, x double").parquet(f"{tmp_path}/in/*")
        sums = state.running_gram(stream.withColumn("one", F.lit(1.0)), "kind", ["x", "one"])
        q = sums.writeStream.outputMode("update").foreachBatch(lambda b, _: out.update({r.key: (r.n, r.s, r.g) for r in b.collect()})).option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
        q.awaitTermination(120)
        return out

    add(0, [("a", 1.0), ("a", 2.0), ("b", 5.0)])
    assert run("first") == {"a": (2, [3.0, 2.0], [5.0, 3.0, 3.0, 2.0]), "b": (1, [5.0, 1.0], [25.0, 5.0, 5.0, 1.0])}
    add(1, [("a", 3.0)])
    assert run("again") == {"a": (3, [6.0, 3.0], [14.0, 6.0, 6.0, 3.0])}
