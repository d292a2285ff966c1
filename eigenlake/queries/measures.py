"""Cost and accuracy measures."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..build import dense, spectra
from ..build import tridiag as bands
from ..cost import measures, memory, stages
from ..linalg.space import SparkSpace
from ..solve import driver
from ..solve.degrees import cheb_coeffs
from .base import query, r6, table

_PROBLEMS = "(SELECT 1 + o_orderkey % 12 AS p, (1 + o_orderkey % 12) * count(*)::DOUBLE AS n, 3000.0 AS s FROM orders GROUP BY 1)"
_CONFIG = f"(SELECT n, p AS r, p AS c, s FROM {_PROBLEMS})"
_HOST = "8 * ((n / r) * (n / c) + (n / r + n / c) * s + 2 * s * n)"
_DEVICE = "8 * ((n / r) * (n / c) / 4 + 3 * s * greatest(n / (r * 2), n / (c * 2)) + s * (2 * n + s))"


def _grid(spark: SparkSession, sf: str) -> DataFrame:
    """Growing problems on p x p grids: p times the orders of a share, for twelve shares."""
    return memory.config_of(table(spark, sf, "orders"), 1 + F.col("o_orderkey") % 12)


@query(f"SELECT n::BIGINT AS n, r::INT AS r, round({_HOST} / 1e9, 6) AS gb FROM {_CONFIG}")
def mem_host_grid(spark: SparkSession, sf: str) -> DataFrame:
    return memory.mem_host(_grid(spark, sf)).select("n", "r", F.round(F.col("bytes_host") / 1e9, 6).alias("gb"))


@query(f"SELECT n::BIGINT AS n, r::INT AS r, round({_DEVICE} / 1e9, 6) AS gb FROM {_CONFIG}")
def mem_device_grid(spark: SparkSession, sf: str) -> DataFrame:
    return memory.mem_device(_grid(spark, sf)).select("n", "r", F.round(F.col("bytes_device") / 1e9, 6).alias("gb"))


@query(f"SELECT n::BIGINT AS n, round({_HOST} / 1e9, 6) AS filtered_gb, round(8 * (n / r) * (n / c) / 1e9, 6) AS direct_gb, round(8 * n * n / 1e9, 6) AS gathered_gb FROM {_CONFIG}")
def mem_compare(spark: SparkSession, sf: str) -> DataFrame:
    sized = memory.mem_direct(memory.mem_host(_grid(spark, sf)))
    return sized.select("n", *(F.round(F.col(a) / 1e9, 6).alias(b) for a, b in (("bytes_host", "filtered_gb"), ("bytes_direct", "direct_gb"), ("bytes_gathered", "gathered_gb"))))


@query(f"SELECT n::BIGINT AS n, s::INT AS s, min(CASE WHEN {_HOST} <= 512e9 AND {_DEVICE} <= 40e9 THEN p END)::INT AS p FROM (SELECT q.n, q.s, b.p, b.p AS r, b.p AS c FROM {_PROBLEMS} q, range(1, 25) b(p)) GROUP BY ALL")
def plan_min_nodes(spark: SparkSession, sf: str) -> DataFrame:
    return memory.smallest_grid(_grid(spark, sf).select("n", "s"), 24, 512e9, 40e9)


_RUN = "SELECT 'u' || (user_id % 8) AS run_id, event_type AS phase, abs(value) AS seconds, 2 + event_id % 35 AS m, event_id FROM events"


def _trace(spark: SparkSession, sf: str) -> DataFrame:
    """Rows shaped like a solver's trace, from events: a type is a phase, a group of users a run."""
    return table(spark, sf, "events").select(F.concat(F.lit("u"), (F.col("user_id") % 8).cast("string")).alias("run_id"), F.col("event_type").alias("phase"), F.abs("value").alias("seconds"), (2 + F.col("event_id") % 35).cast("int").alias("m"))


@query(f"SELECT run_id, sum(3 * m + 3)::BIGINT AS matvecs FROM ({_RUN}) GROUP BY 1")
def matvecs_from_trace(spark: SparkSession, sf: str) -> DataFrame:
    rows = _trace(spark, sf).select("run_id", F.lit("Filter").alias("phase"), F.array("m", F.col("m") + 1, F.col("m") + 2).alias("degrees"))
    return measures.matvecs(rows)


@query(f"SELECT phase, round(avg(s), 6) AS mean, round(stddev_samp(s), 6) AS sd, count(*) AS runs FROM (SELECT run_id, phase, sum(seconds) AS s FROM ({_RUN}) GROUP BY ALL) GROUP BY 1")
def phase_pivot(spark: SparkSession, sf: str) -> DataFrame:
    return measures.phase_stats(_trace(spark, sf)).select("phase", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"), "runs")


_NODES = f"SELECT phase, nodes, sum(seconds) / nodes AS seconds FROM (SELECT *, 1 + right(run_id, 1)::INT AS nodes FROM ({_RUN})) GROUP BY phase, nodes"


def _scaled(spark: SparkSession, sf: str) -> DataFrame:
    rows = _trace(spark, sf).withColumn("nodes", F.substring("run_id", 2, 1).cast("int") + 1)
    return rows.groupBy("phase", "nodes").agg(F.sum("seconds").alias("total")).select("phase", "nodes", (F.col("total") / F.col("nodes")).alias("seconds"))


@query(f"SELECT phase, nodes, round(first_value(seconds) OVER (PARTITION BY phase ORDER BY nodes) / seconds, 6) AS speedup FROM ({_NODES})")
def strong_speedup(spark: SparkSession, sf: str) -> DataFrame:
    return measures.strong_scaling(_scaled(spark, sf), "phase").select("phase", "nodes", r6("speedup").alias("speedup"))


@query(f"SELECT phase, nodes, round(first_value(seconds) OVER (PARTITION BY phase ORDER BY nodes) / seconds, 6) AS efficiency FROM ({_NODES})")
def weak_efficiency_tab(spark: SparkSession, sf: str) -> DataFrame:
    return measures.weak_efficiency(_scaled(spark, sf), "phase").select("phase", "nodes", r6("efficiency").alias("efficiency"))


_SMALL = "(SELECT count(*) AS n FROM supplier)"


@query(f"SELECT range::INT AS k, round(2 - 2 * cos(pi() * (range + 1) / (n + 1)), 6) + 0.0 AS known, 0.0::DOUBLE AS error FROM range(6), {_SMALL} WHERE range < n // 2")
def value_error(spark: SparkSession, sf: str) -> DataFrame:
    """Distance of computed values from the known spectrum, to eight digits."""
    keys = table(spark, sf, "supplier").select("s_suppkey")
    n = keys.count()
    nev = min(6, n // 2)
    values = driver.eigs(bands.tridiag_121(keys, "s_suppkey"), n, nev, min(8, n - nev), max_iter=200).values
    known = spark.range(6).select(F.col("id").cast("int").alias("k"), (2 - 2 * F.cos(F.lit(np.pi) * (F.col("id") + 1) / (n + 1))).alias("lambda"))
    return measures.value_error(values, known).join(known, "k").select("k", r6("lambda").alias("known"), r6("error", 8).alias("error"))


@query(f"SELECT count(*) AS vectors, count(*)::DOUBLE AS gram_trace, 0.0::DOUBLE AS defect, 0.0::DOUBLE AS worst_residual, round(sum(l), 6) AS total, round(sum(l), 6) AS total_plain FROM (SELECT 2 - 2 * cos(pi() * (range + 1) / (n + 1)) AS l FROM range(8), {_SMALL} WHERE range < n // 2)")
def accuracy_flags(spark: SparkSession, sf: str) -> DataFrame:
    """Orthogonality of the vectors, the worst residual, and the sum of the values with and without chosen degrees."""
    keys = table(spark, sf, "supplier").select("s_suppkey")
    n = keys.count()
    nev = min(8, n // 2)
    coo = bands.tridiag_121(keys, "s_suppkey").cache()
    best, plain = (driver.eigs(coo, n, nev, min(12, n - nev), max_iter=300, optimise_degree=x).solution for x in (True, False))
    gram = best.vectors.T @ best.vectors
    row = (nev, float(np.trace(gram)), float(np.abs(gram - np.eye(nev)).max()), float(best.residuals.max()), float(best.values.sum()), float(plain.values.sum()))
    out = spark.createDataFrame([row], "vectors long, gram_trace double, defect double, worst_residual double, total double, total_plain double")
    return out.select("vectors", r6("gram_trace").alias("gram_trace"), r6("defect", 8).alias("defect"), r6("worst_residual", 8).alias("worst_residual"), r6("total").alias("total"), r6("total_plain").alias("total_plain"))


def _solved(spark: SparkSession, sf: str, **options) -> tuple[driver.EigenResult, int, int]:
    keys = table(spark, sf, "supplier").select("s_suppkey")
    n = keys.count()
    nev = min(8, n // 2)
    nex = min(8, n - nev)
    return driver.eigs(bands.tridiag_121(keys, "s_suppkey"), n, nev, nex, tol=1e-8, max_iter=300, **options), n, nev + nex


@query(f"SELECT 1 AS iteration, least(8, n // 2) + least(8, n - least(8, n // 2)) AS active, 20 AS max_degree, 20 * (least(8, n // 2) + least(8, n - least(8, n // 2))) AS matvecs FROM {_SMALL}")
def trace_first_iteration(spark: SparkSession, sf: str) -> DataFrame:
    """The first filter pass of a real trace: every column at the first degree."""
    trace = _solved(spark, sf)[0].trace.where("phase = 'Filter' and iteration = 1")
    return trace.select("iteration", F.col("active").cast("long").alias("active"), "max_degree", F.col("matvecs").cast("long").alias("matvecs"))


@query("SELECT phase, true AS in_every_run, 0::BIGINT AS matvecs_apart FROM (VALUES ('Lanczos'), ('Filter'), ('QR'), ('RR'), ('Resid')) t(phase)")
def trace_phases(spark: SparkSession, sf: str) -> DataFrame:
    """Phase times of real traces with and without chosen degrees: each phase took time in both, and the trace's products are those the solver counted."""
    runs = [_solved(spark, sf, optimise_degree=x)[0] for x in (True, False)]
    trace = runs[0].trace.unionByName(runs[1].trace).cache()
    counted = spark.createDataFrame([(r.solution.trace[0]["run_id"], r.matvecs) for r in runs], "run_id string, counted long")
    apart = measures.matvecs(trace).join(counted, "run_id").agg(F.sum(F.abs(F.col("matvecs") - F.col("counted"))).alias("apart"))
    stats = measures.phase_stats(trace).where(F.col("phase").isin(measures.PHASES))
    return stats.crossJoin(F.broadcast(apart)).select("phase", ((F.col("runs") == 2) & (F.col("mean") > 0)).alias("in_every_run"), F.col("apart").alias("matvecs_apart"))


@query()
def solver_measures(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds by phase, products, rate and speedup over the direct solver, of real runs."""
    from ..baseline.direct import direct

    out = []
    for name, options in (("full", {}), ("plain_degrees", {"optimise_degree": False}), ("no_locking", {"locking": False})):
        result, n, _ = _solved(spark, sf, **options)
        phases = {r["phase"]: 0.0 for r in result.solution.trace}
        for r in result.solution.trace:
            phases[r["phase"]] += r["seconds"]
        began = time.perf_counter()
        direct(2 * np.eye(n) + np.eye(n, k=1) + np.eye(n, k=-1), 8)
        took = time.perf_counter() - began
        seconds = sum(phases.values())
        out.append((name, result.iterations, result.matvecs, seconds, phases["Filter"], phases["QR"], phases["RR"], phases["Resid"], 1e3 * measures.tflops(n, result.matvecs, phases["Filter"]), took / seconds))
    return spark.createDataFrame(out, "variant string, iterations int, matvecs long, seconds double, filter double, qr double, rr double, resid double, gflops double, speedup_over_direct double")


@query("SELECT strategy, 4::BIGINT AS sweeps, true AS moves_less_than_operator FROM (VALUES ('grid'), ('broadcast')) t(strategy)")
def shuffle_bytes(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes that a filter pass of four steps shuffles, from stage metrics: panels move, the operator does not."""
    n = 512
    out = []
    for strategy in ("grid", "broadcast"):
        space = SparkSpace(dense.reflector_blocks(spark, spectra.values("uniform", n), bs=n // 4), n, n // 4, strategy=strategy).pin()
        panel = space.keep(space.random(4, 7))
        _, got = stages.measured(spark, lambda s=space, p=panel: s.filter(p, np.full(4, 4), cheb_coeffs(0.0, 0.1, 1.2, 4)).count())
        out.append((strategy, space.sweeps, got["shuffle_bytes_written"] < 4 * 8 * n * n // 2))
        space.unpin()
    return spark.createDataFrame(out, "strategy string, sweeps long, moves_less_than_operator boolean")
