"""Memory models of the solvers, and the planner that searches with them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import types


def host_elements(n, s, r, c):
    """Elements a process holds: its block, a panel pair, two panels of full height."""
    return (n / r) * (n / c) + (n / r + n / c) * s + 2 * s * n


def device_elements(n, s, r, c, u, w, greatest=max):
    """Elements a device of a u x w grid in the process holds: sub-block, three panels of the longer side, QR and projection space."""
    return (n / r) * (n / c) / (u * w) + 3 * s * greatest(n / (r * u), n / (c * w)) + s * (2 * n + s)


def direct_elements(n, r, c):
    """Elements of the direct solver's process: its part of the operator; one that gathers it all holds n * n."""
    return (n / r) * (n / c)


def spark_bytes(n: int, s: int, bs: int, executors: int, tasks: int, half: bool = False, itemsize: int = 8) -> dict[str, float]:
    """Bytes of an executor (resident blocks, block and panels of running tasks with their Arrow copies) and of the driver."""
    resident = itemsize * n * n * (0.5 if half else 1.0) / executors
    running = 2 * itemsize * tasks * (bs * bs + 2 * bs * s)
    return {"executor": resident + running, "driver": 3.0 * itemsize * s * s}


def config_grid(spark: SparkSession, sides: int = 12, per_side: int = 30_000, nev: int = 2250, nex: int = 750) -> DataFrame:
    """(n, r, c, s) of growing problems on p x p grids, n = per_side * p."""
    p = F.col("id")
    return spark.range(1, sides + 1).select((p * per_side).alias("n"), p.cast("int").alias("r"), p.cast("int").alias("c"), F.lit(nev + nex).alias("s"))


def config_of(rows: DataFrame, side: Column, nev: int = 2250, nex: int = 750) -> DataFrame:
    """(n, r, c, s) of a problem for each grid side p that `side` gives: n is p times the rows it gives p for."""
    sized = rows.groupBy(side.cast("int").alias("p")).agg(F.count(F.lit(1)).alias("rows"))
    return sized.select((F.col("p") * F.col("rows")).alias("n"), F.col("p").alias("r"), F.col("p").alias("c"), F.lit(nev + nex).alias("s"))


def mem_host(config: DataFrame, itemsize: int = 8) -> DataFrame:
    n, s, r, c = (F.col(x).cast("double") for x in ("n", "s", "r", "c"))
    return config.withColumn("bytes_host", host_elements(n, s, r, c) * itemsize)


def mem_device(config: DataFrame, rg: int = 2, cg: int = 2, itemsize: int = 8) -> DataFrame:
    n, s, r, c = (F.col(x).cast("double") for x in ("n", "s", "r", "c"))
    return config.withColumn("bytes_device", device_elements(n, s, r, c, rg, cg, F.greatest) * itemsize)


def mem_direct(config: DataFrame, itemsize: int = 8) -> DataFrame:
    n, r, c = (F.col(x).cast("double") for x in ("n", "r", "c"))
    return config.withColumn("bytes_direct", direct_elements(n, r, c) * itemsize).withColumn("bytes_gathered", n * n * itemsize)


def smallest_grid(problems: DataFrame, sides: int, host_bytes: float, device_bytes: float, devices: tuple[int, int] = (2, 2), itemsize: int = 8) -> DataFrame:
    """For each problem (n, s): the smallest side p of a p x p grid on which both models fit, null if none does."""
    grids = problems.sparkSession.range(1, sides + 1).select(F.col("id").cast("int").alias("r"), F.col("id").cast("int").alias("c"))
    sized = mem_device(mem_host(problems.crossJoin(F.broadcast(grids)), itemsize), *devices, itemsize)
    fits = (F.col("bytes_host") <= host_bytes) & (F.col("bytes_device") <= device_bytes)
    return sized.groupBy("n", "s").agg(F.min(F.when(fits, F.col("r"))).alias("p"))


def largest_n(s: int, r: int, c: int, device_bytes: float, devices: tuple[int, int] = (2, 2), itemsize: int = 8) -> int:
    """The largest order whose device model fits, for a given number of columns."""
    low, high = 0, 1 << 40
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if device_elements(mid, s, r, c, *devices) * itemsize <= device_bytes else (low, mid - 1)
    return low


def plan(spark: SparkSession, n: int, nev: int, nex: int, host_bytes: float, device_bytes: float, sides: int = 64, devices: tuple[int, int] = (2, 2), itemsize: int = 8) -> DataFrame:
    """One row: the smallest square grid that fits, or the largest one with fits = false."""
    s = nev + nex
    p = next((p for p in range(1, sides + 1) if host_elements(n, s, p, p) * itemsize <= host_bytes and device_elements(n, s, p, p, *devices) * itemsize <= device_bytes), None)
    q = p or sides
    row = (n, nev, nex, q, q, *devices, int(host_elements(n, s, q, q) * itemsize), int(device_elements(n, s, q, q, *devices) * itemsize), p is not None)
    return spark.createDataFrame([row], types.PLAN)


def require_fit(spark: SparkSession, *args, **more) -> DataFrame:
    """`plan`, raising when nothing fits."""
    out = plan(spark, *args, **more)
    if not out.first()["fits"]:
        raise types.DoesNotFit("no grid of the allowed size fits", out)
    return out


