"""Where panels live and how the operator meets them.

The solver is written once against this small interface. `LocalSpace` keeps a
panel as an array inside one task, `SparkSpace` as a table of row blocks.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import types
from ..session import broadcast_limit, cut, partitions
from . import blocks as layout
from .operators import Banded, Reflected
from .small import cholesky_inverse, gaussian

Steps = list[tuple[float, float, float]]


class Space:
    """Panels over one operator; counts sweeps over the operator."""

    n: int
    dtype: str
    sweeps: int = 0
    #: A product costs no more than the other work on a panel.
    light: bool = False

    def filter(self, panel, degrees: np.ndarray, steps: Steps):
        """Each column through its own number of steps; columns must come in ascending order of degree."""
        degrees = np.asarray(degrees)
        done, now, before, active = [], panel, None, np.arange(len(degrees))
        for s, (alpha, beta, gamma) in enumerate(steps[: int(degrees.max(initial=0))], 1):
            before, now = now, self.step(now, before, alpha, beta, gamma)
            stay = degrees[active] > s
            if not stay.all():
                done.append((active[~stay], self.columns(now, np.flatnonzero(~stay))))
                now, before, active = self.columns(now, np.flatnonzero(stay)), self.columns(before, np.flatnonzero(stay)), active[stay]
                if not len(active):
                    break
        out, place = done[0][1], done[0][0]
        for more, part in done[1:]:
            out, place = self.beside(out, part), np.concatenate([place, more])
        return self.columns(out, np.argsort(place)) if (place != np.arange(len(place))).any() else out

    def apply(self, panel):
        return self.step(panel, None, 1.0, 0.0, 0.0)


class LocalSpace(Space):
    """One task's copy of the operator: a matrix, its diagonal alone, or a `Banded` or `Reflected` one."""

    def __init__(self, a: np.ndarray | Banded | Reflected, sign: float = 1.0):
        self.light = isinstance(a, (Banded, Reflected))
        a = a if self.light else np.asarray(a)
        if not self.light and a.ndim == 1:
            a, self.light = Banded({0: a}), True
        self.a, self.n, self.sign, self.sweeps = a, len(a), sign, 0
        self.dtype = "c16" if np.issubdtype(a.dtype, np.complexfloating) else "f8"

    def random(self, k: int, seed: int) -> np.ndarray:
        return gaussian(np.arange(self.n), k, seed, self.dtype)

    def load(self, array: np.ndarray) -> np.ndarray:
        return np.asarray(array)

    def gather(self, panel: np.ndarray) -> np.ndarray:
        return panel

    def step(self, now, before, alpha, beta, gamma):
        self.sweeps += 1
        out = (alpha * self.sign) * (self.a @ now) - (alpha * gamma) * now
        return out if before is None or beta == 0 else out + beta * before

    def filter_low(self, panel, degrees: np.ndarray, steps: Steps):
        """The filter in half the bytes: good while residuals are far above what single precision resolves."""
        kind = np.complex64 if self.dtype == "c16" else np.float32
        low = LocalSpace(self.a.astype(kind), self.sign)
        steps = [tuple(kind(0).real.dtype.type(x) for x in step) for step in steps]
        out = low.filter(panel.astype(kind), degrees, steps).astype(panel.dtype)
        self.sweeps += low.sweeps
        return out

    def columns(self, panel, at):
        return panel[:, at]

    def beside(self, left, right):
        return np.concatenate([left, right], 1)

    def gram(self, left, right):
        return left.conj().T @ right

    def rotate(self, panel, matrix):
        return panel @ matrix

    def minus(self, panel, basis, matrix):
        return panel - basis @ matrix

    def residual_norms(self, product, panel, theta):
        return np.linalg.norm(product - panel * theta[None, :], axis=0)

    def keep(self, panel):
        return panel

    def orthonormalise(self, locked, panel, method="local"):
        if method == "local":
            whole = panel if locked is None else np.concatenate([locked, panel], 1)
            q = np.linalg.qr(whole)[0]
            return q[:, whole.shape[1] - panel.shape[1] :]
        return orthonormalise(self, locked, panel, method)

    def triangle(self, panel):
        return np.linalg.qr(panel, mode="r")


#: Passes of `orthonormalise` at most, and what orthonormal columns may miss.
PASSES, DEFECT = 4, 1e-13


def orthonormalise(space: Space, locked, panel, method: str = "cholqr2"):
    """Orthonormal columns that span the panel, orthogonal to the locked ones; two passes.

    'cholqr2' takes the triangle from the Cholesky factor of the Gram matrix
    (shifted, then by 'tsqr', when that breaks down); 'tsqr' from a tree of
    small QR factorisations. A shifted first pass on a panel whose columns
    differ by a power of ten for each digit there is leaves the second one
    with more to do than it can: passes go on until the Gram matrix is the
    identity, as no residual falls below the operator's norm times what is
    missed here.
    """
    for turn in range(PASSES):
        if locked is not None:
            panel = space.minus(panel, locked, space.gram(locked, panel))
        own = space.gram(panel, panel)
        defect = np.abs(own - np.eye(len(own))).max(initial=0)
        if turn > 1 and defect <= DEFECT:
            break
        inverse = cholesky_inverse(own) if method == "cholqr2" else None
        if inverse is None:
            r = space.triangle(panel)
            weak = np.abs(np.diag(r)) < 1e-14 * np.abs(np.diag(r)).max(initial=1e-300)
            inverse = np.linalg.pinv(r) if weak.any() else np.linalg.inv(r)
        panel = space.keep(space.rotate(panel, inverse))
    else:
        own = space.gram(panel, panel)
        defect = np.abs(own - np.eye(len(own))).max(initial=0)
    if defect > 1e-8 and method == "cholqr2":
        return orthonormalise(space, locked, panel, "tsqr")
    return panel


_OUT = pa.schema([("b", pa.int32()), ("src", pa.int32()), ("nr", pa.int32()), ("k", pa.int32()), ("dtype", pa.string()), ("data", pa.binary())])
_PART = "b int, src int, nr int, k int, dtype string, data binary"


def _rows(parts: dict, dtype: str) -> pa.RecordBatch:
    cols = [(b, src, a.shape[0], a.shape[1], dtype, np.ascontiguousarray(a, dtype).tobytes()) for (b, src), a in parts.items()]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*cols) if cols else [[]] * 6, _OUT)], schema=_OUT)


class SparkSpace(Space):
    """Blocks of the operator pinned in partitions; panels as tables of row blocks.

    strategy: 'grid' deals blocks once to the cells of a task grid and sends
    each panel block to the cells of its grid column, so that a step moves
    panels only; 'broadcast' sends the panel (its size is checked first) to the
    blocks, 'paired' also takes two filter steps in one pass over row stripes,
    'coo' joins coordinates in SQL. half: only blocks with bi <= bj are stored
    and each serves twice. Partial sums of a partition meet before the network.
    alternate: every other step goes through the transposed blocks, which for
    a self-adjoint operator gives the same; panels then go along grid rows.
    every: steps between two cuts of the lineage; as a step reads the two before
    it, work between cuts grows like the Fibonacci numbers, so more than 2
    seldom pays. relayout moves the panel once more after every step, as a
    product that cannot use its own output layout would have to: for
    comparison only.
    """

    STRATEGIES = ("auto", "grid", "broadcast", "paired", "coo")

    def __init__(self, blocks: DataFrame, n: int, bs: int, dtype: str = "f8", strategy: str = "auto", half: bool = False, sign: float = 1.0, sub_grid: tuple[int, int] = (1, 1), every: int = 1, shift: str = "fused", relayout: bool = False, alternate: bool = False):
        if strategy not in self.STRATEGIES:
            raise ValueError(f"unknown strategy: {strategy}")
        if shift not in ("fused", "materialised"):
            raise ValueError(f"unknown shift: {shift}")
        self.spark, self.n, self.bs, self.dtype, self.half, self.sign = blocks.sparkSession, n, bs, dtype, half, sign
        self.every, self.shift, self.relayout, self.sweeps, self._steps, self.sub_grid = every, shift, relayout, 0, 0, sub_grid
        self.count = -(-n // bs)
        self.strategy, self.alternate, self.low, self._keys = strategy, alternate, None, {}
        self.source = blocks
        self.blocks = self._pinned(blocks, sub_grid)

    def _pinned(self, blocks: DataFrame, sub_grid: tuple[int, int]) -> DataFrame:
        """Blocks dealt over a near-square task grid (row stripes for 'paired'), each task holding sub_grid cuts of its part."""
        p = min(partitions(self.spark), self.count if self.strategy == "paired" else self.count**2)
        if self.half:
            blocks = blocks.where("bi <= bj")
        if self.strategy == "paired":
            return blocks.repartition(p, "bi").sortWithinPartitions("bi", "bj")
        self.grid = layout.grid_shape(p)
        self.stripes = tuple(max(1, -(-self.count // (x * s))) * s for x, s in zip(self.grid, sub_grid))
        cells = F.broadcast(self._cells())
        at = blocks.join(cells, (F.expr(f"bi div {self.stripes[0]}") == F.col("ri")) & (F.expr(f"bj div {self.stripes[1]}") == F.col("cj")))
        return at.select(*blocks.columns, "cell").repartition(p, "cell").sortWithinPartitions("cell", "bi", "bj")

    def _cells(self) -> DataFrame:
        """(ri, cj, cell): a key for each cell of the grid whose hash is a partition of its own, found by trying numbers."""
        r, c = self.grid
        if (r, c) not in self._keys:
            tried = self.spark.range(int(r * c * (math.log(r * c) + 12)))
            own = {x["part"]: x["cell"] for x in tried.groupBy(F.pmod(F.hash("id"), F.lit(r * c)).alias("part")).agg(F.min("id").alias("cell")).collect()}
            # A partition that no number fell to leaves its cell with a key that shares another's.
            self._keys[r, c] = [(k // c, k % c, own.get(k, -k - 1)) for k in range(r * c)]
        return self.spark.createDataFrame(self._keys[r, c], "ri int, cj int, cell long")

    def pin(self) -> SparkSpace:
        """Keep the operator resident; spills to disk, is rebuilt from its source if an executor goes.

        The blocks are laid out at once: a plan knows how they are dealt only
        when they are there, and then neither moves nor sorts them again.
        """
        self.blocks = self.blocks.persist()
        self.blocks.count()
        return self

    def unpin(self) -> None:
        self.blocks.unpersist()
        if self.low is not None:
            self.low.unpin()

    def _room(self, k: int, what: str) -> None:
        """Raise before a panel of k columns is fetched that is larger than sixteen times what may be broadcast."""
        size = self.n * k * np.dtype(self.dtype).itemsize
        if size > 16 * broadcast_limit(self.spark):
            raise types.DoesNotFit(f"a panel of {size} bytes is not {what}")

    @staticmethod
    def _k(panel: DataFrame) -> int:
        """Columns of a panel; known for those made here, looked up for others."""
        return panel._width if "_width" in panel.__dict__ else panel.first()["k"]

    @staticmethod
    def _wide(panel: DataFrame, k: int) -> DataFrame:
        panel._width = k
        return panel

    # panels

    def load(self, array: np.ndarray) -> DataFrame:
        array = np.asarray(array, self.dtype)
        return self._wide(self.spark.createDataFrame(layout.panel_rows(array, self.bs), types.PANEL), array.shape[1])

    def random(self, k: int, seed: int) -> DataFrame:
        n, bs, dtype = self.n, self.bs, self.dtype

        def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for b in batch.column(0).to_pylist():
                    a = gaussian(np.arange(b * bs, min(n, (b + 1) * bs)), k, seed, dtype)
                    yield pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((b, len(a), k, dtype, a.tobytes()), layout._PANEL)], schema=layout._PANEL)

        return self._wide(self.spark.range(self.count).mapInArrow(make, types.PANEL), k)

    def gather(self, panel: DataFrame) -> np.ndarray:
        """The whole panel on the driver; its size is checked first."""
        self._room(self._k(panel), "gathered")
        rows = sorted(panel.collect(), key=lambda r: r["b"])
        out = np.zeros((self.n, rows[0]["k"]), self.dtype)
        for r in rows:
            out[r["b"] * self.bs : r["b"] * self.bs + r["nr"]] = layout.array(r["data"], r["nr"], r["k"], self.dtype)
        return out

    def _map(self, panel: DataFrame, f) -> DataFrame:
        dtype = self.dtype

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    a = f(row, layout.array(row["data"], row["nr"], row["k"], dtype))
                    yield pa.RecordBatch.from_arrays([pa.array([x], t.type) for x, t in zip((row["b"], row["nr"], a.shape[1], dtype, np.ascontiguousarray(a).tobytes()), layout._PANEL)], schema=layout._PANEL)

        return panel.mapInArrow(run, types.PANEL)

    def columns(self, panel: DataFrame, at: Sequence[int]) -> DataFrame:
        at = np.asarray(at, int)
        return self._wide(self._map(panel, lambda row, a: a[:, at]), len(at))

    def rotate(self, panel: DataFrame, matrix: np.ndarray) -> DataFrame:
        held = self.spark.sparkContext.broadcast(np.asarray(matrix, self.dtype))
        return self._wide(self._map(panel, lambda row, a: a @ held.value), matrix.shape[1])

    def _with(self, left: DataFrame, right: DataFrame) -> DataFrame:
        return left.join(right.select("b", F.col("k").alias("k2"), F.col("data").alias("data2")), "b").select(*left.columns, "k2", "data2")

    def beside(self, left: DataFrame, right: DataFrame) -> DataFrame:
        dtype = self.dtype
        return self._wide(self._map(self._with(left, right), lambda row, a: np.concatenate([a, layout.array(row["data2"], row["nr"], row["k2"], dtype)], 1)), self._k(left) + self._k(right))

    def minus(self, panel: DataFrame, basis: DataFrame, matrix: np.ndarray) -> DataFrame:
        dtype, held = self.dtype, self.spark.sparkContext.broadcast(np.asarray(matrix, self.dtype))
        return self._wide(self._map(self._with(panel, basis), lambda row, a: a - layout.array(row["data2"], row["nr"], row["k2"], dtype) @ held.value), self._k(panel))

    def _tree(self, parts: DataFrame, join) -> np.ndarray:
        """One small matrix from rows (at, rows, cols, data): sixteen at a time, in order of `at`."""
        dtype = self.dtype

        def fold(table: pa.Table) -> pa.Table:
            rows = sorted(table.to_pylist(), key=lambda r: r["at"])
            a = join([layout.array(r["data"], r["rows"], r["cols"], dtype) for r in rows])
            return pa.table({"at": pa.array([rows[0]["at"] // 16], pa.int32()), "rows": pa.array([a.shape[0]], pa.int32()), "cols": pa.array([a.shape[1]], pa.int32()), "data": pa.array([np.ascontiguousarray(a).tobytes()], pa.binary())})

        left = max(self.count, 1)
        while left > 1:
            parts = parts.groupBy(F.expr("at div 16").alias("__g")).applyInArrow(fold, "at int, rows int, cols int, data binary")
            left = -(-left // 16)
        row = parts.first()
        return layout.array(row["data"], row["rows"], row["cols"], dtype)

    def _small(self, rows: DataFrame, f) -> DataFrame:
        dtype = self.dtype

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    a = f(row, layout.array(row["data"], row["nr"], row["k"], dtype))
                    yield pa.RecordBatch.from_arrays([pa.array([row["b"]], pa.int32()), pa.array([a.shape[0]], pa.int32()), pa.array([a.shape[1]], pa.int32()), pa.array([np.ascontiguousarray(a, dtype).tobytes()], pa.binary())], names=["at", "rows", "cols", "data"])

        return rows.mapInArrow(run, "at int, rows int, cols int, data binary")

    def gram(self, left: DataFrame, right: DataFrame) -> np.ndarray:
        dtype = self.dtype
        if left is right:
            return self._tree(self._small(left, lambda row, a: a.conj().T @ a), sum)
        return self._tree(self._small(self._with(left, right), lambda row, a: a.conj().T @ layout.array(row["data2"], row["nr"], row["k2"], dtype)), sum)

    def triangle(self, panel: DataFrame) -> np.ndarray:
        stack = lambda parts: np.linalg.qr(np.concatenate(parts), mode="r")
        return self._tree(self._small(panel, lambda row, a: np.linalg.qr(a, mode="r")), stack)

    def residual_norms(self, product: DataFrame, panel: DataFrame, theta: np.ndarray) -> np.ndarray:
        dtype, theta = self.dtype, np.asarray(theta)

        def one(row: dict, a: np.ndarray) -> np.ndarray:
            off = a - layout.array(row["data2"], row["nr"], row["k2"], dtype) * theta[None, :]
            return (np.abs(off) ** 2).sum(0, keepdims=True)

        return np.sqrt(self._tree(self._small(self._with(product, panel), one), sum).real[0])

    def keep(self, panel: DataFrame) -> DataFrame:
        return self._wide(cut(panel), self._k(panel))

    def orthonormalise(self, locked, panel, method: str = "cholqr2"):
        if method == "local":
            whole = self.gather(panel) if locked is None else np.concatenate([self.gather(locked), self.gather(panel)], 1)
            return self.load(np.linalg.qr(whole)[0][:, whole.shape[1] - self._k(panel) :])
        return orthonormalise(self, locked, panel, method)

    # products

    def _chosen(self, k: int) -> str:
        if self.strategy != "auto":
            return self.strategy
        small = self.n * k * np.dtype(self.dtype).itemsize <= broadcast_limit(self.spark)
        return "broadcast" if small else "grid"

    def _summed(self, parts: DataFrame) -> DataFrame:
        dtype = self.dtype

        def total(key: tuple, table: pa.Table) -> pa.Table:
            rows = sorted(table.to_pylist(), key=lambda r: r["src"])
            a = layout.array(rows[0]["data"], rows[0]["nr"], rows[0]["k"], dtype).copy()
            for r in rows[1:]:
                a += layout.array(r["data"], r["nr"], r["k"], dtype)
            return pa.table({"b": [key[0].as_py()], "nr": [a.shape[0]], "k": [a.shape[1]], "dtype": [dtype], "data": [a.tobytes()]}, layout._PANEL)

        return parts.groupBy("b").applyInArrow(total, types.PANEL)

    def _scaled(self, panel: DataFrame, factor: float, src: int) -> DataFrame:
        return self._map(panel, lambda row, a: a * factor).select("b", F.lit(src).alias("src"), "nr", "k", "dtype", "data")

    def _partials(self, panel: DataFrame, factor: float, k: int, role: str = "row") -> DataFrame:
        """Rows (b, src, ...) whose sum by b is factor * A * panel; a partition's own sums are done first."""
        dtype, half = self.dtype, self.half
        strategy = self._chosen(k)
        if strategy == "coo":
            return self._by_coordinates(panel, factor, k)
        held = None
        turns = F.explode(F.array(F.lit(0), F.lit(1))) if half else F.lit(int(role == "col"))
        if strategy in ("broadcast", "paired"):
            self._room(k, "broadcast; use strategy='grid'")
            held = self.spark.sparkContext.broadcast({r["b"]: (r["data"], r["nr"], r["k"]) for r in panel.collect()})
            source = self.blocks.select("bi", "bj", "nr", "nc", "data", turns.alias("turned"))
        else:
            source = self._along_grid(panel.select("b", F.col("k").alias("vk"), F.col("nr").alias("vn"), F.col("data").alias("v"), turns.alias("turned")))
        if half:
            source = source.where("turned = 0 or bi < bj")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            parts: dict[tuple[int, int], np.ndarray] = {}
            first: dict[int, int] = {}
            for batch in batches:
                for r in batch.to_pylist():
                    a = layout.block(r["data"], r["nr"], r["nc"], dtype)
                    out, src = (r["bj"], r["bi"]) if r["turned"] else (r["bi"], r["bj"])
                    data, nr, nk = held.value[src] if held is not None else (r["v"], r["vn"], r["vk"])
                    add = factor * ((a.conj().T if r["turned"] else a) @ layout.array(data, nr, nk, dtype))
                    key = (out, first.setdefault(out, src))
                    parts[key] = parts[key] + add if key in parts else add
            yield _rows(parts, dtype)

        return source.mapInArrow(run, _PART)

    def _along_grid(self, panel: DataFrame) -> DataFrame:
        """Operator blocks beside the panel blocks they need (bi, bj, nr, nc, data, turned, v, vn, vk).

        Panel blocks are copied to the cells of their grid column (of their
        grid row where blocks serve transposed). Both sides are dealt by cell
        to the same number of partitions, so the join leaves the operator
        where it is. Beside the cell the blocks are matched by two bounds,
        as a second equality would ask for a deal by both.
        """
        if "cell" not in self.blocks.columns:
            raise ValueError(f"blocks laid out for {self.strategy!r} have no grid")
        r, c = self.grid
        along = F.when(F.col("turned") == 1, F.expr(f"b div {self.stripes[0]}") == F.col("ri")).otherwise(F.expr(f"b div {self.stripes[1]}") == F.col("cj"))
        copies = panel.join(F.broadcast(self._cells()), along).drop("ri", "cj").withColumnRenamed("cell", "at").repartition(r * c, "at")
        needs = F.when(F.col("turned") == 1, F.col("bi")).otherwise(F.col("bj"))
        mine = (F.col("cell") == F.col("at")) & (F.col("b") <= needs) & (F.col("b") >= needs)
        return self.blocks.join(copies.hint("merge"), mine).select("bi", "bj", "nr", "nc", "data", "turned", "v", "vn", "vk")

    def _by_coordinates(self, panel: DataFrame, factor: float, k: int) -> DataFrame:
        coo = layout.from_blocks(self.blocks, self.bs, self.dtype)
        if self.half:
            back = coo.where("i != j").select(F.col("j").alias("i"), F.col("i").alias("j"), "v", *([(-F.col("im")).alias("im")] if "im" in coo.columns else []))
            coo = coo.where(f"i div {self.bs} <= j div {self.bs}")
            coo = coo.unionByName(back.where(f"i div {self.bs} > j div {self.bs}"))
        out = layout.to_panel(product_coo(coo, layout.from_panel(panel, self.bs, self.dtype)), self.n, k, self.bs)
        return self._scaled(out, factor, 0)

    def filter_low(self, panel: DataFrame, degrees: np.ndarray, steps: Steps) -> DataFrame:
        """The filter in half the bytes, over a copy of the blocks that is pinned beside them."""
        kind = "c8" if self.dtype == "c16" else "f4"
        if self.low is None:
            self.low = object.__new__(SparkSpace)
            self.low.__dict__.update(self.__dict__)
            self.low.dtype, self.low.low = kind, None
            columns, dtype = self.blocks.columns, self.dtype

            def halve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    place = batch.schema.names.index("data")
                    data = pa.array([layout.recast(r["data"], r["nr"], r["nc"], dtype, kind) for r in batch.select(["data", "nr", "nc"]).to_pylist()], pa.binary())
                    yield pa.RecordBatch.from_arrays([data if i == place else x for i, x in enumerate(batch.columns)], batch.schema.names)

            low = self.source.select("bi", "bj", "nr", "nc", "dtype", "data").mapInArrow(halve, types.BLOCK)
            self.low.source = low
            self.low.blocks = self.low._pinned(low, self.sub_grid).select(*columns)
            self.low.pin()
        self.low.sweeps = 0
        out = self.low.filter(self._cast(panel, kind), degrees, steps)
        self.sweeps += self.low.sweeps
        return self._wide(self.low._cast(out, self.dtype), self._k(panel))

    def _cast(self, panel: DataFrame, kind: str) -> DataFrame:
        dtype = self.dtype

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = batch.to_pylist()
                for r in rows:
                    r["data"], r["dtype"] = np.frombuffer(r["data"], dtype).astype(kind).tobytes(), kind
                yield pa.RecordBatch.from_pylist(rows, layout._PANEL)

        return self._wide(panel.mapInArrow(run, types.PANEL), self._k(panel))

    def step(self, now: DataFrame, before: DataFrame | None, alpha: float, beta: float, gamma: float, role: str | None = None) -> DataFrame:
        """alpha (sign A - gamma I) now + beta before, in one shuffle of partial sums."""
        role = role or ("col" if self.alternate and self.sweeps % 2 else "row")
        self.sweeps += 1
        k = self._k(now)
        if self.shift == "materialised" and gamma:
            parts = self.shifted(gamma * self.sign)._partials(now, alpha * self.sign, k, role)
        else:
            parts = self._partials(now, alpha * self.sign, k, role)
            if gamma:
                parts = parts.unionByName(self._scaled(now, -alpha * gamma, -1))
        if before is not None and beta:
            parts = parts.unionByName(self._scaled(before, beta, -2))
        out = self._summed(parts)
        if self.relayout:
            out = out.repartition(partitions(self.spark), F.hash("b"))
        self._steps += 1
        return self._wide(cut(out) if self._steps % self.every == 0 else out, k)

    def shifted(self, gamma: float) -> SparkSpace:
        """The same space over A - gamma I, with the diagonal blocks rewritten."""
        dtype = self.dtype

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = batch.to_pylist()
                for r in rows:
                    if r["bi"] == r["bj"]:
                        a = layout.block(r["data"], r["nr"], r["nc"], dtype)
                        r["data"] = a.minus(gamma).tobytes(dtype) if not isinstance(a, np.ndarray) else (a - gamma * np.eye(r["nr"])).astype(dtype).tobytes()
                yield pa.RecordBatch.from_pylist(rows, layout._BLOCK)

        other = object.__new__(SparkSpace)
        other.__dict__.update(self.__dict__)
        diagonal = self.spark.range(self.count).select(F.col("id").cast("int").alias("bi"))
        there = self.source.where("bi = bj").select("bi")
        n, bs = self.n, self.bs
        missing = diagonal.join(there, "bi", "left_anti").select("bi", F.col("bi").alias("bj"), F.least(F.lit(bs), n - F.col("bi") * bs).cast("int").alias("nr")).select("bi", "bj", "nr", F.col("nr").alias("nc"), F.lit(dtype).alias("dtype"), F.lit(None).cast("binary").alias("data"))

        def zeros(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = batch.to_pylist()
                for r in rows:
                    r["data"] = np.zeros((r["nr"], r["nc"]), dtype).tobytes()
                yield pa.RecordBatch.from_pylist(rows, layout._BLOCK)

        whole = self.source.where("bi <= bj" if self.half else "true").select(*missing.columns).unionByName(missing.mapInArrow(zeros, types.BLOCK))
        other.source = whole.mapInArrow(run, types.BLOCK)
        other.blocks = other._pinned(other.source, self.sub_grid)
        return other

    def pair(self, now: DataFrame, before: DataFrame | None, one: tuple[float, float, float], two: tuple[float, float, float]) -> tuple[DataFrame, DataFrame]:
        """Two filter steps in one pass over A: (after one, after two).

        A task owns whole row stripes. It finishes a stripe of the first step,
        then at once sends what that stripe adds to the second.
        """
        if self.half:
            raise ValueError("paired steps need whole row stripes")
        self.sweeps += 1
        dtype, sign = self.dtype, self.sign
        (a1, b1, g1), (a2, b2, g2) = one, two
        k = self._k(now)
        self._room(2 * k, "broadcast; use strategy='grid'")
        rows = {r["b"]: (r["data"], r["nr"], r["k"]) for r in now.collect()}
        old = {r["b"]: r["data"] for r in before.collect()} if before is not None and b1 else {}
        held = self.spark.sparkContext.broadcast((rows, old))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            vs, ps = held.value
            panel = lambda b: layout.array(*vs[b], dtype)

            def finish(bi: int, stripe: list[dict], second: dict) -> tuple[tuple[int, int], np.ndarray]:
                w = (-a1 * g1) * panel(bi)
                for r in stripe:
                    w = w + (a1 * sign) * (layout.block(r["data"], r["nr"], r["nc"], dtype) @ panel(r["bj"]))
                if ps:
                    w = w + b1 * layout.array(ps[bi], *vs[bi][1:], dtype)
                for r in stripe:
                    add = (a2 * sign) * (layout.block(r["data"], r["nr"], r["nc"], dtype).conj().T @ w)
                    second[r["bj"]] = second[r["bj"]] + add if r["bj"] in second else add
                return (bi, -1), w

            second: dict[int, np.ndarray] = {}
            stripe: list[dict] = []
            least = None
            for batch in batches:
                for r in batch.to_pylist():
                    if stripe and r["bi"] != stripe[0]["bi"]:
                        yield _rows(dict([finish(stripe[0]["bi"], stripe, second)]), dtype)
                        stripe = []
                    least = r["bi"] if least is None else min(least, r["bi"])
                    stripe.append(r)
            if stripe:
                yield _rows(dict([finish(stripe[0]["bi"], stripe, second)]), dtype)
            yield _rows({(b, least): a for b, a in second.items()}, dtype)

        both = cut(self.blocks.mapInArrow(run, _PART))
        first = both.where("src = -1").select("b", "nr", "k", "dtype", "data")
        lost = self.spark.createDataFrame([(b,) for b in rows], "b int").join(first.select("b"), "b", "left_anti")
        bare = now.join(lost, "b").select(*now.columns)
        empty = self._summed(self._scaled(bare, -a1 * g1, -1).unionByName(self._scaled(before.join(lost, "b").select(*now.columns), b1, -2)) if old else self._scaled(bare, -a1 * g1, -1))
        first = first.unionByName(empty)
        parts = both.where("src >= 0").unionByName(self._scaled(first, -a2 * g2, -1))
        if b2:
            parts = parts.unionByName(self._scaled(now, b2, -2))
        return self._wide(first, k), self._wide(cut(self._summed(parts)), k)

    def filter(self, panel: DataFrame, degrees: np.ndarray, steps: Steps) -> DataFrame:
        if self.strategy != "paired" or (np.asarray(degrees) % 2).any():
            return super().filter(panel, degrees, steps)
        degrees = np.asarray(degrees)
        done, now, before, active = [], panel, None, np.arange(len(degrees))
        for s in range(2, int(degrees.max(initial=0)) + 1, 2):
            before, now = self.pair(now, before, steps[s - 2], steps[s - 1])
            stay = degrees[active] > s
            if not stay.all():
                done.append((active[~stay], self.columns(now, np.flatnonzero(~stay))))
                now, before, active = self.columns(now, np.flatnonzero(stay)), self.columns(before, np.flatnonzero(stay)), active[stay]
                if not len(active):
                    break
        out = done[0][1]
        for _, part in done[1:]:
            out = self.beside(out, part)
        return self.columns(out, np.argsort(np.concatenate([x for x, _ in done])))

    def product(self, panel: DataFrame, role: str = "row") -> DataFrame:
        """A times the panel; role 'col' goes through the transposed blocks."""
        return self._wide(self._summed(self._partials(panel, self.sign, self._k(panel), role)), self._k(panel))


def product_coo(coo: DataFrame, x: DataFrame) -> DataFrame:
    """A times vectors in long form (i, col, v), by join and sum in SQL."""
    a = coo.select(F.col("i").alias("r"), F.col("j").alias("c"), F.col("v").alias("a"), *([F.col("im").alias("ai")] if "im" in coo.columns else []))
    joined = a.join(x, F.col("c") == F.col("i"))
    if "im" in coo.columns:
        vi = F.col("im") if "im" in x.columns else F.lit(0.0)
        return joined.groupBy(F.col("r").alias("i"), "col").agg(F.sum(F.col("a") * F.col("v") - F.col("ai") * vi).alias("v"), F.sum(F.col("a") * vi + F.col("ai") * F.col("v")).alias("im"))
    return joined.groupBy(F.col("r").alias("i"), "col").agg(F.sum(F.col("a") * F.col("v")).alias("v"))


def itemsize(dtype: str) -> int:
    return int(np.dtype(dtype).itemsize)


def blocks_needed(n: int, bs: int) -> int:
    return math.ceil(n / bs) ** 2
