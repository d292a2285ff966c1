"""Block and panel layouts, and checks of what is laid out.

One row holds one contiguous block as binary, dense, by factors or by its entries: an n x n operator is a
table of blocks keyed by (bi, bj), a tall panel a table of row blocks keyed
by b. Ragged last blocks keep their true shape.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import types

#: Rows of a block when none are asked for: 2048 x 2048 doubles are 32 MB.
BLOCK_ROWS = 2048


def grid_shape(tasks: int) -> tuple[int, int]:
    """Rows and columns of the squarest grid of that many tasks."""
    r = int(np.sqrt(tasks))
    while tasks % r:
        r -= 1
    return r, tasks // r


def kind(df: DataFrame) -> str:
    return "c16" if "im" in df.columns else "f8"


def array(data: bytes, rows: int, cols: int, dtype: str) -> np.ndarray:
    return np.frombuffer(data, dtype).reshape(rows, cols)


class Factored:
    """A block left @ right', plus a diagonal if it stands on the operator's own."""

    def __init__(self, left: np.ndarray, right: np.ndarray, diagonal: np.ndarray | None = None):
        self.left, self.right, self.diagonal = left, right, diagonal

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.left), len(self.right)

    @property
    def T(self) -> Factored:  # noqa: N802
        return Factored(self.right, self.left, self.diagonal)

    def conj(self) -> Factored:
        return Factored(self.left.conj(), self.right.conj(), None if self.diagonal is None else self.diagonal.conj())

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        out = self.left @ (self.right.T @ x)
        return out if self.diagonal is None else out + self.diagonal[:, None] * x

    def minus(self, gamma: float) -> Factored:
        """Less gamma times the identity."""
        return Factored(self.left, self.right, (0.0 if self.diagonal is None else self.diagonal) - np.full(len(self.left), gamma))

    def dense(self) -> np.ndarray:
        out = self.left @ self.right.T
        return out if self.diagonal is None else out + np.diag(self.diagonal)

    def tobytes(self, dtype: str) -> bytes:
        """Its numbers in a row; `block` knows them by their count, which must be below that of the dense block."""
        parts = [] if self.diagonal is None else [self.diagonal]
        out = np.concatenate([x.ravel() for x in (*parts, self.left, self.right)])
        if out.size >= len(self.left) * len(self.right):
            return np.ascontiguousarray(self.dense(), dtype).tobytes()
        return out.astype(dtype).tobytes()


class Sparse:
    """A block by its entries, row by row: those of row r stand at first[r] to first[r + 1]."""

    #: What bytes of entries end with, so that their number is none of whole numbers.
    END = b"s"

    def __init__(self, shape: tuple[int, int], first: np.ndarray, at: np.ndarray, v: np.ndarray):
        self.shape, self.first, self.at, self.v = shape, first, at, v

    @classmethod
    def of(cls, shape: tuple[int, int], i: np.ndarray, j: np.ndarray, v: np.ndarray) -> Sparse:
        """From coordinates; those that occur twice are summed."""
        place = i.astype(np.int64) * shape[1] + j
        if len(place) > 1 and not (place[1:] > place[:-1]).all():
            order = np.argsort(place, kind="stable")
            place, v = place[order], v[order]
            new = np.concatenate([[0], np.flatnonzero(place[1:] != place[:-1]) + 1])
            place, v = place[new], np.add.reduceat(v, new)
        return cls(shape, np.searchsorted(place, np.arange(shape[0] + 1) * shape[1]), place % shape[1], v)

    @classmethod
    def read(cls, data: bytes, rows: int, cols: int, dtype: str) -> Sparse:
        count = int(np.frombuffer(data, np.int64, 1)[0])
        kind, wide = np.dtype(data[8:12].decode().strip()), np.int64 if cols > 1 << 16 else np.uint16
        first = np.concatenate([[0], np.cumsum(np.frombuffer(data, np.int32, rows, 12))])
        at = np.frombuffer(data, wide, count, 12 + 4 * rows)
        v = np.frombuffer(data, kind, count, 12 + 4 * rows + at.nbytes)
        return cls((rows, cols), first, at.astype(np.int64), v.astype(dtype))

    @property
    def T(self) -> Sparse:  # noqa: N802
        return Sparse.of(self.shape[::-1], self.at, np.repeat(np.arange(self.shape[0]), np.diff(self.first)), self.v)

    def conj(self) -> Sparse:
        return Sparse(self.shape, self.first, self.at, self.v.conj())

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros((self.shape[0], x.shape[1]), np.result_type(self.v, x))
        there = np.flatnonzero(np.diff(self.first))
        if len(there):
            out[there] = np.add.reduceat(self.v[:, None] * x[self.at], self.first[there], axis=0)
        return out

    def minus(self, gamma: float) -> Sparse:
        """Less gamma times the identity."""
        i = np.arange(min(self.shape))
        rows = np.repeat(np.arange(self.shape[0]), np.diff(self.first))
        return Sparse.of(self.shape, np.concatenate([rows, i]), np.concatenate([self.at, i]), np.concatenate([self.v, np.full(len(i), -gamma, self.v.dtype)]))

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape, self.v.dtype)
        out[np.repeat(np.arange(self.shape[0]), np.diff(self.first)), self.at] = self.v
        return out

    def tobytes(self, dtype: str) -> bytes:
        """Its entries in the narrowest numbers that hold each of them exactly; as a dense block, which multiplies faster, from a quarter of the cells on."""
        v = self.v.astype(dtype)
        for kind in (np.int8, np.int16, np.float32):
            if not np.iscomplexobj(v) and len(v) and np.abs(v).max() < 30_000 and (v.astype(np.int16 if kind is np.int8 else kind) == v).all() and (kind is not np.int8 or np.abs(v).max() < 128):
                v = v.astype(kind)
                break
        wide = np.int64 if self.shape[1] > 1 << 16 else np.uint16
        parts = (np.int64(len(v)).tobytes(), v.dtype.str[1:].ljust(4).encode(), np.diff(self.first).astype(np.int32).tobytes(), self.at.astype(wide).tobytes(), v.tobytes())
        size = sum(map(len, parts))
        cells = self.shape[0] * self.shape[1]
        if 4 * len(v) > cells or size + 32 >= cells * np.dtype(dtype).itemsize:
            return np.ascontiguousarray(self.dense(), dtype).tobytes()
        return b"".join((*parts, bytes(-size % 32), self.END))


def block(data: bytes, rows: int, cols: int, dtype: str) -> np.ndarray | Factored | Sparse:
    """A block as it is stored: dense, by its entries, or by its factors where it has fewer numbers than rows * cols."""
    if len(data) % 32 == 1:
        return Sparse.read(data, rows, cols, dtype)
    x = np.frombuffer(data, dtype)
    if x.size == rows * cols:
        return x.reshape(rows, cols)
    rank, own = divmod(x.size, rows + cols)
    if own not in (0, rows) or own and rows != cols:
        raise ValueError(f"{x.size} numbers are no block of {rows} x {cols}")
    left, right = x[own : own + rows * rank], x[own + rows * rank :]
    return Factored(left.reshape(rows, rank), right.reshape(cols, rank), x[:own] if own else None)


def recast(data: bytes, rows: int, cols: int, dtype: str, kind: str) -> bytes:
    """The same block in numbers of another kind."""
    if len(data) % 32 == 1:
        return Sparse.read(data, rows, cols, kind).tobytes(kind)
    return np.frombuffer(data, dtype).astype(kind).tobytes()


#: Coordinates that a task holds at a time to send them to their blocks in packs.
PACK = 1 << 20


def _packs(batches: Iterator[pa.RecordBatch], bs: int, dtype: str) -> Iterator[pa.RecordBatch]:
    """(bi, bj, at, v): the coordinates of a block that `PACK` of a task's hold, at = i * bs + j within the block."""
    def pack(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(held)
        i, j, v = (t.column(c).to_numpy() for c in ("i", "j", "v"))
        v = (v + 1j * t.column("im").to_numpy()).astype(dtype) if dtype == "c16" else v.astype(dtype)
        bi, bj = i // bs, j // bs
        key = bi * (int(bj.max()) + 1) + bj
        at = ((i - bi * bs) * bs + (j - bj * bs)).astype(np.int32 if bs < 46_000 else np.int64)
        order = np.argsort(key, kind="stable")
        begin = np.concatenate([[0], np.flatnonzero(np.diff(key[order])) + 1, [len(order)]])
        at, v, lead = at[order], v[order], order[begin[:-1]]
        if dtype == "f8" and (v.astype(np.float32) == v).all():
            v = v.astype(np.float32)
        cut_ = lambda a: pa.array([a[x:y].tobytes() for x, y in zip(begin[:-1], begin[1:])], pa.binary())
        kind = pa.array([v.dtype.str[1:]] * len(lead))
        return pa.RecordBatch.from_arrays([pa.array(bi[lead], pa.int32()), pa.array(bj[lead], pa.int32()), kind, cut_(at), cut_(v)], names=["bi", "bj", "kind", "at", "v"])

    held, rows = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            rows += batch.num_rows
        if rows >= PACK:
            yield pack(held)
            held, rows = [], 0
    if held:
        yield pack(held)


def to_blocks(coo: DataFrame, n: int, bs: int = BLOCK_ROWS) -> DataFrame:
    """Blocks of the coordinates (i, j, v[, im]), dense or by their entries, whichever is less; blocks without a coordinate have no row.

    Coordinates travel in packs of a block, without their block's place and in
    half the bytes where that loses nothing.
    """
    dtype = kind(coo)

    def fill(key: tuple, table: pa.Table) -> pa.Table:
        bi, bj = key[0].as_py(), key[1].as_py()
        nr, nc = min(bs, n - bi * bs), min(bs, n - bj * bs)
        at = np.concatenate([np.frombuffer(x, np.int32 if bs < 46_000 else np.int64) for x in table.column("at").to_pylist()])
        v = np.concatenate([np.frombuffer(x, k).astype(dtype) for x, k in zip(table.column("v").to_pylist(), table.column("kind").to_pylist())])
        data = Sparse.of((nr, nc), at // bs, at % bs, v).tobytes(dtype)
        return pa.table({"bi": [bi], "bj": [bj], "nr": [nr], "nc": [nc], "dtype": [dtype], "data": [data]}, _BLOCK)

    own = coo.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), *(F.col(c).cast("double").alias(c) for c in coo.columns if c in ("v", "im")))
    packs = own.mapInArrow(lambda batches: _packs(batches, bs, dtype), "bi int, bj int, kind string, at binary, v binary")
    return packs.groupBy("bi", "bj").applyInArrow(fill, types.BLOCK)


_BLOCK = pa.schema([("bi", pa.int32()), ("bj", pa.int32()), ("nr", pa.int32()), ("nc", pa.int32()), ("dtype", pa.string()), ("data", pa.binary())])
_PANEL = pa.schema([("b", pa.int32()), ("nr", pa.int32()), ("k", pa.int32()), ("dtype", pa.string()), ("data", pa.binary())])


def from_blocks(blocks: DataFrame, bs: int, dtype: str = "f8") -> DataFrame:
    """Coordinates of the non-zero entries."""
    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                a = block(row["data"], row["nr"], row["nc"], dtype)
                a = a if isinstance(a, np.ndarray) else a.dense()
                i, j = np.nonzero(a)
                cols = [pa.array(i + row["bi"] * bs), pa.array(j + row["bj"] * bs), pa.array(a[i, j].real)]
                if dtype == "c16":
                    cols.append(pa.array(a[i, j].imag))
                yield pa.RecordBatch.from_arrays(cols, names=["i", "j", "v", "im"][: len(cols)])

    return blocks.mapInArrow(spread, types.COO_COMPLEX if dtype == "c16" else types.COO)


def to_panel(vectors: DataFrame, n: int, k: int, bs: int = BLOCK_ROWS) -> DataFrame:
    """A panel from its long form (i, col, v[, im])."""
    dtype = kind(vectors)

    def fill(key: tuple, table: pa.Table) -> pa.Table:
        b = key[0].as_py()
        nr = min(bs, n - b * bs)
        out = np.zeros((nr, k), dtype)
        v = table.column("v").to_numpy()
        if dtype == "c16":
            v = v + 1j * table.column("im").to_numpy()
        np.add.at(out, (table.column("i").to_numpy() - b * bs, table.column("col").to_numpy()), v)
        return pa.table({"b": [b], "nr": [nr], "k": [k], "dtype": [dtype], "data": [out.tobytes()]}, _PANEL)

    return vectors.select(F.expr(f"cast(i div {bs} as int)").alias("b"), *vectors.columns).groupBy("b").applyInArrow(fill, types.PANEL)


def from_panel(panel: DataFrame, bs: int, dtype: str = "f8") -> DataFrame:
    """The long form of a panel."""
    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                a = array(row["data"], row["nr"], row["k"], dtype)
                i, j = (x.ravel() for x in np.indices(a.shape))
                cols = [pa.array(i + row["b"] * bs), pa.array(j.astype(np.int32)), pa.array(a.ravel().real)]
                if dtype == "c16":
                    cols.append(pa.array(a.ravel().imag))
                yield pa.RecordBatch.from_arrays(cols, names=["i", "col", "v", "im"][: len(cols)])

    return panel.mapInArrow(spread, types.VEC_LONG_COMPLEX if dtype == "c16" else types.VEC_LONG)


def panel_rows(array_: np.ndarray, bs: int) -> list[tuple]:
    """Rows of a panel held in memory."""
    dtype = "c16" if np.iscomplexobj(array_) else "f8"
    return [(b, min(bs, len(array_) - b * bs), array_.shape[1], dtype, np.ascontiguousarray(array_[b * bs : (b + 1) * bs]).tobytes()) for b in range(-(-len(array_) // bs))]


def validate_operator(coo: DataFrame, n: int, tol: float = 1e-9, full_index: bool = False) -> None:
    """Raise unless the coordinates are finite, unique, inside the index and self-adjoint.

    With `full_index`, every row of the index must have an entry.
    """
    im = F.col("im") if "im" in coo.columns else F.lit(0.0)
    x = coo.select("i", "j", "v", im.alias("im"))
    finite = ~(F.isnan("v") | F.isnan("im") | (F.abs("v") == float("inf")) | (F.abs("im") == float("inf")))
    facts = x.agg(
        F.count_if(F.col("v").isNull() | F.col("im").isNull() | ~finite).alias("bad"),
        F.count_if(F.col("i").isNull() | F.col("j").isNull() | (F.least("i", "j") < 0) | (F.greatest("i", "j") >= n)).alias("outside"),
        F.count_distinct("i").alias("rows"),
    ).first()
    if facts["bad"]:
        raise types.NonFinite(f"{facts['bad']} entries are null or not finite")
    if facts["outside"] or full_index and facts["rows"] < n:
        raise types.MissingIndex(f"{facts['outside']} entries outside 0..{n - 1}; {facts['rows']} of {n} rows have entries")
    if not x.groupBy("i", "j").count().where("count > 1").isEmpty():
        raise types.DuplicateCoordinate("a coordinate occurs more than once")
    upper = x.select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), "v", F.when(F.col("i") <= F.col("j"), F.col("im")).otherwise(-F.col("im")).alias("im"), (F.col("i") == F.col("j")).alias("d"))
    scale = F.lit(tol) * F.greatest(F.lit(1.0), F.max(F.abs("v")))
    odd = upper.groupBy("i", "j").agg(((F.max("v") - F.min("v") > scale) | (F.max("im") - F.min("im") > scale) | (F.max("d") & (F.max(F.abs("im")) > scale)) | (~F.max("d") & (F.count(F.lit(1)) < 2) & (F.max(F.abs("v")) + F.max(F.abs("im")) > scale))).alias("odd"))
    if not odd.where("odd").isEmpty():
        raise types.NotSelfAdjoint("an entry differs from the conjugate of its mirror image")
