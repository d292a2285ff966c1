"""Harmonic packing of token sequences.

A document gives as many full sequences as it can. Its rest is kept whole if
that length, taken k = capacity // length times, nearly fills a sequence;
otherwise one piece of capacity / (k + 1) is cut off and the shorter rest is
treated likewise. A piece of class k goes to the open bin of its class, which
closes with exactly k pieces. Classes and workers never wait for each other;
what is left in open bins at a worker's end is chained into full sequences.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnum, wordpieces

#: A bin may stay empty by this part of its capacity before its pieces are cut smaller.
SLACK = 64

_FIELDS = [("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64()), ("ids", pa.list_(pa.int32()))]
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids array<int>"


def cuts(length: int, capacity: int) -> list[int]:
    """Piece lengths of a rest shorter than a sequence; each fills its class's bins but for a small slack."""
    out = []
    while length:
        k = capacity // length
        if (capacity - k * length) * SLACK <= capacity:
            out.append(length)
            break
        out.append(capacity // (k + 1))
        length -= out[-1]
    return out


class _Bins:
    """A worker's open bins, one for each reciprocal class."""

    def __init__(self, capacity: int, first_id: int, with_ids: bool):
        self.capacity, self.next_id, self.with_ids = capacity, first_id, with_ids
        self.open: dict[int, list[tuple]] = {}
        self.rows: list[tuple] = []

    def close(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc, start, ids, total in pieces:
            self.rows.append((doc, start, len(ids), zlib.crc32(ids.tobytes()), total, self.next_id, offset, ids if self.with_ids else None))
            offset += len(ids)
        self.next_id += 1

    def add(self, doc: int | None, start: int, ids: np.ndarray, total: int) -> None:
        k = self.capacity // len(ids)
        mine = self.open.setdefault(k, [])
        mine.append((doc, start, ids.copy(), total))
        if len(mine) == k:
            self.close(self.open.pop(k))

    def chain(self) -> None:
        """Close what is open as full sequences, cutting pieces where a sequence ends."""
        mine, room = [], self.capacity
        for k in sorted(self.open):
            for doc, start, ids, total in self.open[k]:
                while len(ids):
                    part = ids[:room]
                    mine.append((doc, start, part, total))
                    start, ids, room = start + len(part), ids[room:], room - len(part)
                    if not room:
                        self.close(mine)
                        mine, room = [], self.capacity
        if mine:
            self.close(mine)
        self.open = {}

    def take(self) -> pa.RecordBatch:
        cols = list(zip(*self.rows)) or [()] * len(_FIELDS)
        self.rows = []
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, _FIELDS)], schema=pa.schema(_FIELDS))


def pack(docs: DataFrame, tokenizer: str, key: str = "doc_id", text: str = "text", capacity: int = 2048, end_id: int = 1, with_ids: bool = False) -> DataFrame:
    """One row for each piece: where it is cut from, and its sequence and offset there.

    `tokenizer` is a tokenizer file that workers can open, of a kind that does
    not join words across white space. A document's ids are those of its whole
    text, then end_id; null and empty texts give end_id alone. Every id lies in
    exactly one piece. A sequence holds at most `capacity` ids, and only the
    last one of a worker may be far from full. `ids_crc32` is taken over the
    piece's ids as little-endian 32-bit numbers; `ids` is null unless asked for.

    Repeated rows are packed as often as they occur; a null id stays null. An
    empty table gives no rows; other columns are not read. Nothing is
    shuffled, and memory holds one slice of texts and less than one sequence
    for each class.
    """
    table = {r: cuts(r, capacity) for r in range(1, capacity)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = wordpieces.encoder(tokenizer)
        bins = _Bins(capacity, TaskContext.get().partitionId() << 40, with_ids)
        for batch in batches:
            raw, off = textnum.buffers(batch.column(1))
            for lo, hi in wordpieces.slices(off):
                ids, begin = encode.encode(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], end_id)
                ids = ids.astype("<u4")
                for doc, a, b in zip(batch.column(0).slice(lo, hi - lo).to_pylist(), begin[:-1].tolist(), begin[1:].tolist()):
                    total, at = b - a, a
                    for _ in range(total // capacity):
                        bins.close([(doc, at - a, ids[at : at + capacity], total)])
                        at += capacity
                    for size in table.get(b - at, ()):
                        bins.add(doc, at - a, ids[at : at + size], total)
                        at += size
                del ids, begin
                textnum.settle(keep=True)
                if len(bins.rows) >= 20_000 or with_ids:
                    yield bins.take()
            del batch, raw, off
            textnum.settle(keep=True)
        bins.chain()
        yield bins.take()

    return docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text")).mapInArrow(run, SCHEMA)
