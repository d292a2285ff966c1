"""Removal of repeated token windows (Rabin-Karp hashes counted in Spark).

Windows are the same if 80 bits agree: the 64-bit Rabin-Karp hash by which they
meet and 16 bits of a second one. Among 1e13 different windows some forty pairs
are expected to agree by chance (1e26 / 2 / 2**80), among 1e12 none.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import packed, textnum

SCHEMA = "doc_id long, n_words long, n_removed long, spans array<struct<first:long,last:long>>, kept string"
_SPAN = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))


def _ids(table: pa.Table) -> np.ndarray:
    """Ids for comparing; a null id comes before all others."""
    return table.column("id").fill_null(-(1 << 63)).to_numpy()


def _runs(ids: np.ndarray) -> bytes:
    """Ascending ids as how many differ, those, and how often each comes."""
    new = np.flatnonzero(np.concatenate([np.ones(min(1, len(ids)), bool), ids[1:] != ids[:-1]]))
    often = np.diff(np.concatenate([new, [len(ids)]])).astype(np.int32)
    return np.int64(len(new)).tobytes() + ids[new].tobytes() + often.tobytes()


def _unrun(raw: bytes) -> np.ndarray:
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    return np.repeat(np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.int32, n, 8 + 8 * n))


def _windows(table: pa.Table, n: int) -> tuple:
    """Distinct windows of a block in order of first place, and each window's group and place."""
    raw, off = textnum.buffers(table.column("text"))
    w = textnum.words(raw, off)
    h, at = w.windows(n)
    doc = np.repeat(np.arange(table.num_rows), w.counts)[at]
    ids = _ids(table)[doc]
    start = at - w.first[doc]
    more = w.checks(n, at)
    _, first, group = np.unique(h, return_index=True, return_inverse=True)
    if (more != more[first][group]).any():
        _, first, group = np.unique(np.stack([h, more.astype(np.uint64)], 1), axis=0, return_index=True, return_inverse=True)
    by_place = np.argsort(first)
    rank = np.empty(len(first), np.int64)
    rank[by_place] = np.arange(len(first))
    return raw, off, w, h, more, at, ids, start, first[by_place], rank[group]


def drop_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = 20) -> DataFrame:
    """Remove every word that a window which also starts earlier covers.

    Words stand between the six ASCII white-space characters; a window is
    `window` consecutive words of one document; earlier means a smaller id, or
    the same document and an earlier start. All windows are judged on the
    input. Touching windows merge, so `spans` holds maximal intervals of
    removed words (first and last, from 0), and `kept` the other words joined
    by single spaces.

    Null or empty texts and texts shorter than a window keep all they have. A
    null id comes before all others. Rows that repeat an id and its text count
    as one document, so neither copy removes the other; texts that share an
    id but differ do not remove each other's words across blocks. An
    empty table gives no rows; other columns are not read.
    """
    by = packed.deal(docs, text)
    buckets = by.buckets
    parts = packed.blocks(docs, key, text, by)

    def emit(group: tuple, table: pa.Table) -> pa.Table:
        *_, h, more, _, ids, _, first, _ = _windows(packed.ordered(table), window)
        out = packed.send(group[0].as_py(), h[first], buckets, more=more[first], ids=ids[first])
        out["ids"] = [_runs(np.frombuffer(x, np.int64)) for x in out["ids"]]
        return pa.table(out, _SENT)

    def judge(table: pa.Table) -> pa.Table:
        keys, more, at = packed.gathered(table, "keys", np.uint64), packed.gathered(table, "more", np.uint16), packed.bounds(table)
        ids = np.concatenate([np.zeros(0, np.int64), *map(_unrun, table.column("ids").to_pylist())])
        order = np.argsort(keys)
        same = keys[order[1:]] == keys[order[:-1]]
        if (same & (more[order[1:]] != more[order[:-1]])).any():
            order = np.lexsort((more, keys))
            same = (keys[order[1:]] == keys[order[:-1]]) & (more[order[1:]] == more[order[:-1]])
        late = np.zeros(len(keys), np.bool_)
        if same.any():
            met = np.zeros(len(keys), bool)
            met[1:] |= same
            met[:-1] |= same
            few = order[met]
            few = few[np.lexsort((ids[few], more[few], keys[few]))]
            head = np.concatenate([[True], (keys[few[1:]] != keys[few[:-1]]) | (more[few[1:]] != more[few[:-1]])])
            least = ids[few[np.flatnonzero(head)]][np.cumsum(head) - 1]
            late[few] = ids[few] > least
        return packed.reply(table, at, answer=late)

    def apply(group: tuple, table: pa.Table, said: pa.Table) -> pa.Table:
        table = packed.ordered(table)
        raw, off, w, h, _, at, ids, start, first, own = _windows(table, window)
        late = packed.answers(said, len(first), h[first], buckets, np.bool_)
        gone = late[own] | (ids != ids[first][own]) | (start != start[first][own])
        step = np.zeros(len(w.hashes) + 1, np.int32)
        np.add.at(step, at[gone], 1)
        np.add.at(step, at[gone] + window, -1)
        lost = np.cumsum(step[:-1]) > 0
        data, kept, spans, n_removed = raw.tobytes(), [], [], []
        sums = np.concatenate([[0], np.cumsum(lost)])
        for d in range(table.num_rows):
            lo, hi = w.first[d], w.first[d + 1]
            pieces = data[off[d] : off[d + 1]].split()
            n = int(sums[hi] - sums[lo])
            n_removed.append(n)
            if n:
                mask = lost[lo:hi]
                turn = np.flatnonzero(np.diff(np.concatenate([[0], mask.astype(np.int8), [0]])))
                spans.append([{"first": int(a), "last": int(b) - 1} for a, b in zip(turn[::2], turn[1::2])])
                pieces = list(itertools.compress(pieces, ~mask))
            else:
                spans.append([])
            kept.append(b" ".join(pieces))
        return pa.table(
            {
                "doc_id": table.column("id"),
                "n_words": pa.array(w.counts, pa.int64()),
                "n_removed": pa.array(n_removed, pa.int64()),
                "spans": pa.array(spans, _SPAN),
                "kept": pa.array(kept, pa.binary()).cast(pa.string()),
            }
        )

    _SENT = pa.schema([("block", pa.int32()), ("bucket", pa.int32()), ("keys", pa.binary()), ("more", pa.binary()), ("ids", pa.binary())])
    sent = parts.groupBy("block").applyInArrow(emit, "block int, bucket int, keys binary, more binary, ids binary")
    said = packed.meet(sent, by, judge, "block int, bucket int, answer binary")
    return parts.groupBy("block").cogroup(said.groupBy("block")).applyInArrow(apply, SCHEMA)
