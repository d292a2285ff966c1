"""Words, shingles and windows of many documents at once, as NumPy arrays.

A document column arrives as one byte buffer with offsets (the Arrow layout).
A word's 64-bit hash is a chain of scrambled 8-byte lanes, which no rule of
writing makes collide; `distinct` and `equal` compare the words' own bytes.
Hashes of word windows come from prefix sums of a polynomial over the words'
hashes. No Python object exists per word.
"""

from __future__ import annotations

import contextlib
import ctypes

import numpy as np
import pyarrow as pa
import xxhash


#: What a worker keeps from task to task; it goes when the worker turns to other work.
KEPT: list[dict] = []


def settle(keep: bool = False) -> None:
    """Give memory that is free back to the system: workers live on between tasks, and several share an executor.

    Unless told to keep it, what work of another kind has left in KEPT goes too.
    """
    for held in () if keep else KEPT:
        held.clear()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


with contextlib.suppress(OSError, AttributeError):
    # Fixed value: M_MMAP_THRESHOLD of the C library. Set, it no longer grows, so arrays over 16 MB go back when freed.
    ctypes.CDLL(None).mallopt(-3, 1 << 24)

#: Bytes of text handled at once; bounds the 8-byte-per-character temporaries.
CHUNK = 1 << 20

_WHITE = np.zeros(256, bool)
_WHITE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20

_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_CODE = mix(np.arange(1, 257, dtype=np.uint64))
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n of the base and of its inverse modulo 2**64."""
    if len(_powers[0]) <= n:
        for k, b in enumerate((_BASE, _INVERSE)):
            step = np.full(n + 1, b, np.uint64)
            step[0] = 1
            _powers[k] = np.cumprod(step)
    return _powers[0], _powers[1]


def _spans(values: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Polynomial hashes of values[first:last], equal for equal contents wherever they stand."""
    up, down = _power(len(values) + 1)
    total = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * up[: len(values)], out=total[1:])
    return (total[last] - total[first]) * down[first]


#: Lanes of 8 bytes by which a word is hashed and compared; longer words, which are few, go one by one.
LANES = 8
_STEP = np.uint64(0xD6E8FEB86659FD93)
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def lanes(raw: np.ndarray) -> np.ndarray:
    """The 8 bytes from each place on as one number; zeros follow the end."""
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    return np.ndarray((len(raw) + 1,), "<u8", padded, strides=(1,))


def lane(view: np.ndarray, starts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The first `size` bytes (up to 8) from each start."""
    return view[starts] & _MASK[np.minimum(size, 8)]


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    view, size = lanes(raw), ends - starts
    h = mix(lane(view, starts, size) + size.astype(np.uint64) * _STEP)
    some = np.flatnonzero(size > 8)
    for k in range(1, LANES):
        if not len(some):
            break
        h[some] = mix(h[some] * _STEP + lane(view, starts[some] + 8 * k, size[some] - 8 * k))
        some = some[size[some] > 8 * (k + 1)]
    for i in np.flatnonzero(size > 8 * LANES).tolist():
        h[i] = xxhash.xxh3_64_intdigest(raw[starts[i] : ends[i]].tobytes())
    return h


def equal(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, other: np.ndarray, starts2: np.ndarray, ends2: np.ndarray) -> np.ndarray:
    """Whether the i-th word of one buffer has the bytes of the i-th word of the other."""
    size = ends - starts
    out = size == ends2 - starts2
    view = lanes(raw)
    view2 = view if other is raw else lanes(other)
    some = np.flatnonzero(out)
    for k in range(LANES):
        if not len(some):
            break
        left = size[some] - 8 * k
        same = lane(view, starts[some] + 8 * k, left) == lane(view2, starts2[some] + 8 * k, left)
        out[some[~same]] = False
        some = some[same & (left > 8)]
    for i in some.tolist():
        out[i] = raw[starts[i] : ends[i]].tobytes() == other[starts2[i] : ends2[i]].tobytes()
    return out


def distinct(hashes: np.ndarray, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One word of each kind, in the order of their hashes, and the kind of every word; words with one hash are compared."""
    _, sample, own = np.unique(hashes, return_index=True, return_inverse=True)
    apart = np.flatnonzero(~equal(raw, starts, ends, raw, starts[sample][own], ends[sample][own]))
    if len(apart):
        kinds: dict[bytes, int] = {}
        more = []
        for i in apart.tolist():
            word = raw[starts[i] : ends[i]].tobytes()
            if word not in kinds:
                kinds[word] = len(sample) + len(more)
                more.append(i)
            own[i] = kinds[word]
        sample = np.concatenate([sample, more])
    return sample, own


class Words:
    """The words of consecutive documents: hash of each, and where each document's words begin."""

    def __init__(self, hashes: np.ndarray, first: np.ndarray, starts: np.ndarray, ends: np.ndarray):
        self.hashes, self.first, self.starts, self.ends = hashes, first, starts, ends

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def windows(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all n-word windows inside a document, and each window's first word."""
        at = np.arange(max(len(self.hashes) - n + 1, 0))
        if len(at):
            after = np.repeat(self.first[1:], self.counts)[: len(at)]
            at = at[at + n <= after]
        return mix(_spans(self.hashes, at, at + n) + np.uint64(n)), at

    def checks(self, n: int, at: np.ndarray) -> np.ndarray:
        """16 further bits of the n-word windows at these places, apart from those of `windows`."""
        return (mix(_spans(mix(self.hashes ^ _STEP), at, at + n)) >> np.uint64(48)).astype(np.uint16)


def buffers(column: pa.ChunkedArray | pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and document offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    off = np.frombuffer(column.buffers()[1], wide)[column.offset : column.offset + len(column) + 1].astype(np.int64) if len(column) else np.zeros(1, np.int64)
    data = column.buffers()[2] if len(column) else None
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def _words(raw: np.ndarray, off: np.ndarray, lower: bool, stop: np.ndarray) -> Words:
    n = len(raw)
    if not n:
        none = np.zeros(0, np.int64)
        return Words(np.zeros(0, np.uint64), np.zeros(len(off), np.int64), none, none)
    ink = ~stop[raw]
    edge = np.zeros(n + 1, bool)
    edge[off] = True
    before = np.empty(n, bool)
    before[0], before[1:] = False, ink[:-1]
    starts = np.flatnonzero(ink & (~before | edge[:n]))
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, ink[1:]
    ends = np.flatnonzero(ink & (~after | edge[1:])) + 1
    return Words(word_hashes(_LOWER[raw] if lower else raw, starts, ends), np.searchsorted(starts, off), starts, ends)


def words(raw: np.ndarray, off: np.ndarray, lower: bool = False, stop: np.ndarray = _WHITE) -> Words:
    """All words between stop bytes (white space unless told otherwise), chunk by chunk."""
    parts, at = [], 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + CHUNK, "right")) - 1)
        parts.append((_words(raw[off[at] : off[to]], off[at : to + 1] - off[at], lower, stop), off[at]))
        at = to
    if not parts:
        return _words(raw[:0], np.zeros(1, np.int64), lower, stop)
    shift = np.cumsum([0, *(len(p.hashes) for p, _ in parts)])
    return Words(
        np.concatenate([p.hashes for p, _ in parts]),
        np.concatenate([np.zeros(1, np.int64), *(p.first[1:] + s for (p, _), s in zip(parts, shift))]),
        np.concatenate([p.starts + o for p, o in parts]),
        np.concatenate([p.ends + o for p, o in parts]),
    )
