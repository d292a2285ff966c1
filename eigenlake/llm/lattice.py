"""Language-model scores from a subword lattice.

The vocabulary of a public subword tokenizer, with its own scores, weights
every way to cut a text into pieces. A text's probability is the sum over all
of them, times that of the end; since pieces do not cross white space it is a
product over words, so each distinct word of the corpus is worked out once.
A few rounds of expected counts over the training texts refit the pieces'
probabilities, starting from the vocabulary's scores.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packed, textnum

#: Words worked on together, bytes from which fewer are, and weight of the vocabulary's own scores.
BATCH, LONG, PRIOR = 8192, 96, 1000.0
#: Bytes from which a word is worked on alone, arc after arc: some twenty arcs a byte and a microsecond for each.
ALONE = 1024
#: Parts in which sums over pieces travel, and the least number of turns in which they are added up.
PARTS = 16

_U = np.uint64
_MARK = "▁".encode()


class Vocabulary:
    """Pieces of a sentencepiece model as bytes, and their starting log probabilities.

    Scores that already are log probabilities are taken as such; those of a
    merge-based vocabulary are ranks, from which Zipf's law gives them. The
    number after the last piece stands for the end of a text.
    """

    def __init__(self, path: str):
        from sentencepiece import SentencePieceProcessor

        sp = SentencePieceProcessor(model_file=path)
        texts, scores = [], []
        for k in range(sp.get_piece_size()):
            if sp.is_control(k) or sp.is_unknown(k) or sp.is_unused(k):
                continue
            piece = sp.id_to_piece(k)
            texts.append(bytes([int(piece[3:5], 16)]) if sp.is_byte(k) else piece.encode())
            scores.append(sp.get_score(k))
        scores = np.array(scores)
        if not 0.5 < np.exp(np.minimum(scores, 50)).sum() < 2:
            scores = -np.log(2.0 + np.maximum(0, -scores))
        raw, off = textnum.buffers(pa.array(texts, pa.binary()))
        keys = _hashes(raw, off[:-1], off[1:])
        order = np.lexsort((-scores, keys))
        order = order[np.concatenate([[True], keys[order[1:]] != keys[order[:-1]]])]
        self.keys, size = keys[order], np.diff(off)[order]
        self.lengths = np.unique(size)
        self.start = np.exp(scores[order])
        self.start /= self.start.sum()
        self.bits = np.zeros(1 << 20, bool)
        self.bits[self.keys >> _U(44)] = True

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in h that are pieces, and which."""
        at = np.flatnonzero(self.bits[h >> _U(44)])
        k = np.minimum(np.searchsorted(self.keys, h[at]), len(self.keys) - 1)
        hit = self.keys[k] == h[at]
        return at[hit], k[hit]


def _hashes(raw: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    return textnum.mix(textnum._spans(textnum._CODE[raw], first, last) + (last - first).astype(_U))


_made: dict[str, Vocabulary] = {}


def vocabulary(path: str) -> Vocabulary:
    """This worker's copy of the vocabulary at path."""
    if path not in _made:
        _made[path] = Vocabulary(path)
    return _made[path]


class _Lattice:
    """Words of one length: the piece, if any, that ends at each byte with each length."""

    def __init__(self, vocab: Vocabulary, grid: np.ndarray):
        self.m, self.n = grid.shape
        code = textnum._CODE[grid]
        up, down = textnum._power(self.n + 1)
        total = np.zeros((self.m, self.n + 1), _U)
        np.cumsum(code * up[: self.n], axis=1, out=total[:, 1:])
        self.arcs: list[list[tuple[int, np.ndarray, np.ndarray]]] = [[] for _ in range(self.n + 1)]
        for size in vocab.lengths[vocab.lengths <= self.n].tolist():
            h = textnum.mix((total[:, size:] - total[:, :-size]) * down[: self.n + 1 - size] + _U(size))
            at, piece = vocab.find(h.ravel())
            row, begin = np.divmod(at, self.n + 1 - size)
            order = np.argsort(begin, kind="stable")
            row, begin, piece = row[order], begin[order], piece[order]
            bound = np.searchsorted(begin, np.arange(self.n + 2 - size))
            for b in np.flatnonzero(np.diff(bound)).tolist():
                self.arcs[b + size].append((b, row[bound[b] : bound[b + 1]], piece[bound[b] : bound[b + 1]]))

    def forward(self, logp: np.ndarray) -> np.ndarray:
        """Log probability of reaching each byte, summed over the ways there."""
        a = np.full((self.n + 1, self.m), -np.inf)
        a[0] = 0
        for end in range(1, self.n + 1):
            for begin, row, piece in self.arcs[end]:
                a[end, row] = np.logaddexp(a[end, row], a[begin, row] + logp[piece])
        return a

    def expected(self, logp: np.ndarray, weight: np.ndarray, into: np.ndarray) -> None:
        """Add the expected number of times that each piece is used in the words, counted with weights."""
        a = self.forward(logp)
        b = np.full((self.n + 1, self.m), -np.inf)
        b[self.n] = 0
        for end in range(self.n, 0, -1):
            for begin, row, piece in self.arcs[end]:
                way = logp[piece] + b[end, row]
                use = np.exp(a[begin, row] + way - a[self.n, row]) * weight[row]
                into += np.bincount(piece, np.nan_to_num(use), len(into))
                b[begin, row] = np.logaddexp(b[begin, row], way)


class _Long:
    """One long word: its arcs in the order of their ends, as plain numbers."""

    def __init__(self, vocab: Vocabulary, word: np.ndarray):
        self.n = len(word)
        ends, begins, pieces = [], [], []
        for lo in range(0, self.n, 1 << 16):  # hashes of so many bytes at a time, with what longer pieces need after them
            part = word[lo : lo + (1 << 16) + int(vocab.lengths[-1])]
            for size in vocab.lengths[vocab.lengths <= len(part)].tolist():
                begin = np.arange(min(1 << 16, len(part) - size + 1))
                at, piece = vocab.find(_hashes(part, begin, begin + size))
                ends.append(lo + at + size)
                begins.append(lo + at)
                pieces.append(piece)
        order = np.lexsort((np.concatenate(begins), np.concatenate(ends)))
        self.piece, self.begin = np.concatenate(pieces)[order], np.concatenate(begins)[order].tolist()
        self.bound = np.searchsorted(np.concatenate(ends)[order], np.arange(self.n + 2)).tolist()

    def _ways(self, logp: np.ndarray) -> list[float]:
        a, p, none = [0.0] * (self.n + 1), logp[self.piece].tolist(), -math.inf
        for end in range(1, self.n + 1):
            ways = [a[self.begin[k]] + p[k] for k in range(self.bound[end], self.bound[end + 1])]
            most = max(ways, default=none)
            a[end] = most + math.log(sum(math.exp(x - most) for x in ways)) if most > none else none
        return a

    def forward(self, logp: np.ndarray) -> np.ndarray:
        return np.array(self._ways(logp))[:, None]

    def expected(self, logp: np.ndarray, weight: np.ndarray, into: np.ndarray) -> None:
        a, p, none = self._ways(logp), logp[self.piece].tolist(), -math.inf
        b: list[float] = [none] * self.n + [0.0]
        use = [0.0] * len(p)
        for end in range(self.n, 0, -1):
            if b[end] == none:
                continue
            for k in range(self.bound[end], self.bound[end + 1]):
                at, way = self.begin[k], p[k] + b[end]
                use[k] = math.exp(a[at] + way - a[self.n]) if a[at] > none else 0.0
                high, low = (b[at], way) if b[at] > way else (way, b[at])
                b[at] = high + math.log1p(math.exp(low - high)) if low > none else high
        into += np.bincount(self.piece, np.array(use) * weight[0], len(into))


def _lattices(vocab: Vocabulary, raw: np.ndarray, off: np.ndarray) -> Iterator[tuple[np.ndarray, _Lattice | _Long]]:
    """Lattices of marked words by length, with the words' numbers."""
    size = np.diff(off)
    order = np.argsort(size, kind="stable")
    bound = np.flatnonzero(np.diff(size[order])) + 1
    for group in np.split(order, bound):
        if not len(group):
            continue
        n = int(size[group[0]])
        if n >= ALONE:
            for k in group:
                yield np.array([k]), _Long(vocab, np.concatenate([np.frombuffer(_MARK, np.uint8), raw[off[k] : off[k] + n]]))
            continue
        step = max(1, BATCH if n <= LONG else BATCH * LONG // (n * 4))
        for k in range(0, len(group), step):
            some = group[k : k + step]
            grid = np.empty((len(some), n + 3), np.uint8)
            grid[:, :3] = np.frombuffer(_MARK, np.uint8)
            grid[:, 3:] = raw[off[some][:, None] + np.arange(n)]
            yield some, _Lattice(vocab, grid)


def log_marginals(vocab: Vocabulary, logp: np.ndarray, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Natural log of each word's probability over all segmentations."""
    out = np.zeros(len(off) - 1)
    for some, lattice in _lattices(vocab, raw, off):
        out[some] = lattice.forward(logp)[-1]
    return out


def expected_pieces(vocab: Vocabulary, logp: np.ndarray, raw: np.ndarray, off: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """How often each piece is used in words that occur `weight` times, on average over their segmentations."""
    out = np.zeros(len(vocab.start))
    for some, lattice in _lattices(vocab, raw, off):
        lattice.expected(logp, weight[some], out)
    return out


def _split(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, starts and ends of words joined by line feeds, blob after blob."""
    raw = np.frombuffer(b"".join(b + b"\n" for b in blobs if b), np.uint8)
    ends = np.flatnonzero(raw == 0x0A)
    return raw, np.concatenate([[0], ends[:-1] + 1]).astype(np.int64)[: len(ends)], ends


def _gather(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The chosen words one after the other, and their offsets."""
    size = ends - starts
    off = np.concatenate([[0], np.cumsum(size)])
    return raw[np.repeat(starts - off[:-1], size) + np.arange(off[-1])], off


def _trains(ids: list, folds: int, held: int) -> np.ndarray:
    return np.array([x is not None and zlib.crc32(str(x).encode()) % folds != held for x in ids], bool)


def score(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text", folds: int = 5, held: int = 1, rounds: int = 3) -> DataFrame:
    """One row for every document with its base and lattice log10 probabilities.

    Tokens are words between ASCII white space (A-Z lower-cased) and one end.
    Learning uses the documents whose crc32 of the id as text leaves another
    remainder modulo `folds` than `held`; `held_out` marks the others.
    base_score adds log10((c + 0.5) / (N + 0.5 (V + 1))) over the tokens;
    score is the lattice's log10 probability of the whole text.

    Null and empty texts hold the end alone. Repeated rows count as often as
    they occur. A null id is neither learnt from nor held out. An empty table
    gives no rows; other columns are not read. With nothing to learn from,
    counts are 0 and the vocabulary's own scores are used. Columns of other
    names are not read, so names may clash. Words may be of any length: time
    and memory grow with their bytes (about ten microseconds and 300 bytes
    each); memory holds one block of texts and one bucket of words besides.
    """
    by = packed.deal(docs, text)
    buckets, turns = by.buckets, max(PARTS, math.isqrt(by.buckets))
    parts = packed.blocks(docs, key, text, by)

    def parse(table: pa.Table) -> tuple:
        raw, off = textnum.buffers(table.column("text"))
        raw = textnum._LOWER[raw]
        w = textnum.words(raw, off)
        sample, own = textnum.distinct(w.hashes, raw, w.starts, w.ends)
        return raw, w, w.hashes[sample], sample, own, _trains(table.column("id").to_pylist(), folds, held)

    def emit(group: tuple, table: pa.Table) -> pa.Table:
        block = group[0].as_py()
        raw, w, keys, sample, own, trains = parse(packed.ordered(table))
        count = np.bincount(own, np.repeat(trains, w.counts), len(keys)).astype(np.uint32)
        out = packed.send(block, keys, buckets, count=count)
        order, bound = packed.slots(keys, buckets)
        low = raw.tobytes()
        starts, ends = w.starts[sample[order]].tolist(), w.ends[sample[order]].tolist()
        out["words"] = [b"\n".join([low[a:b] for a, b in zip(starts[bound[k] : bound[k + 1]], ends[bound[k] : bound[k + 1]])]) for k in out["bucket"]]
        if not out["block"]:
            out = {"block": [block], "bucket": [0], "keys": [b""], "count": [b""], "words": [b""]}
        out["docs"] = [int(trains.sum()), *[0] * (len(out["block"]) - 1)]
        return pa.table(out, sent_as)

    def unify(table: pa.Table) -> tuple:
        raw, starts, ends = _split(table.column("words").to_pylist())
        sample, own = textnum.distinct(packed.gathered(table, "keys", _U), raw, starts, ends)
        total = np.bincount(own, packed.gathered(table, "count", np.uint32), len(sample))
        return own, total, *_gather(raw, starts[sample], ends[sample])

    def probabilities(vocab: Vocabulary, fitted: pa.Table) -> tuple[np.ndarray, np.ndarray, float]:
        """Counts known so far, log probabilities of the pieces, and that of the end."""
        got = [np.frombuffer(data) for _, data in sorted(zip(fitted.column("part").to_pylist(), fitted.column("data").to_pylist()))]
        p = PRIOR * vocab.start + np.concatenate(got[1:])
        scale = np.log(p.sum() + got[0][2] + 1)
        return got[0], np.log(p) - scale, float(np.log(got[0][2] + 1) - scale)

    def learn(table: pa.Table, fitted: pa.Table | None = None) -> pa.Table:
        if not table.num_rows:
            return pa.table({"turn": pa.array([], pa.int32()), "part": pa.array([], pa.int32()), "data": pa.array([], pa.binary())})
        _, total, raw, off = unify(table)
        vocab = vocabulary(model)
        known = np.flatnonzero(total)
        use = expected_pieces(vocab, np.log(vocab.start) if fitted is None else probabilities(vocab, fitted)[1], *_gather(raw, off[:-1][known], off[1:][known]), total[known])
        facts = np.array([total.sum(), len(known), sum(table.column("docs").to_pylist())], float)
        cuts = [facts, *np.array_split(use, PARTS)]
        turn = table.column("bucket")[0].as_py() % turns
        return pa.table({"turn": pa.array([turn] * len(cuts), pa.int32()), "part": pa.array(range(len(cuts)), pa.int32()), "data": pa.array([np.ascontiguousarray(c).tobytes() for c in cuts], pa.binary())})

    def fold(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table.column("turn").to_pylist(), table.column("data").to_pylist()))
        total = np.sum([np.frombuffer(data) for _, data in rows], 0)
        return pa.table({"turn": pa.array([rows[0][0]], pa.int32()), "part": table.column("part").slice(0, 1), "data": pa.array([total.tobytes()], pa.binary())})

    def judge(table: pa.Table, fitted: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.table({n: pa.array([], t) for n, t in said_as})
        own, total, raw, off = unify(table)
        vocab = vocabulary(model)
        (n_words, n_types, n_docs), logp, log_end = probabilities(vocab, fitted)
        logp = log_marginals(vocab, logp, raw, off)
        out = packed.reply(table, packed.bounds(table), count=total[own].astype(np.int64), logp=logp[own])
        n = len(out)
        const = {"n_train": n_words + n_docs, "n_types": n_types + (n_docs > 0), "n_docs": n_docs}
        for k, v in const.items():
            out = out.append_column(k, pa.array([int(v)] * n, pa.int64()))
        return out.append_column("log_end", pa.array([log_end] * n, pa.float64()))

    def apply(group: tuple, table: pa.Table, said: pa.Table) -> pa.Table:
        table = packed.ordered(table)
        _, w, keys, _, own, _ = parse(table)
        ids = table.column("id").to_pylist()
        count = packed.answers(said, len(keys), keys, buckets, np.int64, "count")[own]
        logp = packed.answers(said, len(keys), keys, buckets, np.float64, "logp")[own]
        n_train, n_types, n_docs = (said.column(k)[0].as_py() for k in ("n_train", "n_types", "n_docs"))
        doc, n = np.repeat(np.arange(len(ids)), w.counts), len(ids)
        tokens = w.counts + 1
        base = np.bincount(doc, np.log10(count + 0.5), n) + np.log10(n_docs + 0.5) - tokens * np.log10(n_train + 0.5 * (n_types + 1))
        return pa.table(
            {
                "doc_id": table.column("id"),
                "held_out": pa.array([x is not None and zlib.crc32(str(x).encode()) % folds == held for x in ids], pa.bool_()),
                "n_tokens": pa.array(tokens, pa.int64()),
                "n_known": pa.array(np.bincount(doc, count > 0, n).astype(np.int64) + (n_docs > 0), pa.int64()),
                "train_tokens": pa.array([n_train] * n, pa.int64()),
                "base_score": pa.array(base, pa.float64()),
                "score": pa.array((np.bincount(doc, logp, n) + said.column("log_end")[0].as_py()) / np.log(10), pa.float64()),
            }
        )

    said_as = [("block", pa.int32()), ("bucket", pa.int32()), ("count", pa.binary()), ("logp", pa.binary()), ("n_train", pa.int64()), ("n_types", pa.int64()), ("n_docs", pa.int64()), ("log_end", pa.float64())]
    sent_as = pa.schema([("block", pa.int32()), ("bucket", pa.int32()), ("keys", pa.binary()), ("count", pa.binary()), ("words", pa.binary()), ("docs", pa.int64())])
    sent = parts.groupBy("block").applyInArrow(emit, "block int, bucket int, keys binary, count binary, words binary, docs long").repartition(by.tasks, "bucket")
    sums = "turn int, part int, data binary"
    added = lambda parts: parts.groupBy("part", "turn").applyInArrow(fold, sums).groupBy("part").applyInArrow(fold, sums).select(F.explode(F.sequence(F.lit(0), F.lit(buckets - 1))).alias("bucket"), "part", "data")
    spread = added(sent.groupBy("bucket").applyInArrow(lambda table: learn(table), sums))
    for _ in range(1, rounds):
        spread = added(sent.groupBy("bucket").cogroup(spread.groupBy("bucket")).applyInArrow(lambda table, fitted: learn(table, fitted), sums))
    said = sent.groupBy("bucket").cogroup(spread.groupBy("bucket")).applyInArrow(judge, "block int, bucket int, count binary, logp binary, n_train long, n_types long, n_docs long, log_end double")
    return parts.groupBy("block").cogroup(said.groupBy("block")).applyInArrow(apply, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
