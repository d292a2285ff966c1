"""Token ids of whole documents through a cache of words.

A tokenizer whose pre-tokenisation never crosses white space gives a text the
ids of its words one after the other. Words repeat, so each worker encodes a
word once and the rest is array indexing. The cache is looked up by hash and
keeps the words' bytes, which are compared.
"""

from __future__ import annotations

import os

import numpy as np

from . import textnum

#: Words a worker remembers; when more come, it starts afresh.
CACHE_WORDS = 1_500_000
#: Words encoded at once: an encoding takes about a kilobyte until its ids are taken.
BATCH = 4096
#: Bytes of text whose ids are laid out at once.
SLICE = 2 << 20


class Encoder:
    """Ids of documents given as bytes and offsets."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self._forget()

    def _forget(self) -> None:
        self.keys, self.place = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.ids, self.first = np.zeros(0, np.int32), np.zeros(1, np.int64)
        self.raw, self.begin = np.zeros(0, np.uint8), np.zeros(1, np.int64)

    def _ids(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words one after the other, and where each word's ids begin."""
        ids, sizes = [np.zeros(0, np.int32)], [0]
        for at in range(0, len(words), BATCH):
            new = [e.ids for e in self.tokenizer.encode_batch_fast([x.decode("utf-8", "replace") for x in words[at : at + BATCH]], add_special_tokens=False)]
            sizes.extend(map(len, new))
            ids.append(np.fromiter((i for x in new for i in x), np.int32))
        return np.concatenate(ids), np.cumsum(sizes)

    def _learn(self, keys: np.ndarray, words: list[bytes]) -> None:
        ids, first = self._ids(words)
        place = np.arange(len(keys)) + len(self.first) - 1
        self.ids = np.concatenate([self.ids, ids])
        self.first = np.concatenate([self.first, first[1:] + self.first[-1]])
        self.raw = np.concatenate([self.raw, np.frombuffer(b"".join(words), np.uint8)])
        self.begin = np.concatenate([self.begin, np.cumsum([len(x) for x in words], dtype=np.int64) + self.begin[-1]])
        keys, place = np.concatenate([self.keys, keys]), np.concatenate([self.place, place])
        order = np.argsort(keys, kind="stable")
        self.keys, self.place = keys[order], place[order]

    def _find(self, keys: np.ndarray) -> np.ndarray:
        """Cache places of keys, -1 where unknown."""
        if not len(self.keys):
            return np.full(len(keys), -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, self.place[at], -1)

    def _known(self, raw: np.ndarray, w: textnum.Words, sample: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, where each known word's begin there, and the place among them of each word asked for."""
        keys, starts, ends = w.hashes[sample], w.starts[sample], w.ends[sample]
        place = self._find(keys)
        new = np.flatnonzero(place < 0)
        if len(new):
            if len(self.keys) + len(new) > CACHE_WORDS:
                self._forget()
                new = np.arange(len(keys))
            data = raw.tobytes()
            self._learn(keys[new], [data[a:b] for a, b in zip(starts[new].tolist(), ends[new].tolist())])
            place = self._find(keys)
        if textnum.equal(raw, starts, ends, self.raw, self.begin[place], self.begin[place + 1]).all():
            return self.ids, self.first, place
        return *self._ids([raw[a:b].tobytes() for a, b in zip(starts, ends)]), np.arange(len(keys))

    def encode(self, raw: np.ndarray, off: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all documents, each closed by end_id, and where each document's ids begin."""
        w = textnum.words(raw, off)
        sample, own = textnum.distinct(w.hashes, raw, w.starts, w.ends)
        ids, first, place = self._known(raw, w, sample)
        word = place[own]
        size = (first[1:] - first[:-1])[word]
        total = np.concatenate([[0], np.cumsum(size)])
        source = np.repeat(first[word] - total[:-1], size) + np.arange(total[-1])
        docs = np.arange(len(off) - 1)
        begin = total[w.first] + np.arange(len(off))
        out = np.full(begin[-1], end_id, np.int32)
        out[np.arange(total[-1]) + np.repeat(docs, np.diff(total[w.first]))] = ids[source]
        return out, begin


_made: dict[str, Encoder] = {}
textnum.KEPT.append(_made)


def encoder(path: str) -> Encoder:
    """This worker's encoder for the tokenizer file at path."""
    if path not in _made:
        _made[path] = Encoder(path)
    return _made[path]


def slices(off: np.ndarray) -> list[tuple[int, int]]:
    """Runs of documents of about SLICE bytes."""
    out, at = [], 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + SLICE, "right")) - 1)
        out.append((at, to))
        at = to
    return out
