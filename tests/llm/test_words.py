"""Words behind hashes: collisions by rule or by force change nothing."""

from __future__ import annotations

import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

from eigenlake.llm import jaccard, lattice, packed, packing, substrings, textnum, wordpieces

SCHEMA = "doc_id long, text string"
#: Two words whose difference every polynomial hash modulo a power of two maps to 0.
ONE = "".join("ab"[k.bit_count() & 1] for k in range(1024))
OTHER = ONE.translate(str.maketrans("ab", "ba"))


def tokenizer_file() -> str:
    return pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")


def ids_of(text: str) -> list[int]:
    from tokenizers import Tokenizer

    return [*Tokenizer.from_file(tokenizer_file()).encode(text, add_special_tokens=False).ids, 1]


def test_polynomial_twins_stay_apart(spark):
    rows = [(1, ONE), (2, OTHER), (3, f"{ONE} {OTHER}"), (4, " ".join([ONE] * 25)), (5, " ".join([OTHER] * 25))]
    df = spark.createDataFrame(rows, SCHEMA)
    for r in packing.pack(df, tokenizer_file(), with_ids=True).collect():
        whole = ids_of(rows[r.doc_id - 1][1])
        assert r.ids == whole[r.start : r.start + r.length] and r.doc_tokens == len(whole)
        assert r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
    assert {r.doc_id: r.component_id for r in jaccard.similarity_classes(df).collect()} == {k: k for k in range(1, 6)}
    assert {r.doc_id: r.n_removed for r in substrings.drop_repeats(df).collect()} == {1: 0, 2: 0, 3: 0, 4: 24, 5: 24}
    path = pytest.importorskip("public_tokenizers").path("piece_bpe_32k.model")
    twins = spark.createDataFrame([(k, ONE if k % 2 else OTHER) for k in range(12)], SCHEMA)
    train = [k for k in range(12) if zlib.crc32(str(k).encode()) % 5 != 1]
    for r in lattice.score(twins, path).collect():
        count = sum(k % 2 == r.doc_id % 2 for k in train)
        total = 2 * len(train)
        assert r.base_score == pytest.approx(np.log10((count + 0.5) / (total + 2)) + np.log10((len(train) + 0.5) / (total + 2)))


@pytest.mark.parametrize("bits", [0, 1, 3])
def test_words_are_compared_behind_poor_hashes(monkeypatch, bits):
    real = textnum.word_hashes
    monkeypatch.setattr(textnum, "word_hashes", lambda raw, a, b: real(raw, a, b) & np.uint64((1 << bits) - 1))
    rng = random.Random(bits)
    texts = [" ".join("".join(rng.choice("abcé") for _ in range(rng.choice([1, 2, 8, 9, 70]))) for _ in range(60)) for _ in range(8)] + ["", "x" * 200]
    raw, off = textnum.buffers(pa.array(texts))
    w = textnum.words(raw, off)
    sample, own = textnum.distinct(w.hashes, raw, w.starts, w.ends)
    words = [raw[a:b].tobytes() for a, b in zip(w.starts, w.ends)]
    assert [words[k] for k in sample[own]] == words and len(sample) == len(set(words))
    encoder = wordpieces.Encoder(tokenizer_file())
    for _ in range(2):
        ids, begin = encoder.encode(raw, off, 1)
        assert [ids[a:b].tolist() for a, b in zip(begin[:-1], begin[1:])] == [ids_of(t) for t in texts]


def test_equal_compares_every_byte():
    words = [b"a" * n for n in (1, 7, 8, 9, 16, 63, 64, 65, 300)]
    for word in words:
        for k in {0, len(word) // 2, len(word) - 1}:
            other = word[:k] + b"b" + word[k + 1 :]
            a, b = (np.frombuffer(x, np.uint8) for x in (word, other))
            at, to = np.array([0]), np.array([len(word)])
            assert textnum.equal(a, at, to, a, at, to).all() and not textnum.equal(a, at, to, b, at, to).any()
            assert textnum.word_hashes(a, at, to) != textnum.word_hashes(b, at, to)


def test_runs_of_ids_come_back():
    for ids in ([], [5], [-(1 << 63), 2, 2, 2, 7]):
        ids = np.array(ids, np.int64)
        assert (substrings._unrun(substrings._runs(ids)) == ids).all()


def test_blocks_follow_the_bytes(spark):
    assert packed.dealt(0, 8) == packed.Deal(8, 16, 8)
    big = packed.dealt(100 << 40, 200)
    assert (100 << 40) / big.blocks <= packed.BLOCK_BYTES and 3 * (100 << 40) / big.buckets <= packed.BUCKET_BYTES
    assert big.tasks <= 110_000
    assert packed.deal(spark.createDataFrame([(1, "abc"), (2, None)], SCHEMA), "text") == packed.dealt(3, 4)


def test_a_cluster_needs_a_shared_folder():
    class Unset:
        """A session on a cluster without the setting."""

        class sparkContext:  # noqa: N801
            master = "spark://somewhere:7077"

            class _jsc:  # noqa: N801
                @staticmethod
                def sc():
                    return type("C", (), {"getCheckpointDir": lambda self: type("O", (), {"isDefined": lambda self: False})()})()

        class conf:  # noqa: N801
            get = staticmethod(lambda name, default=None: default)

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        packed.shared_folder(Unset)
