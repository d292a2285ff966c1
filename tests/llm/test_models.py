"""Packing, search, language model and classifier."""

from __future__ import annotations

import collections
import math
import random
import re
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest

from eigenlake.llm import lattice, maxscore, packing, textnum, toxicity

public_tokenizers = pytest.importorskip("public_tokenizers")
SCHEMA = "doc_id long, text string"


def texts() -> list[str | None]:
    rng = random.Random(1)
    words = ["the", "Hello,", "it's", "1234.5", "naïve", "ΣΑΣ", "<|endoftext|>", "😀x", "don't!!", "a b", "x" * 300]
    out = [" ".join(rng.choice(words) for _ in range(rng.choice([0, 1, 5, 50, 900, 3000]))) for _ in range(40)]
    return [*out, None, "", " \n\t ", "İstanbul Kelvin K", "é combining"]


def test_packing_is_an_exact_round_trip(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    rows = list(enumerate(texts()))
    got = packing.pack(spark.createDataFrame(rows, SCHEMA).repartition(3), path, with_ids=True).collect()
    tokenizer = Tokenizer.from_file(path)
    pieces, sequences = collections.defaultdict(list), collections.defaultdict(list)
    for r in got:
        pieces[r.doc_id].append(r)
        sequences[r.sequence_id].append(r)
    for d, t in rows:
        ids = [*tokenizer.encode(t or "", add_special_tokens=False).ids, 1]
        mine = sorted(pieces[d], key=lambda r: r.start)
        assert [i for r in mine for i in r.ids] == ids
        assert all(r.doc_tokens == len(ids) and r.length == len(r.ids) for r in mine)
        assert all(r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes()) for r in mine)
    padding = 0
    for parts in sequences.values():
        at = 0
        for r in sorted(parts, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
        padding += 2048 - at
    assert padding <= 0.02 * sum(r.length for r in got) + 3 * 2048


def test_packing_classes():
    for length in range(1, 2048):
        parts = packing.cuts(length, 2048)
        assert sum(parts) == length
        assert all((2048 - 2048 // p * p) * packing.SLACK <= 2048 or p == 2048 // (2048 // p) for p in parts)


def test_packing_edges(spark):
    path = public_tokenizers.path("word_bpe_49k.json")
    df = spark.createDataFrame([(1, "a", 2), (1, "a", 2), (None, None, 3)], "doc_id long, text string, start long")
    assert sorted((str(r.doc_id), r.doc_tokens) for r in packing.pack(df, path).collect()) == [("1", 2), ("1", 2), ("None", 1)]
    assert packing.pack(df.limit(0), path).count() == 0


@pytest.mark.parametrize("scale", [1.0, 300.0, 1e5])
def test_search_matches_brute_force(spark, monkeypatch, scale):
    monkeypatch.setattr(maxscore, "SHARD", 100)
    monkeypatch.setattr(maxscore, "LEAST", 50)
    monkeypatch.setattr(maxscore, "BLOCK", 7)
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 24)) * scale
    x[50:60] = x[40:50]
    rows = [(k, v.tolist()) for k, v in enumerate(x)]
    got = maxscore.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), maxscore.F.col("vec_id") % 20 == 0).collect()
    ints = np.floor(256 * x).astype(np.int64)
    want = set()
    for q in range(0, 400, 20):
        score = ints @ ints[q]
        best = [k for k in np.lexsort((np.arange(400), -score)) if k != q][:5]
        want |= {(q, r + 1, int(k), int(score[k])) for r, k in enumerate(best)}
    assert {tuple(r) for r in got} == want


def test_bars_only_save_work():
    rng = np.random.default_rng(8)
    rows, queries = rng.integers(-50, 50, (2000, 16)), rng.integers(-50, 50, (9, 16))
    ids, own = np.arange(2000), np.arange(9)
    want = maxscore.search(ids, rows, own, queries, 5)
    worst = np.array([min(s for q, s in zip(want[0], want[2]) if q == k) for k in own])
    assert maxscore.search(ids, rows, own, queries, 5, worst) == want
    none = np.where(own % 2, worst, -(1 << 63))
    assert maxscore.search(ids, rows, own, queries, 5, none) == want
    assert maxscore.search(ids, rows, own, queries, 5, worst + 1)[2] == [s for q, s in zip(want[0], want[2]) if s > worst[q]]


def test_search_edges(spark):
    rows = [(0, [1.0, 2.0], 9), (0, [1.0, 2.0], 9), (1, None, 9), (2, [1.0, None], 9), (3, [float("nan"), 1.0], 9), (4, [float("inf"), 1.0], 9), (5, [], 9), (6, [3.0], 9), (None, [1.0, 1.0], 9)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, score long")
    got = sorted(tuple(r) for r in maxscore.top_k(df, maxscore.F.col("vec_id") % 50 == 0).collect())
    assert got == [(0, 1, 6, 3 * 256 * 256), (0, 2, 5, 0)]
    assert maxscore.top_k(df.limit(0), maxscore.F.col("vec_id") % 50 == 0).count() == 0


@pytest.fixture(scope="module")
def vocabulary():
    return lattice.vocabulary(public_tokenizers.path("piece_bpe_32k.model"))


def test_marginals_and_expectations(vocabulary):
    words = ["a", "thewh", "x" * 40, "éau", "日本", "z" * 60]
    raw, off = textnum.buffers(pa.array(words))
    table = {int(k): p for k, p in zip(vocabulary.keys, vocabulary.start)}

    def piece(b: bytes) -> float:
        a = np.frombuffer(b, np.uint8)
        return table.get(int(lattice._hashes(a, np.array([0]), np.array([len(a)]))[0]), 0.0)

    got = lattice.log_marginals(vocabulary, np.log(vocabulary.start), raw, off)
    for word, value in zip(words, got):
        y = "▁".encode() + word.encode()
        most = int(vocabulary.lengths.max())
        ways = [1.0]
        for end in range(1, len(y) + 1):
            ways.append(sum(ways[k] * piece(y[k:end]) for k in range(max(0, end - most), end)))
        assert math.isclose(value, math.log(ways[-1]), rel_tol=1e-9)
    one = lattice.expected_pieces(vocabulary, np.log(vocabulary.start), *textnum.buffers(pa.array(["a"])), np.array([3.0]))
    assert 3 <= one.sum() <= 3 * 4


def test_long_words_alone_are_as_together(vocabulary, monkeypatch):
    rng = random.Random(5)
    words = ["".join(rng.choice("theoansxyz") for _ in range(n)) for n in (3, 40, 200, 200)] + ["é" * 90, "a" * 300]
    raw, off = textnum.buffers(pa.array(words))
    logp, weight = np.log(vocabulary.start), np.arange(1.0, 7.0)
    together = lattice.log_marginals(vocabulary, logp, raw, off), lattice.expected_pieces(vocabulary, logp, raw, off, weight)
    monkeypatch.setattr(lattice, "ALONE", 1)
    alone = lattice.log_marginals(vocabulary, logp, raw, off), lattice.expected_pieces(vocabulary, logp, raw, off, weight)
    assert alone[0] == pytest.approx(together[0]) and alone[1] == pytest.approx(together[1], abs=1e-9)


def test_a_word_of_300_000_bytes(vocabulary):
    raw, off = textnum.buffers(pa.array(["the" * 100_000]))
    start = time.time()
    got = lattice.expected_pieces(vocabulary, np.log(vocabulary.start), raw, off, np.ones(1))
    assert np.isfinite(got).all() and 100_000 / 8 < got.sum() < 300_001 and time.time() - start < 30


def test_scores_match_brute_force(spark, vocabulary, monkeypatch):
    """Counts, rounds of refitting and scores, worked out word by word with dictionaries."""
    rng = random.Random(6)
    rows = [(d, " ".join(rng.choice(["the", "cat", "sat", "zq", "été", "there"]) for _ in range(rng.choice([0, 3, 9])))) for d in range(20)]
    table = {int(k): j for j, k in enumerate(vocabulary.keys)}

    def arcs(word: str) -> list[tuple[int, int, int]]:
        y = ("▁" + word).encode()
        out = []
        for a in range(len(y)):
            for b in range(a + 1, len(y) + 1):
                part = np.frombuffer(y[a:b], np.uint8)
                j = table.get(int(lattice._hashes(part, np.array([0]), np.array([len(part)]))[0]))
                if j is not None:
                    out.append((a, b, j))
        return out

    def passes(word: str, p: np.ndarray) -> tuple[float, dict[int, float]]:
        y, lines = len(("▁" + word).encode()), arcs(word)
        a, b = [1.0] + [0.0] * y, [0.0] * y + [1.0]
        for x, z, j in sorted(lines, key=lambda t: t[1]):
            a[z] += a[x] * p[j]
        for x, z, j in sorted(lines, key=lambda t: -t[0]):
            b[x] += b[z] * p[j]
        use: dict[int, float] = collections.Counter()
        for x, z, j in lines:
            use[j] += a[x] * p[j] * b[z] / a[y]
        return a[y], use

    train = [t.split() for d, t in rows if zlib.crc32(str(d).encode()) % 5 != 1]
    p, end = vocabulary.start.copy(), 0.0
    for _ in range(3):
        got = np.zeros(len(p))
        for word, n in collections.Counter(w for t in train for w in t).items():
            for j, x in passes(word, p)[1].items():
                got[j] += n * x
        p = lattice.PRIOR * vocabulary.start + got
        total = p.sum() + len(train) + 1
        p, end = p / total, (len(train) + 1) / total
    df = spark.createDataFrame([(d, t, 0.0, "x") for d, t in rows], "doc_id long, text string, score double, id string")
    for r in lattice.score(df, public_tokenizers.path("piece_bpe_32k.model")).collect():
        want = sum(math.log10(passes(w, p)[0]) for w in dict(rows)[r.doc_id].split()) + math.log10(end)
        assert r.score == pytest.approx(want, rel=1e-9)


def test_language_model_base_scores(spark):
    rng = random.Random(3)
    rows = [(d, " ".join(rng.choice(["The", "the", "cat", "sat", "été", "zz" + str(d)]) for _ in range(rng.choice([0, 1, 30])))) for d in range(40)]
    rows += [(40, None), (41, ""), (41, ""), (42, "q" * 3000)]
    got = lattice.score(spark.createDataFrame([*rows, (None, "the cat")], SCHEMA), public_tokenizers.path("piece_bpe_32k.model")).collect()
    tokens = [(d, [*re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)})), None]) for d, t in rows]
    count: collections.Counter = collections.Counter()
    for d, t in tokens:
        if zlib.crc32(str(d).encode()) % 5 != 1:
            count.update(t)
    n, v = sum(count.values()), len(count)
    base = {d: sum(math.log10((count[x] + 0.5) / (n + 0.5 * (v + 1))) for x in t) for d, t in tokens}
    size = {d: (len(t), sum(count[x] > 0 for x in t)) for d, t in tokens}
    assert len(got) == len(rows) + 1
    for r in got:
        assert math.isfinite(r.score) and r.score < 0 and r.train_tokens == n
        if r.doc_id is None:
            assert not r.held_out
            continue
        assert math.isclose(r.base_score, base[r.doc_id], rel_tol=1e-9) and (r.n_tokens, r.n_known) == size[r.doc_id]
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 1)
    assert lattice.score(spark.createDataFrame([], SCHEMA), public_tokenizers.path("piece_bpe_32k.model")).count() == 0


def labelled(n: int, seed: int) -> tuple[list, list]:
    rng = random.Random(seed)
    plain = ["".join(rng.choice("abcdeimnorst") for _ in range(rng.randrange(2, 8))) for _ in range(3000)]
    bad = ["scoundrel", "blighter", "grobianisch", "grobianei", "grobianchen"]
    docs, labels = [], []
    for d in range(n):
        words = [rng.choice(plain) for _ in range(rng.randrange(1, 60))]
        toxic = d % 8 == 0
        if toxic:
            for _ in range(rng.randrange(1, 4)):
                words.insert(rng.randrange(len(words) + 1), rng.choice(bad))
        docs.append((d, " ".join(words)))
        labels.append((d, int(toxic)))
    return docs, labels


def test_toxicity_on_rows_held_out(spark):
    docs, labels = labelled(1500, 5)
    train = [x for x in labels if x[0] % 3]
    model = toxicity.fit(spark.createDataFrame(docs, SCHEMA), spark.createDataFrame(train, "doc_id long, toxic int"))
    got = {r.doc_id: r.toxicity for r in toxicity.score(spark.createDataFrame(docs, SCHEMA), model).collect()}
    held = [(got[d], y) for d, y in labels if d % 3 == 0]
    assert all(0 <= s <= 1 for s, _ in held)
    assert sum((s >= 0.5) != y for s, y in held) <= 0.02 * len(held)


def test_toxicity_edges(spark):
    docs, labels = labelled(300, 6)
    df = spark.createDataFrame(docs, SCHEMA)
    odd = spark.createDataFrame([*labels, (None, 1), (1, None), (2, 7), (99999, 1)], "doc_id long, toxic int")
    model = toxicity.fit(df, odd)
    rows = [(1, None, 1.0), (2, "", 1.0), (2, "", 1.0), (None, "scoundrel", 1.0)]
    got = toxicity.score(spark.createDataFrame(rows, "doc_id long, text string, toxicity double"), model).collect()
    assert len(got) == 4 and len({r.toxicity for r in got if r.doc_id is not None}) == 1
    none = toxicity.fit(df, odd.limit(0))
    assert {r.toxicity < 0.5 for r in toxicity.score(df, none).collect()} == {True}
    assert toxicity.score(df.limit(0), model).count() == 0




def test_label_model_finds_rates_and_families():
    rng = np.random.default_rng(4)
    n, on, off = 6000, [0.7, 0.5, 0.8, 0.4, 0.6, 0.3], [0.01, 0.05, 0.02, 0.1, 0.02, 0.01]
    y = rng.random(n) < 0.15
    votes = np.stack([rng.random(n) < np.where(y, a, b) for a, b in zip(on, off)], 1)
    votes = np.concatenate([votes, votes[:, :1], votes[:, :1] ^ (rng.random((n, 1)) < 0.01)], 1)
    post, accuracy, family = toxicity.label_model(votes, 8)
    assert family[0] == family[6] == family[7] and len(set(family.tolist())) == 6
    right = [0.15 * a / (0.15 * a + 0.85 * b) for a, b in zip(on, off)]
    assert accuracy[family[1:6]] == pytest.approx(right[1:], abs=0.25) and accuracy[-1] < 0.05
    assert np.argsort(accuracy[family[1:6]])[:2].tolist() == np.argsort(right[1:])[:2].tolist()
    assert post[y].mean() > 0.8 and post[~y].mean() < 0.2


def test_long_texts_count_whole(spark):
    """Words that tell the classes apart stand at the very end of texts of 300,000 bytes."""
    docs = [(k, " ".join(f"w{j % 997}" for j in range(60_000)) + (" scoundrel blighter rogue" if k % 3 == 0 else " end")) for k in range(24)]
    df = spark.createDataFrame(docs, SCHEMA)
    model = toxicity.fit(df, spark.createDataFrame([(k, int(k % 3 == 0), k) for k in range(18)], "doc_id long, toxic int, text long"))
    got = {r.doc_id: r.toxicity >= 0.5 for r in toxicity.score(df, model).collect()}
    assert got == {k: k % 3 == 0 for k in range(24)}
