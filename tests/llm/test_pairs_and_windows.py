"""Repeated windows and similarity classes against brute force."""

from __future__ import annotations

import collections
import random
import re

import pytest

from eigenlake.llm import jaccard, links, substrings

SCHEMA = "doc_id long, text string"


def corpus(seed: int, n: int = 60) -> list[tuple]:
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(400)] + ["Über", "É", "x" * 50]
    passage = [rng.choice(vocabulary) for _ in range(30)]
    out = []
    for d in range(n):
        words = [rng.choice(vocabulary) for _ in range(rng.choice([0, 1, 3, 4, 5, 25, 60, 120]))]
        if d % 3 == 0:
            at = rng.randrange(len(words) + 1)
            words[at:at] = passage
        if d % 4 == 1 and out:
            words = list(re.findall(r"\S+", out[rng.randrange(len(out))][1] or ""))
            for _ in range(len(words) // 60):
                words[rng.randrange(len(words))] = rng.choice(vocabulary)
        out.append((d, rng.choice([" ", "\n", "\t  "]).join(words)))
    rng.shuffle(out)
    return [*out, (n, None), (n + 1, ""), (n + 2, " \n ")]


def removed(rows: list[tuple], window: int) -> dict[int, tuple[int, str]]:
    first, out = {}, {}
    for d, t in sorted(rows):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        gone = set()
        for k in range(len(w) - window + 1):
            if first.setdefault(tuple(w[k : k + window]), (d, k)) != (d, k):
                gone |= set(range(k, k + window))
        out[d] = (len(gone), " ".join(x for k, x in enumerate(w) if k not in gone))
    return out


@pytest.mark.parametrize("seed,window", [(1, 20), (2, 6)])
def test_windows_match_brute_force(spark, seed, window):
    rows = corpus(seed)
    got = substrings.drop_repeats(spark.createDataFrame(rows, SCHEMA), window=window).collect()
    assert {r.doc_id: (r.n_removed, r.kept) for r in got} == removed(rows, window)
    for r in got:
        assert sum(s.last - s.first + 1 for s in r.spans) == r.n_removed


def test_windows_edges(spark):
    text = " ".join(f"a{k}" for k in range(25))
    long = " ".join(f"b{k % 5000}" for k in range(20_000))
    rows = [(1, text, "x"), (1, text, "x"), (2, text, "y"), (None, text.upper(), "z"), (3, long, "l")]
    df = spark.createDataFrame(rows, "doc_id long, text string, kept string")
    got = substrings.drop_repeats(df).collect()
    by = collections.defaultdict(list)
    for r in got:
        by[r.doc_id].append(r.n_removed)
    assert by == {1: [0, 0], 2: [25], None: [0], 3: [15_000]}
    assert substrings.drop_repeats(df.limit(0)).count() == 0


def shingles(text: str | None) -> frozenset:
    lower = (text or "").translate({c: c + 32 for c in range(65, 91)})
    w = re.findall(r"[^\x20\x09-\x0D]+", lower)
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def classes(rows: list[tuple]) -> dict[int, tuple[int, int]]:
    sets = {d: shingles(t) for d, t in rows}
    label = {d: d for d in sets}

    def root(d):
        while label[d] != d:
            d = label[d]
        return d

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                label[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), root(d)) for d in ids}


@pytest.mark.parametrize("seed,rare,chunk,group", [(3, 64, 256, 1 << 14), (4, 1, 256, 1 << 14), (5, 2, 4, 1 << 14), (5, 2, 4, 2), (6, 64, 4, 2)])
def test_classes_match_brute_force(spark, monkeypatch, seed, rare, chunk, group):
    monkeypatch.setattr(jaccard, "CHUNK", chunk)
    monkeypatch.setattr(jaccard, "GROUP", group)
    monkeypatch.setattr(jaccard, "PIVOTS", 2)
    rng = random.Random(seed)
    rows = corpus(seed, 50)
    base = [f"h{k}" for k in range(90)]
    for d in range(100, 130):
        words = list(base)
        for _ in range(rng.choice([0, 1, 2, 3, 6])):
            words[rng.randrange(90)] = f"n{d % 103}"
        rows.append((d, " ".join(words)))
    got = jaccard.similarity_classes(spark.createDataFrame(rows, SCHEMA), rare=rare).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == classes(rows)


def test_classes_edges(spark):
    text = "one two three four five six seven"
    rows = [(5, text, 1), (5, text, 1), (3, text.upper(), 2), (None, text, 3), (9, "one two", 4), (8, "One  two", 5), (7, None, 6), (6, "", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, component_id long")
    got = sorted((str(r.doc_id), r.n_shingles, r.component_id) for r in jaccard.similarity_classes(df).collect())
    assert got == [("3", 3, 3), ("5", 3, 3), ("5", 3, 3), ("6", 0, 6), ("7", 0, 7), ("8", 1, 8), ("9", 1, 8), ("None", 3, None)]
    assert jaccard.similarity_classes(df.limit(0)).count() == 0


def test_components_of_paths_and_stars(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 120)] + [(7, 7), (200, 199), (199, 200)]
    got = {r.v: r.comp for r in links.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(41)} | {k: 100 for k in range(100, 120)} | {199: 199, 200: 199}
    assert links.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_equal_texts_carry_their_shingles_once(spark):
    """Copies of a text are one class, and neither send nor carry what only they hold."""
    near = [f"n{k}" for k in range(60)]
    texts = [" ".join(f"{a}{k}" for k in range(60)) for a in "abc"] + [" ".join(near), " ".join([*near[:-1], "other"])]
    rows = [(100 * c + k, t) for c in range(12) for k, t in enumerate(texts)] + [(None, texts[0]), (7, texts[0]), (7, texts[0])]
    df = spark.createDataFrame(rows, SCHEMA).repartition(5)
    found = jaccard._survivors(df, "doc_id", "text", 5, 75).collect()
    assert sorted(r.doc_id for r in found if r.tokens is not None) == [3, 4]
    assert all(r.kept for r in found if r.doc_id is not None) and len(found) == len(rows)
    got = {(r.doc_id, r.component_id) for r in jaccard.similarity_classes(df).collect()}
    assert got == {(100 * c + k, min(k, 3)) for c in range(12) for k in range(5)} | {(7, 0), (None, None)}
