"""The pipeline's stages against what they must keep, on a small corpus with planted cases."""

from __future__ import annotations

import random

import pytest

import corpus_pipeline

pytest.importorskip("public_tokenizers")

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(9)
    plain = ["".join(rng.choice("abcdeimnorst") for _ in range(rng.randrange(2, 8))) for _ in range(2000)]
    item = "How many of the 14 sailors on the ship had seen the island before the storm of that year began?"
    rows, labels = [], []
    for d in range(400):
        words = [rng.choice(plain) for _ in range(rng.randrange(20, 90))]
        toxic = d % 7 == 0
        if toxic:
            for _ in range(3):
                words.insert(rng.randrange(len(words)), rng.choice(["scoundrel", "blighter"]))
        if d % 50 == 3:
            words[10:10] = item.split()
        if d % 40 == 5:
            words.append("token=abcdef123456")
        rows.append((d, " ".join(words)))
        labels.append((d, 1, int(toxic)))
    rows += [(400 + k, rows[11 + k][1]) for k in range(20)] + [(430, None), (431, "")]
    path = tmp_path_factory.mktemp("sf")
    spark.createDataFrame([(d, t, "en", "s", len(t or "")) for d, t in rows], COLUMNS).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    return str(path), dict(rows), {d for d, _, y in labels if y}


def test_stages(spark, folder):
    path, texts, toxic = folder
    docs = spark.read.parquet(f"{path}/documents.parquet")
    want = set(texts)
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        out = stage(spark, docs, path)
        assert out.columns == docs.columns
        kept = {r.doc_id: r.text for r in out.collect()}
        if name == "toxicity":
            assert len((want - set(kept)) ^ toxic) <= 3
        elif name == "ngram_jaccard_join":
            first: dict = {}
            assert set(kept) == {d for d in sorted(want) if not texts[d] or first.setdefault(texts[d], d) == d}
        elif name == "benchmark_decontamination":
            assert set(kept) == {d for d in want if "sailors on the ship" not in (texts[d] or "")}
        else:
            assert set(kept) == want and not any("abcdef123456" in (t or "") for t in kept.values())
            assert all(t == texts[d] or "<assign>" in t for d, t in kept.items())
        want = set(kept)
        out.write.parquet(f"{path}/stage-{k}")
        docs = spark.read.parquet(f"{path}/stage-{k}")


def test_run_packs_every_document_left(spark, folder):
    path, texts, _ = folder
    got = corpus_pipeline.run(spark, path).collect()
    total = {}
    for r in got:
        total[r.doc_id] = total.get(r.doc_id, 0) + r.length
    assert all(total[r.doc_id] == r.doc_tokens for r in got)
    assert 300 < len(total) < len(texts)


def test_stages_on_odd_tables(spark, folder):
    path, _, _ = folder
    text = "one two three four five six seven eight nine ten token=abcdef123456"
    rows = [(1, text, "en", "s", None, 7), (1, text, "en", "s", None, 7), (2, text, None, None, 3, 8), (None, text, "en", "s", 3, 9), (3, None, None, None, None, None), (4, "", "en", "s", 0, 1), (5, "x" * 200_000, "en", "s", 1, 1)]
    docs = spark.createDataFrame(rows, COLUMNS + ", toxicity int")
    one = corpus_pipeline.one_of_each_class(spark, docs, path).collect()
    assert sorted(str(r.doc_id) for r in one) == ["1", "3", "4", "5", "None"]
    clean = {str(r.doc_id): r for r in corpus_pipeline.without_secrets(spark, docs, path).collect()}
    assert clean["2"].text.endswith("<assign>") and clean["2"].n_chars == len(clean["2"].text) and clean["3"].text is None and clean["2"].toxicity == 8
    assert corpus_pipeline.without_benchmark(spark, docs, path).count() == len(rows)
    assert corpus_pipeline.without_toxic(spark, docs.drop("toxicity"), path).count() == len(rows)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.drop("toxicity").limit(0), path).count() == 0


def test_labels_of_one_kind_drop_nothing(spark, tmp_path):
    docs = spark.createDataFrame([(k, f"word{k} scoundrel text " * 20, "en", "s", 1) for k in range(40)], COLUMNS)
    schema = "doc_id long, quality int, toxic int"
    spark.createDataFrame([(k, 1, 1) for k in range(30)], schema).write.parquet(f"{tmp_path}/a/labels.parquet")
    spark.createDataFrame([(k, 1, 1) for k in range(30)] + [(1000 + k, 1, 0) for k in range(30)], schema).write.parquet(f"{tmp_path}/b/labels.parquet")
    assert corpus_pipeline.without_toxic(spark, docs, f"{tmp_path}/a").count() == 40
    assert corpus_pipeline.without_toxic(spark, docs, f"{tmp_path}/b").count() == 40
    long = [(k, "blighter scoundrel rogue " * 4000, "en", "s", 1) for k in range(30)] + [(k, "fair and kind words here " * 4000, "en", "s", 1) for k in range(30, 60)]
    spark.createDataFrame([(k, 1, int(k < 30)) for k in range(60)], schema).write.parquet(f"{tmp_path}/c/labels.parquet")
    kept = corpus_pipeline.without_toxic(spark, spark.createDataFrame(long, COLUMNS), f"{tmp_path}/c").collect()
    assert {r.doc_id for r in kept} == set(range(30, 60))


def test_texts_under_one_id_are_told_apart(spark):
    x, y, z = (" ".join(f"{c}{k}" for k in range(30)) for c in "xyz")
    rows = [(3, x), (7, x), (7, y), (9, y), (8, z), (8, z), (8, x + " end"), (None, x), (5, None), (5, "")]
    docs = spark.createDataFrame([(d, t, "en", "s", 1) for d, t in rows], COLUMNS)
    got = corpus_pipeline.one_of_each_class(spark, docs, "")
    assert got.columns == docs.columns
    assert sorted((str(r.doc_id), str(r.text)) for r in got.collect()) == sorted([("3", x), ("7", y), ("8", z), ("None", x), ("5", "None"), ("5", "")])


def test_stages_on_columns_with_names_of_their_own(spark, folder):
    path, _, _ = folder
    rows = [(1, "one two three four five six", "en", "s", 5, 7, 8), (2, "one two three four five six", "en", "s", 5, 7, 8), (3, "seven eight nine", "en", "s", 5, 7, 8)]
    docs = spark.createDataFrame(rows, COLUMNS + ", toxicity int, other int")
    for want, (_, stage) in zip(({1, 2, 3}, {1, 3}, {1, 2, 3}, {1, 2, 3}), corpus_pipeline.STAGES[:-1]):
        out = stage(spark, docs, path)
        assert out.columns == docs.columns
        assert {(r.doc_id, r.toxicity, r.other) for r in out.collect()} == {(k, 7, 8) for k in want}


def test_a_worker_drops_the_tokenizer_when_it_turns_to_other_work(tmp_path):
    from eigenlake.llm import queries, textnum, wordpieces

    path = queries.tokenizer_path("word_bpe_49k.json")
    held = wordpieces.encoder(path)
    textnum.settle(keep=True)
    assert wordpieces.encoder(path) is held
    textnum.settle()
    assert not wordpieces._made


def test_words_are_encoded_a_batch_at_a_time(monkeypatch):
    from eigenlake.llm import queries, wordpieces

    words = [f"word{k}é".encode() for k in range(1000)]
    encoder = wordpieces.Encoder(queries.tokenizer_path("word_bpe_49k.json"))
    plain, first = encoder._ids(words)
    monkeypatch.setattr(wordpieces, "BATCH", 7)
    ids, at = encoder._ids(words)
    assert (ids == plain).all() and (at == first).all() and len(at) == 1001
    assert len(encoder._ids([])[0]) == 0
