"""A training corpus from raw documents, in five stages.

Each stage gets all that the one before kept, written as Parquet and read
again; the last gives the packed pieces.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenlake.llm import decontam, jaccard, packed, packing, queries, secrets, toxicity

#: Ids up to this many are broadcast to be left out (8 bytes each); more are joined by a shuffle.
BROADCAST_IDS = 2_000_000


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored under 0.5 stay. Without labelled documents of both kinds to learn from all stay."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = queries.toxicity_model(docs, labels)
    if not model.fitted:
        return docs
    others = tuple(c for c in docs.columns if c != "doc_id")
    kept = toxicity.score(docs, model, also=others, name="__toxicity").where("__toxicity < 0.5")
    return kept.select(*docs.columns)


def one_of_each_class(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that are alike, the one with the smallest id stays; null ids all stay.

    Texts are told apart under an id that repeats: only those that are alike go.
    """
    texts = docs.where("doc_id is not null").select("doc_id", F.xxhash64("text").alias("print"))
    if texts.groupBy("doc_id").agg(F.min("print").alias("a"), F.max("print").alias("b")).where("a != b").isEmpty():
        return _first_of_each(docs, "doc_id")
    # Numbers in the order of the ids stand for the texts.
    numbers = packed.cut(texts.distinct().orderBy("doc_id", "print").select(F.col("doc_id").alias("__id"), F.col("print").alias("__print"), F.monotonically_increasing_id().alias("__number")))
    numbered = docs.join(numbers, (F.col("doc_id") == F.col("__id")) & (F.xxhash64("text") == F.col("__print")), "left").drop("__id", "__print")
    return _first_of_each(packed.cut(numbered), "__number").drop("__number")


def _first_of_each(docs: DataFrame, key: str) -> DataFrame:
    """Of documents that are alike the one with the smallest key; a key stands for one text."""
    classes = packed.cut(jaccard.similarity_classes(docs, key=key).select("doc_id", "component_id"))
    others = classes.where("doc_id != component_id").select(F.col("doc_id").alias("__other")).distinct()
    if others.count() <= BROADCAST_IDS:
        others = F.broadcast(others)
    kept = docs.join(others, F.col(key) == F.col("__other"), "left_anti")
    if classes.where("doc_id = component_id").groupBy("doc_id").count().where("count > 1").isEmpty():
        return kept
    return kept.where(F.col(key).isNotNull()).dropDuplicates([key]).unionByName(kept.where(F.col(key).isNull()))


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item stay."""
    return decontam.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay; each secret gives way to its kind in angle brackets, and n_chars follows."""
    clean = secrets.redact(docs)
    if "n_chars" in docs.columns:
        clean = clean.withColumn("n_chars", F.coalesce(F.char_length("text").cast("long"), F.col("n_chars")))
    return clean


def packed_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of 2048 tokens."""
    return packing.pack(docs, queries.tokenizer_path("word_bpe_49k.json")).drop("ids")


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
STAGES: list[tuple[str, Stage]] = [
    ("toxicity", without_toxic),
    ("ngram_jaccard_join", one_of_each_class),
    ("benchmark_decontamination", without_benchmark),
    ("secret_scan", without_secrets),
    ("packing", packed_pieces),
]

#: No SQL expresses a fitted classifier or a tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def _remove(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir; between stages the rows lie in the shared folder.

    A stage's rows go once the next one's are written; those that the result
    is read from stay beside the checkpoints.
    """
    folder = f"{packed.shared_folder(spark)}/corpus-pipeline-{uuid.uuid4().hex}"
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if (name, stage) != STAGES[-1]:
            docs.write.parquet(f"{folder}/{name}")
            docs = spark.read.parquet(f"{folder}/{name}")
            if before:
                _remove(spark, before)
            before = f"{folder}/{name}"
    return docs
