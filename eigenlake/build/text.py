"""Links and similarities from texts and pages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def terms(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(key, term): distinct lower-case words of letters a-z."""
    words = F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0)))
    return docs.select(key, F.explode(words).alias("term")).distinct()


def shared_terms(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(i, j, v): how many distinct words two different keys share, whatever rows they stand in."""
    t = terms(docs, key, text)
    left, right = t.select(F.col(key).cast("long").alias("i"), "term"), t.select(F.col(key).cast("long").alias("j"), "term")
    return left.join(right, "term").where("i != j").groupBy("i", "j").agg(F.count(F.lit(1)).cast("double").alias("v"))


def link_edges(pages: DataFrame, key: str = "page_id", source: str = "html") -> DataFrame:
    """(key, target): what the href attributes of a page point at, as often as they do."""
    return pages.select(key, F.explode(F.regexp_extract_all(source, F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))
