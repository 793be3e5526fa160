"""Inverted index of node texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"


def build_index(vertices: DataFrame) -> DataFrame:
    """``(term, node_id)``, each pair once: lower-cased runs of letters and digits."""
    terms = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(TOKEN), F.lit(0)))
    return vertices.where("text is not null").select("node_id", F.explode(terms).alias("term")).select("term", "node_id")


def document_frequency(index: DataFrame) -> DataFrame:
    return index.groupBy("term").agg(F.count("*").alias("df"))


def write_index(index: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed and sorted by term: a lookup reads the buckets of its terms only."""
    index.write.mode("overwrite").bucketBy(buckets, "term").sortBy("term").saveAsTable(name)
