"""Label tables as the classifiers of this package read them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def residue(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; a null id counts as residue -1."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus, F.lit(-1))


def training_labels(labels: DataFrame, column: str, id_col: str = "doc_id") -> DataFrame:
    """``(doc_id, label)`` with one row per id: the larger of its labels, null ids and labels left out."""
    rows = labels.select(F.col(id_col).alias("doc_id"), F.col(column).cast("int").alias("label")).where("doc_id is not null and label is not null")
    return rows.groupBy("doc_id").agg(F.max("label").alias("label"))


def bounded_sample(labels: DataFrame, per_class: int) -> DataFrame:
    """At most ``per_class`` ids of each of the labels 0 and 1, those whose ids hash lowest."""
    parts = [labels.where(F.col("label") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for k in (0, 1)]
    return parts[0].unionByName(parts[1])
