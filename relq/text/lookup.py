"""Keyword nodes of a query as ``seeds(node_id, mask)``: bit i stands for keyword i."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MAX_KEYWORDS = 16


def _check(keywords: list) -> None:
    if not keywords or len(keywords) > MAX_KEYWORDS:
        raise ValueError(f"a query has 1 to {MAX_KEYWORDS} keywords")


def _masked(parts: list[DataFrame]) -> DataFrame:
    union = reduce(DataFrame.unionByName, [p.select("node_id", F.lit(1 << k).alias("mask")) for k, p in enumerate(parts)])
    return union.groupBy("node_id").agg(F.bit_or("mask").cast("int").alias("mask"))


def find_seeds(index: DataFrame, vertices: DataFrame, keywords: list, mode: str = "token") -> DataFrame:
    """Nodes of each keyword.

    ``token``: a term equal to the keyword. ``phrase``: all words of the
    keyword, in order, in the text. ``prefix``: a term that begins so.
    ``regex``: the text matches. ``predicate``: keywords are columns over the
    vertices. Repeated keywords keep their own bits.
    """
    _check(keywords)
    if mode == "token":
        spark = index.sparkSession
        terms = spark.createDataFrame([(k.lower(), 1 << i) for i, k in enumerate(keywords)], "term string, mask int").groupBy("term").agg(F.bit_or("mask").alias("mask"))
        return index.join(F.broadcast(terms), "term").groupBy("node_id").agg(F.bit_or("mask").cast("int").alias("mask"))
    if mode == "prefix":
        return _masked([index.where(F.col("term").startswith(k.lower())).select("node_id") for k in keywords])
    if mode == "phrase":
        patterns = [r"(?i)(?<![\p{L}\p{N}])" + r"[^\p{L}\p{N}]+".join(re.escape(w).replace("\\#", "#") for w in re.findall(r"[^\W_]+", k)) + r"(?![\p{L}\p{N}])" for k in keywords]
        return _masked([vertices.where(F.col("text").rlike(p)) for p in patterns])
    if mode == "regex":
        return _masked([vertices.where(F.col("text").rlike(k)) for k in keywords])
    if mode == "predicate":
        return _masked([vertices.where(k if isinstance(k, (str, Column)) else F.lit(False)) for k in keywords])
    raise ValueError(f"no lookup mode {mode}")


def expand_submasks(seeds: DataFrame) -> DataFrame:
    """Every non-empty part of each node's mask."""
    parts = F.filter(F.sequence(F.lit(1), F.col("mask")), lambda k: k.bitwiseAND(F.col("mask")) == k)
    return seeds.select("node_id", F.explode(parts).alias("mask"))
