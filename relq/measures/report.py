"""Cost and accuracy measures of searches."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..search.driver import SearchResult


def timed(f: Callable) -> tuple[object, float]:
    """Result and seconds; the session, the graph and its cache stand before."""
    t = time.time()
    out = f()
    return out, time.time() - t


def percentile90(rows: DataFrame, value: str, *by: str) -> DataFrame:
    return rows.groupBy(*by).agg(F.percentile(value, F.lit(0.9)).alias("p90"), F.avg(value).alias("mean"), F.count("*").alias("queries"))


def component_shares(result: SearchResult) -> dict[str, float]:
    """Percent of the time of the five components."""
    total = sum(result.timers.values()) or 1.0
    return {k: 100 * v / total for k, v in result.timers.items()}


def deep_messages(result: SearchResult) -> int:
    return sum(r["deep_msgs"] for r in result.rows)


def report_row(query_id: int, m: int, k: int, result: SearchResult, seconds: float, keyword_nodes: int) -> tuple:
    best = result.best[0]["length"] if result.best else None
    return (query_id, m, k, keyword_nodes, result.status, best, result.spa_ratio, result.pct_explored, result.pct_messages, deep_messages(result), len(result.rows), seconds)


REPORT = "query_id int, m int, k int, keyword_nodes long, status string, best double, spa_ratio double, pct_explored double, pct_messages double, deep_msgs long, rounds int, seconds double"


def report(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """One row per run, in the order of keyword count and keyword nodes."""
    return spark.createDataFrame(rows, REPORT).orderBy("m", "keyword_nodes", "k")


def parallel_efficiency(seconds: dict[int, float]) -> dict[int, float]:
    """T1 / (p Tp) by number of cores p."""
    one = seconds[min(seconds)] * min(seconds)
    return {p: one / (p * s) for p, s in seconds.items()}


def growth_of_keyword_nodes(workload: DataFrame) -> DataFrame:
    """Slope of the log of the keyword nodes over the place in the workload."""
    return workload.agg(F.regr_slope(F.log10("total_df"), "query_id").alias("slope"))
