"""Edge lengths from the in-degree of the target, the cut-off, and mirrored edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def step_log10(degree: Column) -> Column:
    """Whole part of the decimal logarithm, by counting digits, so no rounding enters; 0 below 10."""
    return (F.length(degree.cast("string")) - 1).cast("double")


SCHEMES = {
    "step_log10": step_log10,
    "step_log10_plus1": lambda d: step_log10(d) + 1,
    "log_degree": lambda d: F.log2(1 + d.cast("double")),
    "uniform": lambda d: F.lit(1.0),
}


def assign_lengths(edges: DataFrame, scheme: str = "step_log10_plus1", tau: int | None = 1001) -> DataFrame:
    """Adds ``length`` to ``edges(src, dst, label[, strength])`` and drops edges at targets of in-degree ``tau`` or more.

    Schemes: ``step_log10`` (literal; zero below degree 10, for comparison
    only), ``step_log10_plus1``, ``log_degree``, ``uniform``,
    ``inverse_strength`` (1 / strength) and ``given`` (keeps ``length``). The
    in-degree is that of the directed graph, before mirroring. Null ends are dropped.
    """
    edges = edges.where("src is not null and dst is not null")
    if tau is None and scheme in ("given", "inverse_strength", "uniform"):
        degreed = edges.withColumn("degree", F.lit(1))
    else:
        degrees = edges.groupBy("dst").agg(F.count("*").alias("degree"))
        if tau is not None:  # of so many edges at most one in tau is such a target; theirs are not exchanged
            edges = edges.join(F.broadcast(degrees.where(F.col("degree") >= tau).select("dst")), "dst", "left_anti")
        degreed = edges.join(degrees, "dst")
    if tau is not None:
        degreed = degreed.where(F.col("degree") < tau)
    if scheme == "given":
        out = degreed
    elif scheme == "inverse_strength":
        out = degreed.withColumn("length", 1 / F.col("strength").cast("double"))
    else:
        out = degreed.withColumn("length", SCHEMES[scheme](F.col("degree")))
    return out.select("src", "dst", "label", F.col("length").cast("double").alias("length"))


def mirror(edges: DataFrame) -> DataFrame:
    """Adds the reverse of every edge with its length; drops self loops, keeps the shortest of parallels."""
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y"), "label", "length", (F.col("src") > F.col("dst")).alias("down"))
    least = lambda mirrored: F.min(F.struct("length", mirrored.alias("mirrored"), "label"))
    best = pairs.repartition("x", "y").groupBy("x", "y").agg(least(F.col("down")).alias("up"), least(~F.col("down")).alias("down"))
    ways = F.array(F.struct(F.col("x").alias("src"), F.col("y").alias("dst"), F.col("up").alias("b")), F.struct(F.col("y").alias("src"), F.col("x").alias("dst"), F.col("down").alias("b")))
    return best.select(F.explode(ways).alias("e")).select("e.src", "e.dst", "e.b.label", "e.b.length", "e.b.mirrored")


def min_edge_length(edges: DataFrame) -> DataFrame:
    """One row with ``e_min``."""
    return edges.agg(F.min("length").alias("e_min"))
