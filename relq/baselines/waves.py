"""Baselines as Spark plans: parallel breadth-first search, backward expansion, threshold top-k, path unions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.workspace import Workspace
from ..schema import RelGraph


def parallel_bfs(graph: RelGraph, sources: DataFrame, max_hops: int | None = None) -> tuple[DataFrame, list[dict]]:
    """``(node_id, hop)`` from ``sources(node_id)``, and per hop the reached nodes and messages; one shuffle a hop."""
    work = Workspace(graph.edges.sparkSession, "bfs")
    edges = graph.edges.select("src", "dst")
    reached = work.save(sources.select("node_id").distinct().withColumn("hop", F.lit(0)), "hop0")
    wave, trace, hop = reached, [], 0
    while max_hops is None or hop < max_hops:
        hop += 1
        sent = wave.join(edges, wave["node_id"] == edges["src"])
        fresh = sent.select(F.col("dst").alias("node_id")).distinct().join(reached, "node_id", "left_anti").withColumn("hop", F.lit(hop))
        wave = work.save(fresh, f"wave{hop}")
        n = wave.count()
        trace.append({"hop": hop, "fresh": n})
        if not n:
            break
        reached = work.save(reached.unionByName(wave), f"hop{hop}")
        work.drop(f"hop{hop - 1}")
    return reached, trace


def keyword_distances(graph: RelGraph, seeds: DataFrame, m: int, max_rounds: int | None = None) -> DataFrame:
    """``(node_id, bit, length, via)``: one shortest-path wave per keyword, all in one loop; only improved rows are sent on."""
    work = Workspace(graph.edges.sparkSession, "waves")
    edges = graph.edges.select("src", "dst", F.col("length").alias("w"))
    bits = F.array(*[F.when(F.col("mask").bitwiseAND(1 << i) != 0, F.lit(i)) for i in range(m)])
    state = work.save(seeds.select("node_id", F.explode(bits).alias("bit")).where("bit is not null").withColumns({"length": F.lit(0.0), "via": F.lit(None).cast("long")}), "state0")
    delta, number = state, 0
    while max_rounds is None or number < max_rounds:
        number += 1
        sent = delta.join(edges, delta["node_id"] == edges["src"]).select(F.col("dst").alias("node_id"), "bit", F.struct((F.col("length") + F.col("w")).alias("length"), F.col("src").alias("via")).alias("m"))
        best = sent.groupBy("node_id", "bit").agg(F.min("m").alias("m")).select("node_id", "bit", "m.length", "m.via")
        had = state.select("node_id", "bit", F.col("length").alias("had"))
        delta = work.save(best.join(had, ["node_id", "bit"], "left").where(F.col("had").isNull() | (F.col("length") < F.col("had"))).drop("had"), f"delta{number}")
        if delta.isEmpty():
            break
        state = work.save(state.join(delta, ["node_id", "bit"], "left_anti").unionByName(delta), f"state{number}")
        work.drop(f"state{number - 1}")
    return state


def backward_expansion(graph: RelGraph, seeds: DataFrame, m: int, k: int = 1, max_rounds: int | None = None) -> DataFrame:
    """``(rank, root, score)``: the k nodes with the least sum of distances to all keywords; paths may share edges, so a score is no tree weight."""
    lengths = keyword_distances(graph, seeds, m, max_rounds)
    scored = lengths.groupBy("node_id").agg(F.count("*").alias("n"), F.sum("length").alias("score")).where(F.col("n") == m)
    top = scored.select(F.col("node_id").alias("root"), "score").orderBy("score", "root").limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy("score", "root"))).select("rank", "root", "score")  # k rows


def backward_trees(graph: RelGraph, seeds: DataFrame, m: int, k: int = 1, max_rounds: int | None = None) -> DataFrame:
    """``(rank, root, score, weight, edges)``: the k best roots with the union of their paths to all keywords.

    ``weight`` counts an edge that several paths share once, so it is at most
    the score. Paths are followed through the pointers of the waves; the
    driver holds the nodes of k trees.
    """
    spark, lengths = graph.edges.sparkSession, keyword_distances(graph, seeds, m, max_rounds)
    scored = lengths.groupBy("node_id").agg(F.count("*").alias("n"), F.sum("length").alias("score")).where(F.col("n") == m)
    top = [(rank, r["node_id"], r["score"]) for rank, r in enumerate(scored.orderBy("score", "node_id").limit(k).collect(), 1)]
    paths: dict[int, dict[tuple[int, int], float]] = {rank: {} for rank, *_ in top}
    held = [(rank, root, bit, None, None) for rank, root, _ in top for bit in range(m)]
    while held:
        here = F.broadcast(spark.createDataFrame([h[:3] for h in held], "rank int, node_id long, bit int"))
        came = {(rank, node, bit): (length, before) for rank, node, bit, before, length in held}
        held = []
        for r in lengths.join(here, ["node_id", "bit"]).collect():
            length, before = came[r["rank"], r["node_id"], r["bit"]]
            if before is not None:
                paths[r["rank"]][min(before, r["node_id"]), max(before, r["node_id"])] = length - r["length"]
            if r["via"] is not None:
                held.append((r["rank"], r["via"], r["bit"], r["node_id"], r["length"]))
    rows = [(rank, root, float(score), float(sum(paths[rank].values())), sorted((a, b) for a, b in paths[rank])) for rank, root, score in top]
    return spark.createDataFrame(rows, "rank int, root long, score double, weight double, edges array<struct<a:bigint,b:bigint>>")


def threshold_topk(lists: DataFrame, k: int, steps: int = 12) -> tuple[DataFrame, int]:
    """The k least sums over ``lists(list_no, item, value)`` by sorted and random access, and the rows read in order.

    Each list is read up to a value, at first that of a 4096th of its rows,
    then of ever larger shares. An item not seen yet is above that value in
    every list, so once the k-th best of the items seen is at most the sum of
    the values read up to, none of the others can enter. Only items seen are
    looked up in the other lists; no list is ranked or sorted as a whole.
    """
    shares = [0.5**j for j in range(steps, -1, -1)]
    cuts = lists.groupBy("list_no").agg(F.percentile_approx("value", F.lit(shares), F.lit(100_000)).alias("cuts")).collect()  # a row a list
    best, read = lists.limit(0).select("item", F.col("value").alias("total")), 0
    for j in range(len(shares)):
        upto = F.broadcast(lists.sparkSession.createDataFrame([(c["list_no"], float(c["cuts"][j])) for c in cuts] or [(None, 0.0)], f"list_no {dict(lists.dtypes)['list_no']}, upto double"))
        seen = lists.join(upto, "list_no").where(F.col("value") <= F.col("upto"))
        totals = lists.join(seen.select("item").distinct(), "item", "left_semi").groupBy("item").agg(F.sum("value").alias("total"), F.countDistinct("list_no").alias("n"))
        best = totals.where(F.col("n") == len(cuts)).select("item", "total").orderBy("total", "item").limit(k)
        worst, read = [r["total"] for r in best.collect()], seen.count()
        if len(worst) == k and worst[-1] <= sum(c["cuts"][j] for c in cuts):
            break
    return best, read
