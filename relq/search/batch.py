"""Best answers of many queries in one loop: K = 1, rows carry lengths and no trees.

First every keyword's distances are relaxed, all keywords of all queries
together: one row per query and node, one message per query and pair of nodes.
The least sum of distances at a node is the weight of a tree, so it bounds the
best weight. Then subsets of keywords are merged and carried on, and a partial
tree is dropped as soon as its length and a lower bound on what is missing
reach the best weight known: before the exchange by its length, after it by
the distances at the node. Trees are read back at the end from which lengths
add up, for the best root of each query alone.

The rules that drop rows are known from exact searches for group Steiner trees
by growing and merging subsets: a tree has a node all of whose branches weigh
at most half; of three parts or more the two lightest weigh two thirds at most;
and what connects a node with groups is at least half a round trip.
"""

from __future__ import annotations

import functools
import math
import time
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.workspace import Workspace, buckets_of
from ..schema import RelGraph

NODE = ["query_id", "node_id"]
KEY = [*NODE, "mask"]
PART = "struct<mask:int,length:double>"
MAX_WIDTH = 16
TOUR_WIDTH = 8


def without_dead_ends(edges: DataFrame, kept: DataFrame) -> DataFrame:
    """Edges without the nodes that have a single neighbour and are not in ``kept(node_id)``: they are leaves of no minimal tree."""
    alone = edges.groupBy("src").agg(F.count("*").alias("n")).where("n = 1").join(kept, F.col("src") == F.col("node_id"), "left_anti").select(F.col("src").alias("end"))
    out = edges.join(alone, F.col("src") == F.col("end"), "left_anti")
    return out.join(alone, F.col("dst") == F.col("end"), "left_anti")


def edges_by_source(edges: DataFrame, work: Workspace, name: str = "edges") -> DataFrame:
    """``(src, dst, w)`` in buckets of the source, so no round exchanges the edges again."""
    rows = edges.select("src", "dst", F.col("length").alias("w"))
    return work.save(rows.repartition(buckets_of(edges.sparkSession), "src"), name, ["src"])


class _Limits:
    """What is known of each query on the driver: a few numbers a query, broadcast every round."""

    def __init__(self, spark: SparkSession, queries: dict[int, int], bounded: bool):
        self.spark, self.queries, self.bounded = spark, queries, bounded
        self.best: dict[int, tuple[float, int]] = {}
        self.gaps: dict[int, list[float]] = {}
        self.width = max(queries.values(), default=1)
        if self.width > MAX_WIDTH:
            raise ValueError(f"a query has at most {MAX_WIDTH} keywords")
        self.pairs = list(combinations(range(self.width), 2))

    def improve(self, query: int, weight: float | None, root: int) -> None:
        if weight is not None and (query not in self.best or weight < self.best[query][0]):
            self.best[query] = (weight, root)

    def bound(self, query: int) -> float:
        return self.best[query][0] if self.bounded and query in self.best else math.inf

    def gap_table(self, query: int) -> np.ndarray:
        out = np.zeros((self.queries[query],) * 2)
        for (i, j), gap in zip(self.pairs, self.gaps.get(query, [0.0] * len(self.pairs)), strict=True):
            if j < len(out):
                out[i, j] = out[j, i] = gap
        return out

    def frame(self) -> DataFrame:
        """``(query_id, m, limit)``, as constants of the plan."""
        rows = ", ".join(f"({q}, {m}, double('{self.bound(q)}'))" for q, m in self.queries.items())
        return F.broadcast(self.spark.sql(f"SELECT * FROM VALUES {rows} AS t(query_id, m, limit)"))


def keyword_fields(edges: DataFrame, seeds: DataFrame, limits: _Limits, work: Workspace, share: int, max_rounds: int | None) -> tuple[DataFrame, list[dict], bool]:
    """``(query_id, node_id, d0, d1, …)``, the distance of each keyword where it matters; the trace; and whether the waves came to rest.

    Only distances that are below the best weight over ``share`` are sent on.
    """
    bits, began = range(limits.width), time.time()
    holds = lambda i: F.col("mask").bitwiseAND(1 << i) != 0
    start = seeds.groupBy(*NODE).agg(F.bit_or("mask").alias("mask"))
    start = start.select(*NODE, *[F.when(holds(i), 0.0).alias(f"d{i}") for i in bits], *[F.when(holds(i), 0.0).alias(f"n{i}") for i in bits], F.lit(True).alias("moved"))
    state, trace, number, done = work.save(start, "waves0", NODE), [], 0, False
    while True:
        known = state.join(limits.frame().select("query_id", "m"), "query_id")
        total = sum((F.when(F.col("m") > i, F.col(f"d{i}")).otherwise(0.0) for i in bits), F.lit(0.0))
        nearest = F.least(*[F.col(f"n{i}") for i in bits]) if limits.width > 1 else F.col("n0")
        facts = known.withColumn("total", total).groupBy("query_id").agg(
            F.min(F.when(F.col("total").isNotNull(), F.struct("total", "node_id"))).alias("b"), F.min(nearest).alias("nearest"), F.count_if("moved").alias("moved"), F.count("*").alias("rows")
        ).collect()  # a row a query
        for r in facts:
            if r["b"]:
                limits.improve(r["query_id"], r["b"]["total"], r["b"]["node_id"])
        trace.append({"phase": "waves", "round": number, "seconds": round(time.time() - began, 2), "rows": sum(r["rows"] for r in facts), "moved": sum(r["moved"] for r in facts)})
        done = not any(r["nearest"] is not None and share * r["nearest"] < limits.bound(r["query_id"]) for r in facts)
        if done or (max_rounds is not None and number >= max_rounds):
            break
        number += 1
        near = state.where("moved").join(limits.frame().select("query_id", "limit"), "query_id")
        near = near.select(*NODE, "limit", *[F.when(share * F.col(f"n{i}") < F.col("limit"), F.col(f"n{i}")).alias(f"n{i}") for i in bits]).where(F.coalesce(*[F.col(f"n{i}") for i in bits]).isNotNull())
        sent = near.join(edges, F.col("node_id") == F.col("src"))
        sent = sent.select("query_id", F.col("dst").alias("node_id"), *[F.when(F.col(f"n{i}") + F.col("w") < F.col("limit"), F.col(f"n{i}") + F.col("w")).alias(f"a{i}") for i in bits])
        arrived = sent.groupBy(*NODE).agg(*[F.min(f"a{i}").alias(f"a{i}") for i in bits]).where(F.coalesce(*[F.col(f"a{i}") for i in bits]).isNotNull())
        both = state.drop("moved", *[f"n{i}" for i in bits]).join(arrived, NODE, "full")
        better = [F.when(F.col(f"d{i}").isNull() | (F.col(f"a{i}") < F.col(f"d{i}")), F.col(f"a{i}")).alias(f"n{i}") for i in bits]
        after = both.select(*NODE, *[F.least(f"d{i}", f"a{i}").alias(f"d{i}") for i in bits], *better)
        state = work.save(after.withColumn("moved", F.coalesce(*[F.col(f"n{i}") for i in bits]).isNotNull()), f"waves{number}", NODE)
        work.drop(f"waves{number - 1}")
    return state.drop("moved", *[f"n{i}" for i in bits]), trace, done


def shortest_tours(gaps: np.ndarray) -> np.ndarray:
    """``[subset, a, b]``: at least how long a way from keyword a to keyword b is that visits the subset, ``gaps`` being at least how far two are apart."""
    m = len(gaps)
    out = np.full((1 << m, m, m), np.inf)
    for a in range(m):
        out[1 << a, a, a] = 0.0
    for mask in range(1, 1 << m):
        for c in range(m):
            if not mask >> c & 1:
                np.minimum(out[mask | 1 << c, :, c], (out[mask] + gaps[:, c]).min(1), out=out[mask | 1 << c, :, c])
    return out


def _round_trips(near: np.ndarray, gaps: np.ndarray) -> np.ndarray:
    """At least what the keywords outside each subset add at each node of one query, as rows of 2^m columns.

    ``near`` holds at least how far each keyword is, ``gaps`` at least how far
    two are from each other. What connects a node with keywords is half a walk
    from it past all of them and back; of many keywords, past any two.
    """
    n, m = near.shape
    tours = shortest_tours(gaps) if m <= TOUR_WIDTH else None
    near, out = np.asfortranarray(near), np.zeros((n, 1 << m), near.dtype, order="F")
    for mask in sorted(range((1 << m) - 1), key=int.bit_count, reverse=True):
        rest = [i for i in range(m) if not mask >> i & 1]
        for i in rest:
            np.maximum(out[:, mask], out[:, mask | 1 << i], out=out[:, mask])
        if len(rest) == 1:
            out[:, mask] = near[:, rest[0]]
        elif tours is not None or len(rest) == 2:
            least, inside = None, sum(1 << i for i in rest)
            for i, j in combinations(rest, 2):
                way = near[:, i] + near[:, j]
                way += gaps[i, j] if tours is None else tours[inside, i, j]
                least = way if least is None else np.minimum(least, way, out=least)
            np.maximum(out[:, mask], least / 2, out=out[:, mask])
    return out


def _close(table: np.ndarray, fresh: np.ndarray, missing: np.ndarray, limit: np.ndarray) -> np.ndarray:
    """Merges disjoint subsets at every node, in place, in the order of their size; True where a subset got lighter.

    ``table`` are lengths by node and subset, ``fresh`` marks those that are
    new; only pairs with a new one are tried.
    """
    n, size = table.shape
    gained = fresh.copy()
    for mask in sorted(range(1, size), key=int.bit_count):
        part = (mask - 1) & mask
        while part > mask ^ part:
            other = mask ^ part
            both = table[:, part] + table[:, other]
            ok = (gained[:, part] | gained[:, other]) & (both < table[:, mask])
            ok &= (both < limit) if mask == size - 1 else (3 * both < 2 * limit) & (both + missing[:, mask] < limit)
            if ok.any():
                table[ok, mask] = both[ok]
                gained[ok, mask] = True
            part = (part - 1) & mask
    return gained


def _receive(limits: _Limits, share: int, e_min: float) -> Callable:
    """What nodes do in a round: take what arrived, merge, and say what got lighter. A function over Arrow batches.

    A record is a node of a query with its distances, its partial trees and
    what arrived. Work at a node depends on the keywords alone, whatever its
    degree; records of as many keywords are taken together.
    """
    bounds = {q: (m, limits.bound(q), limits.gap_table(q)) for q, m in limits.queries.items()}
    width, bounded = limits.width, limits.bounded

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            query = batch.column("query_id").to_numpy()
            for m in sorted({bounds[q][0] for q in set(query.tolist())}):
                mine = np.flatnonzero(np.isin(query, [q for q, b in bounds.items() if b[0] == m]))
                rows, size = batch.take(pa.array(mine)), 1 << m
                asked = query[mine]
                limit = np.array([bounds[q][1] for q in asked.tolist()])
                far = np.stack([rows.column(f"d{i}").to_numpy(zero_copy_only=False) for i in range(m)], 1)
                far = np.where(np.isnan(far), np.inf, far)
                table, arrived = _dense(rows.column("parts"), size), _dense(rows.column("got"), size)
                if bounded:
                    rim = limit[:, None] / share + e_min
                    missing = np.zeros((len(mine), size))
                    for q in set(asked.tolist()):
                        missing[asked == q] = _round_trips(np.minimum(far, rim)[asked == q], bounds[q][2])
                else:
                    missing = np.full((len(mine), size), -np.inf)  # nothing is dropped
                first = rows.column("first").to_numpy(zero_copy_only=False)
                if bounded and first[0]:  # nodes too far from two keywords for any tree that is still sought
                    near = np.flatnonzero(missing[:, 0] < limit)
                    rows, first, limit, far, missing, table, arrived = rows.take(pa.array(near)), *(x[near] for x in (first, limit, far, missing, table, arrived))
                for i in range(m):
                    table[:, 1 << i] = far[:, i]
                    arrived[:, 1 << i] = np.where(first & (far[:, i] + missing[:, 1 << i] < limit), far[:, i], np.inf)
                    if bounded:
                        table[far[:, i] + missing[:, 1 << i] >= limit, 1 << i] = np.inf
                lone = np.bitwise_count(np.arange(size)) == 1
                fresh = (arrived < table) & ((arrived + missing < limit[:, None]) | ~np.isfinite(limit[:, None])) | (lone & np.isfinite(arrived))
                table[fresh] = arrived[fresh]
                gained = _close(table, fresh, missing, limit)
                complete = np.where(gained[:, size - 1], table[:, size - 1], np.nan)
                gained[:, lone] = False
                kept = np.isfinite(table)
                kept[:, lone] = False
                kept[:, 0] = gained[:, 0] = False
                sent = gained.copy()
                sent[:, size - 1] = False
                columns = [rows.column("query_id"), rows.column("node_id"), *[rows.column(f"d{i}") for i in range(width)], _sparse(table, kept), _sparse(table, sent)]
                columns += [pa.array(complete, from_pandas=True), pa.array(sent.any(1))]
                yield pa.RecordBatch.from_arrays(columns, ["query_id", "node_id", *[f"d{i}" for i in range(width)], "parts", "gained", "complete", "moved"])

    return run


def _dense(column: pa.Array, size: int) -> np.ndarray:
    """Rows of ``size`` lengths from a column of maps from subset to length; infinite where there is none."""
    out = np.full((len(column), size), np.inf)
    counts = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = column.flatten()
    out[np.repeat(np.arange(len(column)), counts), flat.field("mask").to_numpy()] = flat.field("length").to_numpy()
    return out


def _sparse(table: np.ndarray, kept: np.ndarray) -> pa.Array:
    row, mask = np.nonzero(kept)
    ends = np.concatenate([[0], np.cumsum(kept.sum(1))]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(mask.astype(np.int32)), pa.array(table[row, mask])], ["mask", "length"]))


def batch_search(graph: RelGraph, seeds: DataFrame, queries: dict[int, int], max_supersteps: int | None = None, half_cut: bool = True, bounded: bool = True) -> tuple[DataFrame, DataFrame, list[dict]]:
    """``(answers, state, trace)`` for ``seeds(query_id, node_id, mask)`` and ``queries`` as number of keywords by id.

    ``answers(query_id, root, weight, by_sum, proven)``: a lightest tree of each
    query that has one, its root, whether the distances at the root add up to
    it, and whether the search ended by itself; with ``max_supersteps`` each
    phase stops after so many rounds and nothing is proven unless it had come
    to rest. ``state(query_id, node_id, parts)`` has the least length of each
    subset at each node; ``partial_rows`` lists them.
    ``half_cut=False`` sends up to the whole best weight, ``bounded=False``
    drops nothing, so the state holds every node and subset.

    The merges at a node run over Arrow batches of nodes: as SQL they are a
    self-join for every size of subset, or nested functions over arrays, which
    took a millisecond a node.
    """
    spark, work, share = graph.edges.sparkSession, Workspace(graph.edges.sparkSession, "batch"), 2 if half_cut else 1
    limits, began = _Limits(spark, queries, bounded), time.time()
    whole = edges_by_source(without_dead_ends(graph.edges, seeds.select("node_id").distinct()) if bounded else graph.edges, work)
    e_min = whole.agg(F.min("w")).first()[0] or 0.0
    fields, trace, at_rest = keyword_fields(whole, seeds, limits, work, share, max_supersteps)
    sums = dict(limits.best)
    if limits.pairs and bounded:
        gaps = fields.groupBy("query_id").agg(*[F.min(F.col(f"d{i}") + F.col(f"d{j}")).alias(f"g{i}_{j}") for i, j in limits.pairs]).collect()  # a row a query
        for r in gaps:
            limits.gaps[r["query_id"]] = [min(limits.bound(r["query_id"]), math.inf if v is None else v) for v in tuple(r)[1:]]
    names = [f"d{i}" for i in range(limits.width)]
    record = f"query_id int, node_id long, {', '.join(f'{n} double' for n in names)}, parts array<{PART}>, gained array<{PART}>, complete double, moved boolean"
    none = F.array().cast(f"array<{PART}>")

    def settled(rows: DataFrame, number: int, same: DataFrame | None = None) -> DataFrame:
        """The node records after a round, with what they gained, and those that nothing reached as they were; in buckets of query and node."""
        rows = rows.select(*NODE, *names, F.coalesce("parts", none).alias("parts"), F.coalesce("got", none).alias("got"), F.lit(number == 0).alias("first"))
        after = rows.mapInArrow(_receive(limits, share, e_min), record)
        return work.save(after.unionByName(same) if same is not None else after, f"nodes{number}", NODE)

    nodes, number, done = settled(fields.withColumns({"parts": none, "got": none}), 0), 0, False
    while True:
        facts = nodes.groupBy("query_id").agg(
            F.min(F.when(F.col("complete").isNotNull(), F.struct("complete", "node_id"))).alias("b"), F.min(F.array_min(F.transform("gained", lambda p: p["length"]))).alias("nearest"),
            F.sum(F.size("gained")).alias("moved"), F.sum(F.size("parts")).alias("rows"),
        ).collect()  # a row a query
        for r in facts:
            if r["b"]:
                limits.improve(r["query_id"], r["b"]["complete"], r["b"]["node_id"])
        trace.append({"phase": "merges", "round": number, "seconds": round(time.time() - began, 2), "rows": sum(r["rows"] for r in facts), "moved": sum(r["moved"] for r in facts)})
        done = not any(r["nearest"] is not None and share * r["nearest"] < limits.bound(r["query_id"]) for r in facts)
        if done or (max_supersteps is not None and number >= max_supersteps):
            break
        number += 1
        delta = nodes.where("moved").select(*NODE, F.explode("gained").alias("p")).select(*NODE, "p.mask", "p.length").join(limits.frame(), "query_id")
        sent = delta.where(share * F.col("length") < F.col("limit")).join(whole, F.col("node_id") == F.col("src"))
        sent = sent.where(F.col("length") + F.col("w") < F.col("limit")) if bounded else sent
        arrived = sent.groupBy("query_id", F.col("dst").alias("node_id"), "mask").agg(F.min(F.col("length") + F.col("w")).alias("length"))
        box = arrived.groupBy(*NODE).agg(F.collect_list(F.struct("mask", "length")).alias("got"))  # one entry a subset
        # a node that no wave reached lies too far out for any tree that is still sought
        met = nodes.select(*NODE, *names, "parts").join(box, NODE, "inner" if bounded else "right")
        same = nodes.select(*NODE, *names, "parts", none.alias("gained"), F.lit(None).cast("double").alias("complete"), F.lit(False).alias("moved")).join(box.select(*NODE), NODE, "left_anti")
        nodes = settled(met, number, same)
        work.drop(f"nodes{number - 1}")
    ended = done and at_rest
    rows = [(q, r, float(w), sums.get(q, (None,))[0] == w, ended) for q, (w, r) in limits.best.items()]
    answers = spark.createDataFrame(rows, "query_id int, root long, weight double, by_sum boolean, proven boolean")
    singles = F.filter(F.array(*[F.struct(F.lit(1 << i).alias("mask"), F.col(n).alias("length")) for i, n in enumerate(names)]), lambda p: p["length"].isNotNull())
    state = fields.join(nodes.select(*NODE, "parts"), NODE, "left" if bounded else "full")
    state = state.select(*NODE, F.concat(singles, F.coalesce("parts", none)).cast(f"array<{PART}>").alias("parts"))
    work.drop("edges")
    return answers, state, trace


def partial_rows(state: DataFrame) -> DataFrame:
    """``(query_id, node_id, mask, length)`` of a state."""
    return state.select(*NODE, F.explode("parts").alias("p")).select(*NODE, "p.mask", "p.length")


def rebuild(graph: RelGraph, answers: DataFrame, state: DataFrame) -> DataFrame:
    """``(query_id, a, b, length)``: the edges of each query's tree.

    A partial tree is two parts at its node or a part of a neighbour and the
    edge from there, whichever adds up. Rows held on the driver are at most the
    nodes of one tree a query. Raises RuntimeError if nothing adds up, which
    only a search that was cut short can cause.
    """
    spark = answers.sparkSession
    wanted = "query_id int, node_id long, mask int, length double"
    found: list[tuple] = []
    held = [(r["query_id"], r["root"], None, r["weight"], r["by_sum"]) for r in answers.collect()]
    while held:
        nodes = spark.createDataFrame(list({(q, n) for q, n, *_ in held}), "query_id int, node_id long")
        here: dict[tuple, dict[int, float]] = {}
        for r in state.join(F.broadcast(nodes), NODE).collect():
            here[r["query_id"], r["node_id"]] = {p["mask"]: p["length"] for p in r["parts"]}
        split, carried = [], []
        for q, n, mask, length, by_sum in held:
            table = here[q, n]
            if mask is None:  # a root: all keywords that meet there
                mask = functools.reduce(int.__or__, table)
            if by_sum:
                split += [(q, n, 1 << i, table[1 << i], False) for i in range(mask.bit_length()) if mask >> i & 1]
            elif length > 0 or mask & (mask - 1):
                pair = next(((a, mask ^ a) for a in sorted(table) if a & mask == a and a < mask ^ a and mask ^ a in table and table[a] + table[mask ^ a] == length), None)
                if pair:
                    split += [(q, n, a, table[a], False) for a in pair]
                else:
                    carried.append((q, n, mask, length))
        held = [x for x in split if x[3] > 0 or x[2] & (x[2] - 1)]
        if carried:
            open_rows = F.broadcast(spark.createDataFrame(carried, wanted))
            steps = open_rows.join(graph.edges.select(F.col("src").alias("near"), "dst", F.col("length").alias("w")), F.col("node_id") == F.col("dst"))
            before = state.withColumnRenamed("node_id", "near")
            shorter = F.array_min(F.transform(F.filter("parts", lambda p: p["mask"] == F.col("mask")), lambda p: p["length"]))
            back = steps.join(before, ["query_id", "near"]).withColumn("shorter", shorter).where(F.col("shorter") + F.col("w") == F.col("length"))
            rows = back.groupBy(*KEY).agg(F.min(F.struct("near", "shorter", "w")).alias("s")).collect()
            if len(rows) < len(set(carried)):
                raise RuntimeError("a partial tree has no origin; the search was cut short")
            for r in rows:
                s = r["s"]
                found.append((r["query_id"], min(s["near"], r["node_id"]), max(s["near"], r["node_id"]), s["w"]))
                held.append((r["query_id"], s["near"], r["mask"], s["shorter"], False))
    return spark.createDataFrame(found, "query_id int, a long, b long, length double").distinct()
