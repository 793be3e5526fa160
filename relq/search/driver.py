"""The round-wise search for the K lightest minimal trees."""

from __future__ import annotations

import functools
import math
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.workspace import Workspace, buckets_of
from ..schema import RelGraph
from . import masks, trees

TRACE = (
    "round int, phase string, active long, frontier long, bfs_msgs long, deep_msgs long, reached long, state_rows long, combinations long, tree_edges long, "
    "s map<int,double>, l map<int,double>, w_k double, candidates long, traversed long, decision string, ms long"
)
ANSWER = "rank int, root long, weight double, n_edges int, members array<long>, edges array<struct<a:bigint,b:bigint,len:double>>, parts array<struct<mask:int,length:double>>, sig long"


@dataclass(frozen=True)
class Cut:
    """What a run that stops before a round of more than so many messages ends with."""

    status: str
    best: float | None
    smallest_possible: float | None
    spa_ratio: float | None


@dataclass
class SearchResult:
    """Answers and trace as DataFrames, with the status and the measures of the run."""

    answers: DataFrame
    trace: DataFrame
    status: str
    smallest_possible: float | None
    spa_ratio: float | None
    pct_explored: float | None
    pct_messages: float | None
    pct_messages_mirrored: float | None
    timers: dict[str, float] = field(default_factory=dict)
    rows: list[dict] = field(default_factory=list)
    best: list[dict] = field(default_factory=list)
    cuts: dict[int, Cut] = field(default_factory=dict)


def _owners(row: dict, full: int) -> dict[int, int]:
    return {b["node"]: b["mask"] & full for b in row["bearers"]}


def _fold(best: list[dict], fresh: list[dict], k: int) -> list[dict]:
    """Global top-K without repeated trees."""
    every = {a["sig"]: a for a in [*fresh, *best]}
    return sorted(every.values(), key=lambda a: (a["length"], a["sig"]))[:k]


def relationship_search(
    graph: RelGraph, seeds: DataFrame, m: int, k: int = 1, *, stop: str = "published", scope: str = "frontier", deep: bool = True, drain: bool = True,
    max_messages: int | None = None, max_supersteps: int | None = None, slack: int = 2, half_cut: bool = False, local_minimal: bool = True, tie_ok: bool = False,
    prune: bool = True, profile: bool = False, measures: bool = False, cut_at: tuple[int, ...] = (),
) -> SearchResult:
    """Top-K minimal trees of ``seeds(node_id, mask)`` over m keywords.

    ``stop``: ``published`` (estimates above the lengths in the present
    answers, then a drain of deep messages), ``certified`` (a bound on what is
    not found yet; looks at all active nodes) or ``none`` (to quiescence).
    ``deep=False`` sends to unreached nodes only, ``drain=False`` halts at the
    stop test, ``prune=False`` keeps every partial tree (tiny graphs).
    ``max_messages`` cuts the run before a round that would send more;
    ``cut_at`` lists limits at which a run would end as told in ``cuts``, all
    from this one run, as a limit changes nothing before its cut.
    ``profile`` sends the two classes of messages one after the other, so each
    has a time of its own; ``measures`` also counts candidates, state rows and
    the combinations that merges look at.
    Status: optimal (stop test or bound, and drained), optimal_unproven (the
    stop test alone, without its drain), exhausted, truncated_messages,
    truncated_rounds, no_answer or unknown_keyword.

    A round writes its messages and its state, both in buckets of the node, so
    neither is exchanged again; what the driver needs comes in one job.
    """
    spark, full, work = graph.edges.sparkSession, (1 << m) - 1, Workspace(graph.edges.sparkSession, "search")
    keep = k + slack if prune else 1 << 30
    scope = "active" if stop == "certified" else scope
    covered = seeds.agg(F.bit_or("mask")).first()[0] or 0
    e_min = graph.e_min()
    timers = dict.fromkeys(("send_bfs", "receive", "send_deep", "send_aggregator", "evaluate"), 0.0)
    out = SearchResult(None, None, "unknown_keyword", None, None, None, None, None, timers)
    if covered & full != full:
        return _finish(spark, graph, out, [], [], m, None, measures)
    edges = work.save(graph.edges.select("src", "dst", "length").repartition(buckets_of(spark), "src"), "edges", ["src"])

    def timed(name: str, df: DataFrame, table: str) -> DataFrame:
        t = time.time()
        saved = work.save(df, table, ["node_id"])
        timers[name] += time.time() - t
        return saved

    state = work.save(trees.seed_rows(seeds).withColumn("born", F.lit(0)), "state0", ["node_id"])
    visits = [work.save(seeds.select("node_id", "mask"), "visits0")]
    n_reached = visits[0].count()
    best: list[dict] = _fold([], [r.asDict(True) for r in trees.minimal_answers(state, full).dropDuplicates(["sig"]).orderBy("length", "sig").limit(k).collect()], k)
    trace: list[dict] = []
    phase, status, smallest, number = "RUN", "exhausted", {}, 0
    while True:
        number += 1
        if max_supersteps is not None and number > max_supersteps:
            status = "truncated_rounds"
            break
        began = time.time()
        w_k = best[-1]["length"] if len(best) == k else math.inf
        growable = state.where((F.col("born") == number - 1) & (F.col("mask") != full)).drop("born")
        if not math.isinf(w_k):
            growable = growable.where(F.col("length") <= w_k)
            if half_cut:
                growable = growable.where(2 * F.col("length") <= w_k)
        if max_messages is not None or cut_at:
            predicted = growable.select("node_id").distinct().join(edges, F.col("node_id") == F.col("src")).count()
            for most in cut_at:
                if predicted > most and most not in out.cuts:
                    bound, lightest = masks.smallest_possible(masks.estimate_next(smallest, e_min, full) if smallest else {}, m), best[0]["length"] if best else None
                    out.cuts[most] = Cut("truncated_messages", lightest, bound, masks.spa_ratio(lightest, bound, False))
            if max_messages is not None and predicted > max_messages:
                status = "truncated_messages"
                break
        reached = functools.reduce(DataFrame.unionByName, visits)
        tagged = trees.grow(growable, edges, reached)
        if phase == "DRAIN":
            tagged = tagged.where("known")
        elif not deep:
            tagged = tagged.where("not known")
        if profile:
            parts = [timed("send_bfs", tagged.where("not known"), f"msgs{number}"), timed("send_deep", tagged.where("known"), f"deep{number}")]
            msgs = parts[0].unionByName(parts[1])
        else:
            msgs = timed("send_bfs", tagged, f"msgs{number}")
        incoming = msgs.select(*trees.COLUMNS)
        if not math.isinf(w_k):
            incoming = incoming.where(F.col("length") <= w_k)
        if local_minimal:
            incoming = trees.leaves_needed(incoming, F.col("mask"))
        t = time.time()
        incoming = trees.prune(incoming, keep)
        old_rows = state.join(incoming.select("node_id").distinct(), "node_id", "left_semi")
        pools = [_pool(incoming, old_rows, number, keep).persist()]
        looked_at = []
        for _ in range(max(0, math.ceil(math.log2(m)))):
            pool = pools[-1]
            fresh = pool.where(F.col("born") == number).drop("born")
            looked_at.append(trees.pairs_at_nodes(fresh, pool.drop("born")))
            born = trees.merge(fresh, pool.drop("born"))
            if not math.isinf(w_k):
                born = born.where(F.col("length") <= w_k)
            if local_minimal:
                born = trees.leaves_needed(born, F.col("mask"))
            pools.append(_pool(born, pool, number, keep).persist())
        pool = pools[-1]
        untouched = state.join(pool.select("node_id").distinct(), "node_id", "left_anti")
        new_state = work.save(untouched.unionByName(pool), f"state{number}", ["node_id"])
        combinations = sum(x.count() for x in looked_at) if measures else None
        for x in pools:
            x.unpersist()
        timers["receive"] += time.time() - t
        t = time.time()
        first_time = work.save(msgs.where("not known").select("node_id").distinct().withColumn("mask", F.lit(None).cast("int")), f"visits{number}")
        visits.append(first_time)
        delta = new_state.where(F.col("born") == number)
        looked = delta if scope == "active" else delta.join(first_time.select("node_id"), "node_id", "left_semi")
        fact = lambda what, key, x, n: (F.lit(what).alias("what"), key.cast("int").alias("key"), x.cast("double").alias("x"), n.cast("long").alias("n"))
        nothing = F.lit(None)
        facts = [
            looked.groupBy("mask").agg(F.min("length").alias("s")).select(*fact("smallest", F.col("mask"), F.col("s"), nothing)),
            delta.agg(F.countDistinct("node_id").alias("c")).select(*fact("active", nothing, nothing, F.col("c"))),
            first_time.agg(F.count("*").alias("c")).select(*fact("frontier", nothing, nothing, F.col("c"))),
            msgs.select("src", "node_id", "known").distinct().groupBy("known").agg(F.count("*").alias("c")).select(*fact("pairs", F.col("known"), nothing, F.col("c"))),
            msgs.agg(F.sum(F.size("tree")).alias("c")).select(*fact("tree_edges", nothing, nothing, F.coalesce("c", F.lit(0)))),
        ]
        facts += [new_state.agg(F.count("*").alias("c")).select(*fact("state_rows", nothing, nothing, F.col("c")))] if measures else []
        told: dict[str, dict] = {}
        for r in functools.reduce(DataFrame.unionByName, facts).collect():  # a few rows and 2^m
            told.setdefault(r["what"], {})[r["key"]] = r["x"] if r["what"] == "smallest" else r["n"]
        smallest = told.get("smallest", {})
        active, n_frontier, pairs = told["active"][None], told["frontier"][None], told.get("pairs", {})
        n_reached += n_frontier
        timers["send_aggregator"] += time.time() - t
        t = time.time()
        found = [r.asDict(True) for r in trees.minimal_answers(delta.drop("born"), full).dropDuplicates(["sig"]).orderBy("length", "sig").limit(k).collect()]
        timers["evaluate"] += time.time() - t
        best = _fold(best, found, k)
        largest: dict[int, float] = {}
        for a in best:
            for s, v in masks.subset_lengths([(e["a"], e["b"], e["len"]) for e in a["tree"]], _owners(a, full), full).items():
                largest[s] = max(largest.get(s, 0.0), v)
        estimate = masks.estimate_next(smallest, e_min, full)
        w_k = best[-1]["length"] if len(best) == k else math.inf
        candidates = traversed = 0
        if measures and largest:
            wanted = [f"(mask = {s} AND length + {e_min} < {v})" for s, v in largest.items() if not math.isinf(v)]
            may = delta.where(" OR ".join(wanted)).select("node_id").distinct()
            candidates = may.count()
            traversed = may.join(first_time, "node_id", "left_anti").count()
        decision = "go on"
        if not active:
            decision = "quiet"
        elif phase == "RUN" and stop == "published" and masks.stop_published(estimate, largest, len(best), k, tie_ok):
            decision = "drain"
        elif stop == "certified" and masks.lower_bound(smallest, e_min, full) >= w_k:
            decision = "certified"
        trace.append({
            "round": number, "phase": phase, "active": active, "frontier": n_frontier, "bfs_msgs": pairs.get(0, 0), "deep_msgs": pairs.get(1, 0), "reached": n_reached,
            "state_rows": told["state_rows"][None] if measures else None, "combinations": combinations, "tree_edges": told["tree_edges"][None], "s": smallest, "l": largest,
            "w_k": None if math.isinf(w_k) else w_k, "candidates": candidates, "traversed": traversed, "decision": decision, "ms": int(1000 * (time.time() - began)),
        })
        for name in (f"state{number - 1}", f"msgs{number}", *([f"deep{number}"] if profile else [])):
            work.drop(name)
        state = new_state
        if decision == "quiet":
            status = "optimal" if phase == "DRAIN" else "exhausted"
            break
        if decision == "certified":
            status = "optimal"
            break
        if decision == "drain":
            if not drain:
                status = "optimal_unproven"
                break
            phase = "DRAIN"
    work.close()
    if not best:
        status = "no_answer" if status in ("exhausted", "optimal") else status
    out.status = status
    estimate = masks.estimate_next(smallest, e_min, full) if smallest else {}
    return _finish(spark, graph, out, best, trace, m, estimate if status.startswith("truncated") else None, measures)


def _pool(fresh: DataFrame, had: DataFrame, number: int, keep: int) -> DataFrame:
    """Pruned rows of the touched nodes, dealt by node; ``born`` is the round in which a row came, the first if it came again."""
    both = fresh.withColumn("born", F.lit(number)).unionByName(had).repartition("node_id")
    return trees.prune(both, keep).select(*trees.COLUMNS, "born")


def _finish(spark: SparkSession, graph: RelGraph, out: SearchResult, best: list[dict], trace: list[dict], m: int, estimate: dict | None, measures: bool) -> SearchResult:
    full = (1 << m) - 1
    answers = []
    for rank, a in enumerate(best, 1):
        edges = sorted((e["a"], e["b"], e["len"]) for e in a["tree"])
        parts = masks.constituents(edges, _owners(a, full), a["node_id"])
        answers.append((rank, a["node_id"], float(a["length"]), len(edges), sorted(a["members"]), edges, parts, a["sig"]))
    out.best, out.rows = best, trace
    out.answers = spark.createDataFrame(answers, ANSWER)
    names = [x.split()[0] for x in TRACE.split(", ")]
    out.trace = spark.createDataFrame([tuple(t[n] for n in names) for t in trace], TRACE)
    if estimate is not None:
        out.smallest_possible = masks.smallest_possible(estimate, m)
        out.spa_ratio = masks.spa_ratio(best[0]["length"] if best else None, out.smallest_possible, False)
    elif out.status == "optimal" or (out.status == "exhausted" and best):
        out.spa_ratio = 0.0
    if measures and trace:
        n_v, n_e = graph.n_vertices(), graph.n_edges()
        sent = sum(t["bfs_msgs"] + t["deep_msgs"] for t in trace)
        out.pct_explored = 100 * trace[-1]["reached"] / max(1, n_v)
        out.pct_messages = 100 * sent / max(1, n_e)
        out.pct_messages_mirrored = out.pct_messages / 2
    return out


def cut_results(found: SearchResult, cut_at: tuple[int, ...]) -> dict[int, Cut]:
    """The end of a run by limit: its cut, or for limits that no round passed the end of the whole run."""
    whole = Cut(found.status, found.best[0]["length"] if found.best else None, found.smallest_possible, found.spa_ratio)
    return {most: found.cuts.get(most, whole) for most in cut_at}


def connecting_nodes(graph: RelGraph, seeds: DataFrame, m: int, k: int = 1, **options) -> DataFrame:
    """Only the roots of the K lightest trees, with their weights."""
    return relationship_search(graph, seeds, m, k, **options).answers.select("rank", "root", "weight")
