"""Parts of the method against plain versions, and plans that must not exchange more than they need."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from relq.baselines import exact, waves
from relq.graph import builders
from relq.graph.lengths import mirror
from relq.plans.workspace import Workspace, buckets_of
from relq.schema import RelGraph, check_names, node_id
from relq.search import batch, trees
from relq.search.driver import relationship_search
from relq.workload.queries import global_tiles


def random_case(spark, seed, n=40, m=3):
    rng = random.Random(seed)
    edges = [(a, rng.randrange(a), rng.randint(1, 4)) for a in range(1, n)] + [(*rng.sample(range(n), 2), rng.randint(1, 4)) for _ in range(n)]
    groups = [set(rng.sample(range(n), 3)) for _ in range(m)]
    e = mirror(spark.createDataFrame([(a, b, "e", float(w)) for a, b, w in edges], "src long, dst long, label string, length double")).persist()
    owners = {}
    for i, g in enumerate(groups):
        for x in g:
            owners[x] = owners.get(x, 0) | 1 << i
    graph = RelGraph(spark.createDataFrame([(k, "n", k, str(k)) for k in range(n)], "node_id long, kind string, key long, text string"), e)
    return edges, groups, graph, spark.createDataFrame(list(owners.items()), "node_id long, mask int").persist()


def exchanges(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")


def test_search_and_batch_agree_with_the_exact_weight(spark):
    edges, groups, graph, seeds = random_case(spark, 4, 30, 4)
    want = exact.exact_group_steiner(edges, groups)
    found = relationship_search(graph, seeds, 4, 1, measures=True)
    assert found.best[0]["length"] == want and found.status == "optimal"
    assert sum(r["combinations"] for r in found.rows) > 0 and sum(r["tree_edges"] for r in found.rows) > 0
    queries = seeds.select(F.lit(0).alias("query_id"), "node_id", "mask")
    answer = batch.batch_search(graph, queries, {0: 4})[0].first()
    assert answer.weight == want and answer.proven
    cut = batch.batch_search(graph, queries, {0: 4}, max_supersteps=1)[0].first()
    assert cut is None or not cut.proven


def test_a_profile_times_both_classes_of_messages(spark):
    *_, graph, seeds = random_case(spark, 5, 20, 2)
    timers = relationship_search(graph, seeds, 2, 1, profile=True).timers
    assert set(timers) == {"send_bfs", "receive", "send_deep", "send_aggregator", "evaluate"} and all(x > 0 for x in timers.values())


def test_backward_trees_lie_between_optimum_and_score(spark):
    edges, groups, graph, seeds = random_case(spark, 6)
    best, lengths = exact.exact_group_steiner(edges, groups), {}
    for r in graph.edges.collect():
        lengths[r.src, r.dst] = r.length
    rows = waves.backward_trees(graph, seeds, 3, 4).collect()
    assert [r["rank"] for r in rows] == [1, 2, 3, 4]
    for r in rows:
        assert best <= r.weight <= r.score and r.weight == sum(lengths[e["a"], e["b"]] for e in r.edges)


def test_threshold_topk_reads_a_part_and_equals_the_sort(spark):
    rng = random.Random(2)
    values = {(no, item): rng.random() ** 3 for no in range(3) for item in range(3_000) if rng.random() < 0.9}
    lists = spark.createDataFrame([(no, item, v) for (no, item), v in values.items()], "list_no int, item int, value double").persist()
    totals = sorted((sum(values[no, i] for no in range(3)), i) for i in range(3_000) if all((no, i) in values for no in range(3)))
    best, read = waves.threshold_topk(lists, 5)
    assert [r.item for r in best.collect()] == [i for _, i in totals[:5]] and read < len(values)
    assert waves.threshold_topk(lists.limit(0), 5)[0].count() == 0
    assert waves.threshold_topk(lists.where("item < 3"), 5)[0].count() <= 3


def test_nearest_neighbours_in_blocks(spark):
    rng = np.random.default_rng(1)
    points = rng.standard_normal((90, 8))
    points[50] = points[7]
    rows = spark.createDataFrame([(k, p.tolist(), 1) for k, p in enumerate(points)] + [(90, None, 1), (91, [0.0] * 8, 1)], "vec_id long, embedding array<double>, label int")
    unit = points / np.linalg.norm(points, axis=1, keepdims=True)
    far = np.round(np.maximum(1 - unit @ unit.T, 1e-9), 9)
    np.fill_diagonal(far, 9)
    want = {(i, j) for i in range(90) for j in sorted(range(90), key=lambda j, i=i: (far[i, j], j))[:3]}
    for block in (16, 2_048):
        assert {(r.vec_id, r.near_id) for r in builders.knn_pairs(rows, 3, block).collect()} == want


def test_tiles_equal_ntile(spark):
    rows = spark.createDataFrame([(k % 7, f"t{k}") for k in range(53)], "df int, term string")
    want = {r.term: r.rung for r in rows.selectExpr("term", "ntile(20) OVER (ORDER BY df, term) AS rung").collect()}
    assert {r.term: r.rung for r in global_tiles(rows, ["df", "term"], 20).collect()} == want


def test_keys_that_do_not_fit_stop_the_job(spark):
    assert spark.range(1).select(node_id("user", F.lit((1 << 48) - 1)).alias("x")).first().x == (7 << 48) | (1 << 48) - 1
    for key in (1 << 48, -1):
        with pytest.raises(Exception, match="48 bits"):
            spark.range(1).select(node_id("user", F.lit(key))).collect()
    assert spark.range(1).select(node_id("user", F.lit(None).cast("long")).alias("x")).first().x is None
    names = spark.createDataFrame([("a",), ("b",), ("a",), (None,)], "name string")
    assert check_names(names, "name").count() == 2


def test_two_names_of_one_key_are_refused(spark, monkeypatch):
    monkeypatch.setattr("relq.schema.text_key", lambda c: F.length(c).cast("long"))
    with pytest.raises(ValueError, match="share a hashed key"):
        check_names(spark.createDataFrame([("a",), ("b",)], "name string"), "name")


def test_turns_of_long_conversations_have_their_own_keys(spark):
    rows = spark.createDataFrame([(1, 4096, "user", "x"), (2, 0, "user", "y")], "conv_id long, turn long, role string, text string")
    assert builders.dialog_parts(rows)[0].where("kind = 'turn'").select("node_id").distinct().count() == 2


def test_bucketed_tables_are_not_exchanged_again(spark):
    work = Workspace(spark, "t")
    edges = batch.edges_by_source(spark.createDataFrame([(1, 2, 1.0), (2, 1, 1.0)], "src long, dst long, length double"), work)
    delta = spark.createDataFrame([(0, 1, 3.0)], "query_id int, node_id long, d double")
    plan = delta.join(edges.hint("merge"), F.col("node_id") == F.col("src"))
    assert exchanges(plan) == 1 and buckets_of(spark) == 4
    nodes = work.save(delta.repartition(4, "query_id", "node_id"), "nodes", ["query_id", "node_id"])
    assert exchanges(nodes.join(delta.groupBy("query_id", "node_id").agg(F.min("d").alias("x")), ["query_id", "node_id"], "full")) == 1
    work.close()


def test_receiving_exchanges_rows_once(spark):
    seeds = spark.createDataFrame([(1, 1), (2, 2)], "node_id long, mask int")
    dealt = trees.seed_rows(seeds).repartition("node_id")
    assert exchanges(trees.prune(dealt, 3)) == 1
    assert exchanges(trees.prune(trees.seed_rows(seeds), 3)) == 1


def test_words_of_documents_are_paired_without_an_exchange(spark):
    """A document names a word once, so its pairs are not compared; where documents share an id they are, and count once."""
    from relq.graph import builders

    def pairs(ids):
        docs = spark.createDataFrame([(k, text, "en", "web") for k, text in zip(ids, ("a b a", "b c"), strict=True)], "doc_id long, text string, lang string, source string")
        found = builders._word_edges(docs, builders.content_words(docs))
        return found._jdf.queryExecution().executedPlan().toString().count("Exchange"), sorted((r.src & 7, r.strength, r.label) for r in found.collect())

    assert pairs((1, 2)) == (0, [(1, 1, "contains")] * 2 + [(2, 1, "contains")] * 2)
    held, rows = pairs((1, 1))
    assert held and rows == [(1, 1, "contains")] * 2 + [(1, 2, "contains")]


def test_edges_at_targets_past_the_cut_are_not_exchanged(spark):
    """Rows of heavy targets go before the join on the target; lengths of the others are by their degree, as before."""
    from relq.graph.lengths import assign_lengths, mirror

    edges = spark.createDataFrame([(k, 100 + (k >= 8) * (k % 5), "e") for k in range(40)], "src long, dst long, label string")
    found = assign_lengths(edges, "step_log10_plus1", 12)
    assert "LeftAnti" in found._jdf.queryExecution().optimizedPlan().toString()
    counts = {}
    for r in edges.collect():
        counts[r.dst] = counts.get(r.dst, 0) + 1
    want = sorted((r.src, r.dst, float(len(str(counts[r.dst])))) for r in edges.collect() if counts[r.dst] < 12)
    assert sorted((r.src, r.dst, r.length) for r in found.collect()) == want and len(want) < 40
    rows = [(1, 2, "x", 2.0), (2, 1, "a", 2.0), (2, 1, "z", 3.0), (5, 4, "s", 1.0), (4, 4, "s", 1.0)]
    both = mirror(spark.createDataFrame(rows, "src long, dst long, label string, length double"))
    assert sorted(map(tuple, both.collect())) == [(1, 2, "x", 2.0, False), (2, 1, "a", 2.0, False), (4, 5, "s", 1.0, True), (5, 4, "s", 1.0, False)]
