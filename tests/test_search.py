import math
import random

import numpy as np
import pytest

from relq.baselines import exact
from relq.graph.lengths import mirror
from relq.schema import RelGraph
from relq.search import masks, replicated
from relq.search.batch import batch_search, rebuild
from relq.search.driver import Cut, cut_results, relationship_search

FIXTURES = {
    "meet": ([(10, 11, 1), (11, 12, 1)], [{10}, {12}], [2]),
    "three": ([(1, 4, 1), (2, 4, 2), (3, 4, 1), (1, 2, 4), (2, 3, 5)], [{1}, {2}, {3}], [4, 6, 7, 7, 8, 9]),
    "unbalanced": ([(2, 4, 1), (4, 5, 1), (5, 6, 1), (6, 7, 1), (7, 8, 1), (5, 9, 1)], [{2}, {8}, {9}], [6]),
    "joints": ([(1, 5, 2), (2, 5, 2), (5, 6, 1), (3, 6, 2), (4, 6, 2)], [{1}, {2}, {3}, {4}], [9]),
    "ties": ([(1, 2, 1), (2, 3, 1), (1, 4, 1), (4, 3, 1), (1, 3, 5)], [{1}, {3}], [2, 2, 5]),
    "drain": ([(0, 1, 3), (0, 2, 1), (0, 3, 1), (2, 4, 1)], [{2}, {1, 4}, {3}], [3, 5]),
    "one node": ([(1, 2, 2), (2, 3, 1)], [{1, 2}, {1, 3}], [0, 1]),
    "apart": ([(1, 2, 1), (3, 4, 1)], [{1}, {4}], []),
    "kept branch": ([(1, 5, 2), (2, 5, 3), (3, 5, 9), (5, 6, 1), (6, 7, 1)], [{1, 2}, {2, 7}, {3, 7}], [4, 5, 12]),
}


def build(spark, edges, groups):
    e = spark.createDataFrame([(a, b, "e", float(w)) for a, b, w in edges], "src long, dst long, label string, length double")
    nodes = sorted({x for a, b, _ in edges for x in (a, b)})
    v = spark.createDataFrame([(n, "n", n, str(n)) for n in nodes], "node_id long, kind string, key long, text string")
    owners = {}
    for i, g in enumerate(groups):
        for n in g:
            owners[n] = owners.get(n, 0) | 1 << i
    return RelGraph(v, mirror(e).persist()), spark.createDataFrame(list(owners.items()), "node_id long, mask int").persist()


@pytest.mark.parametrize("name", FIXTURES)
def test_enumeration_agrees_with_hand_values(name):
    edges, groups, weights = FIXTURES[name]
    assert [w for w, _ in exact.enumerate_answers(edges, groups)] == weights
    assert exact.exact_group_steiner(edges, groups) == (weights[0] if weights else math.inf)


@pytest.mark.parametrize("name", FIXTURES)
def test_topk_equals_enumeration(spark, name):
    edges, groups, weights = FIXTURES[name]
    graph, seeds = build(spark, edges, groups)
    k = min(5, max(1, len(weights)))
    found = relationship_search(graph, seeds, len(groups), k, stop="none")
    assert [a["length"] for a in found.best] == weights[:k]
    assert found.status == ("exhausted" if weights else "no_answer")
    for row in found.answers.collect():
        assert len(row.members) == row.n_edges + 1 and sum(e["len"] for e in row.edges) == row.weight
        assert not row.parts or math.isclose(sum(p["length"] for p in row.parts), row.weight)


def test_published_stop_needs_its_drain(spark):
    edges, groups, weights = FIXTURES["drain"]
    graph, seeds = build(spark, edges, groups)
    drained = relationship_search(graph, seeds, 3, 1)
    halted = relationship_search(graph, seeds, 3, 1, drain=False)
    certified = relationship_search(graph, seeds, 3, 1, stop="certified")
    assert drained.best[0]["length"] == certified.best[0]["length"] == 3 and drained.status == "optimal"
    assert halted.best[0]["length"] == 5


def test_unbalanced_trees_need_deep_messages(spark):
    edges, groups, _ = FIXTURES["unbalanced"]
    graph, seeds = build(spark, edges, groups)
    assert relationship_search(graph, seeds, 3, 1, deep=False, stop="none").status == "no_answer"
    found = relationship_search(graph, seeds, 3, 1, stop="none", measures=True)
    assert found.best[0]["length"] == 6
    assert found.pct_explored == 100 and found.pct_messages == 2 * found.pct_messages_mirrored


def test_cut_runs_report_a_bound(spark):
    edges, groups, _ = FIXTURES["three"]
    graph, seeds = build(spark, edges, groups)
    cut = relationship_search(graph, seeds, 3, 1, max_messages=3)
    assert cut.status == "truncated_messages"
    rounds = relationship_search(graph, seeds, 3, 2, stop="none", max_supersteps=1)
    assert rounds.status == "truncated_rounds" and rounds.smallest_possible is not None
    assert rounds.spa_ratio == rounds.best[0]["length"] / rounds.smallest_possible


def test_one_run_tells_what_every_limit_ends_with(spark):
    edges, groups, _ = FIXTURES["three"]
    graph, seeds = build(spark, edges, groups)
    limits = (0, 6, 1_000)
    told = cut_results(relationship_search(graph, seeds, 3, 1, max_messages=1_000, cut_at=limits), limits)
    for most in limits:
        alone = relationship_search(graph, seeds, 3, 1, max_messages=most)
        assert told[most] == Cut(alone.status, alone.best[0]["length"] if alone.best else None, alone.smallest_possible, alone.spa_ratio)
    assert told[0].status == "truncated_messages" != told[1_000].status


def test_unknown_keyword_and_single_keyword(spark):
    edges, groups, _ = FIXTURES["three"]
    graph, seeds = build(spark, edges, groups)
    assert relationship_search(graph, seeds, 4, 1).status == "unknown_keyword"
    graph, seeds = build(spark, edges, [{1, 3}])
    assert [a["length"] for a in relationship_search(graph, seeds, 1, 2, stop="none").best] == [0, 0]


def random_graph(rng, n, m):
    edges = [(a, rng.randrange(a), rng.randint(1, 4)) for a in range(1, n)] + [(*rng.sample(range(n), 2), rng.randint(1, 4)) for _ in range(n // 2)]
    return edges, [set(rng.sample(range(n), rng.randint(1, 2))) for _ in range(m)]


def test_batch_equals_exact_on_random_graphs(spark):
    """Many graphs side by side are one graph; each query sees its own part."""
    rng, cases, edges, seeds, queries = random.Random(7), [], [], [], {}
    for q in range(60):
        m = rng.randint(2, 4)
        e, groups = random_graph(rng, rng.randint(4, 12), m)
        cases.append((q, e, groups))
        edges += [(a + 1000 * q, b + 1000 * q, "e", float(w)) for a, b, w in e]
        owners = {}
        for i, g in enumerate(groups):
            for x in g:
                owners[x] = owners.get(x, 0) | 1 << i
        seeds += [(q, x + 1000 * q, mask) for x, mask in owners.items()]
        queries[q] = m
    e = mirror(spark.createDataFrame(edges, "src long, dst long, label string, length double")).persist()
    graph = RelGraph(spark.createDataFrame([(0, "n", 0, "")], "node_id long, kind string, key long, text string"), e)
    rows = spark.createDataFrame(seeds, "query_id int, node_id long, mask int")
    for half_cut in (True, False):
        answers, state, _ = batch_search(graph, rows, queries, half_cut=half_cut)
        got = {r.query_id: r.weight for r in answers.collect()}
        want = {q: exact.exact_group_steiner(e, g) for q, e, g in cases}
        assert got == {q: w for q, w in want.items() if not math.isinf(w)}
    lengths = {(min(a, b), max(a, b)): w for a, b, w in e.select("src", "dst", "length").collect()}
    weights = {}
    for r in rebuild(graph, answers, state).collect():
        weights[r.query_id] = weights.get(r.query_id, 0) + lengths[r.a, r.b]
    assert {q: weights.get(q, 0.0) for q in got} == got
    assert want == {q: exact.standalone_search(e, g)[0] for q, e, g in cases}


@pytest.mark.parametrize("limit", [replicated.MAX_EDGES, 0])
def test_best_trees_with_and_without_rounds_equal_exact(spark, limit, monkeypatch):
    """A graph that fits a task takes no rounds; a larger one does. Weights are exact both ways, and trees weigh as much and join their keywords."""
    rng, edges, seeds, queries, want, groups = random.Random(11), [], [], {}, {}, {}
    for q in range(40):
        m, shift = rng.randint(1, 5), 1000 * q
        e, sets = random_graph(rng, rng.randint(4, 30), m)
        e = [x for x in e if rng.random() < 0.9] or e
        want[q], queries[q], groups[q] = exact.exact_group_steiner(e, sets), m, [{x + shift for x in g} for g in sets]
        edges += [(a + shift, b + shift, "e", float(w)) for a, b, w in e]
        seeds += [(q, x, sum(1 << i for i, g in enumerate(groups[q]) if x in g)) for x in set().union(*groups[q])]
    graph = RelGraph(spark.createDataFrame([(0, "n", 0, "")], "node_id long, kind string, key long, text string"), mirror(spark.createDataFrame(edges, "src long, dst long, label string, length double")).persist())
    rounds = []
    monkeypatch.setattr(replicated, "batch_search", lambda *a: rounds.append(1) or batch_search(*a))
    answers, found = replicated.best_trees(graph, spark.createDataFrame(seeds, "query_id int, node_id long, mask int"), queries, max_edges=limit)
    got = {r.query_id: (r.weight, r.root) for r in answers.where("proven").collect()}
    assert len(rounds) == (limit == 0)
    assert {q: w for q, (w, _) in got.items()} == {q: w for q, w in want.items() if not math.isinf(w)} and len(got) < 40
    ways = {q: [] for q in got}
    for r in found.collect():
        ways[r.query_id].append((r.a, r.b, r.length))
    for q, (weight, root) in got.items():
        reached = {root}
        for _ in ways[q]:
            reached |= {x for a, b, _ in ways[q] if a in reached or b in reached for x in (a, b)}
        assert sum(w for *_, w in ways[q]) == weight and all(g & reached for g in groups[q])


def test_tours_bound_what_is_missing_by_all_keywords():
    """Three keywords at 2 from a node and 4 from each other: the tree weighs 6 at least, as half a walk past all of them; by twos it is 4."""
    from relq.search.batch import _round_trips

    missing = _round_trips(np.full((1, 3), 2.0), 4.0 * (1 - np.eye(3)))
    assert missing.tolist() == [[6.0, 4.0, 4.0, 2.0, 4.0, 2.0, 2.0, 0.0]]


def test_topk_on_a_random_graph(spark):
    rng = random.Random(3)
    for _ in range(2):
        edges, groups = random_graph(rng, 6, 3)
        graph, seeds = build(spark, edges, groups)
        want = [w for w, _ in exact.enumerate_answers(edges, groups, 3)]
        assert [a["length"] for a in relationship_search(graph, seeds, 3, 3, stop="none").best] == want
        assert [a["length"] for a in relationship_search(graph, seeds, 3, 3).best] == want


def test_combination_formulas():
    assert masks.count_combinations(2, 3) == 26
    paths = [(i, 1.0, frozenset({(i, j, 1.0)})) for i in range(3) for j in range(2)]
    assert exact.brute_local_topk(paths, 3, 2)[1] == 26
    assert masks.fold_cost(4, 1, 3) == 4 * 27 and masks.fold_cost(4, 1, 3, pairwise=False) == 125


def test_folds_agree():
    rng = random.Random(1)
    tables = [{1 << i: sorted((float(rng.randint(1, 9)), frozenset({10 * j + i})) for _ in range(2)) for i in range(3)} for j in range(3)]
    one, n_one = exact.fold(tables, 3, 2)
    all_, n_all = exact.fold(tables, 3, 2, pairwise=False)
    assert {s: [x for x, _ in r] for s, r in one.items()} == {s: [x for x, _ in r] for s, r in all_.items()} and n_one <= n_all


def test_bounds():
    estimate = {1: 4, 2: 5, 3: 6, 4: 2, 5: 9, 6: 3, 7: math.inf}
    assert masks.smallest_possible(estimate, 3) == 7
    assert masks.spa_ratio(13, 7, False) == 13 / 7 and masks.spa_ratio(13, 7, True) == 0
    assert masks.stop_published({1: 3, 2: 3, 3: 9}, {1: 1, 2: 3, 3: 4}, 1, 1) is False
    assert masks.stop_published({1: 3, 2: 3, 3: 9}, {1: 1, 2: 3, 3: 4}, 1, 1, tie_ok=True) is True


def test_heuristics_are_never_below_the_optimum():
    rng = random.Random(5)
    for _ in range(50):
        edges, groups = random_graph(rng, 9, 3)
        best = exact.exact_group_steiner(edges, groups)
        assert exact.path_union_heuristic(edges, groups) >= best
        lone = [{min(g)} for g in groups]
        assert exact.metric_closure_mst(edges, [min(g) for g in groups]) <= 2 * exact.exact_group_steiner(edges, lone)


@pytest.mark.parametrize("lengths", [replicated.MAX_LENGTHS, 1])
def test_arrays_written_by_tasks_equal_plain_ones(spark, lengths, monkeypatch):
    """Tasks write the rows of neighbours by blocks of nodes; joined they are those of the whole graph, whether lengths are numbered or not."""
    from relq.plans.workspace import Workspace

    monkeypatch.setattr(replicated, "BLOCK", 64)
    monkeypatch.setattr(replicated, "MAX_LENGTHS", lengths)
    rng, work = random.Random(5), Workspace(spark, "test")
    pairs = {tuple(sorted(rng.sample(range(0, 900, 3), 2))): rng.choice([0.25, 1.0, 2.0]) for _ in range(700)}
    once = spark.createDataFrame([(a, b, w) for (a, b), w in pairs.items()], "src long, dst long, length double").repartition(3)
    got = replicated.map_arrays(replicated.write_arrays(once, work, 1.0))
    near = {}
    for (a, b), w in pairs.items():
        near.setdefault(a, []).append((b, w))
        near.setdefault(b, []).append((a, w))
    assert got.ids.tolist() == sorted(near) and (got.scale is None) == (lengths == 1)
    for k, node in enumerate(got.ids.tolist()):
        at = slice(got.starts[k], got.starts[k + 1])
        assert list(zip(got.ids[got.ends[at]].tolist(), got.length(at).tolist(), strict=True)) == sorted(near[node])
    work.close()


def test_merges_see_few_nodes_where_the_first_weight_is_far_off():
    """Six keywords on arms of two legs that share long ways: distances sum to far more than the tree weighs, and the merges stay near it."""
    rng, edges = random.Random(2), [(0, 1, 4), (1, 2, 4), (2, 3, 4)]
    hands = list(range(10, 16))
    edges += [(0 if x < 13 else 3, x, 1) for x in hands]
    edges += [(x, 100 + 200 * i + j, 2 + j % 3) for i, x in enumerate(hands) for j in range(200)]
    edges += [(100 + rng.randrange(1200), 2000 + j, 5) for j in range(3000) for _ in range(2)]
    edges = list({(a, b): (a, b, float(w)) for a, b, w in edges}.values())
    ids, spots = np.unique([x for a, b, _ in edges for x in (a, b)], return_inverse=True)
    a, b, w = spots[::2], spots[1::2], np.array([w for *_, w in edges])
    near, order = np.concatenate([a, b]), np.argsort(np.concatenate([a, b]), kind="stable")
    starts = np.concatenate([[0], np.cumsum(np.bincount(near))])
    graph = replicated.Arrays(ids, starts, np.concatenate([b, a])[order].astype(np.int32), np.concatenate([w, w])[order], None, 1.0)
    seen, plain = [], replicated._merges
    replicated._merges = lambda g, nodes, *rest: seen.append(len(nodes)) or plain(g, nodes, *rest)
    try:
        _, weight, by_sum, tree = replicated.best_tree(graph, np.array(hands), np.array([1 << i for i in range(6)]), 6)
    finally:
        replicated._merges = plain
    assert weight == sum(x for *_, x in tree) == 18.0 and not by_sum
    assert max(seen) < 1000 < len(ids) / 4, seen
