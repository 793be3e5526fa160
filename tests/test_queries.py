"""A part of the queries against their SQL at the smallest size, and plans without what must not be there."""

import glob
import os

import duckdb
import pytest

from relq.plans import registry

SF = "/root/testdata/sf0.001"
SOME = [
    "graph_fk_edges", "graph_contact_edges", "graph_link_edges", "graph_triple_edges", "edge_length_tau", "edge_length_strength", "mirror_edges", "index_postings_df", "seed_lookup_phrase", "seed_lookup_predicate",
    "keyword_distance", "bfs_levels", "explored_and_messages", "rel_m2_top1", "rel_m3_top1", "rel_m2_topk_weights", "deep_counts", "rel_lead_groups_apart", "graph_knn_edges", "state_subset_lengths", "workload_100", "keyword_node_growth", "threshold_topk", "spa_bound", "op_join_asof_event", "op_join_interval_contact",
    "op_agg_grouping_sets", "op_win_range_frame", "op_map_merge_min", "op_udtf_partitions", "op_sql_recursive_bfs", "op_scan_text_triples", "op_scale_free_source", "st_session", "st_dedup", "st_incremental_edges",
]


@pytest.fixture(scope="module")
def tables():
    c = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return c


def plain(v):
    if isinstance(v, float):
        return "NULL" if v != v else round(v, 6) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    return "NULL" if v is None else v


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_sql(spark, tables, name):
    df = registry.QUERIES[name](spark, SF)
    order = sorted(df.columns)
    found = tables.execute(registry.ORACLES[name])
    names = [x[0] for x in found.description]
    assert sorted(names) == order
    want = sorted(repr([plain(row[names.index(c)]) for c in order]) for row in found.fetchall())
    assert sorted(repr([plain(row[c]) for c in order]) for row in df.collect()) == want


def test_every_query_has_a_name_of_its_own():
    assert set(registry.ORACLES) <= set(registry.QUERIES) and len(registry.QUERIES) > 120


def test_scans_are_pruned_and_filters_pushed(spark):
    plan = registry.QUERIES["op_scan_filtered"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity)" in plan.replace("PushedFilters: [IsNotNull(l_returnflag), IsNotNull(l_quantity)", "PushedFilters: [IsNotNull(l_quantity)")
    assert "l_comment" not in plan and "l_extendedprice" not in plan


def test_no_python_and_no_product_in_the_search_loop(spark):
    from relq.search import trees

    seeds = spark.createDataFrame([(1, 1), (2, 2)], "node_id long, mask int")
    edges = spark.createDataFrame([(1, 2, 1.0)], "src long, dst long, length double")
    state = trees.seed_rows(seeds)
    grown = trees.grow(state, edges, seeds).drop("src")
    plan = trees.prune(trees.leaves_needed(trees.merge(grown.select(*trees.COLUMNS), state), trees.F.col("mask")), 3)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan and "NestedLoop" not in plan


@pytest.fixture(scope="module")
def unconnected(tmp_path_factory):
    """Tables whose events have a bucket of more than a thousand users, so no edge of the contact graph is short enough to stay."""
    folder = tmp_path_factory.mktemp("unconnected")
    c = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        name = os.path.basename(p)
        if name == "events.parquet":
            c.execute(f"COPY (SELECT e.* REPLACE (event_id + i * 1000 AS event_id, i * 1000 + user_id AS user_id, 'error' AS event_type, '{{\"k\": ' || CASE WHEN i % 2 = 0 THEN 3 ELSE 77 END || '}}' AS props) FROM '{p}' e, range(400) r(i)) TO '{folder}/{name}'")
        else:
            os.symlink(p, folder / name)
    for p in glob.glob(f"{folder}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return str(folder), c


@pytest.mark.parametrize("name", ["explored_and_messages", "stop_weights", "rel_lead_groups_apart", "rel_m2_top1", "rel_m3_top1", "rel_m4_top1", "search_m3_top1", "deep_counts"])
def test_query_equals_its_sql_without_edges(spark, unconnected, name):
    folder, c = unconnected
    df, found = registry.QUERIES[name](spark, folder), c.execute(registry.ORACLES[name])
    names = [x[0] for x in found.description]
    want = sorted(repr([row[names.index(k)] for k in df.columns]) for row in found.fetchall())
    assert sorted(repr(list(row)) for row in df.collect()) == want


def test_heuristics_without_an_answer(spark, unconnected):
    found = {r.method: r.weight for r in registry.QUERIES["heuristics_compare"](spark, unconnected[0]).collect()}
    assert found == {"exact": None, "search": None, "path union": None, "standalone": None, "standalone reads": 0.0, "metric closure": None}


@pytest.fixture(scope="module")
def one_order(tmp_path_factory):
    """A table of the lines of three orders alone."""
    path = tmp_path_factory.mktemp("one_order") / "lineitem.parquet"
    c = duckdb.connect()
    c.execute(f"COPY (SELECT * FROM '{SF}/lineitem.parquet' WHERE l_orderkey IN (SELECT DISTINCT l_orderkey FROM '{SF}/lineitem.parquet' ORDER BY 1 LIMIT 3)) TO '{path}'")
    c.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{path}'")
    return str(path.parent), c


@pytest.mark.parametrize("name", ["combination_counts", "cost_models", "op_bitmask_ops", "op_join_cross_masks", "op_join_theta_disjoint", "op_scale_free_source", "op_udtf_partitions", "op_udtf_submasks", "spa_bound"])
def test_query_follows_its_table(spark, tables, one_order, name):
    for folder, c in ((SF, tables), one_order):
        df, found = registry.QUERIES[name](spark, folder), c.execute(registry.ORACLES[name])
        names = [x[0] for x in found.description]
        want = sorted(repr([plain(row[names.index(k)]) for k in df.columns]) for row in found.fetchall())
        assert sorted(repr([plain(v) for v in row]) for row in df.collect()) == want
        if folder == SF:
            whole = want
    assert want != whole
