"""The experiment workloads on the given tables, and the pieces of the method as queries."""

from __future__ import annotations

import math
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..baselines import exact, waves
from ..graph import builders, lengths
from ..graph.builders import table as t
from ..measures import report
from ..operators.relational import query
from ..plans.workspace import Workspace
from ..schema import RelGraph, node_id, text_key
from ..search import masks, trees
from ..search.batch import batch_search, partial_rows
from ..search.driver import cut_results, relationship_search
from ..search.replicated import best_trees
from ..text.index import build_index, document_frequency
from ..text.lookup import expand_submasks, find_seeds

# graphs -------------------------------------------------------------------
_FK = """WITH l AS (SELECT DISTINCT l_orderkey o, l_partkey p, l_suppkey s FROM lineitem), fk AS (
SELECT 'in_region' label, 'nation'||n_nationkey a, 'region'||n_regionkey b FROM nation UNION ALL SELECT 'customer_in', 'customer'||c_custkey, 'nation'||c_nationkey FROM customer
UNION ALL SELECT 'supplier_in', 'supplier'||s_suppkey, 'nation'||s_nationkey FROM supplier UNION ALL SELECT 'placed_by', 'order'||o_orderkey, 'customer'||o_custkey FROM orders
UNION ALL SELECT DISTINCT 'order_part', 'order'||o, 'part'||p FROM l UNION ALL SELECT DISTINCT 'order_supplier', 'order'||o, 'supplier'||s FROM l UNION ALL SELECT DISTINCT 'part_supplier', 'part'||p, 'supplier'||s FROM l),
deg AS (SELECT b, count(*) AS degree FROM fk GROUP BY b)"""


@query("SELECT 'region' AS kind, count(*) AS n FROM region UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT 'customer', count(*) FROM customer UNION ALL SELECT 'supplier', count(*) FROM supplier UNION ALL SELECT 'part', count(*) FROM part UNION ALL SELECT 'order', count(*) FROM orders")
def graph_fk_nodes(s, d):
    return builders.fk_vertices(s, d).groupBy("kind").agg(F.count("*").alias("n"))


@query(_FK + " SELECT label, count(*) AS n FROM fk GROUP BY label")
def graph_fk_edges(s, d):
    return builders.fk_edges(s, d).groupBy("label").agg(F.count("*").alias("n"))


_CONTACT = """WITH p AS (SELECT DISTINCT 'u'||user_id a, 'b'||CAST(json_extract_string(props, '$.k') AS BIGINT) b FROM events UNION SELECT DISTINCT 'u'||user_id, 'e'||event_type FROM events),
deg AS (SELECT b, count(*) AS degree FROM p GROUP BY b), g1 AS (SELECT a, p.b, length(CAST(degree AS VARCHAR))::DOUBLE AS w FROM p JOIN deg ON p.b = deg.b WHERE degree < 1001),
g AS (SELECT a AS src, b AS dst, w FROM g1 UNION ALL SELECT b, a, w FROM g1)"""


@query(_CONTACT + " SELECT substr(b, 1, 1) AS side, count(*) AS n, sum(w) AS total FROM g1 GROUP BY 1")
def graph_contact_edges(s, d):
    g = builders.contact_graph(s, d).edges.where("not mirrored")
    return g.groupBy(F.when(F.col("label") == "did", "e").otherwise("b").alias("side")).agg(F.count("*").alias("n"), F.sum("length").alias("total"))


@query("SELECT 'refers_to' AS label, count(*) AS n FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages) UNION ALL SELECT 'served_by', count(*) FROM pages WHERE regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) <> ''")
def graph_link_edges(s, d):
    return builders.link_parts(t(s, d, "pages"))[1].groupBy("label").agg(F.count("*").alias("n"))


@query("SELECT 'part_of' AS label, count(*) AS n FROM conversations UNION ALL SELECT 'next', count(*) - count(DISTINCT conv_id) FROM conversations")
def graph_dialog_edges(s, d):
    return builders.dialog_parts(t(s, d, "conversations"))[1].groupBy("label").agg(F.count("*").alias("n"))


@query("SELECT 'written_in' AS label, count(*) AS n FROM documents WHERE lang IS NOT NULL UNION ALL SELECT 'comes_from', count(*) FROM documents WHERE source IS NOT NULL UNION ALL SELECT 'marked', 2 * count(*) FROM labels UNION ALL SELECT 'contains', sum(len(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))))::BIGINT FROM documents")
def graph_content_edges(s, d):
    return builders.content_parts(t(s, d, "documents"), t(s, d, "labels"))[1].groupBy("label").agg(F.count("*").alias("n"))


@query("""WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), p AS (SELECT a.vec_id, b.vec_id AS near_id, greatest(1 - list_cosine_similarity(a.e, b.e), 1e-9) AS distance FROM v a JOIN v b ON a.vec_id <> b.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY round(distance, 9), near_id) AS r FROM p) SELECT vec_id, near_id, round(distance, 5) AS distance FROM r WHERE r <= 3""")
def graph_knn_edges(s, d):
    return builders.knn_pairs(t(s, d, "embeddings"), 3).withColumn("distance", F.round("distance", 5))


@query("SELECT 'has_name' AS text_found, count(*) AS n FROM nation UNION ALL SELECT 'edges', 2 * count(*) FROM nation")
def graph_triple_edges(s, d):
    nation = t(s, d, "nation")
    sub = F.concat(F.lit("nation/"), "n_nationkey")
    triples = nation.select(sub.alias("subject"), F.lit("name").alias("predicate"), F.concat(F.lit('"'), "n_name", F.lit('"')).alias("object")).unionByName(nation.select(sub.alias("subject"), F.lit("in").alias("predicate"), F.concat(F.lit("region/"), "n_regionkey").alias("object")))
    g = builders.triple_graph(triples)
    named = g.vertices.where(~F.col("text").contains("/")).agg(F.lit("has_name").alias("text_found"), F.count("*").alias("n"))
    return named.unionByName(g.edges.agg(F.lit("edges").alias("text_found"), F.count("*").alias("n")))


def _length_query(name: str, scheme: str, tau: int | None, sql_length: str) -> None:
    where = f"WHERE degree < {tau}" if tau else ""
    sql = f"{_FK} SELECT label, round(sum({sql_length}), 4) AS total, count(*) AS n FROM fk JOIN deg ON fk.b = deg.b {where} GROUP BY label"
    query(sql, name)(lambda s, d: lengths.assign_lengths(builders.fk_edges(s, d), scheme, tau).groupBy("label").agg(F.round(F.sum("length"), 4).alias("total"), F.count("*").alias("n")))


_DIGITS = "length(CAST(degree AS VARCHAR))"
_length_query("edge_length_step", "step_log10", None, f"({_DIGITS} - 1)::DOUBLE")
_length_query("edge_length_plus1", "step_log10_plus1", None, f"{_DIGITS}::DOUBLE")
_length_query("edge_length_tau", "step_log10_plus1", 1001, f"{_DIGITS}::DOUBLE")
_length_query("edge_length_log", "log_degree", None, "log2(1 + degree)")
_length_query("edge_length_uniform", "uniform", None, "1.0::DOUBLE")


@query("SELECT round(sum(1.0 / n), 6) AS total, count(*) AS edges FROM (SELECT l_partkey, l_suppkey, count(*) AS n FROM lineitem GROUP BY 1, 2)")
def edge_length_strength(s, d):
    e = lengths.assign_lengths(builders.fk_edges(s, d).where("label = 'part_supplier'"), "inverse_strength", None)
    return e.agg(F.round(F.sum("length"), 6).alias("total"), F.count("*").alias("edges"))


@query(_CONTACT + " SELECT count(*) AS n, count(DISTINCT src) AS nodes, sum(w) AS total FROM g")
def mirror_edges(s, d):
    return builders.contact_graph(s, d).edges.agg(F.count("*").alias("n"), F.countDistinct("src").alias("nodes"), F.sum("length").alias("total"))


@query(_CONTACT + " SELECT min(w) AS e_min FROM g")
def min_edge(s, d):
    return lengths.min_edge_length(builders.contact_graph(s, d).edges)


# index and lookup ---------------------------------------------------------
_TERMS = "SELECT p_partkey, unnest(list_distinct(regexp_extract_all(lower(p_name || ' ' || p_brand || ' ' || p_type), '[\\p{L}\\p{N}]+'))) AS term FROM part"


def _parts(s, d) -> DataFrame:
    return builders.fk_vertices(s, d).where("kind = 'part'")


@query(f"SELECT term, count(*) AS df FROM ({_TERMS}) GROUP BY term")
def index_postings_df(s, d):
    return document_frequency(build_index(_parts(s, d)))


_KEYS = (1 << 48) - 1


def _seed_keys(seeds: DataFrame) -> DataFrame:
    return seeds.select(F.col("node_id").bitwiseAND(_KEYS).alias("key"), "mask")


@query(f"SELECT p_partkey AS key, bit_or(CASE term WHEN 'anvil' THEN 1 WHEN 'bolt' THEN 2 ELSE 4 END)::INT AS mask FROM ({_TERMS}) WHERE term IN ('anvil', 'bolt', 'blue') GROUP BY p_partkey")
def seed_lookup_token(s, d):
    v = _parts(s, d)
    return _seed_keys(find_seeds(build_index(v), v, ["anvil", "bolt", "blue"]))


@query("SELECT p_partkey AS key, 1 AS mask FROM part WHERE regexp_matches(lower(p_name), '(^|[^a-z0-9])blue[^a-z0-9]+bolt($|[^a-z0-9])')")
def seed_lookup_phrase(s, d):
    v = _parts(s, d)
    return _seed_keys(find_seeds(build_index(v), v, ["blue bolt"], "phrase"))


@query(f"SELECT DISTINCT p_partkey AS key, 1 AS mask FROM ({_TERMS}) WHERE starts_with(term, 'bo')")
def seed_lookup_prefix(s, d):
    v = _parts(s, d)
    return _seed_keys(find_seeds(build_index(v), v, ["bo"], "prefix"))


@query("SELECT DISTINCT user_id AS key, 1 AS mask FROM events WHERE user_id % 10 = 7")
def seed_lookup_regex(s, d):
    v = builders.contact_parts(t(s, d, "events"))[0]
    return _seed_keys(find_seeds(build_index(v), v, ["^user .*7$"], "regex"))


@query("SELECT c_custkey AS key, (CASE WHEN c_mktsegment = 'BUILDING' THEN 1 ELSE 0 END | CASE WHEN c_custkey % 10 = 7 THEN 2 ELSE 0 END)::INT AS mask FROM customer WHERE c_mktsegment = 'BUILDING' OR c_custkey % 10 = 7")
def seed_lookup_predicate(s, d):
    v = builders.fk_vertices(s, d).where("kind = 'customer'")
    return _seed_keys(find_seeds(v, v, ["text LIKE '% BUILDING'", "key % 10 = 7"], "predicate"))


@query(f"SELECT mask, count(*) AS n FROM (SELECT p_partkey, bit_or(CASE term WHEN 'anvil' THEN 1 WHEN 'bolt' THEN 2 ELSE 4 END)::INT AS mask FROM ({_TERMS}) WHERE term IN ('anvil', 'bolt', 'blue') GROUP BY p_partkey) GROUP BY mask")
def seed_masks(s, d):
    return seed_lookup_token(s, d).groupBy("mask").agg(F.count("*").alias("n"))


@query(f"WITH q AS (SELECT p_partkey, bit_or(CASE term WHEN 'anvil' THEN 1 WHEN 'bolt' THEN 2 ELSE 4 END)::INT AS m FROM ({_TERMS}) WHERE term IN ('anvil', 'bolt', 'blue') GROUP BY p_partkey) SELECT k::INT AS mask, count(*) AS n FROM q, range(1, 8) r(k) WHERE k & m = k GROUP BY k")
def seed_expansion(s, d):
    v = _parts(s, d)
    return expand_submasks(find_seeds(build_index(v), v, ["anvil", "bolt", "blue"])).groupBy("mask").agg(F.count("*").alias("n"))


# searches on the contact graph --------------------------------------------
TERMS = ["3", "77", "error", "12"]
ROUNDS = 8


def _named(graph: RelGraph) -> DataFrame:
    name = F.concat(F.substring("kind", 1, 1), F.when(F.col("kind") == "event_type", F.col("text")).otherwise(F.col("key").cast("string")))
    return graph.vertices.select("node_id", name.alias("name"))


def _contact(s, d, m: int) -> tuple[RelGraph, DataFrame]:
    g = builders.contact_graph(s, d)
    g = RelGraph(g.vertices, g.edges.persist(), g.tau, g.scheme)
    return g, find_seeds(build_index(g.vertices), g.vertices, TERMS[:m])


def _sql_seeds(m: int) -> str:
    """Nodes of the first m keywords by name: a number names a user and a bucket, a word an event type."""
    rows = []
    for i, term in enumerate(TERMS[:m]):
        rows += [f"SELECT node, {i} AS q FROM nodes WHERE node IN ({', '.join(repr(p + term) for p in ('u', 'b', 'e'))})"]
    return " UNION ALL ".join(rows)


def _sql_distances(m: int, rounds: int = ROUNDS, seeds: str | None = None) -> str:
    """Unrolled relaxation: layer n holds the least length of each node and keyword over at most n edges."""
    out = [_CONTACT, f", nodes AS (SELECT DISTINCT src AS node FROM g UNION SELECT DISTINCT a FROM p UNION SELECT DISTINCT b FROM p), d0 AS (SELECT node, q, 0.0::DOUBLE AS w FROM ({seeds or _sql_seeds(m)}))"]
    for n in range(1, rounds + 1):
        out.append(f", d{n} AS (SELECT node, q, min(w) AS w FROM (SELECT * FROM d{n - 1} UNION ALL SELECT g.dst, q, x.w + g.w FROM d{n - 1} x JOIN g ON g.src = x.node) GROUP BY node, q)")
    return " ".join(out)


@query(_sql_distances(2, 3).replace(", nodes AS", ", nodes AS", 1) + " SELECT node AS name, q::INT AS bit, w AS length FROM d3")
def keyword_distance(s, d):
    g, seeds = _contact(s, d, 2)
    return waves.keyword_distances(g, seeds, 2, 3).join(_named(g), "node_id").select("name", "bit", "length")


@query(_sql_distances(1, 0) + ", h0 AS (SELECT node, 0 AS hop FROM d0), " + ", ".join(f"h{n} AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM h{n - 1} UNION ALL SELECT g.dst, hop + 1 FROM h{n - 1} JOIN g ON g.src = node) GROUP BY node)" for n in (1, 2, 3)) + " SELECT hop::INT AS hop, count(*) AS n FROM h3 GROUP BY hop")
def bfs_levels(s, d):
    g, seeds = _contact(s, d, 1)
    return waves.parallel_bfs(g, seeds, 3)[0].groupBy("hop").agg(F.count("*").alias("n"))


@query(_sql_distances(1, 0) + ", h0 AS (SELECT node, 0 AS hop FROM d0), " + ", ".join(f"h{n} AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM h{n - 1} UNION ALL SELECT g.dst, hop + 1 FROM h{n - 1} JOIN g ON g.src = node) GROUP BY node)" for n in (1, 2)) + """
SELECT round(100.0 * (SELECT count(*) FROM h2) / (SELECT count(*) FROM nodes), 6) AS pct_explored, round(100.0 * (SELECT count(*) FROM h2 JOIN g ON g.src = h2.node WHERE hop < 2) / (SELECT count(*) FROM g1), 6) AS pct_messages""")
def explored_and_messages(s, d):
    """Share of nodes reached and of edges used in two rounds."""
    g, seeds = _contact(s, d, 1)
    reached = waves.parallel_bfs(g, seeds, 2)[0]
    sent = reached.where("hop < 2").join(g.edges, reached["node_id"] == F.col("src")).count()
    n, e = g.vertices.select("node_id").distinct().count(), g.n_edges()
    share = lambda part, whole: F.round(F.lit(100.0) * part / whole if whole else F.lit(math.nan), 6)
    return reached.agg(share(F.count("*"), n).alias("pct_explored")).withColumn("pct_messages", share(F.lit(sent), e))


def _sum_of(m: int, seeds: str | None = None) -> str:
    return f"{_sql_distances(m, seeds=seeds)}, t AS (SELECT node, sum(w) AS w, count(*) AS n FROM d{ROUNDS} GROUP BY node) SELECT {m} AS m, min(w) AS weight FROM t WHERE n = {m}"


def _one_weight(answers: DataFrame, m: int) -> DataFrame:
    """One row with the least weight; null where no tree joins the keywords."""
    return answers.agg(F.min("weight").alias("weight")).select(F.lit(m).alias("m"), "weight")


def _best_weight(s, d, m: int) -> DataFrame:
    g, seeds = _contact(s, d, m)
    answers, _, _ = batch_search(g, seeds.withColumn("query_id", F.lit(0)).select("query_id", "node_id", "mask"), {0: m})
    return _one_weight(answers, m)


@query(_sum_of(1))
def rel_m1(s, d):
    return _best_weight(s, d, 1)


@query(_sum_of(2))
def rel_m2_top1(s, d):
    return _best_weight(s, d, 2)


@query(_sum_of(3))
def rel_m3_top1(s, d):
    return _best_weight(s, d, 3)


def _four() -> str:
    pairs = [(a, b) for a in range(4) for b in range(a + 1, 4)]
    layers = [f", p0 AS (SELECT x.node, x.q * 4 + y.q AS q, min(x.w + y.w) AS w FROM d{ROUNDS} x JOIN d{ROUNDS} y ON x.node = y.node AND x.q < y.q GROUP BY 1, 2)"]
    for n in range(1, ROUNDS + 1):
        layers.append(f", p{n} AS (SELECT node, q, min(w) AS w FROM (SELECT * FROM p{n - 1} UNION ALL SELECT g.dst, q, x.w + g.w FROM p{n - 1} x JOIN g ON g.src = x.node) GROUP BY node, q)")
    joins = []
    for a, b in pairs:
        c, e = (x for x in range(4) if x not in (a, b))
        joins.append(f"SELECT p.w + c.w + e.w AS w FROM p{ROUNDS} p JOIN d{ROUNDS} c ON c.node = p.node AND c.q = {c} JOIN d{ROUNDS} e ON e.node = p.node AND e.q = {e} WHERE p.q = {a * 4 + b}")
    return _sql_distances(4) + " ".join(layers) + " SELECT 4 AS m, min(w) AS weight FROM (" + " UNION ALL ".join(joins) + ")"


@query(_four())
def rel_m4_top1(s, d):
    return _best_weight(s, d, 4)


@query(f"{_sql_distances(2)}, t AS (SELECT node, sum(w) AS w, count(*) AS n FROM d{ROUNDS} GROUP BY node) SELECT node AS name, w AS weight FROM t WHERE n = 2")
def rel_m2_roots(s, d):
    """Best weight at every node as root."""
    g, seeds = _contact(s, d, 2)
    _, state, _ = batch_search(g, seeds.withColumn("query_id", F.lit(0)).select("query_id", "node_id", "mask"), {0: 2}, bounded=False)
    return partial_rows(state).where("mask = 3").join(_named(g), "node_id").select("name", F.col("length").alias("weight"))


@query(f"{_sql_distances(2, 2)} SELECT node AS name, (q + 1)::INT AS mask, w AS length FROM d2 UNION ALL SELECT x.node, 3, x.w + y.w FROM d2 x JOIN d2 y ON x.node = y.node AND x.q = 0 AND y.q = 1")
def state_subset_lengths(s, d):
    g, seeds = _contact(s, d, 2)
    _, state, _ = batch_search(g, seeds.withColumn("query_id", F.lit(0)).select("query_id", "node_id", "mask"), {0: 2}, max_supersteps=2, bounded=False)
    return partial_rows(state).join(_named(g), "node_id").select("name", "mask", "length")


@query(f"{_sql_distances(2, 2)} SELECT q::INT + 1 AS mask, min(w) AS s FROM d2 WHERE node NOT IN (SELECT node FROM d1) GROUP BY q")
def smallest_lengths_by_round(s, d):
    """Least lengths of single keywords over the nodes first reached in round two."""
    g, seeds = _contact(s, d, 2)
    two, one = (waves.keyword_distances(g, seeds, 2, n) for n in (2, 1))
    return two.join(one.select("node_id").distinct(), "node_id", "left_anti").groupBy((F.col("bit") + 1).alias("mask")).agg(F.min("length").alias("s"))


@query(f"{_sql_distances(3)}, t AS (SELECT node, sum(w) AS w, count(*) AS n FROM d{ROUNDS} GROUP BY node) SELECT w AS score FROM t WHERE n = 3 ORDER BY w LIMIT 5")
def backward_expansion_topk(s, d):
    g, seeds = _contact(s, d, 3)
    return waves.backward_expansion(g, seeds, 3, 5).select("score")


def _lead_weight(s, d, groups: list[DataFrame]) -> DataFrame:
    """Lightest tree over groups of users, each given as rows with ``user_id``."""
    g, _ = _contact(s, d, 1)
    parts = [rows.select(node_id("user", "user_id").alias("node_id"), F.lit(1 << i).alias("mask")).distinct() for i, rows in enumerate(groups)]
    seeds = reduce(DataFrame.unionByName, parts).groupBy("node_id").agg(F.bit_or("mask").cast("int").alias("mask")).select(F.lit(0).alias("query_id"), "node_id", "mask")
    return _one_weight(batch_search(g, seeds, {0: len(groups)})[0], len(groups))


@query()
def backward_expansion_trees(s, d):
    """The five best roots with the union of their shortest paths."""
    g, seeds = _contact(s, d, 3)
    return waves.backward_trees(g, seeds, 3, 5)


@query(_sum_of(3, """SELECT DISTINCT 'u'||user_id AS node, 0 AS q FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) = 3
UNION ALL SELECT DISTINCT 'u'||user_id, 1 FROM events WHERE user_id % 10 = 7 UNION ALL SELECT DISTINCT 'u'||user_id, 2 FROM events WHERE event_type = 'error'"""))
def rel_lead_groups(s, d):
    """Three groups of leads: users of a bucket, users whose id ends in 7, users with an error. They may share users."""
    e = t(s, d, "events")
    return _lead_weight(s, d, [e.where(F.get_json_object("props", "$.k").cast("long") == 3), e.where("user_id % 10 = 7"), e.where("event_type = 'error'")])


@query(_sum_of(3, """SELECT DISTINCT 'u'||user_id AS node, 0 AS q FROM events WHERE user_id < 4
UNION ALL SELECT DISTINCT 'u'||user_id, 1 FROM events WHERE user_id BETWEEN 5 AND 7 UNION ALL SELECT DISTINCT 'u'||user_id, 2 FROM events WHERE user_id BETWEEN 9 AND 12"""))
def rel_lead_groups_apart(s, d):
    """Three groups of leads without a common user: the answer is the way they are connected."""
    e = t(s, d, "events")
    return _lead_weight(s, d, [e.where("user_id < 4"), e.where("user_id BETWEEN 5 AND 7"), e.where("user_id BETWEEN 9 AND 12")])


# the search for trees, against SQL ------------------------------------------
@query(_sum_of(3))
def search_m3_top1(s, d):
    """Weight of the lightest tree, by the search that carries trees, its own stop test and drain."""
    g, seeds = _contact(s, d, 3)
    return _one_weight(relationship_search(g, seeds, 3, 1).answers, 3)


@query(_sql_distances(2, 0) + """, a AS (SELECT node FROM d0 WHERE q = 0), z AS (SELECT node FROM d0 WHERE q = 1), inner_nodes AS (SELECT node FROM nodes WHERE node NOT IN (SELECT node FROM d0)),
way AS (SELECT 0.0::DOUBLE AS w FROM a JOIN z ON a.node = z.node
UNION ALL SELECT g.w FROM a JOIN g ON g.src = a.node JOIN z ON z.node = g.dst WHERE a.node NOT IN (SELECT node FROM z) AND z.node NOT IN (SELECT node FROM a)
UNION ALL SELECT x.w + y.w FROM a JOIN g x ON x.src = a.node JOIN inner_nodes i ON i.node = x.dst JOIN g y ON y.src = x.dst JOIN z ON z.node = y.dst WHERE a.node NOT IN (SELECT node FROM z) AND z.node NOT IN (SELECT node FROM a)
UNION ALL SELECT x.w + y.w + v.w FROM a JOIN g x ON x.src = a.node JOIN inner_nodes i ON i.node = x.dst JOIN g y ON y.src = x.dst JOIN inner_nodes j ON j.node = y.dst JOIN g v ON v.src = y.dst JOIN z ON z.node = v.dst
WHERE a.node NOT IN (SELECT node FROM z) AND z.node NOT IN (SELECT node FROM a))
SELECT row_number() OVER (ORDER BY w)::INT AS rank, w AS weight FROM way ORDER BY w LIMIT 5""")
def rel_m2_topk_weights(s, d):
    """The five least weights of minimal trees for two keywords; the SQL lists ways of up to three edges."""
    g, seeds = _contact(s, d, 2)
    return relationship_search(g, seeds, 2, 5).answers.select("rank", "weight")


@query(_sql_distances(2, 0) + """, sent1 AS (SELECT DISTINCT src, dst FROM g WHERE src IN (SELECT node FROM d0)), known1 AS (SELECT node FROM d0 UNION SELECT dst FROM sent1),
held AS (SELECT DISTINCT g.dst AS node, x.node AS leaf FROM d0 x JOIN g ON g.src = x.node LEFT JOIN d0 y ON y.node = g.dst AND y.q = x.q WHERE y.node IS NULL),
sent2 AS (SELECT DISTINCT g.src, g.dst FROM held JOIN g ON g.src = held.node WHERE g.dst <> held.leaf)
SELECT 1::INT AS round, count(*) FILTER (dst NOT IN (SELECT node FROM d0)) AS bfs_msgs, count(*) FILTER (dst IN (SELECT node FROM d0)) AS deep_msgs FROM sent1
UNION ALL SELECT 2, count(*) FILTER (dst NOT IN (SELECT node FROM known1)), count(*) FILTER (dst IN (SELECT node FROM known1)) FROM sent2""")
def deep_counts(s, d):
    """Messages to unreached and to reached nodes in the first two rounds."""
    g, seeds = _contact(s, d, 2)
    sent = {r["round"]: (r["bfs_msgs"], r["deep_msgs"]) for r in relationship_search(g, seeds, 2, 10, stop="none", max_supersteps=2).rows}
    return s.createDataFrame([(n, *sent.get(n, (0, 0))) for n in (1, 2)], "round int, bfs_msgs long, deep_msgs long")


@query(_sum_of(2).replace("SELECT 2 AS m, min(w) AS weight FROM t WHERE n = 2", "SELECT variant, weight FROM (SELECT min(w) AS weight FROM t WHERE n = 2), (VALUES ('published'), ('certified'), ('none'), ('half cut')) v(variant)"))
def stop_weights(s, d):
    """Each exact stop rule ends at the same weight."""
    g, seeds = _contact(s, d, 2)
    rows = []
    for name, options in EXACT_STOPS.items():
        found = relationship_search(g, seeds, 2, 1, **options)
        rows.append((name, float(found.best[0]["length"]) if found.best else None))
    return s.createDataFrame(rows, "variant string, weight double")


EXACT_STOPS = {"published": {}, "certified": {"stop": "certified"}, "none": {"stop": "none"}, "half cut": {"stop": "none", "half_cut": True}}


_ORDER_WEIGHTS = "SELECT bit_or(1 << (l_suppkey % 3)::INT)::INT AS k, sum(l_quantity) AS w FROM lineitem WHERE l_orderkey IS NOT NULL AND l_suppkey IS NOT NULL GROUP BY l_orderkey"


@query(f"""WITH RECURSIVE e AS (SELECT k, min(w) AS v FROM ({_ORDER_WEIGHTS}) WHERE k < 7 GROUP BY k), c(m, w, n) AS (SELECT 0, 0.0::DOUBLE, 0 UNION SELECT m | k, c.w + v, n + 1 FROM c JOIN e ON k & m <> k WHERE n < 3) SELECT min(w)::DOUBLE AS bound FROM c WHERE m = 7""")
def spa_bound(s, d):
    """Smallest possible weight of all three groups of suppliers from the lightest orders of each other subset, by unrolled joins of covers."""
    lines = t(s, d, "lineitem").where("l_orderkey is not null and l_suppkey is not null")
    orders = lines.groupBy("l_orderkey").agg(F.bit_or(F.expr("shiftleft(1, cast(l_suppkey % 3 as int))")).alias("k"), F.sum("l_quantity").alias("v"))
    estimates = F.broadcast(orders.where("k < 7").groupBy("k").agg(F.min("v").alias("v")))
    cover = s.createDataFrame([(0, 0.0)], "m int, w double")
    for _ in range(3):
        more = cover.join(estimates, F.col("k").bitwiseAND(F.col("m")) != F.col("k")).select(F.col("m").bitwiseOR(F.col("k")).alias("m"), (F.col("w") + F.col("v")).alias("w"))
        cover = cover.unionByName(more).groupBy("m").agg(F.min("w").alias("w"))
    return cover.where("m = 7").agg(F.min("w").alias("bound"))


@query("""WITH o AS (SELECT p, count(*) AS orders FROM (SELECT l_orderkey, count(DISTINCT l_linenumber) AS p FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY l_orderkey) GROUP BY p)
SELECT m::INT AS m, p::INT AS p, orders, CAST(pow(1 + p, m) - 1 AS BIGINT) AS trees, CAST(4 * pow(1 + 2 * p, m) AS BIGINT) AS pairwise, CAST(pow(1 + 4 * p, m) AS BIGINT) AS at_once FROM range(2, 7) a(m), o""")
def combination_counts(s, d):
    """Combinations of m keywords with as many nodes each as orders have lines, by the number of lines."""
    sizes = t(s, d, "lineitem").where("l_orderkey is not null").groupBy("l_orderkey").agg(F.countDistinct("l_linenumber").alias("p")).groupBy("p").agg(F.count("*").alias("orders")).collect()  # a row a number of lines
    rows = [(m, r["p"], r["orders"], masks.count_combinations(r["p"], m), masks.fold_cost(4, r["p"], m), masks.fold_cost(4, r["p"], m, False)) for m in range(2, 7) for r in sizes]
    return s.createDataFrame(rows, "m int, p int, orders long, trees long, pairwise long, at_once long")


@query("""WITH e AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem WHERE l_orderkey IS NOT NULL AND l_partkey IS NOT NULL), g AS (SELECT (count(DISTINCT o) + count(DISTINCT p))::DOUBLE AS n, count(*)::DOUBLE AS e FROM e)
SELECT k::INT AS k, n * (e / n) * pow(1 + 2 * k, 3) + n * pow(2, 3) AS time_model, e * pow(2, 3) AS comm_model FROM g, (VALUES (1), (2), (5), (10)) b(k)""")
def cost_models(s, d):
    """The cost formulas for the graph of orders and parts, by K."""
    edges = t(s, d, "lineitem").select("l_orderkey", "l_partkey").dropna().distinct()
    n, e = edges.agg(F.countDistinct("l_orderkey") + F.countDistinct("l_partkey"), F.count("*")).first()
    return s.createDataFrame([(k, float(masks.time_model(n, e / max(1, n), k, 3, 2, 3)), float(masks.comm_model(e, 2, 3))) for k in (1, 2, 5, 10)], "k int, time_model double, comm_model double")


# workload of a hundred queries --------------------------------------------
_WORDS = "SELECT term, count(*) AS df FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))) AS term FROM documents) GROUP BY term HAVING count(*) >= 2"


def global_tiles(rows: DataFrame, order: list[str], tiles: int) -> DataFrame:
    """Adds ``rung``, the tile of each row in the order of all rows, as ``ntile`` would; rows are sorted by ranges, none in one task."""
    work = Workspace(rows.sparkSession, "tiles")
    ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    placed = work.save(ranged.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)), "placed")
    counts = sorted((r["part"], r["n"]) for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect())  # a row a partition
    n, begins, total = sum(c for _, c in counts), [], 0
    for part, c in counts:
        begins.append((part, total))
        total += c
    starts = F.broadcast(rows.sparkSession.createDataFrame(begins or [(0, 0)], "part int, begin long"))
    spot, (size, larger) = F.col("begin") + F.col("at"), divmod(n, tiles)
    rung = F.when(spot < larger * (size + 1), F.floor(spot / (size + 1)) + 1).otherwise(F.floor((spot - larger * (size + 1)) / max(1, size)) + larger + 1)
    return placed.join(starts, "part").withColumn("rung", rung.cast("int")).drop("part", "at", "begin")


def make_workload(index: DataFrame, per_m: int = 20) -> DataFrame:
    """``(query_id, m, rung, terms, total_df)``: for 2 to 6 keywords a ladder of rungs of rising frequency.

    Words of two nodes or more are cut into as many rungs as there are queries
    a keyword count; each query takes the first words of its rung in the order
    of their digest, so the choice is the same everywhere.
    """
    words = document_frequency(index).where("df >= 2").withColumn("digest", F.md5("term"))
    ranked = global_tiles(words, ["df", "term"], per_m)
    place = F.row_number().over(Window.partitionBy("rung").orderBy("digest"))
    picked = ranked.withColumn("place", place).where(F.col("place") <= 20)
    wanted = [(m, m * (m - 1) // 2 - 1) for m in range(2, 7)]
    rows = None
    for m, skip in wanted:
        part = picked.where((F.col("place") > skip) & (F.col("place") <= skip + m)).groupBy("rung").agg(F.sort_array(F.collect_list("term")).alias("terms"), F.sum("df").alias("total_df")).withColumn("m", F.lit(m))
        rows = part if rows is None else rows.unionByName(part)
    return rows.select(((F.col("m") - 2) * per_m + F.col("rung") - 1).cast("int").alias("query_id"), "m", F.col("rung").cast("int").alias("rung"), "terms", "total_df")


_WORKLOAD = f"""WITH w AS ({_WORDS}), r AS (SELECT *, ntile(20) OVER (ORDER BY df, term) AS rung FROM w), p AS (SELECT *, row_number() OVER (PARTITION BY rung ORDER BY md5(term)) AS place FROM r),
q AS (SELECT m, rung, list_sort(list(term)) AS terms, sum(df)::BIGINT AS total_df FROM p JOIN range(2, 7) x(m) ON place > m * (m - 1) // 2 - 1 AND place <= m * (m - 1) // 2 - 1 + m GROUP BY m, rung)
SELECT ((m - 2) * 20 + rung - 1)::INT AS query_id, m::INT AS m, rung::INT AS rung, terms, total_df FROM q"""


def _documents_index(s, d) -> DataFrame:
    docs = t(s, d, "documents")
    return build_index(docs.select(node_id("document", "doc_id").alias("node_id"), "text"))


@query(_WORKLOAD)
def workload_100(s, d):
    return make_workload(_documents_index(s, d))


@query(_WORKLOAD.replace("SELECT ((m", "SELECT m::INT AS m, min(total_df) AS least, max(total_df) AS most FROM (SELECT ((m", 1) + ") GROUP BY m")
def keyword_node_counts(s, d):
    return workload_100(s, d).groupBy("m").agg(F.min("total_df").alias("least"), F.max("total_df").alias("most"))


@query("SELECT item, sum(value) AS total FROM (SELECT l_suppkey AS list_no, l_partkey AS item, min(l_quantity) AS value FROM lineitem WHERE l_suppkey BETWEEN 1 AND 3 GROUP BY 1, 2) GROUP BY item HAVING count(*) = 3 ORDER BY total, item LIMIT 5")
def threshold_topk(s, d):
    lists = t(s, d, "lineitem").where("l_suppkey BETWEEN 1 AND 3").groupBy(F.col("l_suppkey").alias("list_no"), F.col("l_partkey").alias("item")).agg(F.min("l_quantity").alias("value"))
    return waves.threshold_topk(lists, 5)[0]


# runs whose results are trees, traces and shares --------------------------
@query()
def answer_trees(s, d):
    """The five lightest trees for three keywords of the contact graph, with the status of the search."""
    g, seeds = _contact(s, d, 3)
    found = relationship_search(g, seeds, 3, 5)
    return found.answers.withColumns({"status": F.lit(found.status), "spa_ratio": F.lit(found.spa_ratio).cast("double")})


@query()
def search_trace(s, d):
    g, seeds = _contact(s, d, 2)
    return relationship_search(g, seeds, 2, 1, measures=True).trace


@query()
def batch_trees(s, d):
    """Edges of the best trees of ten workload queries of two to six keywords, each searched to its own end."""
    g, seeds, queries = content_batch(s, d, list(range(0, 100, 10)))
    return best_trees(g, seeds, queries)[1]


@query()
def stop_compare(s, d):
    """Rounds, weight, status and deep messages under each stop rule and ablation, each run to its own end."""
    g, seeds = _contact(s, d, 2)
    variants = EXACT_STOPS | {"ties stop": {"tie_ok": True}, "balanced only": {"deep": False, "stop": "none"}, "no drain": {"drain": False}}
    rows = []
    for name, options in variants.items():
        found = relationship_search(g, seeds, 2, 1, **options)
        rows.append((name, found.status, found.best[0]["length"] if found.best else None, len(found.rows), report.deep_messages(found)))
    return s.createDataFrame(rows, "variant string, status string, weight double, rounds int, deep_msgs long")


@query()
def profile_shares(s, d):
    """Percent of the time of the five components, for queries of two to four keywords and K of 1, 2, 5 and 10 (K above 1 with two keywords)."""
    rows = []
    for m, k in ((2, 1), (3, 1), (4, 1), (2, 2), (2, 5), (2, 10)):
        g, seeds = _contact(s, d, m)
        shares = report.component_shares(relationship_search(g, seeds, m, k, profile=True))
        rows += [(m, k, name, share) for name, share in shares.items()]
    return s.createDataFrame(rows, "m int, k int, component string, percent double")


@query()
def measures_by_k(s, d):
    """Explored nodes, messages, deep messages, combinations and payload of whole runs, by K."""
    g, seeds = _contact(s, d, 2)
    rows = []
    for k in (1, 2, 5, 10):
        found = relationship_search(g, seeds, 2, k, measures=True)
        total = lambda name: sum(r[name] or 0 for r in found.rows)  # noqa: E731, B023
        rows.append((k, found.status, found.pct_explored, found.pct_messages, total("bfs_msgs"), total("deep_msgs"), total("combinations"), 24 * total("tree_edges"), total("candidates"), len(found.rows)))
    return s.createDataFrame(rows, "k int, status string, pct_explored double, pct_messages double, bfs_msgs long, deep_msgs long, combinations long, payload_bytes long, candidates long, rounds int")


@query()
def cut_runs(s, d):
    """Status, bound and ratio of searches that stop before a round of too many messages, and the 90th percentile of the ratio by limit and K."""
    g, limits, rows = builders.contact_graph(s, d), (200, 2_000, 1_000_000), []
    g = RelGraph(g.vertices.persist(), g.edges.persist(), g.tau, g.scheme)
    index = build_index(g.vertices).persist()
    for terms in (["3", "77"], ["12", "error"], ["41", "8"]):
        seeds = find_seeds(index, g.vertices, terms).persist()
        for k in (1, 2):  # one run serves all limits
            found = relationship_search(g, seeds, 2, k, max_messages=limits[-1], cut_at=limits)
            rows += [(most, k, cut.status, cut.best, cut.smallest_possible, cut.spa_ratio) for most, cut in cut_results(found, limits).items()]
        seeds.unpersist()
    for kept in (index, g.edges, g.vertices):
        kept.unpersist()
    runs = s.createDataFrame(rows, "max_messages long, k int, status string, best double, smallest_possible double, spa_ratio double")
    return runs.groupBy("max_messages", "k").agg(
        F.count("*").alias("queries"), F.count_if(F.col("status") == "optimal").alias("optimal"), F.count_if(F.col("status") == "truncated_messages").alias("cut"), F.percentile("spa_ratio", F.lit(0.9)).alias("p90_ratio")
    )


def _fold_sizes(s, d, how: str) -> DataFrame:
    """Combinations that each way of filtering evaluates at the nodes of one round, a grouped map by node."""
    g, seeds = _contact(s, d, 3)
    arrived = trees.grow(trees.seed_rows(seeds), g.edges, seeds)
    rows = arrived.select("node_id", "mask", "length", F.col("src").cast("long").alias("src"))

    def count(frame: pd.DataFrame) -> pd.DataFrame:
        if how == "brute":
            paths = [(int(mask).bit_length() - 1, w, frozenset({(int(src), int(mask), float(w))})) for mask, w, src in zip(frame["mask"], frame["length"], frame["src"], strict=True)]
            tried = exact.brute_local_topk(paths, 3, 1)[1]
        else:
            tables = [{int(m): [(float(w), frozenset({int(x)}))] for m, w, x in zip(g["mask"], g["length"], g["src"], strict=True)} for _, g in frame.groupby("src")]
            tried = exact.fold(tables, 3, 1, pairwise=how == "pairwise")[1]
        return pd.DataFrame({"node_id": [int(frame["node_id"].iloc[0])], "n": [tried]})

    counted = rows.groupBy("node_id").applyInPandas(count, "node_id long, n long")
    return counted.agg(F.lit(how).alias("method"), F.count("*").alias("nodes"), F.sum("n").alias("combinations"))


@query()
def measured_combinations(s, d):
    """Combinations evaluated in a round by brute force, all messages at once, pairwise folding, and the relational merge."""
    found = reduce(DataFrame.unionByName, [_fold_sizes(s, d, how) for how in ("brute", "at once", "pairwise")])
    g, seeds = _contact(s, d, 3)
    arrived = trees.prune(trees.grow(trees.seed_rows(seeds), g.edges, seeds).select(*trees.COLUMNS), 1)
    merged = trees.pairs_at_nodes(arrived, arrived).agg(F.lit("relational").alias("method"), F.countDistinct("node_id").alias("nodes"), F.count("*").alias("combinations"))
    return found.unionByName(merged)


SMALL_GRAPH = 200_000


@query()
def heuristics_compare(s, d):
    """Exact weight against the path-union and closure heuristics on a collected graph, null where no tree joins the keywords; raises ValueError above 200,000 edges."""
    g, seeds = _contact(s, d, 3)
    if g.n_edges() > SMALL_GRAPH:
        raise ValueError(f"the graph has more than {SMALL_GRAPH} edges, too many for one machine's searches")
    edges = [(r.src, r.dst, r.length) for r in g.edges.where("not mirrored").collect()]
    groups = [set() for _ in range(3)]
    for r in seeds.collect():
        for i in range(3):
            if r.mask >> i & 1:
                groups[i].add(r.node_id)
    best, counters = exact.standalone_search(edges, groups)
    found = relationship_search(g, seeds, 3, 1).best
    closure = exact.metric_closure_mst(edges, [min(x) for x in groups]) if all(groups) else math.inf
    rows = [("exact", exact.exact_group_steiner(edges, groups)), ("search", float(found[0]["length"]) if found else math.inf), ("path union", exact.path_union_heuristic(edges, groups)), ("standalone", best), ("standalone reads", float(counters["reads"])), ("metric closure", closure)]
    return s.createDataFrame([(name, None if math.isinf(w) else w) for name, w in rows], "method string, weight double")


# the hundred queries, run ----------------------------------------------------
_CONTENT = """, word AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))) AS term FROM documents),
link AS (SELECT 'd'||doc_id AS a, 'w'||term AS b FROM word UNION ALL SELECT 'd'||doc_id, 'l'||lang FROM documents WHERE lang IS NOT NULL UNION ALL SELECT 'd'||doc_id, 's'||source FROM documents WHERE source IS NOT NULL
UNION SELECT 'd'||doc_id, 'q'||quality FROM labels WHERE quality IS NOT NULL UNION SELECT 'd'||doc_id, 't'||toxic FROM labels WHERE toxic IS NOT NULL),
deg AS (SELECT b, count(*) AS degree FROM link GROUP BY b), g1 AS (SELECT a, link.b, length(CAST(degree AS VARCHAR))::DOUBLE AS w FROM link JOIN deg ON link.b = deg.b WHERE degree BETWEEN 2 AND 1000),
g AS MATERIALIZED (SELECT a AS src, b AS dst, w FROM g1 UNION ALL SELECT b, a, w FROM g1)"""


def _workload_sql(m: int, rounds: int = 8) -> str:
    """Unrolled distances of all keywords of the queries of ``m`` keywords; nodes of one neighbour other than documents lead nowhere."""
    out = [_WORKLOAD.replace("SELECT ((m", f", picked AS (SELECT ((m", 1) + f" WHERE m = {m})", _CONTENT]
    out.append(", d0 AS MATERIALIZED (SELECT query_id, q, 'd'||doc_id AS node, 0.0::DOUBLE AS w FROM (SELECT query_id, unnest(range(len(terms))) AS q, unnest(terms) AS term FROM picked) x JOIN word ON word.term = x.term)")
    for n in range(1, rounds + 1):
        out.append(f", d{n} AS MATERIALIZED (SELECT query_id, q, node, min(w) AS w FROM (SELECT * FROM d{n - 1} UNION ALL SELECT query_id, q, g.dst, x.w + g.w FROM d{n - 1} x JOIN g ON g.src = x.node) GROUP BY ALL)")
    out.append(f", total AS (SELECT query_id, node, sum(w) AS w FROM d{rounds} GROUP BY ALL HAVING count(*) = {m}) SELECT query_id, min(w) AS weight FROM total GROUP BY query_id")
    return " ".join(out)


def _workload_sql_of_four(rounds: int = 8) -> str:
    """Four keywords: pairs that meet at a node are relaxed like keywords and meet the other two."""
    out = [_workload_sql(4, rounds).split(", total AS (")[0]]
    out.append(f", p0 AS MATERIALIZED (SELECT x.query_id, x.q * 4 + y.q AS q, x.node, min(x.w + y.w) AS w FROM d{rounds} x JOIN d{rounds} y ON x.query_id = y.query_id AND x.node = y.node AND x.q < y.q GROUP BY ALL)")
    for n in range(1, rounds + 1):
        out.append(f", p{n} AS MATERIALIZED (SELECT query_id, q, node, min(w) AS w FROM (SELECT * FROM p{n - 1} UNION ALL SELECT query_id, q, g.dst, x.w + g.w FROM p{n - 1} x JOIN g ON g.src = x.node) GROUP BY ALL)")
    ways = []
    for a in range(4):
        for b in range(a + 1, 4):
            c, e = (x for x in range(4) if x not in (a, b))
            ways.append(f"SELECT x.query_id, x.w + c.w + e.w AS w FROM p{rounds} x JOIN d{rounds} c ON c.query_id = x.query_id AND c.node = x.node AND c.q = {c} JOIN d{rounds} e ON e.query_id = x.query_id AND e.node = x.node AND e.q = {e} WHERE x.q = {a * 4 + b}")
    return " ".join(out) + f" SELECT query_id, min(w) AS weight FROM ({' UNION ALL '.join(ways)}) GROUP BY query_id"


def _workload_weights(s, d, m: int) -> DataFrame:
    g, seeds, queries = content_batch(s, d, list(range(20 * (m - 2), 20 * (m - 1))))
    return best_trees(g, seeds, queries, trees=False)[0].select("query_id", "weight")


@query(_workload_sql(2))
def workload_m2(s, d):
    """Best weights of the twenty workload queries of two keywords, to their own end."""
    return _workload_weights(s, d, 2)


@query(_workload_sql(3))
def workload_m3(s, d):
    """Best weights of the twenty workload queries of three keywords, to their own end."""
    return _workload_weights(s, d, 3)


@query(_workload_sql_of_four())
def workload_m4(s, d):
    """Best weights of the twenty workload queries of four keywords, to their own end."""
    return _workload_weights(s, d, 4)


@query()
def workload_answers(s, d):
    """All hundred workload queries, two to six keywords, each searched to its own end: weight, root and whether it is proven."""
    g, seeds, queries = content_batch(s, d, list(range(100)))
    return best_trees(g, seeds, queries, trees=False)[0]


@query(f"SELECT m, round(regr_slope(log10(total_df), rung), 6) AS slope FROM ({_WORKLOAD}) GROUP BY m")
def keyword_node_growth(s, d):
    """Slope of the logarithm of keyword nodes over the rungs of the workload."""
    return workload_100(s, d).groupBy("m").agg(F.round(F.regr_slope(F.log10("total_df"), F.col("rung")), 6).alias("slope"))


def content_batch(s, d, ids: list[int]) -> tuple[RelGraph, DataFrame, dict[int, int]]:
    """The document graph, and seeds of the workload queries named; texts are split into words once."""
    work, docs = Workspace(s, "content"), t(s, d, "documents")
    words = work.save(builders.content_words(docs).drop("w"), "words").withColumn("w", text_key(F.col("word")))
    vertices, links = builders.content_parts(docs, t(s, d, "labels"), words)
    g = RelGraph(vertices, lengths.mirror(work.save(lengths.assign_lengths(links), "links")), 1001, "step_log10_plus1")
    index = words.select(F.col("word").alias("term"), node_id("document", "doc_id").alias("node_id"))
    picked = work.save(make_workload(index).where(F.col("query_id").isin(ids)).select("query_id", "m", F.posexplode("terms").alias("bit", "term")), "picked")
    queries = {r["query_id"]: r["m"] for r in picked.groupBy("query_id").agg(F.first("m").alias("m")).collect()}
    seeds = index.join(F.broadcast(picked), "term").groupBy("query_id", "node_id").agg(F.bit_or(F.expr("shiftleft(1, bit)")).cast("int").alias("mask"))
    return g, seeds, queries
