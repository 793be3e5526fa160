"""Scalar, array, map, JSON and user-defined functions on the given tables, each with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph.builders import table as t
from ..graph.lengths import step_log10
from ..operators.relational import MASKS_SQL, order_masks, query
from ..search import masks


@query("SELECT p_partkey, regexp_extract_all(lower(p_name), '[a-z0-9]+') AS words, len(regexp_extract_all(lower(p_name), '[a-z0-9]+'))::INT AS n FROM part")
def op_str_tokens(s, d):
    words = F.regexp_extract_all(F.lower("p_name"), F.lit("[a-z0-9]+"), F.lit(0))
    return t(s, d, "part").select("p_partkey", words.alias("words"), F.size(words).alias("n"))


@query("SELECT p_partkey, upper(p_name) AS up, length(p_name)::INT AS n, substring(p_name, 2, 3) AS mid, p_brand || '/' || p_type AS both_, replace(p_name, ' ', '_') AS joined, translate(p_name, 'aeiou', '12345') AS coded FROM part")
def op_str_misc(s, d):
    return t(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").alias("n"), F.substring("p_name", 2, 3).alias("mid"), F.concat_ws("/", "p_brand", "p_type").alias("both_"), F.replace(F.col("p_name"), F.lit(" "), F.lit("_")).alias("joined"), F.translate("p_name", "aeiou", "12345").alias("coded"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host FROM pages")
def op_url_host(s, d):
    return t(s, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1")
def op_date_trunc(s, d):
    return t(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@query("SELECT l_orderkey, l_partkey, l_suppkey, date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))::INT AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def op_date_diff(s, d):
    both = t(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate").join(t(s, d, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.select("l_orderkey", "l_partkey", "l_suppkey", F.date_diff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).alias("days"))


@query("SELECT degree, (length(CAST(degree AS VARCHAR)) - 1)::DOUBLE AS step, length(CAST(degree AS VARCHAR))::DOUBLE AS plus1 FROM (SELECT l_suppkey, count(*) AS degree FROM lineitem GROUP BY l_suppkey)")
def op_math_log_step(s, d):
    rows = t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("degree"))
    return rows.select("degree", step_log10(F.col("degree")).alias("step"), (step_log10(F.col("degree")) + 1).alias("plus1"))


@query(f"SELECT m, (m & 5)::INT AS low, (m | 8)::INT AS with8, xor(m, 15)::INT AS rest, bit_count(m)::INT AS n, (m << 2)::INT AS shifted FROM ({MASKS_SQL})")
def op_bitmask_ops(s, d):
    m = F.col("m")
    return order_masks(s, d).select(m, m.bitwiseAND(5).alias("low"), m.bitwiseOR(8).alias("with8"), m.bitwiseXOR(15).alias("rest"), F.bit_count(m).alias("n"), F.shiftleft(m, 2).alias("shifted"))


@query("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS positives, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2, list_sort(embedding)[64] > 0.3 AS has_large FROM embeddings")
def op_array_hof(s, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    norm2 = F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 6)
    return t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positives"), norm2.alias("norm2"), (F.array_max("embedding") > F.lit(0.3).cast("float")).alias("has_large"))


@query("""WITH w AS (SELECT p_partkey, list_sort(list_distinct(regexp_extract_all(lower(p_name), '[a-z]+'))) AS a, list_sort(list_distinct(regexp_extract_all(lower(p_type), '[a-z]+'))) AS b FROM part)
SELECT p_partkey, list_sort(list_distinct(list_concat(a, b))) AS either, list_sort(list_filter(a, lambda x: list_contains(b, x))) AS both_, list_sort(list_filter(a, lambda x: NOT list_contains(b, x))) AS only_a FROM w""")
def op_array_sets(s, d):
    words = lambda c: F.array_distinct(F.regexp_extract_all(F.lower(c), F.lit("[a-z]+"), F.lit(0)))
    rows = t(s, d, "part").select("p_partkey", words("p_name").alias("a"), words("p_type").alias("b"))
    return rows.select("p_partkey", F.array_sort(F.array_union("a", "b")).alias("either"), F.array_sort(F.array_intersect("a", "b")).alias("both_"), F.array_sort(F.array_except("a", "b")).alias("only_a"))


@query("SELECT p_partkey, generate_subscripts(w, 1)::INT - 1 AS pos, unnest(w) AS word FROM (SELECT p_partkey, regexp_extract_all(lower(p_name), '[a-z]+') AS w FROM part)")
def op_explode_pos(s, d):
    return t(s, d, "part").select("p_partkey", F.posexplode(F.regexp_extract_all(F.lower("p_name"), F.lit("[a-z]+"), F.lit(0))).alias("pos", "word"))


@query("SELECT user_id, event_type, min(value) AS least FROM events GROUP BY user_id, event_type")
def op_map_merge_min(s, d):
    """Two halves of the events as maps of least values, zipped with the smaller of each key."""
    least = lambda rows: rows.groupBy("user_id", "event_type").agg(F.min("value").alias("v")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "v"))).alias("m"))
    e = t(s, d, "events")
    both = least(e.where("event_id % 2 = 0")).withColumnRenamed("m", "a").join(least(e.where("event_id % 2 = 1")).withColumnRenamed("m", "b"), "user_id", "full")
    none = F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<double>"))
    zipped = F.map_zip_with(F.coalesce("a", none), F.coalesce("b", none), lambda k, x, y: F.least(x, y))
    return both.select("user_id", F.explode(zipped).alias("event_type", "least"))


@query("SELECT n_regionkey, n_name AS name, (n_nationkey * 2)::INT AS twice FROM nation WHERE n_nationkey > 3")
def op_map_entries(s, d):
    m = t(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m"))
    doubled = F.transform_values(F.map_filter("m", lambda k, v: v > 3), lambda k, v: v * 2)
    return m.select("n_regionkey", F.explode(doubled).alias("name", "twice"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS next_k FROM events")
def op_json_props(s, d):
    return t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), (F.from_json("props", "k long")["k"] + 1).alias("next_k"))


# user-defined functions: parity with built-in forms, and table functions over masks
@query("SELECT l_orderkey, string_agg(p, '-' ORDER BY p) AS signature FROM (SELECT DISTINCT l_orderkey, lpad(CAST(l_partkey AS VARCHAR), 8, '0') AS p FROM lineitem) GROUP BY l_orderkey")
def op_udf_signature(s, d):
    """A text that names an order's set of parts, by a vectorised function over arrays."""

    @F.pandas_udf("string")
    def sign(parts: pd.Series) -> pd.Series:
        return parts.map(lambda p: "-".join(sorted(p)))

    parts = t(s, d, "lineitem").groupBy("l_orderkey").agg(F.collect_set(F.lpad(F.col("l_partkey").cast("string"), 8, "0")).alias("p"))
    return parts.select("l_orderkey", sign("p").alias("signature"))


@query("SELECT o_custkey, list_sort(list(o_totalprice))[1:3] AS least FROM orders GROUP BY o_custkey")
def op_udaf_topk(s, d):
    """The three least values of a group, by a grouped aggregate function."""

    @F.pandas_udf("array<double>")
    def least(v: pd.Series) -> list:
        return sorted(v.nsmallest(3).tolist())

    return t(s, d, "orders").groupBy("o_custkey").agg(least("o_totalprice").alias("least"))


@F.udtf(returnType="part: int")
class Submasks:
    """Non-empty parts of a mask."""

    def eval(self, mask: int):
        for k in masks.submasks(mask):
            yield (k,)


@F.udtf(returnType="a: int, b: int")
class SubsetPartitions:
    """Unordered pairs of disjoint parts that make up a mask."""

    def eval(self, mask: int):
        for a, b in masks.partitions(mask):
            if a < b:
                yield (a, b)


@F.udtf(returnType="a: bigint, b: bigint, len: double")
class AnswerEdges:
    """Edges of an answer's array, one row each."""

    def eval(self, edges):
        for e in edges or []:
            yield e["a"], e["b"], e["len"]


def register(spark: SparkSession) -> None:
    """Names the table functions for SQL."""
    for name, f in (("submasks", Submasks), ("subset_partitions", SubsetPartitions), ("answer_edges", AnswerEdges)):
        spark.udtf.register(name, f)


@query(f"SELECT m AS mask, k::INT AS part FROM ({MASKS_SQL}) x, range(1, 16) y(k) WHERE k & m = k")
def op_udtf_submasks(s, d) -> DataFrame:
    register(s)
    return s.sql("SELECT m AS mask, part FROM {masks}, LATERAL submasks(m)", masks=order_masks(s, d))


@query(f"SELECT m AS mask, a::INT AS a, (m - a)::INT AS b FROM ({MASKS_SQL}) x, range(1, 16) y(a) WHERE a & m = a AND a < m - a")
def op_udtf_partitions(s, d) -> DataFrame:
    register(s)
    return s.sql("SELECT m AS mask, a, b FROM {masks}, LATERAL subset_partitions(m)", masks=order_masks(s, d))


@query("""WITH RECURSIVE e AS (SELECT 'r' || n_regionkey AS a, 'n' || n_nationkey AS b FROM nation UNION ALL SELECT 'n' || c_nationkey, 'c' || c_custkey FROM customer),
w(node, hop) AS (SELECT 'r1', 0 UNION ALL SELECT e.b, w.hop + 1 FROM w JOIN e ON e.a = w.node WHERE w.hop < 2) SELECT node, hop FROM w""")
def op_sql_recursive_bfs(s, d) -> DataFrame:
    for name in ("nation", "customer"):
        t(s, d, name).createOrReplaceTempView(f"relq_{name}")
    return s.sql("""WITH RECURSIVE e AS (SELECT concat('r', n_regionkey) AS a, concat('n', n_nationkey) AS b FROM relq_nation UNION ALL SELECT concat('n', c_nationkey), concat('c', c_custkey) FROM relq_customer),
        w(node, hop) AS (SELECT 'r1', 0 UNION ALL SELECT e.b, w.hop + 1 FROM w JOIN e ON e.a = w.node WHERE w.hop < 2) SELECT node, hop FROM w""")
