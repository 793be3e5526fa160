"""Joins, aggregates, windows, sorts and set operators on the given tables, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph.builders import table as t

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable:
    """Registers a function of (spark, sf_dir) under its own name, with its SQL."""

    def keep(f: Callable) -> Callable:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return keep


#: The subsets of four groups of suppliers, as masks, that orders name.
MASKS_SQL = "SELECT DISTINCT bit_or(1 << (l_suppkey % 4)::INT)::INT AS m FROM lineitem WHERE l_orderkey IS NOT NULL AND l_suppkey IS NOT NULL GROUP BY l_orderkey"


def order_masks(s, d) -> DataFrame:
    """``m``, the different subsets of four groups of suppliers that orders name: at most fifteen."""
    lines = t(s, d, "lineitem").where("l_orderkey is not null and l_suppkey is not null")
    return lines.groupBy("l_orderkey").agg(F.bit_or(F.expr("shiftleft(1, cast(l_suppkey % 4 as int))")).alias("m")).select("m").distinct()


# projections and filters
@query("SELECT l_orderkey, l_quantity FROM lineitem")
def op_scan_pruned(s, d):
    return t(s, d, "lineitem").select("l_orderkey", "l_quantity")


@query("SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")
def op_scan_filtered(s, d):
    return t(s, d, "lineitem").where((F.col("l_quantity") >= 49) & (F.col("l_returnflag") == "R")).select("l_orderkey", "l_partkey")


@query("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class, CAST(p_retailprice AS BIGINT) AS price FROM part")
def op_project_case(s, d):
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return t(s, d, "part").select("p_partkey", size.alias("size_class"), F.rint("p_retailprice").cast("long").alias("price"))


@query("SELECT p_partkey, p_name FROM part WHERE p_size BETWEEN 5 AND 25 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13', 'Brand#23') AND p_name LIKE '%o%' AND regexp_matches(p_name, '^[a-m]')")
def op_filter_between_in_like(s, d):
    p = t(s, d, "part")
    return p.where(p.p_size.between(5, 25) & p.p_brand.isin("Brand#11", "Brand#12", "Brand#13", "Brand#23") & p.p_name.like("%o%") & p.p_name.rlike("^[a-m]")).select("p_partkey", "p_name")


# joins
_ORDERS_BY_SEGMENT = "SELECT c_mktsegment, count(*) AS n, sum(CAST(o_orderkey AS BIGINT))::BIGINT AS keys FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"


def _by_segment(s, d, hint):
    joined = t(s, d, "orders").join(t(s, d, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query(_ORDERS_BY_SEGMENT)
def op_join_broadcast(s, d):
    """Customers are a side of checked size: the plan broadcasts them under the session's threshold only."""
    return t(s, d, "orders").join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query(_ORDERS_BY_SEGMENT)
def op_join_sortmerge(s, d):
    return _by_segment(s, d, "merge")


@query(_ORDERS_BY_SEGMENT)
def op_join_shufflehash(s, d):
    return _by_segment(s, d, "shuffle_hash")


@query("SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def op_join_left_outer(s, d):
    return t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n_orders"))


@query("SELECT c_custkey, user_id FROM customer FULL JOIN (SELECT DISTINCT user_id FROM events) ON c_custkey = user_id")
def op_join_full_outer(s, d):
    return t(s, d, "customer").select("c_custkey").join(t(s, d, "events").select("user_id").distinct(), F.col("c_custkey") == F.col("user_id"), "full")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def op_join_semi_reached(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def op_join_anti_unreached(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query(f"SELECT x.m AS a, y.m AS b FROM ({MASKS_SQL}) x, ({MASKS_SQL}) y")
def op_join_cross_masks(s, d):
    """The subsets of four groups that orders name with each other: a product of fifteen rows at most a side."""
    masks = order_masks(s, d)
    return masks.select(F.col("m").alias("a")).crossJoin(masks.select(F.col("m").alias("b")))


@query(f"SELECT x.m AS a, y.m AS b, (x.m | y.m)::INT AS whole FROM ({MASKS_SQL}) x, ({MASKS_SQL}) y WHERE x.m & y.m = 0 AND x.m < y.m")
def op_join_theta_disjoint(s, d):
    masks = order_masks(s, d).select(F.col("m").alias("a"))
    return masks.join(masks.withColumnRenamed("a", "b"), (F.col("a").bitwiseAND(F.col("b")) == 0) & (F.col("a") < F.col("b"))).withColumn("whole", F.col("a").bitwiseOR(F.col("b")))


@query("""WITH w AS (SELECT unnest(list_distinct(regexp_extract_all(lower(p_name), '[a-z0-9]+'))) AS term FROM part), f AS (SELECT term, count(*) AS df FROM w GROUP BY term),
b(band, low, high) AS (VALUES (1, 1, 50), (2, 51, 500), (3, 501, 1000000000)) SELECT term, df, band FROM f JOIN b ON df BETWEEN low AND high""")
def op_join_range_df(s, d):
    bands = s.createDataFrame([(1, 1, 50), (2, 51, 500), (3, 501, 1_000_000_000)], "band int, low long, high long")
    terms = t(s, d, "part").select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower("p_name"), F.lit("[a-z0-9]+"), F.lit(0)))).alias("term"))
    return terms.groupBy("term").agg(F.count("*").alias("df")).join(F.broadcast(bands), F.col("df").between(F.col("low"), F.col("high"))).select("term", "df", "band")


@query("""SELECT a.user_id, count(*) AS n_pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch(a.ts) - epoch(b.ts)) <= 86400 GROUP BY a.user_id""")
def op_join_interval_contact(s, d):
    """Pairs of a user's events within a day: equal buckets of a day or neighbouring ones, then the exact bound."""
    e = t(s, d, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    day = 86_400_000_000
    left = e.withColumn("day", F.floor(F.col("at") / day))
    right = e.select("user_id", F.col("event_id").alias("other_id"), F.col("at").alias("other_at"), F.explode(F.array(*[F.floor(F.col("at") / day) + k for k in (-1, 0, 1)])).alias("day"))
    return left.join(right, ["user_id", "day"]).where((F.col("event_id") < F.col("other_id")) & (F.abs(F.col("at") - F.col("other_at")) <= day)).groupBy("user_id").agg(F.count("*").alias("n_pairs"))


@query("""SELECT o_orderkey, event_id FROM (SELECT o_orderkey, o_custkey, o_orderdate FROM orders) o LEFT JOIN LATERAL (SELECT event_id FROM events e WHERE e.user_id = o.o_custkey AND e.ts <= o.o_orderdate ORDER BY e.ts DESC, e.event_id DESC LIMIT 1) ON true""")
def op_join_asof_event(s, d):
    """The latest event of the customer at or before each order: both are put in one order, the last event is carried on."""
    o = t(s, d, "orders").select(F.col("o_custkey").alias("who"), F.col("o_orderdate").alias("at"), "o_orderkey", F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("side"))
    e = t(s, d, "events").select(F.col("user_id").alias("who"), F.col("ts").alias("at"), F.lit(None).cast("long").alias("o_orderkey"), "event_id", F.lit(0).alias("side"))
    w = Window.partitionBy("who").orderBy("at", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return o.unionByName(e).withColumn("last", F.last("event_id", True).over(w)).where("side = 1").select("o_orderkey", F.col("last").alias("event_id"))


@query("SELECT a.l_partkey AS part_a, b.l_partkey AS part_b, count(DISTINCT a.l_orderkey) AS n_orders FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(DISTINCT a.l_orderkey) > 1")
def op_self_cooccur(s, d):
    lines = t(s, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = lines.select("l_orderkey", F.col("l_partkey").alias("part_a")).join(lines.select("l_orderkey", F.col("l_partkey").alias("part_b")), "l_orderkey").where("part_a < part_b")
    return pairs.groupBy("part_a", "part_b").agg(F.count("*").alias("n_orders")).where("n_orders > 1")


# aggregates
@query("SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total, min(o_orderkey) AS first_key, max(o_orderkey) AS last_key FROM orders GROUP BY o_orderstatus")
def op_agg_hash(s, d):
    return t(s, d, "orders").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.min("o_orderkey").alias("first_key"), F.max("o_orderkey").alias("last_key"))


@query("SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderpriority")
def op_agg_distinct(s, d):
    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("customers"))


@query("SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY o_custkey")
def op_agg_minby(s, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return t(s, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", by).alias("cheapest"), F.max_by("o_orderkey", by).alias("dearest"))


@query("SELECT user_id, bit_or(CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 ELSE 4 END)::INT AS mask FROM events GROUP BY user_id")
def op_agg_bitor(s, d):
    bit = F.when(F.col("event_type") == "click", 1).when(F.col("event_type") == "purchase", 2).otherwise(4)
    return t(s, d, "events").groupBy("user_id").agg(F.bit_or(bit).cast("int").alias("mask"))


@query("SELECT user_id, list_sort(list(DISTINCT event_type)) AS kinds FROM events GROUP BY user_id")
def op_agg_collect_set(s, d):
    return t(s, d, "events").groupBy("user_id").agg(F.sort_array(F.collect_set("event_type")).alias("kinds"))


@query("SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY o_orderstatus")
def op_agg_percentile90(s, d):
    return t(s, d, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", F.lit(0.9)), 4).alias("p90"))


def _grouped(sql_group: str) -> str:
    return f"SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {sql_group}"


@query(_grouped("ROLLUP (o_orderstatus, o_orderpriority)"))
def op_agg_rollup(s, d):
    return t(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query(_grouped("CUBE (o_orderstatus, o_orderpriority)"))
def op_agg_cube(s, d):
    return t(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query(_grouped("GROUPING SETS ((o_orderstatus), (o_orderpriority))"))
def op_agg_grouping_sets(s, d):
    return t(s, d, "orders").groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_orderpriority")
def op_agg_pivot(s, d):
    wide = t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return wide.select("o_orderpriority", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"])


@query("SELECT degree, count(*) AS customers FROM (SELECT o_custkey, count(*) AS degree FROM orders GROUP BY o_custkey) GROUP BY degree")
def op_degree_histogram(s, d):
    return t(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("customers"))


@query("SELECT round(regr_slope(p_retailprice, p_size), 6) AS slope, round(regr_intercept(p_retailprice, p_size), 6) AS base FROM part")
def op_regr_slope(s, d):
    return t(s, d, "part").agg(F.round(F.regr_slope("p_retailprice", "p_size"), 6).alias("slope"), F.round(F.regr_intercept("p_retailprice", "p_size"), 6).alias("base"))


# windows
def _ranked(f: str) -> str:
    return f"SELECT o_orderkey, {f} OVER (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey) AS place FROM orders"


def _place(s, d, f: Callable, *order: str) -> DataFrame:
    return t(s, d, "orders").select("o_orderkey", f().over(Window.partitionBy("o_custkey").orderBy(*order)).cast("long").alias("place"))


@query(_ranked("row_number()"))
def op_win_row_number(s, d):
    return _place(s, d, F.row_number, "o_orderpriority", "o_orderkey")


@query("SELECT o_orderkey, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS place FROM orders")
def op_win_rank(s, d):
    return _place(s, d, F.rank, "o_orderpriority")


@query("SELECT o_orderkey, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS place FROM orders")
def op_win_dense_rank(s, d):
    return _place(s, d, F.dense_rank, "o_orderpriority")


@query(_ranked("ntile(4)"))
def op_win_ntile(s, d):
    return _place(s, d, lambda: F.ntile(4), "o_orderpriority", "o_orderkey")


@query("SELECT conv_id, turn, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations")
def op_win_lag_turns(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def op_win_running_sum(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("running"))


@query("SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM part")
def op_win_range_frame(s, d):
    return t(s, d, "part").select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("near"))


@query("SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def op_win_first_last(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(s, d, "events").select("user_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id")).distinct()


@query("SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 6) AS share FROM part")
def op_win_percent_rank(s, d):
    return t(s, d, "part").select("p_partkey", F.round(F.percent_rank().over(Window.partitionBy("p_brand").orderBy("p_retailprice")), 6).alias("share"))


# sorts
@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey")
def op_sort_global(s, d):
    return t(s, d, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey")


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
def op_topk(s, d):
    return op_sort_global(s, d).limit(10)


@query("SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def op_topk_per_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(s, d, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_brand", "p_partkey")


@query("SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 5 OFFSET 7")
def op_limit_offset(s, d):
    return t(s, d, "part").select("p_partkey").orderBy("p_partkey").offset(7).limit(5)


# sets
_SIDES = ("SELECT c_custkey AS id FROM customer", "SELECT user_id AS id FROM events")
for _name, _op in (("op_union_all", "UNION ALL"), ("op_union_distinct", "UNION"), ("op_intersect", "INTERSECT"), ("op_intersect_all", "INTERSECT ALL"), ("op_except", "EXCEPT"), ("op_except_all", "EXCEPT ALL")):

    def _set(s, d, op=_op) -> DataFrame:
        a, b = t(s, d, "customer").select(F.col("c_custkey").alias("id")), t(s, d, "events").select(F.col("user_id").alias("id"))
        if op in ("EXCEPT", "EXCEPT ALL", "INTERSECT ALL"):
            a, b = b, a
        return {"UNION ALL": a.unionAll, "UNION": lambda x: a.union(x).distinct(), "INTERSECT": a.intersect, "INTERSECT ALL": a.intersectAll, "EXCEPT": a.subtract, "EXCEPT ALL": a.exceptAll}[op](b)

    _turn = _op in ("EXCEPT", "EXCEPT ALL", "INTERSECT ALL")
    query(f"{_SIDES[_turn]} {_op} {_SIDES[1 - _turn]}", _name)(_set)
