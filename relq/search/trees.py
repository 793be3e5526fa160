"""One round of the search over partial trees, as joins, filters and windows.

A row is a partial tree rooted at ``node_id`` for the keyword subset ``mask``.
``members`` are its nodes, ``bearers`` those of them with keywords, ``tree``
its edges with the smaller end first, ``sig`` a hash of the edges.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

COLUMNS = ["node_id", "mask", "length", "sig", "origin", "members", "bearers", "tree"]
EDGE = "struct<a:bigint,b:bigint,len:double>"
BEARER = "struct<node:bigint,mask:int>"


def signature(tree: Column, node: Column) -> Column:
    ends = F.transform(tree, lambda e: F.struct(e["a"].alias("a"), e["b"].alias("b")))
    return F.when(F.size(tree) == 0, F.xxhash64(node)).otherwise(F.xxhash64(F.array_sort(ends)))


def seed_rows(seeds: DataFrame) -> DataFrame:
    """State rows of length 0 for every part of each keyword node's mask."""
    parts = F.filter(F.sequence(F.lit(1), F.col("mask")), lambda k: k.bitwiseAND(F.col("mask")) == k)
    bearers = F.array(F.struct(F.col("node_id").alias("node"), F.col("mask").alias("mask")))
    return seeds.select(
        "node_id", F.explode(parts).alias("part"), F.lit(0.0).alias("length"), F.xxhash64("node_id").alias("sig"), F.lit("seed").alias("origin"),
        F.array("node_id").alias("members"), bearers.alias("bearers"), F.array().cast(f"array<{EDGE}>").alias("tree"),
    ).withColumnRenamed("part", "mask").select(*COLUMNS)


def grow(delta: DataFrame, edges: DataFrame, reached: DataFrame) -> DataFrame:
    """Trees carried over one edge to ``node_id``; ``src`` is the sender, ``known`` says if the receiver was reached before.

    ``reached(node_id, mask)`` are the nodes reached so far, with the mask of
    those that have keywords. A node already in the tree is not entered again.
    One exchange, by the receiver, serves this join and all that follows there.
    """
    own = reached.select(F.col("node_id").alias("dst"), F.col("mask").alias("own"), F.lit(True).alias("known"))
    sent = delta.join(edges.select("src", "dst", F.col("length").alias("w")), delta["node_id"] == F.col("src")).where(~F.array_contains("members", F.col("dst")))
    sent = sent.drop("node_id").join(own, "dst", "left")
    edge = F.struct(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), F.col("w").alias("len"))
    bearer = F.array(F.struct(F.col("dst").alias("node"), F.col("own").alias("mask")))
    tree = F.array_append("tree", edge)
    return sent.select(
        F.col("dst").alias("node_id"), "mask", (F.col("length") + F.col("w")).alias("length"), signature(tree, F.col("dst")).alias("sig"), F.lit("grow").alias("origin"),
        F.array_append("members", F.col("dst")).alias("members"), F.when(F.col("own").isNull(), F.col("bearers")).otherwise(F.concat("bearers", bearer)).alias("bearers"), tree.alias("tree"),
        "src", F.coalesce("known", F.lit(False)).alias("known"),
    )


def pairs_at_nodes(fresh: DataFrame, pool: DataFrame) -> DataFrame:
    """Trees of disjoint subsets that meet at a node: what a merge looks at."""
    a = fresh.select("node_id", *[F.col(c).alias(f"a_{c}") for c in COLUMNS[1:]])
    b = pool.select("node_id", *[F.col(c).alias(f"b_{c}") for c in COLUMNS[1:]])
    return a.join(b, "node_id").where(F.col("a_mask").bitwiseAND(F.col("b_mask")) == 0)


def merge(fresh: DataFrame, pool: DataFrame) -> DataFrame:
    """Trees of disjoint subsets at one node that share the root alone."""
    both = pairs_at_nodes(fresh, pool).where(F.size(F.array_intersect("a_members", "b_members")) == 1)
    rows = both.select(
        "node_id", F.col("a_mask").bitwiseOR(F.col("b_mask")).alias("mask"), (F.col("a_length") + F.col("b_length")).alias("length"), F.lit("merge").alias("origin"),
        F.array_union("a_members", "b_members").alias("members"), F.array_union("a_bearers", "b_bearers").alias("bearers"), F.concat("a_tree", "b_tree").alias("tree"),
    )
    return rows.withColumn("sig", signature(F.col("tree"), F.col("node_id"))).select(*COLUMNS)


def leaves_needed(rows: DataFrame, mask: Column) -> DataFrame:
    """Rows in which every leaf but the root owns a keyword of ``mask`` that no other member has."""
    tree, bearers, node = F.col("tree"), F.col("bearers"), F.col("node_id")
    degree = lambda x: F.size(F.filter(tree, lambda e: (e["a"] == x) | (e["b"] == x)))
    owned = lambda x: F.aggregate(bearers, F.lit(0), lambda acc, b: F.when(b["node"] == x, acc.bitwiseOR(b["mask"])).otherwise(acc))
    others = lambda x: F.aggregate(bearers, F.lit(0), lambda acc, b: F.when(b["node"] == x, acc).otherwise(acc.bitwiseOR(b["mask"])))
    spare = F.exists("members", lambda x: (x != node) & (degree(x) == 1) & (owned(x).bitwiseAND(mask).bitwiseAND(F.bitwise_not(others(x))) == 0))
    return rows.where(~spare)


def minimal_answers(rows: DataFrame, full: int) -> DataFrame:
    """Complete trees of which nothing can be removed, root leaf included."""
    complete = rows.where((F.col("mask") == full) & (F.col("origin") != "grow"))
    lone = complete.where(F.size("tree") == 0)
    rest = leaves_needed(complete.where(F.size("tree") > 0), F.lit(full))
    # the root, too, must be needed if it is a leaf
    degree = F.size(F.filter("tree", lambda e: (e["a"] == F.col("node_id")) | (e["b"] == F.col("node_id"))))
    mine = F.aggregate("bearers", F.lit(0), lambda acc, b: F.when(b["node"] == F.col("node_id"), acc.bitwiseOR(b["mask"])).otherwise(acc))
    theirs = F.aggregate("bearers", F.lit(0), lambda acc, b: F.when(b["node"] == F.col("node_id"), acc).otherwise(acc.bitwiseOR(b["mask"])))
    needed = (degree > 1) | (mine.bitwiseAND(full).bitwiseAND(F.bitwise_not(theirs)) != 0)
    return lone.unionByName(rest.where(needed))


def prune(rows: DataFrame, keep: int) -> DataFrame:
    """The ``keep`` lightest different trees of each node and subset; ties by signature.

    Rows that lie by ``node_id`` already are not exchanged; others are once.
    """
    order = Window.partitionBy("node_id", "mask").orderBy("length", "sig")
    lightest = rows.withColumn("place", F.dense_rank().over(order)).where(F.col("place") <= keep)
    twin = Window.partitionBy("node_id", "mask").orderBy("length", "sig", *(["born"] if "born" in rows.columns else []))
    return lightest.withColumn("again", F.lag("sig").over(twin)).where(F.col("again").isNull() | (F.col("again") != F.col("sig"))).drop("place", "again")
