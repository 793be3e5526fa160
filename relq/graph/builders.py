"""Graphs from tables: tuples become nodes, references edges."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..schema import RelGraph, check_names, node_id, text_key
from .lengths import assign_lengths, mirror


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _nodes(rows: DataFrame, kind: str, key: Column | str, text: Column) -> DataFrame:
    key = F.col(key) if isinstance(key, str) else key
    return rows.select(node_id(kind, key).alias("node_id"), F.lit(kind).alias("kind"), key.cast("long").alias("key"), text.cast("string").alias("text"))


def _edges(rows: DataFrame, a: tuple, b: tuple, label: str) -> DataFrame:
    """Distinct pairs with their number of rows as ``strength``."""
    pairs = rows.select(node_id(*a).alias("src"), node_id(*b).alias("dst")).where("src is not null and dst is not null")
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("strength")).withColumn("label", F.lit(label))


def _word_edges(documents: DataFrame, words: DataFrame) -> DataFrame:
    """As ``_edges``. A document names each word once, so pairs are only compared if documents share an id."""
    a, b = ("document", "doc_id"), ("word", "w")
    if documents.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count():
        return _edges(words, a, b, "contains")
    pairs = words.select(node_id(*a).alias("src"), node_id(*b).alias("dst")).where("src is not null and dst is not null")
    return pairs.withColumns({"strength": F.lit(1).cast("long"), "label": F.lit("contains")})


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _finish(vertices: DataFrame, edges: DataFrame, scheme: str, tau: int | None) -> RelGraph:
    return RelGraph(vertices, mirror(assign_lengths(edges, scheme, tau)), tau, scheme)


def fk_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    return _all([
        _nodes(t("region"), "region", "r_regionkey", F.col("r_name")), _nodes(t("nation"), "nation", "n_nationkey", F.col("n_name")),
        _nodes(t("customer"), "customer", "c_custkey", F.concat_ws(" ", "c_name", "c_mktsegment")), _nodes(t("supplier"), "supplier", "s_suppkey", F.col("s_name")),
        _nodes(t("part"), "part", "p_partkey", F.concat_ws(" ", "p_name", "p_brand", "p_type")), _nodes(t("orders"), "order", "o_orderkey", F.lit("")),
    ])


def fk_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed reference edges, before lengths: ``src, dst, strength, label``."""
    t = lambda n: table(spark, sf_dir, n)
    lines = t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    return _all([
        _edges(t("nation"), ("nation", "n_nationkey"), ("region", "n_regionkey"), "in_region"),
        _edges(t("customer"), ("customer", "c_custkey"), ("nation", "c_nationkey"), "customer_in"),
        _edges(t("supplier"), ("supplier", "s_suppkey"), ("nation", "s_nationkey"), "supplier_in"),
        _edges(t("orders"), ("order", "o_orderkey"), ("customer", "o_custkey"), "placed_by"),
        _edges(lines, ("order", "l_orderkey"), ("part", "l_partkey"), "order_part"),
        _edges(lines, ("order", "l_orderkey"), ("supplier", "l_suppkey"), "order_supplier"),
        _edges(lines, ("part", "l_partkey"), ("supplier", "l_suppkey"), "part_supplier"),
    ])


def fk_graph(spark: SparkSession, sf_dir: str, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    return _finish(fk_vertices(spark, sf_dir), fk_edges(spark, sf_dir), scheme, tau)


def contact_parts(events: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Users with the buckets and event types of their events; types are numbered in the order of their names."""
    rows = events.select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"), "event_type")
    types = rows.select("event_type").where("event_type is not null").distinct().withColumn("type_no", F.row_number().over(Window.orderBy("event_type")))  # a handful of types
    rows = rows.join(F.broadcast(types), "event_type", "left")
    vertices = _all([
        _nodes(rows.where("user_id is not null").select("user_id").distinct(), "user", "user_id", F.concat(F.lit("user "), F.col("user_id"))),
        _nodes(rows.where("k is not null").select("k").distinct(), "bucket", "k", F.concat(F.lit("bucket "), F.col("k"))),
        _nodes(types, "event_type", "type_no", F.col("event_type")),
    ])
    return vertices, _all([_edges(rows, ("user", "user_id"), ("bucket", "k"), "in_bucket"), _edges(rows, ("user", "user_id"), ("event_type", "type_no"), "did")])


def contact_graph(spark: SparkSession, sf_dir: str, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    return _finish(*contact_parts(table(spark, sf_dir, "events")), scheme, tau)


HREF = 'href="([^"]*)"'


def link_parts(pages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Pages with the paths they refer to and the hosts that serve them."""
    rows = pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.array_distinct(F.regexp_extract_all("html", F.lit(HREF), F.lit(1))).alias("hrefs"), "url")
    links = rows.select("page_id", F.explode("hrefs").alias("path"))
    paths, hosts = check_names(links, "path"), check_names(rows, "host")
    vertices = _all([_nodes(rows, "page", "page_id", F.col("url")), _nodes(paths, "path", "name_key", F.col("path")), _nodes(hosts, "host", "name_key", F.col("host"))])
    hosted = rows.where("host is not null").withColumn("h", text_key(F.col("host")))
    return vertices, _all([_edges(links.withColumn("p", text_key(F.col("path"))), ("page", "page_id"), ("path", "p"), "refers_to"), _edges(hosted, ("page", "page_id"), ("host", "h"), "served_by")])


def link_graph(spark: SparkSession, sf_dir: str, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    return _finish(*link_parts(table(spark, sf_dir, "pages")), scheme, tau)


def dialog_parts(conversations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Turns with the next turn of their conversation, and with the conversation; a turn's key is a hash of both numbers, checked for clashes."""
    name = F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    named = conversations.select("conv_id", "turn", "text", name.alias("turn_name"))
    check_names(named, "turn_name")
    rows = named.withColumn("turn_no", text_key(F.col("turn_name")))
    following = rows.withColumn("next_no", F.lead("turn_no").over(Window.partitionBy("conv_id").orderBy("turn"))).where("next_no is not null")
    vertices = _all([_nodes(rows, "turn", "turn_no", F.col("text")), _nodes(rows.select("conv_id").distinct(), "conversation", "conv_id", F.lit(""))])
    return vertices, _all([_edges(following, ("turn", "turn_no"), ("turn", "next_no"), "next"), _edges(rows, ("turn", "turn_no"), ("conversation", "conv_id"), "part_of")])


def dialog_graph(spark: SparkSession, sf_dir: str, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    return _finish(*dialog_parts(table(spark, sf_dir, "conversations")), scheme, tau)


WORD = r"[\p{L}\p{N}]+"


def content_words(documents: DataFrame) -> DataFrame:
    """``(doc_id, word, w)``: each word of a document once, and its key."""
    return documents.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(WORD), F.lit(0)))).alias("word")).withColumn("w", text_key(F.col("word")))


def content_parts(documents: DataFrame, labels: DataFrame, words: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Documents with their words (nodes without text; ``content_words``, if given), source, language and labels."""
    rows = documents.select("doc_id", "text", "lang", "source")
    words = content_words(rows) if words is None else words
    known = check_names(words, "word")
    facts = rows.withColumn("l", text_key(F.col("lang"))).withColumn("s", text_key(F.col("source")))
    marks = labels.select("doc_id", F.explode(F.array(F.col("quality"), F.col("toxic") + 2)).alias("mark"))
    vertices = _all([
        _nodes(rows, "document", "doc_id", F.col("text")), _nodes(known, "word", "name_key", F.lit("")), _nodes(facts.where("l is not null").select("l", "lang").distinct(), "lang", "l", F.col("lang")),
        _nodes(facts.where("s is not null").select("s", "source").distinct(), "source", "s", F.col("source")), _nodes(marks.select("mark").distinct(), "label", "mark", F.element_at(F.array(*[F.lit(x) for x in ("poor", "good", "civil", "toxic")]), F.col("mark") + 1)),
    ])
    return vertices, _all([
        _word_edges(rows, words), _edges(facts, ("document", "doc_id"), ("lang", "l"), "written_in"),
        _edges(facts, ("document", "doc_id"), ("source", "s"), "comes_from"), _edges(marks, ("document", "doc_id"), ("label", "mark"), "marked"),
    ])


def content_graph(spark: SparkSession, sf_dir: str, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    return _finish(*content_parts(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")), scheme, tau)


def knn_pairs(embeddings: DataFrame, k: int = 8, block: int = 2_048) -> DataFrame:
    """``vec_id, near_id, distance``: the k nearest by cosine distance, ties by id.

    Vectors are dealt to blocks of about ``block`` rows; every two blocks are
    one task's matrix product, which keeps the k nearest of each of its rows,
    so what is merged is k rows a vector and block, never a row a pair.
    """
    unit = F.transform("embedding", lambda x: x.cast("double"))
    norm = F.sqrt(F.aggregate(unit, F.lit(0.0), lambda a, x: a + x * x))
    rows = embeddings.where("embedding is not null").select("vec_id", F.transform(unit, lambda x: x / norm).alias("v")).where(norm > 0)
    blocks = max(1, -(-rows.count() // block))
    spread = rows.withColumn("mine", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    asks = spread.select("vec_id", "v", F.col("mine").alias("i"), F.col("other").alias("j"), F.lit(True).alias("ask"))
    answers = spread.select("vec_id", "v", F.col("other").alias("i"), F.col("mine").alias("j"), F.lit(False).alias("ask"))

    def nearest(frame: pd.DataFrame) -> pd.DataFrame:
        left, right = frame[frame["ask"]], frame[~frame["ask"]].sort_values("vec_id")
        if left.empty or right.empty:
            return pd.DataFrame({"vec_id": [], "near_id": [], "distance": []}).astype({"vec_id": "int64", "near_id": "int64"})
        ids, others = left["vec_id"].to_numpy(), right["vec_id"].to_numpy()
        far = np.maximum(1 - np.stack(left["v"].to_numpy()) @ np.stack(right["v"].to_numpy()).T, 1e-9)
        far[ids[:, None] == others[None]] = np.inf
        order = np.argsort(np.round(far, 9), axis=1, kind="stable")[:, :k]
        found = pd.DataFrame({"vec_id": np.repeat(ids, order.shape[1]), "near_id": others[order].ravel(), "distance": np.take_along_axis(far, order, 1).ravel()})
        return found[np.isfinite(found["distance"])]

    pairs = asks.unionByName(answers).groupBy("i", "j").applyInPandas(nearest, "vec_id long, near_id long, distance double")
    order = Window.partitionBy("vec_id").orderBy(F.round("distance", 9), "near_id")
    return pairs.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).drop("r")


def knn_graph(spark: SparkSession, sf_dir: str, k: int = 8) -> RelGraph:
    """Vectors joined to their nearest, with the distance as length; the label is the node's text."""
    rows = table(spark, sf_dir, "embeddings")
    near = knn_pairs(rows, k)
    vertices = _nodes(rows, "vector", "vec_id", F.concat(F.lit("label"), F.col("label")))
    edges = near.select(node_id("vector", "vec_id").alias("src"), node_id("vector", "near_id").alias("dst"), F.lit("near").alias("label"), F.col("distance").alias("length"))
    return _finish(vertices, edges, "given", None)


def triple_graph(triples: DataFrame, tau: int | None = 1001, scheme: str = "step_log10_plus1") -> RelGraph:
    """From ``(subject, predicate, object)``: resources are numbered by hash; a literal (in quotes) becomes text of its subject.

    Raises ValueError if two names share a number.
    """
    literal = F.col("object").startswith('"')
    names = triples.select(F.col("subject").alias("name")).unionByName(triples.where(~literal).select(F.col("object").alias("name")))
    numbered = check_names(names, "name").withColumnRenamed("name_key", "n")
    texts = triples.where(literal).groupBy("subject").agg(F.concat_ws(" ", F.sort_array(F.collect_list(F.expr("trim(both '\"' from object)")))).alias("t"))
    named = numbered.join(texts, numbered["name"] == texts["subject"], "left").select("n", F.coalesce("t", "name").alias("text"))
    vertices = _nodes(named, "resource", "n", F.col("text"))
    links = triples.where(~literal).select(text_key(F.col("subject")).alias("s"), text_key(F.col("object")).alias("o"), F.col("predicate").alias("label"))
    edges = links.select(node_id("resource", "s").alias("src"), node_id("resource", "o").alias("dst"), "label").groupBy("src", "dst").agg(F.min("label").alias("label"), F.count("*").alias("strength"))
    return _finish(vertices, edges, scheme, tau)
