"""Readers, writers and a source in Python, with round trips as queries."""

from __future__ import annotations

import re
import uuid

import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..graph.builders import table as t
from ..operators.relational import query
from ..plans.workspace import shared_dir

TRIPLE = r"^<([^>]*)>\s+<([^>]*)>\s+(<[^>]*>|\"[^\"]*\")\s*\.$"
SUPPLIER = "s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE"


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/relq-io-{name}-{uuid.uuid4().hex}"


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    """``(subject, predicate, object)`` of an N-Triples file; lines of other forms are left out."""
    lines = spark.read.text(path).where(F.col("value").rlike(TRIPLE))
    part = lambda k: F.regexp_extract("value", TRIPLE, k)
    return lines.select(part(1).alias("subject"), part(2).alias("predicate"), F.regexp_replace(part(3), "^<|>$", "").alias("object"))


def write_triples(rows: DataFrame, path: str) -> None:
    """Writes ``(subject, predicate, object)``; objects in quotes are literals."""
    end = F.when(F.col("object").startswith('"'), F.col("object")).otherwise(F.concat(F.lit("<"), "object", F.lit(">")))
    rows.select(F.concat(F.lit("<"), "subject", F.lit("> <"), "predicate", F.lit("> "), end, F.lit(" .")).alias("value")).write.text(path)


@query("SELECT 'nation/' || n_nationkey AS subject, p AS predicate, CASE p WHEN 'name' THEN '\"' || n_name || '\"' ELSE 'region/' || n_regionkey END AS object FROM nation, (VALUES ('name'), ('in_region')) v(p)")
def op_scan_text_triples(s, d):
    nation = t(s, d, "nation")
    subject = F.concat(F.lit("nation/"), "n_nationkey")
    both = nation.select(subject.alias("subject"), F.lit("name").alias("predicate"), F.concat(F.lit('"'), "n_name", F.lit('"')).alias("object")).unionByName(
        nation.select(subject.alias("subject"), F.lit("in_region").alias("predicate"), F.concat(F.lit("region/"), "n_regionkey").alias("object"))
    )
    path = _folder(s, "triples")
    write_triples(both, path)
    return read_triples(s, path)


def _round_trip(s, d, form: str) -> DataFrame:
    path = _folder(s, form)
    writer, reader = t(s, d, "supplier").write, s.read.schema(SUPPLIER)
    if form == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    writer.format(form).save(path)
    return reader.format(form).load(path)


for _form in ("csv", "json", "orc"):
    query("SELECT s_suppkey, s_name, s_nationkey, s_acctbal FROM supplier", f"op_{_form}_roundtrip")(lambda s, d, f=_form: _round_trip(s, d, f))


class EdgeSource(DataSource):
    """Edges ``(src, dst)`` of the Parquet files in the folder ``path``, read in Python through Arrow's file systems."""

    @classmethod
    def name(cls) -> str:
        return "edge_files"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return EdgeReader(self.options["path"])


class Block(InputPartition):
    def __init__(self, file: str):
        self.file = file


class EdgeReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = re.sub("^s3[an]:", "s3:", path)

    def partitions(self) -> list[Block]:
        store, folder = pafs.FileSystem.from_uri(self.path)
        return [Block(x.path) for x in store.get_file_info(pafs.FileSelector(folder)) if x.path.endswith(".parquet")]

    def read(self, block: Block):
        store, _ = pafs.FileSystem.from_uri(self.path)
        with store.open_input_file(block.file) as file:
            for batch in pq.ParquetFile(file).iter_batches(columns=["src", "dst"]):
                yield batch


@query("SELECT count(*) AS n_edges, count(DISTINCT o) AS n_sources FROM (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem WHERE l_orderkey IS NOT NULL AND l_partkey IS NOT NULL)")
def op_scale_free_source(s, d):
    """Links of orders to parts, of which a few gather many, written by Spark and read by a source in Python."""
    path = _folder(s, "edges")
    t(s, d, "lineitem").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst")).dropna().distinct().write.parquet(path)
    s.dataSource.register(EdgeSource)
    edges = s.read.format("edge_files").option("path", path).load()
    return edges.agg(F.count("*").alias("n_edges"), F.countDistinct("src").alias("n_sources"))
