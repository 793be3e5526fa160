"""Intermediate tables in the folder that all executors share.

Iterative operators cut their lineage by writing a Parquet table below
``spark.checkpoint.dir`` and reading it again; a lost executor then costs a
re-read, never a recomputation of the whole chain. Tables that later rounds
join on a key are written in buckets of that key, so they are not exchanged
again. What a run does not need any longer it drops; the rest goes when
``clean_up`` is called, at the end of the program at the latest.
"""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names.

    Only in local mode, where driver and executors are one process, an unset
    folder is replaced by a temporary one.
    """
    configured = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return f"file://{tempfile.gettempdir()}/relq-checkpoints"


def delete_path(spark: SparkSession, path: str) -> None:
    """Deletes a folder through Hadoop's file system, so any store works."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def buckets_of(spark: SparkSession) -> int:
    """Buckets of a keyed table: as many as a shuffle has partitions, so an exchange can meet it as it is."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


_OPEN: dict[str, Workspace] = {}


class Workspace:
    """Named tables of one operator run, each below its own random folder."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.tag = f"relq_{label}_{uuid.uuid4().hex}"
        self.root = f"{shared_dir(spark)}/{self.tag.replace('_', '-')}"
        self._tables: set[str] = set()
        _OPEN[self.root] = self

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str, by: list[str] | None = None) -> DataFrame:
        """Writes ``df`` and returns the table as read back, with the same schema; in buckets of the columns ``by``, if given.

        A bucketed table should come from a plan that already deals its rows by
        those columns; each task then writes one bucket.
        """
        if by is None:
            df.write.mode("overwrite").option("compression", "zstd").parquet(self.path(name))
            return self.spark.read.schema(df.schema).parquet(self.path(name))
        table = f"{self.tag}_{name}"
        self._tables.add(table)
        df.write.mode("overwrite").option("compression", "zstd").option("path", self.path(name)).bucketBy(buckets_of(self.spark), *by).format("parquet").saveAsTable(table)
        return self.spark.table(table)

    def drop(self, name: str) -> None:
        """Deletes one table."""
        table = f"{self.tag}_{name}"
        if table in self._tables:
            self.spark.sql(f"DROP TABLE IF EXISTS {table}")
            self._tables.discard(table)
        delete_path(self.spark, self.path(name))

    def close(self) -> None:
        """Deletes all tables; DataFrames that read them can no longer be evaluated."""
        for table in self._tables:
            self.spark.sql(f"DROP TABLE IF EXISTS {table}")
        self._tables.clear()
        delete_path(self.spark, self.root)
        _OPEN.pop(self.root, None)


def clean_up() -> None:
    """Deletes the tables of all runs of this program, results that were not written elsewhere included."""
    for work in list(_OPEN.values()):
        work.close()


@atexit.register
def _at_exit() -> None:
    with contextlib.suppress(Exception):  # the session may be gone
        clean_up()
