"""Shared types and node numbering."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kind codes stand above bit 48 of a node id, the key of the tuple below it.
KINDS = {
    "region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "user": 7, "bucket": 8, "event_type": 9, "page": 10,
    "path": 11, "host": 12, "turn": 13, "conversation": 14, "document": 15, "word": 16, "vector": 17, "label": 18, "source": 19, "lang": 20, "resource": 21,
}
KEY_BITS = 48


def node_id(kind: str, key: Column | str) -> Column:
    """Id of a tuple; null for a null key. A key below zero or of more than 48 bits stops the job, as it would meet another node's id."""
    key = (F.col(key) if isinstance(key, str) else key).cast("long")
    fits = key.isNull() | ((key >= 0) & (key < 1 << KEY_BITS))
    return F.when(fits, F.lit(KINDS[kind] << KEY_BITS).bitwiseOR(key)).otherwise(F.raise_error(F.lit(f"a key of kind {kind} does not fit 48 bits")).cast("long"))


def text_key(text: Column) -> Column:
    """A key for nodes named by text alone: 47 bits of a hash; ``check_names`` tells if two names share one."""
    return F.xxhash64(text).bitwiseAND((1 << 47) - 1)


def check_names(names: DataFrame, column: str) -> DataFrame:
    """The distinct names of ``column`` with their key as ``name_key``; raises ValueError if two of them share it."""
    numbered = names.select(column).where(F.col(column).isNotNull()).distinct().withColumn("name_key", text_key(F.col(column)))
    if numbered.groupBy("name_key").count().where("count > 1").limit(1).count():
        raise ValueError(f"two values of {column} share a hashed key")
    return numbered


@dataclass(frozen=True)
class RelGraph:
    """``vertices(node_id, kind, key, text)`` and ``edges(src, dst, label, length, mirrored)``."""

    vertices: DataFrame
    edges: DataFrame
    tau: int | None = None
    scheme: str = "given"

    def e_min(self) -> float:
        """The least edge length; it must be positive, as every bound adds it."""
        least = self.edges.agg(F.min("length")).first()[0]
        if least is not None and least <= 0:
            raise ValueError("edge lengths must be positive")
        return least if least is not None else float("inf")

    def n_vertices(self) -> int:
        return self.vertices.count()

    def n_edges(self) -> int:
        """Edges as given, without their mirrors."""
        return self.edges.where("not mirrored").count()
