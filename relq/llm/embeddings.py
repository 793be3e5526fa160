"""Near-duplicate vectors by sorted projection passes, with exact link counts inside components.

In each pass vectors are ordered by the concatenated signs of random
projections and compared with their neighbours in that order; verified pairs of
all passes are united. Links are then counted exactly among all members of a
component, in blocks, so a group wider than a window loses none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .simhash import spanning_links
from .workers import tidy
from .workspace import Workspace

PASSES, BITS, BLOCK, WINDOW, SEED = 8, 62, 1_024, 512, 20_241
#: Members of a component in one part of its count, and vectors of small components in one task's group.
PART, GROUP = 256, 1_024


def _unit(vectors: np.ndarray) -> np.ndarray:
    """Rows of length one in double precision, without overflow."""
    x = np.asarray(vectors, np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _rows(column: pa.Array) -> list[np.ndarray]:
    ends, flat = column.offsets.to_numpy(), column.values.to_numpy(zero_copy_only=False)
    return [flat[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)]


def projection_keys(vectors: np.ndarray, number: int, bits: int = BITS, seed: int = SEED) -> np.ndarray:
    """Signs of ``bits`` random projections of pass ``number``, first sign in the highest place."""
    planes = np.random.default_rng([seed, number, vectors.shape[1]]).standard_normal((vectors.shape[1], bits))
    signs = (_unit(vectors) @ planes) > 0
    return signs.astype(np.int64) @ (np.int64(1) << np.arange(bits - 1, -1, -1, dtype=np.int64))


def comparable(vectors: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    """``vec_id, label, vector, valid``: null, zero, empty or non-finite vectors and null labels are not valid."""
    v = F.col("vector")
    finite = F.forall(v, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))), F.lit(False)))
    some = F.exists(v, lambda x: F.coalesce(x != 0, F.lit(False)))
    rows = vectors.select(F.col(id_col).alias("vec_id"), F.col(label_col).alias("label"), F.col(vector_col).alias("vector"))
    return rows.withColumn("valid", F.coalesce(F.col("label").isNotNull() & finite & some, F.lit(False)))


def window_links(classes: DataFrame, threshold: float, work: Workspace, passes: int = PASSES) -> DataFrame:
    """Spanning edges ``(a, b)`` over class ids of pairs verified in the windows of all passes."""
    kinds = dict(classes.dtypes)

    def project(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = _rows(batch.column(2))
            sizes = np.array([len(r) for r in rows], np.int32)
            for number in range(passes):
                keys = np.zeros(len(rows), np.int64)
                for size in np.unique(sizes):
                    at = np.nonzero(sizes == size)[0]
                    keys[at] = projection_keys(np.stack([rows[k] for k in at]), number)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(rows), number, np.int32)), pa.array(sizes), pa.array(keys), batch.column(0), batch.column(1), batch.column(2)],
                    ["pass", "size", "key", "rid", "label", "vector"],
                )

    dealt = classes.select("rid", "label", "vector").mapInArrow(tidy(project), f"pass int, size int, key long, rid long, label {kinds['label']}, vector {kinds['vector']}")
    order = ["pass", "label", "size", "key", "rid"]
    ordered = dealt.repartitionByRange(*order).sortWithinPartitions(*order)
    placed = work.save(ordered.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)), "ordered")
    counts = sorted((r["part"], r["n"]) for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect())  # one row per partition
    begins = list(np.cumsum([0, *(n for _, n in counts)]))
    starts = placed.sparkSession.createDataFrame([(p, int(b)) for (p, _), b in zip(counts, begins, strict=False)], "part int, begin long")
    spots = placed.join(F.broadcast(starts), "part").withColumn("spot", F.col("at") + F.col("begin"))
    block = F.floor(F.col("spot") / BLOCK).cast("long")
    early = (F.col("spot") % BLOCK < WINDOW) & (block > 0)
    blocks = spots.withColumn("block", F.explode(F.when(early, F.array(block, block - 1)).otherwise(F.array(block))))

    def compare(rows: pd.DataFrame) -> pd.DataFrame:
        found = []
        for _, g in rows.groupby(["pass", "label", "size"], sort=False):
            unit, ids = _unit(np.stack(g["vector"].to_numpy())), g["rid"].to_numpy(np.int64)
            i, j = np.nonzero(np.triu(unit @ unit.T >= threshold, 1))
            found.append((ids[i], ids[j]))
        return spanning_links(*(np.concatenate(x) for x in zip(*found, strict=True)))

    return blocks.select("pass", "label", "size", "rid", "vector", "block").groupBy("block").applyInPandas(compare, "a long, b long")


def link_counts(members: DataFrame, threshold: float) -> DataFrame:
    """``(rid, others)``: for every member of ``(root, rid, copies, vector)``, the vectors of other classes linked to it.

    A component of n members is cut into about n / PART parts and every pair
    of parts is one group's work; small components share groups, of which there
    are as many as the members need.
    """
    slots = max(64, members.count() // GROUP)
    sizes = members.groupBy("root").agg(F.ceil(F.count("*") / F.lit(PART)).cast("int").alias("parts"))
    rows = members.join(sizes, "root").withColumn("mine", F.pmod(F.xxhash64("rid"), F.col("parts")).cast("int"))
    spread = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    tasks = spread.select("root", "rid", "copies", "vector", "mine", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "parts")
    tasks = tasks.withColumn("slot", F.when(F.col("parts") > 1, F.xxhash64("root", "i", "j")).otherwise(F.pmod(F.xxhash64("root"), F.lit(slots)))).drop("parts")

    def count(rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        for (_, i, j), g in rows.groupby(["root", "i", "j"], sort=False):
            low = g["mine"].to_numpy() == i
            unit, ids, copies = _unit(np.stack(g["vector"].to_numpy())), g["rid"].to_numpy(np.int64), g["copies"].to_numpy(np.int64)
            if i == j:
                near = unit @ unit.T >= threshold
                np.fill_diagonal(near, False)
                out.append(pd.DataFrame({"rid": ids, "others": near @ copies}))
            elif low.any() and not low.all():
                near = unit[low] @ unit[~low].T >= threshold
                out += [pd.DataFrame({"rid": ids[low], "others": near @ copies[~low]}), pd.DataFrame({"rid": ids[~low], "others": near.T @ copies[low]})]
        return pd.concat(out) if out else pd.DataFrame({"rid": [], "others": []}, dtype="int64")

    return tasks.groupBy("slot").applyInPandas(count, "rid long, others long").groupBy("rid").agg(F.sum("others").alias("others"))


def near_duplicate_vectors(vectors: DataFrame, threshold: float = 0.98, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str | None = "label", passes: int = PASSES) -> DataFrame:
    """``vec_id, n_links, component_id, kept``, one row per input row.

    Vectors are compared by cosine in double precision, only if their labels
    (if given) and sizes are equal. Null, empty, zero and non-finite vectors and
    those with a null label link with nothing: no links, own component, kept.
    Equal vectors are one class with a number of copies, which link with each
    other. Repeated rows are vectors of their own; a component whose ids are
    all null has a null id and its rows are kept. Empty tables give no rows.
    """
    work = Workspace(vectors.sparkSession, "vectors")
    labelled = vectors if label_col else vectors.withColumn("one_label", F.lit(0))
    rows = comparable(labelled, id_col, vector_col, label_col or "one_label")
    grouped = rows.where("valid").groupBy("label", "vector").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("copies"))
    classes = work.save(grouped.withColumn("rid", F.monotonically_increasing_id()), "classes")
    roots = work.save(connected_components(work.save(window_links(classes, threshold, work, passes), "links"), work), "roots")
    members = work.save(classes.join(roots.withColumnRenamed("node", "rid"), "rid").select("root", "rid", "copies", "vector", "first_id"), "members")
    least = members.groupBy("root").agg(F.min("first_id").alias("least"))
    linked = work.save(
        roots.withColumnRenamed("node", "rid").join(link_counts(members, threshold), "rid", "left").join(least, "root").select("rid", "others", "least"), "linked"
    )
    facts = classes.join(linked, "rid", "left").select(
        "label", "vector", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("least", "first_id").alias("component_id")
    )
    found = rows.where("valid").join(facts, ["label", "vector"]).select("vec_id", "n_links", "component_id")
    alone = rows.where("not valid").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return found.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op9_vectors(spark, sf_dir: str) -> DataFrame:
    """Every vector with its number of links at cosine 0.98 and its component."""
    return near_duplicate_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
