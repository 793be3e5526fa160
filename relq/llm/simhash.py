"""SimHash fingerprints and exact pairs within a Hamming radius by vantage-point shards.

A vantage-point tree over a bounded sample of fingerprints deals all of them
into shards. A fingerprint lives in one shard and visits every other shard
whose side of a boundary the triangle inequality cannot rule out, so every
pair within the radius meets in the home shard of either end. Inside a shard
the same bound prunes rings of equal distance before bits are compared.
"""

from __future__ import annotations

import functools
import math
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .workers import release, tidy
from .workspace import Workspace

#: Fingerprints on which the tree is grown: pivots only, results do not depend on it.
PIVOT_SAMPLE = 16_384
#: Fingerprints aimed at in a shard, and rows of one task's comparison.
SHARD_ROWS, TASK_ROWS = 32_768, 65_536
MAX_DEPTH = 12

_hash = functools.partial(xxhash.xxh64_intdigest, seed=42)


def shingle_hashes(text: bytes, width: int) -> np.ndarray:
    """XXH64 of every shingle of ``width`` words; ASCII letters lower-cased, ASCII white space splits."""
    words = text.lower().split()
    if not words:
        return np.empty(0, np.uint64)
    if len(words) <= width:
        return np.array([_hash(b" ".join(words))], np.uint64)
    runs = map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False))
    return np.fromiter(map(_hash, runs), np.uint64, len(words) - width + 1)


def majority_bits(hashes: np.ndarray) -> int:
    """A bit is 1 if it is set in over half the hashes; no hashes give zero."""
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 65_536):
        part = hashes[k : k + 65_536]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.uint32)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """``(doc_id, fp)`` with the fingerprint as a signed long, one row per input row.

    Null and blank texts have fingerprint zero; texts are read whole, whatever
    their length. Repeated rows stay repeated; other columns are not looked at.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).cast(pa.binary()).to_pylist()
            bits = np.fromiter((majority_bits(shingle_hashes(t or b"", shingle)) for t in texts), np.uint64, len(texts))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(bits.view(np.int64))], ["doc_id", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), f"doc_id {kind}, fp long")


class VantageTree:
    """Splits on the Hamming distance to a pivot; ``route`` deals fingerprints to leaves."""

    def __init__(self, sample: np.ndarray, leaf_rows: int, max_depth: int = MAX_DEPTH):
        self.pivot, self.cut, self.inner, self.outer, self.leaves = [], [], [], [], 0
        self._grow(np.unique(sample), max(1, leaf_rows), max_depth)

    def _grow(self, points: np.ndarray, leaf_rows: int, depth: int) -> int:
        at = len(self.pivot)
        for column in (self.pivot, self.cut, self.inner, self.outer):
            column.append(0)
        if depth and len(points) > leaf_rows:
            for pivot in points[:: max(1, len(points) // 5)][:5]:
                far = np.bitwise_count(points ^ pivot)
                cut = int(np.median(far))
                near = far < cut
                if 0.2 <= near.mean() <= 0.8:
                    self.pivot[at], self.cut[at] = pivot, cut
                    self.inner[at] = self._grow(points[near], leaf_rows, depth - 1)
                    self.outer[at] = self._grow(points[~near], leaf_rows, depth - 1)
                    return at
        self.cut[at], self.inner[at] = -1, self.leaves
        self.leaves += 1
        return at

    def route(self, points: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``(leaf, index, home)``: each point's home leaf and the leaves within ``radius`` of it."""
        found = []

        def visit(node: int, index: np.ndarray, home: np.ndarray) -> None:
            if not len(index):
                return
            cut = self.cut[node]
            if cut < 0:
                found.append((np.full(len(index), self.inner[node]), index, home))
                return
            far = np.bitwise_count(points[index] ^ np.uint64(self.pivot[node])).astype(np.int64)
            near, far_side = far < cut + radius, far + radius >= cut
            visit(self.inner[node], index[near], (home & (far < cut))[near])
            visit(self.outer[node], index[far_side], (home & (far >= cut))[far_side])

        visit(0, np.arange(len(points)), np.ones(len(points), bool))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.empty(0, int),) * 3


def _close(queries: np.ndarray, homes: np.ndarray, radius: int, depth: int = 3) -> list[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of queries and homes within ``radius``; rings around a pivot prune first."""
    found = []

    def visit(q: np.ndarray, h: np.ndarray, left: int) -> None:
        if not len(q) or not len(h):
            return
        if left and len(q) * len(h) > 1 << 18:
            pivot = homes[h[len(h) // 2]]
            dq, dh = (np.bitwise_count(x ^ pivot).astype(np.int64) for x in (queries[q], homes[h]))
            if dh.min() < dh.max():
                for ring in np.unique(dh):
                    visit(q[np.abs(dq - ring) <= radius], h[dh == ring], left - 1)
                return
        step = max(1, (1 << 22) // len(h))
        for k in range(0, len(q), step):
            i, j = np.nonzero(np.bitwise_count(queries[q[k : k + step], None] ^ homes[None, h]) <= radius)
            found.append((q[k + i], h[j]))

    visit(np.arange(len(queries)), np.arange(len(homes)), depth)
    return found


def spanning_links(left: np.ndarray, right: np.ndarray) -> pd.DataFrame:
    """Star edges ``(a, b)`` that join the same nodes as the links between ``left`` and ``right``."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while parent.setdefault(root, root) != root:
            root = parent[root]
        while parent[x] != root:
            parent[x], x = root, parent[x]
        return root

    for a, b in zip(left.tolist(), right.tolist(), strict=True):
        a, b = find(a), find(b)
        if a != b:
            parent[max(a, b)] = min(a, b)
    return pd.DataFrame([(x, find(x)) for x in parent if find(x) != x], columns=["a", "b"], dtype="int64")


def links_within(distinct: DataFrame, radius: int, work: Workspace, pairs: bool = False) -> DataFrame:
    """Edges ``(a, b)`` whose components equal those of all pairs of ``distinct(fp)`` within ``radius`` bits.

    A shard of a task emits a spanning forest, so a group of copies costs as
    many edges as it has members. Large shards are dealt to several tasks: the
    home side is repeated, each query goes to one of them. With ``pairs`` the
    edges are the pairs of ``distinct(fp, team)`` themselves, once each, the
    lesser first, but for those of one team; teams below zero are no teams.
    """
    names = ["fp", "team"] if pairs else ["fp"]
    spark = distinct.sparkSession
    n = distinct.count()
    sample = distinct.orderBy(F.xxhash64("fp"), "fp").limit(PIVOT_SAMPLE).toPandas()["fp"].to_numpy(np.int64).view(np.uint64)
    tree = VantageTree(sample, max(2, int(len(sample) * SHARD_ROWS / max(n, 1))))
    shared = spark.sparkContext.broadcast(tree)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            points = batch.column(0).to_numpy().view(np.uint64)
            leaf, index, home = shared.value.route(points, radius)
            columns = [column.to_numpy()[index] for column in batch.columns]
            yield pa.RecordBatch.from_arrays([pa.array(leaf.astype(np.int32)), pa.array(home.astype(bool)), *map(pa.array, columns)], ["shard", "home", *names])

    dealt = work.save(distinct.select(*names).mapInArrow(tidy(deal), f"shard int, home boolean, {', '.join(f'{n} long' for n in names)}"), "dealt")
    sizes = dealt.groupBy("shard").agg(F.ceil(F.count("*") / F.lit(TASK_ROWS)).cast("int").alias("slots"))  # one row a leaf, 4,096 at most
    placed = dealt.join(F.broadcast(sizes), "shard").withColumn("mine", F.pmod(F.xxhash64("fp"), F.col("slots")).cast("int"))
    tasks = placed.select("shard", *names, "home", "mine", F.explode(F.when(F.col("home"), F.sequence(F.lit(0), F.col("slots") - 1)).otherwise(F.array("mine"))).alias("slot"))

    def compare(rows: pd.DataFrame) -> pd.DataFrame:
        points, is_home, is_query = rows["fp"].to_numpy(np.int64), rows["home"].to_numpy(bool), (rows["mine"] == rows["slot"]).to_numpy(bool)
        homes, queries = points[is_home], points[is_query]
        found = _close(queries.view(np.uint64), homes.view(np.uint64), radius)
        if not found:
            return pd.DataFrame({"a": [], "b": []}, dtype="int64")
        i, j = (np.concatenate(x) for x in zip(*found, strict=True))
        if pairs:
            team = rows["team"].to_numpy(np.int64)
            left, right = team[is_query][i], team[is_home][j]
            keep = (queries[i] < homes[j]) & ((left != right) | (left < 0))
            return pd.DataFrame({"a": queries[i[keep]], "b": homes[j[keep]]})
        keep = queries[i] != homes[j]
        return spanning_links(queries[i[keep]], homes[j[keep]])

    return tasks.groupBy("shard", "slot").applyInPandas(compare, "a long, b long")


def simhash_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 2) -> DataFrame:
    """``(doc_id, fp, component_id)``: documents whose fingerprints are chained by links of ``radius`` bits.

    ``component_id`` is the smallest id reachable, the document itself
    included; null ids count last, so a component of null ids alone has a null.
    Equal fingerprints are one point, however many documents share it. Empty
    tables give an empty result; repeated rows are returned as often as given.
    """
    work = Workspace(docs.sparkSession, "simhash")
    marked = work.save(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    points = work.save(marked.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "points")
    roots = connected_components(work.save(links_within(points.select("fp"), radius, work), "links"), work)
    rooted = points.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = rooted.join(least, "root").select("fp", "component_id")
    return marked.join(named, "fp").select("doc_id", "fp", "component_id")


def op7_simhash(spark, sf_dir: str) -> DataFrame:
    """Every document with its fingerprint in hex and its component, at three words and two bits."""
    found = simhash_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


#: Least values of 48 hash functions in 12 bands of four: a pair at 0.8 shares a band with probability 0.998.
BANDS, BAND_ROWS = 12, 4
_MULTIPLIERS = (np.random.default_rng(5).integers(1, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)


def band_keys(hashes: np.ndarray) -> np.ndarray:
    """One key per band from the least hash values of a set of shingles."""
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint64).max, np.uint64)
    for k in range(0, len(hashes), 4_096):
        np.minimum(least, (hashes[k : k + 4_096, None] * _MULTIPLIERS).min(0), out=least)
    return np.array([xxhash.xxh64_intdigest(row.tobytes()) for row in least.reshape(BANDS, BAND_ROWS)], np.uint64)


def sketches(docs: DataFrame, text_col: str, shingle: int) -> DataFrame:
    """``(mark, fp, size, bands)`` of every row; ``mark`` is the digest of its text, ``size`` counts different shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, sizes, keys = [], [], []
            for text in batch.column(1).cast(pa.binary()):
                hashes = shingle_hashes(text.as_py(), shingle)
                fps.append(majority_bits(hashes))
                hashes = np.unique(hashes)
                sizes.append(len(hashes))
                keys.append(band_keys(hashes).view(np.int64))
            flat = np.concatenate(keys) if keys else np.zeros(0, np.int64)
            ends = pa.array(np.arange(len(fps) + 1, dtype=np.int32) * BANDS)
            columns = [batch.column(0), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), pa.ListArray.from_arrays(ends, pa.array(flat))]
            yield pa.RecordBatch.from_arrays(columns, ["mark", "fp", "size", "bands"])

    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.md5(body.cast("binary")).alias("mark"), body.alias("text")).mapInArrow(tidy(run), "mark string, fp long, size long, bands array<long>")


#: Shingles of the sets that leave a worker at once.
SET_HASHES = 200_000


def _shingle_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """``(node, hashes)``: the sorted distinct shingle hashes of ``texts(node, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, at = batch.column(1).cast(pa.binary()), 0
            while at < batch.num_rows:
                sets, held = [], 0
                while at + len(sets) < batch.num_rows and len(sets) < 64 and held < SET_HASHES:
                    sets.append(np.unique(shingle_hashes(texts[at + len(sets)].as_py(), shingle)).view(np.int64))
                    held += len(sets[-1])
                ends = pa.array(np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(sets)), pa.ListArray.from_arrays(ends, pa.array(np.concatenate(sets)))], ["node", "hashes"])
                at += len(sets)

    return texts.select("node", "text").mapInArrow(tidy(run), "node long, hashes array<long>")


#: Texts and shingles of one block of a bucket; a task compares two blocks.
BLOCK_TEXTS, BLOCK_SHINGLES = 512, 400_000


def shared_counts(owner: np.ndarray, hashes: np.ndarray, n: int) -> np.ndarray:
    """How many values each two of ``n`` sets share, of all values and the sets that own them.

    Values of the same owners are one column with their number as its weight,
    so a passage that many texts share costs as much as a single shingle.
    """
    _, value, times = np.unique(hashes, return_inverse=True, return_counts=True)
    marks = np.zeros(len(times), np.uint64)
    np.add.at(marks, value, np.random.default_rng(7).integers(1, 1 << 63, n, dtype=np.uint64)[owner])
    used = np.flatnonzero(times > 1)
    _, first, column = np.unique(marks[used], return_index=True, return_inverse=True)
    weight = np.bincount(column, minlength=len(first)).astype(float)
    column_of = np.full(len(times), -1)
    column_of[used[first]] = np.arange(len(first))
    spots = column_of[value]
    owner, spots = owner[spots >= 0], spots[spots >= 0]
    order = np.argsort(spots)
    owner, spots = owner[order], spots[order]
    out = np.zeros((n, n))
    for k in range(0, len(first), 2_048):
        low, high = np.searchsorted(spots, [k, k + 2_048])
        part = weight[k : k + 2_048]
        dense = np.zeros((n, len(part)))
        dense[owner[low:high], spots[low:high] - k] = 1
        out += (dense * part) @ dense.T
    return out


def links_in_buckets(members: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links ``(a, b)`` of roots, from all pairs of ``members(bucket, node, home, size, root)`` that meet in a bucket.

    A pair with at least one end at home is compared by its ``sets(node,
    hashes)`` unless both ends have the same root already; buckets of a single
    root are left. A large bucket is cut into blocks, and every two blocks are
    a task of their own, which emits a spanning forest of the links it verified.
    """
    slots = F.ceil(F.greatest(F.count("*") / F.lit(BLOCK_TEXTS), F.sum("size") / F.lit(BLOCK_SHINGLES))).cast("int")
    mixed = members.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high"), slots.alias("slots")).where("low < high").select("bucket", "slots")
    placed = members.join(mixed, "bucket").withColumn("mine", F.pmod(F.xxhash64("node"), F.col("slots")).cast("int"))
    others = F.filter(F.sequence(F.lit(0), F.col("slots") - 1), lambda k: (k != F.col("mine")) | (F.col("slots") == 1))
    tasks = placed.select("bucket", "node", "home", "root", "mine", F.explode(others).alias("other"))
    tasks = tasks.select("bucket", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "node", "home", "root")

    def compare(table: pa.Table) -> pa.Table:
        hashes = table.column("hashes").combine_chunks()
        sizes = np.diff(hashes.offsets.to_numpy()).astype(np.int64)
        home, root = table.column("home").to_numpy(), table.column("root").to_numpy()
        shared = shared_counts(np.repeat(np.arange(len(sizes)), sizes), hashes.flatten().to_numpy(), len(sizes))
        linked = shared >= similarity * (sizes[:, None] + sizes - shared) - 1e-9
        linked &= (root[:, None] != root) & (home[:, None] | home)
        a, b = np.nonzero(linked)
        del hashes, shared, linked
        if sizes.sum() > BLOCK_SHINGLES // 2:
            release()
        return pa.Table.from_pandas(spanning_links(root[a], root[b]), preserve_index=False)

    return tasks.join(sets, "node").groupBy("bucket", "i", "j").applyInArrow(compare, "a long, b long")


def near_duplicate_texts(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", shingle: int = 5, similarity: float = 0.8, radius: int = 2) -> tuple[DataFrame, Workspace]:
    """``(mark, root, first_id)`` for every different text: its group, and the smallest id that bears the text.

    Equal texts are one node. Texts of fingerprints within ``radius`` bits are
    candidates by vantage-point shards, every pair of them. A similarity of 0.8 lets a fingerprint of five-word
    shingles differ in up to some 14 bits, where triangle bounds prune nothing,
    so texts that share a band of least hash values are candidates too. Buckets
    are parted by size, every text standing in two neighbouring classes, as
    similar sets are of similar size. Candidates, those of equal fingerprints
    included, are linked if the exact Jaccard similarity of their shingle sets
    reaches ``similarity``. Each text is first compared with the first and the
    last node of its bucket and the first of its fingerprint, which joins groups
    of copies; then all candidate pairs that are not joined yet are.
    """
    work = Workspace(docs.sparkSession, "texts")
    ids = docs.select(F.md5(F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")).alias("mark"), F.col(id_col).alias("id"))
    firsts = ids.groupBy("mark").agg(F.min("id").alias("first_id"))
    marked = work.save(sketches(docs, text_col, shingle), "sketches")
    different = marked.groupBy("mark").agg(F.first("fp").alias("fp"), F.first("size").alias("size"), F.first("bands").alias("bands"))
    nodes = work.save(different.withColumn("node", F.monotonically_increasing_id()), "nodes")

    points = nodes.groupBy("fp").agg(F.min("node").alias("first"))
    equal = nodes.select("node", "fp").join(points, "fp").select("node", F.col("first").alias("hub"))

    step = math.log(1 / similarity) + 1e-9
    grade = F.floor(F.log(F.greatest("size", F.lit(1))) / step)
    banded = nodes.select("node", grade.alias("grade"), F.posexplode("bands").alias("band", "key"))
    keyed = banded.select("node", F.explode(F.array(*[F.xxhash64("band", "key", F.col("grade") + k) for k in (0, 1)])).alias("bucket"))
    # buckets of the same members are one
    hubs = keyed.groupBy("bucket").agg(F.min("node").alias("low"), F.max("node").alias("high"), F.count("*").alias("n"), *[F.bit_xor(F.xxhash64("node", F.lit(k))).alias(f"mark{k}") for k in (0, 1)])
    hubs = hubs.where("low < high").groupBy("low", "high", "n", "mark0", "mark1").agg(F.min("bucket").alias("bucket")).select("bucket", "low", "high")
    crowded = work.save(keyed.join(hubs, "bucket"), "crowded")
    sought = crowded.select("node", F.explode(F.array("low", "high")).alias("hub")).unionByName(equal)
    pairs = work.save(sought.where("node <> hub").select(F.least("node", "hub").alias("node"), F.greatest("node", "hub").alias("hub")).distinct(), "pairs")
    wanted = pairs.select("node").unionByName(pairs.select(F.col("hub").alias("node"))).distinct()
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    texts = docs.select(F.md5(body.cast("binary")).alias("mark"), F.struct(F.col(id_col).alias("i"), body.alias("text")).alias("row"))

    def sets_of(wanted: DataFrame, name: str) -> DataFrame:
        keepers = wanted.join(nodes.select("node", "mark"), "node").join(firsts, "mark")
        some = texts.join(keepers, "mark").where(F.col("row.i").eqNullSafe(F.col("first_id"))).select("node", "row.text")
        return work.save(_shingle_sets(some, shingle), name).dropDuplicates(["node"])

    sets = sets_of(wanted, "sets")
    sized = pairs.join(sets, "node").withColumnRenamed("hashes", "left").join(sets.select(F.col("node").alias("hub"), F.col("hashes").alias("right")), "hub")
    shared = F.size(F.array_intersect("left", "right"))
    alike = sized.select("node", "hub", shared.alias("s"), (F.size("left") + F.size("right")).alias("t")).where(F.col("s") >= similarity * (F.col("t") - F.col("s")) - 1e-9)
    links = alike.select(F.col("node").alias("a"), F.col("hub").alias("b"))
    roots = connected_components(work.save(links, "links"), work)
    rooted = work.save(nodes.select("node", "mark", "fp", "size").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")), "rooted")

    # pairs within the radius: the texts of a fingerprint are at home in its bucket, those of greater ones near it visit
    teams = work.save(rooted.groupBy("fp").agg(F.min("root").alias("low"), F.max("root").alias("high")), "teams")
    near = work.save(links_within(teams.select("fp", F.when(F.col("low") == F.col("high"), F.col("low")).otherwise(-1).alias("team")), radius, work, pairs=True), "near")
    hosts = near.select("a").unionByName(teams.where("low < high").select(F.col("fp").alias("a"))).distinct().withColumn("b", F.col("a"))
    meeting = near.unionByName(hosts).select(F.xxhash64(F.lit("fp"), "a").alias("bucket"), F.col("b").alias("fp"), (F.col("a") == F.col("b")).alias("home"))
    meeting = meeting.join(rooted.select("fp", "node", "size", "root"), "fp").select("bucket", "node", "home", "size", "root")
    banded = crowded.select("bucket", "node", F.lit(True).alias("home")).join(rooted.select("node", "size", "root"), "node")
    members = work.save(banded.unionByName(meeting.select(*banded.columns)), "members")
    rest = work.save(members.select("node").distinct().join(sets.select("node"), "node", "left_anti"), "rest")
    if not rest.isEmpty():
        sets = sets.unionByName(sets_of(rest, "more_sets"))
    more = connected_components(work.save(links_in_buckets(members, sets, similarity), "more"), work)
    named = rooted.select("mark", "root").join(more.select(F.col("node").alias("root"), F.col("root").alias("top")), "root", "left").select("mark", F.coalesce("top", "root").alias("root"))
    return work.save(named.join(firsts, "mark"), "groups"), work


def keep_one_of_each(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", **options) -> DataFrame:
    """The rows that stay when one document of each group of near-duplicates does, with all their columns.

    It is the one with the smallest id (null ids come last; equal ids with
    different texts: the text with the smaller digest; repeated rows: one of
    them). Null and blank texts are one group. Empty tables stay empty.
    """
    groups, _ = near_duplicate_texts(docs, text_col, id_col, **options)
    own = uuid.uuid4().hex  # columns of ours that clash with none
    row_mark, mark, first = (f"{x}_{own}" for x in ("row_mark", "mark", "first"))
    best = groups.groupBy("root").agg(F.min(F.struct(F.col("first_id").isNull().alias("nameless"), "first_id", "mark")).alias("k")).select(F.col("k.mark").alias(mark), F.col("k.first_id").alias(first))
    names = docs.columns
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.withColumn(row_mark, F.md5(body.cast("binary")))
    kept = rows.join(best, (F.col(row_mark) == F.col(mark)) & F.col(id_col).eqNullSafe(F.col(first)), "left_semi")
    repeated = rows.select(F.col(id_col).alias("i"), row_mark).groupBy("i", row_mark).count().where("count > 1").limit(1).count()
    if repeated:
        kept = kept.dropDuplicates([id_col, row_mark])
    return kept.select(*[F.col(f"`{n}`") for n in names])
