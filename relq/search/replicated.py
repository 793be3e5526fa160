"""Best trees of many queries on a graph that fits a machine: tasks map its arrays and share the queries.

The rounds of ``batch`` exchange a row a query and node over and over. Where
the whole graph fits a machine its arrays are written once to the shared
folder, in tasks, and each query is searched to its end in one task, by the
same rules: distances of each keyword up to half the best weight known, then
partial trees merged and carried on where less than that weight can come of
them. Tasks map the files, so those of one machine share them. Larger graphs
take the rounds.

The weight known first may be far above the least. So the waves rest at every
step, and trees lighter than twice their level are sought: where there is one,
the lightest is the answer, found among few nodes; where not, the waves go on.

Distances settle in the order of their length, so what no wave has reached yet
is at least as far as the waves are. That bounds every tree through a node
early: it falls into two parts that meet there. A node where no such tree is
lighter than the best one known passes no wave on.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from itertools import combinations
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.workspace import Workspace
from ..schema import RelGraph
from .batch import _close, _round_trips, batch_search, rebuild

#: Edges, counted once, up to which the graph is mapped by every task: some 10 bytes each in the shared folder.
MAX_EDGES = 150_000_000
#: Edges, both ways, that a step looks at together.
CHUNK = 1 << 20
#: Edges, both ways, that a task of the build sorts at a time.
BLOCK = 1 << 23
#: Different lengths that are written as numbers of a list.
MAX_LENGTHS = 1 << 16
FOUND = "query_id int, root long, weight double, by_sum boolean, edges array<struct<a:long,b:long,length:double>>"


class Arrays(NamedTuple):
    """A graph by rows of neighbours: those of node ``k``, whose id is ``ids[k]``, stand from ``starts[k]`` up to ``starts[k + 1]``.

    The length of an edge is ``scale[codes[at]]``, or ``codes[at]`` itself without a scale.
    """

    ids: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    codes: np.ndarray
    scale: np.ndarray | None
    step: float  #: how far waves go at a time

    def length(self, at: np.ndarray | slice) -> np.ndarray:
        return self.codes[at] if self.scale is None else self.scale[self.codes[at]]


class Files(NamedTuple):
    """Where the arrays of a graph stand, below ``folder``, and the lengths that its codes stand for."""

    folder: str
    codes: str
    scale: np.ndarray | None
    step: float


def _store(folder: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(folder)


def _read(folder: str, name: str, kind: str) -> np.ndarray:
    """An array as it stands in a file, mapped if the folder is a local one."""
    files, path = _store(f"{folder}/{name}")
    if not files.get_file_info(path).size:
        return np.zeros(0, kind)
    if isinstance(files, pafs.LocalFileSystem):
        return np.asarray(np.memmap(path, kind, "r"))
    with files.open_input_file(path) as held:
        return np.frombuffer(held.read_buffer(), kind)


def _write(folder: str, name: str, array: np.ndarray) -> None:
    files, path = _store(f"{folder}/{name}")
    with files.open_output_stream(path) as out:
        out.write(memoryview(np.ascontiguousarray(array)).cast("B") if len(array) else b"")


def map_arrays(files: Files) -> Arrays:
    """The graph that ``write_arrays`` wrote."""
    names = (("ids", "int64"), ("starts", "int64"), ("ends", "int32"), ("codes", files.codes))
    return Arrays(*[_read(files.folder, name, kind) for name, kind in names], files.scale, files.step)


def _pieces(folder: str, cuts: np.ndarray, scale: np.ndarray | None, codes: str) -> Callable:
    """Edges as pieces of both ways, one a block of nodes: positions of the ends instead of ids. A function over Arrow batches."""

    def piece(a: np.ndarray, b: np.ndarray, length: np.ndarray, ids: np.ndarray) -> pa.RecordBatch:
        a, b = (np.searchsorted(ids, x).astype(np.int32) for x in (a, b))
        code = length if scale is None else np.searchsorted(scale, length).astype(codes)
        near, far, code = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([code, code])
        order = np.argsort(near, kind="stable")
        near, far, code = near[order], far[order], code[order]
        at = np.searchsorted(near, cuts)
        some = np.flatnonzero(np.diff(at))
        column = lambda x: pa.array([x[at[k] : at[k + 1]].tobytes() for k in some], pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), column(near), column(far), column(code)], ["block", "near", "far", "code"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, held, n = _read(folder, "ids", "int64"), [], 0
        for batch in batches:
            held.append([batch.column(c).to_numpy(zero_copy_only=False) for c in ("src", "dst", "length")])
            n += batch.num_rows
            if 4 * n >= BLOCK:
                yield piece(*[np.concatenate(x) for x in zip(*held, strict=True)], ids)
                held, n = [], 0
        if n:
            yield piece(*[np.concatenate(x) for x in zip(*held, strict=True)], ids)

    return run


def _sorted_block(folder: str, codes: str) -> Callable:
    """Writes the rows of neighbours of a block of nodes, from its pieces; a function over Arrow tables.

    A task that is run again writes files of other names; only those it returns are read.
    """

    def run(rows: pa.Table) -> pa.Table:
        near, far, code = (np.concatenate([np.frombuffer(x.as_py(), kind) for x in rows.column(c)]) for c, kind in (("near", "int32"), ("far", "int32"), ("code", codes)))
        order, name = np.argsort(near.astype(np.int64) << 32 | far), uuid.uuid4().hex
        _write(folder, f"ends-{name}", far[order])
        _write(folder, f"codes-{name}", code[order])
        return pa.table({"block": rows.column("block")[:1].cast(pa.int32()), "name": pa.array([name])})

    return run


def _joined(folder: str, kind: str, names: list[str]) -> None:
    """One file of the blocks in their order, copied a few MB at a time."""
    files, path = _store(folder)
    with files.open_output_stream(f"{path}/{kind}") as out:
        for name in names:
            with files.open_input_stream(f"{path}/{kind}-{name}") as part:
                while chunk := part.read(1 << 23):
                    out.write(chunk)
            files.delete_file(f"{path}/{kind}-{name}")


def write_arrays(once: DataFrame, work: Workspace, step: float) -> Files:
    """The arrays of a graph from its edges, ``(src, dst, length)``, that stand once and go both ways.

    The driver holds a row a node, its degree. Edges are sorted in tasks, by
    blocks of nodes of as many edges each.
    """
    folder = work.path("arrays")
    files, path = _store(folder)
    files.create_dir(path, recursive=True)
    degrees = once.select(F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count("*").alias("n")).toArrow()
    ids, degree = (degrees.column(c).to_numpy() for c in ("node", "n"))
    order = np.argsort(ids)
    starts = np.concatenate([[0], np.cumsum(degree[order])]).astype(np.int64)
    _write(folder, "ids", ids[order])
    _write(folder, "starts", starts)
    scale, codes = np.sort([r["length"] for r in once.select("length").distinct().limit(MAX_LENGTHS + 1).collect()]), "float64"
    if len(scale) > MAX_LENGTHS:
        scale = None
    else:
        codes = "uint8" if len(scale) <= 256 else "uint16"
        if (scale == np.round(scale)).all() and scale.max(initial=0) < 1 << 12:
            scale = scale.astype(np.float32)  # sums of them are exact
    blocks = max(1, -(-int(starts[-1]) // BLOCK))
    cuts = np.unique(np.searchsorted(starts, np.arange(1, blocks) * int(starts[-1]) // blocks))
    cuts = np.concatenate([[0], cuts[(cuts > 0) & (cuts < len(ids))], [len(ids)]])
    pieces = once.select("src", "dst", "length").mapInArrow(_pieces(folder, cuts, scale, codes), "block int, near binary, far binary, code binary")
    done = pieces.repartition(len(cuts) - 1, "block").groupBy("block").applyInArrow(_sorted_block(folder, codes), "block int, name string").collect()  # a row a block
    names = [r["name"] for r in sorted(done, key=lambda r: r["block"])]
    for kind in ("ends", "codes"):
        _joined(folder, kind, names)
    return Files(folder, codes, scale, step)


def _fans(starts: np.ndarray, nodes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For parts of ``nodes``, the node and the position of each of their edges."""
    degrees = starts[nodes + 1] - starts[nodes]
    part = np.cumsum(degrees) // CHUNK
    cuts = np.flatnonzero(np.diff(part)) + 1
    for some, n in zip(np.split(nodes, cuts), np.split(degrees, cuts), strict=True):
        if total := int(n.sum()):
            yield np.repeat(some, n), np.repeat(starts[some] - np.cumsum(n) + n, n) + np.arange(total)


def _through(missing: np.ndarray) -> np.ndarray:
    """At least what a tree of all keywords through each node weighs: two parts that meet there."""
    whole = missing.shape[1] - 1
    out = np.full(len(missing), np.inf)
    for mask in range(1, whole, 2):
        np.minimum(out, missing[:, mask] + missing[:, whole ^ mask], out=out)
    return out


def _gaps(far: np.ndarray, reach: float) -> np.ndarray:
    """At least how far two keywords are apart, all distances below half of ``reach`` being known."""
    out = np.zeros((len(far),) * 2)
    for i, j in combinations(range(len(far)), 2):
        out[i, j] = out[j, i] = min((far[i] + far[j]).min(), reach)
    return out


def _alive(far: np.ndarray, nodes: np.ndarray, rim: float, gaps: np.ndarray, limit: float) -> tuple[np.ndarray, np.ndarray]:
    """Those of ``nodes`` that a tree lighter than ``limit`` may hold, and at least what is missing there."""
    kept, rows = [nodes[:0]], [np.zeros((0, 1 << len(far)), far.dtype)]
    block = max(64, CHUNK >> len(far))
    for begin in range(0, len(nodes), block):
        some = nodes[begin : begin + block]
        near = np.minimum(far[:, some], rim)
        ok = near.max(0) + near.min(0) < limit  # each part holds a keyword
        some, missing = some[ok], _round_trips(near[:, ok].T, gaps)
        ok = _through(missing) < limit
        kept.append(some[ok])
        rows.append(missing[ok].astype(far.dtype))
    return np.concatenate(kept), np.concatenate(rows)


class _Waves:
    """Distances by keyword and node, as far as ``level``; the least sum at a node, ``limit``, and that node, ``root``.

    ``blind`` nodes are passed by. A distance that gets shorter is sent again.
    """

    def __init__(self, graph: Arrays, seeds: list[np.ndarray], blind: np.ndarray):
        lengths = graph.codes if graph.scale is None else graph.scale
        self.graph, self.blind, self.limit, self.root, self.level = graph, blind, np.inf, -1, 0.0
        self.e_min = float(lengths.min())
        self.far = np.full((len(seeds), len(graph.ids)), np.inf, lengths.dtype)
        self.sent = np.zeros(self.far.shape, bool)
        for i, group in enumerate(seeds):
            self.far[i, group] = 0.0
        self._look()

    def _look(self) -> None:
        total = self.far.sum(0)
        if total.min() < self.limit:
            self.limit, self.root = float(total.min()), int(total.argmin())
        self.level = min(float(f[~s].min(initial=np.inf)) for f, s in zip(self.far, self.sent, strict=True))

    def at_rest(self) -> bool:
        """Whether no further distance can matter for a tree lighter than ``limit``."""
        return 2 * self.level >= self.limit or np.isinf(self.level)

    def near(self, limit: float) -> tuple[np.ndarray, np.ndarray]:
        """The nodes that a tree lighter than ``limit`` may hold, and at least what is missing there; distances below half of it are known."""
        rim = min(self.level, limit / 2) + self.e_min
        some = ~self.blind
        some &= np.minimum(self.far.max(0), rim) + np.minimum(self.far.min(0), rim) < limit
        return _alive(self.far, np.flatnonzero(some), rim, _gaps(self.far, limit), limit)

    def go_on(self) -> None:
        """One step of all waves."""
        far, sent, limit, level, graph = self.far, self.sent, self.limit, self.level, self.graph
        fronts = [np.flatnonzero(~s & (d < level + graph.step)) for s, d in zip(sent, far, strict=True)]
        if np.isfinite(limit):
            alive = np.zeros(len(graph.ids), bool)
            alive[_alive(far, np.unique(np.concatenate(fronts)), level + self.e_min, _gaps(far, 2 * level), limit)[0]] = True
        for i, front in enumerate(fronts):
            sent[i, front] = True
            if np.isfinite(limit):
                front = front[alive[front] & (2 * far[i, front] < limit)]
            for node, at in _fans(graph.starts, front):
                end, length = graph.ends[at], far[i, node] + graph.length(at)
                shorter = (length < far[i, end]) & (length < limit) & ~self.blind[end]
                np.minimum.at(far[i], end[shorter], length[shorter])
                sent[i, end[shorter]] = False
        self._look()


def _merges(graph: Arrays, nodes: np.ndarray, far: np.ndarray, missing: np.ndarray, limit: float) -> tuple[Arrays, np.ndarray, float, int]:
    """The part of the graph among ``nodes``, the lengths of partial trees by node and subset, the least weight below ``limit`` and its node."""
    n, m, root = len(nodes), len(far), -1
    whole, spot = (1 << m) - 1, np.full(len(graph.ids), -1, np.int32)
    spot[nodes] = np.arange(n)
    inner = [(np.zeros(0, np.int32), np.zeros(0, np.int32), graph.codes[:0])]
    for node, at in _fans(graph.starts, nodes):
        end = spot[graph.ends[at]]
        inner.append((spot[node[end >= 0]], end[end >= 0], graph.codes[at[end >= 0]]))
    a, b, codes = (np.concatenate(x) for x in zip(*inner, strict=True))
    part = Arrays(graph.ids[nodes], np.concatenate([[0], np.cumsum(np.bincount(a, minlength=n))]), b, codes, graph.scale, graph.step)
    table = np.full((n, whole + 1), np.inf, far.dtype, order="F")
    for i in range(m):
        mine = far[i, nodes] + missing[:, 1 << i] < limit
        table[mine, 1 << i] = far[i, nodes[mine]]
    gained = _close(table, np.isfinite(table), missing, limit)
    while True:
        if n and table[:, whole].min() < limit:
            limit, root = float(table[:, whole].min()), int(table[:, whole].argmin())
        fresh = np.zeros_like(gained)
        for mask in range(3, whole):
            if mask & (mask - 1) == 0:
                continue
            for node, at in _fans(part.starts, np.flatnonzero(gained[:, mask] & (2 * table[:, mask] < limit))):
                end, length = part.ends[at], table[node, mask] + part.length(at)
                lighter = (length < table[end, mask]) & (length + missing[end, mask] < limit)
                np.minimum.at(table[:, mask], end[lighter], length[lighter])
                fresh[end[lighter], mask] = True
        met = np.flatnonzero(fresh.any(1))
        if not len(met):
            return part, table, limit, root
        here, gained = table[met], np.zeros_like(gained)
        gained[met] = _close(here, fresh[met], missing[met], limit)
        table[met] = here


def _back(graph: Arrays, lengths: np.ndarray, node: int) -> tuple[int, float]:
    """The neighbour from which a length at ``node`` came, and the length of the edge."""
    at = slice(graph.starts[node], graph.starts[node + 1])
    way = graph.length(at)
    k = int((lengths[graph.ends[at]] + way).argmin())
    return int(graph.ends[at][k]), float(way[k])


def _tree(graph: Arrays, far: np.ndarray, starts: list[tuple[int, int]]) -> set[tuple[int, int, float]]:
    """The edges of the shortest ways from nodes to keywords."""
    out = set()
    for node, i in starts:
        while far[i, node] > 0:
            near, length = _back(graph, far[i], node)
            out.add((*sorted((int(graph.ids[near]), int(graph.ids[node]))), length))
            node = near
    return out


def _merged_tree(graph: Arrays, part: Arrays, nodes: np.ndarray, far: np.ndarray, table: np.ndarray, root: int) -> set[tuple[int, int, float]]:
    """The edges of the tree of all keywords at ``root``, a node of ``part``."""
    out, singles, held = set(), [], [(root, table.shape[1] - 1)]
    while held:
        node, mask = held.pop()
        if mask & (mask - 1) == 0:
            singles.append((int(nodes[node]), mask.bit_length() - 1))
            continue
        pair = next((a for a in range(1, mask) if a & mask == a and table[node, a] + table[node, mask ^ a] <= table[node, mask]), None)
        if pair:
            held += [(node, pair), (node, mask ^ pair)]
        else:
            near, length = _back(part, table[:, mask], node)
            if table[near, mask] + length > table[node, mask]:
                raise RuntimeError("a partial tree has no origin")
            out.add((*sorted((int(part.ids[near]), int(part.ids[node]))), length))
            held.append((near, mask))
    return out | _tree(graph, far, singles)


def best_tree(graph: Arrays, node_ids: np.ndarray, masks: np.ndarray, m: int) -> tuple[int, float, bool, set] | None:
    """Root, weight, whether distances add up to it, and edges of a lightest tree of one query, from the nodes of its keywords; None if no tree joins them."""
    whole = (1 << m) - 1
    if (masks == whole).any():
        return int(node_ids[masks == whole].min()), 0.0, True, set()
    spots = np.searchsorted(graph.ids, node_ids)
    known = spots < len(graph.ids)
    known[known] = graph.ids[spots[known]] == node_ids[known]  # others have no edge
    spots, masks = spots[known], masks[known]
    seeds = [spots[masks >> i & 1 == 1] for i in range(m)]
    if not all(len(s) for s in seeds):
        return None
    blind = np.diff(graph.starts) == 1  # a node with one neighbour is a leaf, which only a keyword can be
    blind[spots] = False
    waves = _Waves(graph, seeds, blind)
    while True:
        limit = min(waves.limit, 2 * waves.level)
        if m > 2 and 0 < limit < np.inf:  # lighter trees than this are known by now, or there is none
            nodes, missing = waves.near(limit)
            part, table, weight, root = _merges(graph, nodes, waves.far, missing, limit)
            if root >= 0:
                return int(part.ids[root]), weight, False, _merged_tree(graph, part, nodes, waves.far, table, root)
        if waves.at_rest():
            return None if waves.root < 0 else (int(graph.ids[waves.root]), waves.limit, True, _tree(graph, waves.far, [(waves.root, i) for i in range(m)]))
        waves.go_on()


def _search_one(files: Files, queries: dict[int, int]) -> Callable:
    """The search of one query, from its rows of ``(query_id, node_id, mask)``; a function over Arrow tables."""

    def run(rows: pa.Table) -> pa.Table:
        query = rows.column("query_id")[0].as_py()
        found = best_tree(map_arrays(files), rows.column("node_id").to_numpy(), rows.column("mask").to_numpy(), queries[query])
        out = []
        if found:
            root, weight, by_sum, edges = found
            out = [{"query_id": query, "root": root, "weight": weight, "by_sum": by_sum, "edges": [{"a": a, "b": b, "length": w} for a, b, w in sorted(edges)]}]
        edge = pa.struct([("a", pa.int64()), ("b", pa.int64()), ("length", pa.float64())])
        return pa.Table.from_pylist(out, pa.schema([("query_id", pa.int32()), ("root", pa.int64()), ("weight", pa.float64()), ("by_sum", pa.bool_()), ("edges", pa.list_(edge))]))

    return run


def best_trees(graph: RelGraph, seeds: DataFrame, queries: dict[int, int], trees: bool = True, max_edges: int = MAX_EDGES) -> tuple[DataFrame, DataFrame | None]:
    """``(answers, edges)`` as ``batch_search`` and ``rebuild`` return them for K = 1; no edges unless ``trees``.

    ``graph`` holds every edge both ways, as ``mirror`` makes it. One with more
    than ``max_edges`` edges, or with edges of no length, takes the rounds.
    """
    spark, work = graph.edges.sparkSession, Workspace(graph.edges.sparkSession, "replicated")
    once = work.save(graph.edges.where("src < dst").select("src", "dst", "length"), "once")
    n, e_min, mean = once.agg(F.count("*"), F.min("length"), F.avg("length")).first()
    if n > max_edges or (n and e_min <= 0):
        held = RelGraph(graph.vertices, graph.edges.persist(), graph.tau, graph.scheme)
        answers, state, _ = batch_search(held, seeds, queries)
        return answers, rebuild(held, answers, state) if trees else None
    # waves go as far as the shortest edge, or farther if edges differ much
    files = write_arrays(once, work, max(e_min or 0.0, (mean or 0.0) / 4))
    dealt = seeds.select("query_id", "node_id", "mask").repartition(max(1, 2 * len(queries)), "query_id")
    found = work.save(dealt.groupBy("query_id").applyInArrow(_search_one(files, queries), FOUND), "found")
    work.drop("arrays")
    work.drop("once")
    answers = found.select("query_id", "root", "weight", "by_sum", F.lit(True).alias("proven"))
    return answers, found.select("query_id", F.explode("edges").alias("e")).select("query_id", "e.*") if trees else None
