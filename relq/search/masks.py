"""Arithmetic on keyword subsets, on the driver: at most 2^m entries."""

from __future__ import annotations

import math


def submasks(mask: int) -> list[int]:
    """Non-empty parts of ``mask``, ascending."""
    return [k for k in range(1, mask + 1) if k & mask == k]


def partitions(mask: int) -> list[tuple[int, int]]:
    """Unordered pairs of disjoint non-empty parts that make up ``mask``."""
    return [(k, mask ^ k) for k in submasks(mask) if k < mask ^ k]


def estimate_next(smallest: dict[int, float], e_min: float, full: int, close: bool = False) -> dict[int, float]:
    """Lower bound of each subset's length in the next round; a subset not seen yet is infinite.

    ``close`` lowers a subset to the sum of two parts that make it up.
    """
    found = {k: smallest.get(k, math.inf) + e_min for k in range(1, full + 1)}
    if close:
        for k in sorted(found, key=lambda x: x.bit_count()):
            for a, b in partitions(k):
                found[k] = min(found[k], found[a] + found[b])
    return found


def stop_published(estimate: dict[int, float], largest: dict[int, float], answers: int, wanted: int, tie_ok: bool = False) -> bool:
    """True if there are enough answers and every estimate is above the largest length of its subset among them."""
    if answers < wanted or not largest:
        return False
    return all(estimate[k] >= v if tie_ok else estimate[k] > v for k, v in largest.items())


def lower_bound(smallest: dict[int, float], e_min: float, full: int) -> float:
    """Least weight of a tree not found yet: two branches of its centre are at least as high as the rounds done, and one edge is to come."""
    if full & (full - 1) == 0:
        return math.inf  # a single keyword is answered by its own nodes
    pairs = [(a, b) for a in range(1, full + 1) for b in range(1, full + 1) if not a & b]
    return min((smallest.get(a, math.inf) + e_min + smallest.get(b, math.inf) for a, b in pairs), default=math.inf)


def smallest_possible(estimate: dict[int, float], m: int) -> float:
    """Least sum of estimates of subsets that together cover all m keywords; subsets may overlap."""
    full = (1 << m) - 1
    best = [math.inf] * (full + 1)
    best[0] = 0.0
    for covered in range(1, full + 1):
        best[covered] = min((best[covered & ~k] + v for k, v in estimate.items() if k & covered), default=math.inf)
    return best[full]


def spa_ratio(best: float | None, bound: float, optimal: bool) -> float | None:
    """Best weight found over the smallest possible one; 0 if it is proven optimal."""
    if optimal:
        return 0.0
    if best is None or not bound or math.isinf(bound):
        return None
    return best / bound


def count_combinations(p: int, m: int) -> int:
    """Trees evaluated for all subsets with p keyword nodes for each of m keywords."""
    return sum(math.comb(m, r) * p**r for r in range(1, m + 1))


def fold_cost(messages: int, k: int, m: int, pairwise: bool = True) -> int:
    """Path-lengths evaluated at a node that gets ``messages`` messages with k trees a subset."""
    return messages * (1 + 2 * k) ** m if pairwise else (1 + messages * k) ** m


def time_model(n: int, d: float, k: int, m: int, c: float, h: float) -> float:
    return n * d * (1 + 2 * k) ** m + n * c**h


def comm_model(edges: int, c: float, h: float) -> float:
    return edges * c**h


def subset_lengths(edges: list[tuple[int, int, float]], owners: dict[int, int], full: int) -> dict[int, float]:
    """Least length of a connected part of a tree that covers each subset, over all its nodes as roots."""
    nodes = {x for a, b, _ in edges for x in (a, b)} | set(owners)
    near: dict[int, list[tuple[int, float]]] = {x: [] for x in nodes}
    for a, b, w in edges:
        near[a].append((b, w))
        near[b].append((a, w))
    best = {k: math.inf for k in range(1, full + 1)}

    def visit(node: int, parent: int | None) -> list[float]:
        table = [math.inf] * (full + 1)
        for k in submasks(owners.get(node, 0)):
            table[k] = 0.0
        table[0] = 0.0
        for child, w in near[node]:
            if child != parent:
                below = visit(child, node)
                for k in range(full, 0, -1):
                    table[k] = min([table[k], *(table[k & ~j] + below[j] + w for j in submasks(k))])
        for k in range(1, full + 1):
            best[k] = min(best[k], table[k])
        return table

    if nodes:
        visit(min(nodes), None)
    return best


def constituents(edges: list[tuple[int, int, float]], owners: dict[int, int], root: int) -> list[tuple[int, float]]:
    """For each child subtree of the root, the keywords it brings and its length with the edge to it; they sum to the weight."""
    near: dict[int, list[tuple[int, float]]] = {}
    for a, b, w in edges:
        near.setdefault(a, []).append((b, w))
        near.setdefault(b, []).append((a, w))

    def walk(node: int, parent: int) -> tuple[int, float]:
        mask, length = owners.get(node, 0), 0.0
        for child, w in near.get(node, []):
            if child != parent:
                m, x = walk(child, node)
                mask, length = mask | m, length + x + w
        return mask, length

    return [(m, x + w) for child, w in near.get(root, []) for m, x in [walk(child, root)]]


def is_minimal(edges: list[tuple[int, int, float]], owners: dict[int, int], full: int) -> bool:
    """No node or edge can go: every leaf owns a keyword that no other node of the tree has."""
    degree: dict[int, int] = {}
    for a, b, _ in edges:
        degree[a], degree[b] = degree.get(a, 0) + 1, degree.get(b, 0) + 1
    covered = 0
    for v in owners.values():
        covered |= v
    if covered & full != full:
        return False
    if not edges:
        return len(owners) == 1
    for leaf in (x for x, d in degree.items() if d == 1):
        others = 0
        for x, v in owners.items():
            others |= v if x != leaf else 0
        if not owners.get(leaf, 0) & full & ~others:
            return False
    return True

