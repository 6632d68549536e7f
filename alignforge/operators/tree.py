"""Fusion trees: greedy fusing of all pairs, of one growing chain, and with pruned searches.

A block's codes are fused on one worker. Slots are the codes in code-point order; a fused template takes
the slot of its smaller rep, so slot order is rep order and argmin picks the first pair of the total order
(cost, rep, rep). Any schedule that fuses mutually first pairs gives the same tree.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from .kernel import Pool, Template, fuse, leaf
from .metric import CharMetric

FAR = 1 << 28
#: The same in half words.
HALF = 32_000


@dataclass
class Node:
    template: Template
    left: tuple[str, int] | None = None
    right: tuple[str, int] | None = None
    left_map: list[int] = field(default_factory=list)
    right_map: list[int] = field(default_factory=list)
    round: int = 0


@dataclass
class Fused:
    """Nodes in the order they were made, and what it cost."""

    nodes: list[Node]
    counters: dict[str, int]
    refine_hist: dict[int, int]


def start(codes: list[str], weights: list[int] | None, metric: CharMetric) -> tuple[Pool, list[Node]]:
    order = sorted(range(len(codes)), key=codes.__getitem__)
    leaves = [leaf(codes[k], metric, weights[k] if weights else 1) for k in order]
    return Pool(leaves, metric), [Node(t) for t in leaves]


def join(pool: Pool, a: int, b: int, nodes: list[Node], tie: str, cost: int | None = None) -> Template:
    p, q = pool.items[a], pool.items[b]
    t, left, right = fuse(p, q, pool.metric, tie, cost, pool.seen if pool.metric.packed else None)
    nodes.append(Node(t, (p.rep, p.card), (q.rep, q.card), left, right, len(nodes)))
    pool.put(a, t), pool.drop(b)
    return t


def pair_fuse(codes: list[str], metric: CharMetric, weights: list[int] | None = None, tie: str = "gap_late", max_cost: int | None = None, templates: list[Template] | None = None) -> Fused:
    """Always fuses the cheapest of all pairs; costs are kept, so N codes take (N-1)^2 evaluations.

    Costs are half words as long as they fit, and the first ones share what codes that begin alike have in common.
    templates: goes on from these, whose nodes are known elsewhere, instead of codes.
    """
    began = time.perf_counter()
    pool, nodes = start(codes, weights, metric) if templates is None else (Pool(sorted(templates, key=lambda t: t.rep), metric), [])
    n = len(pool.items)
    kind, far = (np.int16, HALF) if metric.packed and 2 * int(pool.alone.max(initial=0)) < HALF else (np.int32, FAR)
    cost = np.full((n, n), far, kind)
    evals = 0
    if metric.packed:
        for k, at, c in pool.triangle():
            cost[k, at : at + len(c)] = c
            evals += len(c)
    else:
        for k in range(n - 1):
            cost[k, k + 1 :] = pool.star(pool.items[k], np.arange(k + 1, n))
            evals += n - 1 - k
    best = cost.min(axis=1) if n else np.zeros(0, kind)
    arg = cost.argmin(axis=1) if n else np.zeros(0, np.int64)
    live = np.ones(n, bool)
    for _ in range(n - 1):
        a = int(best.argmin())
        b = int(arg[a])
        if max_cost is not None and best[a] > max_cost:
            break
        t = join(pool, a, b, nodes, tie)
        live[b] = False
        others = np.flatnonzero(live)
        others = others[others != a]
        c = pool.star(t, others)
        evals += len(others)
        if far < FAR and int(c.max(initial=0)) >= far:
            dead, cost, best = cost >= far, cost.astype(np.int32), best.astype(np.int32)
            far, cost[dead], best[best >= far] = FAR, FAR, FAR
        cost[b, :], cost[:, b], best[b] = far, far, far
        low, high = others < a, others > a
        cost[a, :] = far
        cost[a, others[high]] = c[high]
        cost[others[low], a] = c[low]
        rows = np.flatnonzero(live & ((arg == a) | (arg == b)))
        rows = np.union1d(rows, [a])
        best[rows], arg[rows] = cost[rows].min(axis=1), cost[rows].argmin(axis=1)
        mine = others[low]
        better = (cost[mine, a] < best[mine]) | ((cost[mine, a] == best[mine]) & (a < arg[mine]))
        best[mine[better]], arg[mine[better]] = cost[mine[better], a], a
    return Fused(nodes, counters("pair", n, evals, nodes, 0, 0, began), {})


def chain_fuse(codes: list[str], metric: CharMetric, weights: list[int] | None = None, tie: str = "gap_late", max_cost: int | None = None) -> Fused:
    """Grows one template from the cheapest pair by the code that is cheapest to absorb."""
    began = time.perf_counter()
    pool, nodes = start(codes, weights, metric)
    n, evals = len(pool.items), 0
    if n > 1:
        first = (FAR, 0, 0)
        for k in range(n - 1):
            c = pool.star(pool.items[k], np.arange(k + 1, n))
            evals += len(c)
            j = int(c.argmin())
            first = min(first, (int(c[j]), k, k + 1 + j))
        at, left = first[1], np.ones(n, bool)
        left[[first[1], first[2]]] = False
        t = join(pool, first[1], first[2], nodes, tie)
        while left.any():
            rest = np.flatnonzero(left)
            c = pool.star(t, rest)
            evals += len(rest)
            k = int(rest[c.argmin()])
            if max_cost is not None and int(c.min()) > max_cost:
                break
            left[k] = False
            t = join(pool, min(at, k), max(at, k), nodes, tie)
            at = min(at, k)
    return Fused(nodes, counters("chain", n, evals, nodes, 0, 0, began), {})


def counters(name: str, n: int, evals: int, nodes: list[Node], refines: int, tightenings: int, began: float) -> dict[str, int]:
    done = sum(x.left is not None for x in nodes)
    return {"n": n, "fuse_evals": evals, "fuse_done": done, "refines": refines, "tightenings": tightenings, "rounds": done, "wall_ms": int(1000 * (time.perf_counter() - began))}


def run(codes: list[str], metric: CharMetric, algorithm: str = "bounded", weights: list[int] | None = None, **options) -> Fused:
    if algorithm == "pair":
        return pair_fuse(codes, metric, weights, options.get("tie", "gap_late"), options.get("max_cost"))
    if algorithm == "chain":
        return chain_fuse(codes, metric, weights, options.get("tie", "gap_late"), options.get("max_cost"))
    from .bounded import bounded_fuse

    return bounded_fuse(codes, metric, weights, **options)


def spans(fused: Fused) -> dict[tuple[str, int], Node]:
    return {(x.template.rep, x.template.card): x for x in fused.nodes}


def aligned_members(fused: Fused, key: tuple[str, int]) -> dict[str, list[str | None]]:
    """Gap-padded codes of a node's members, by composing column maps."""
    nodes = spans(fused)

    def walk(key: tuple[str, int], at: list[int], out: dict) -> None:
        x = nodes[key]
        if x.left is None:
            out[key[0]] = [key[0][k - 1] if k else None for k in at]
            return
        walk(x.left, [x.left_map[k - 1] if k else 0 for k in at], out)
        walk(x.right, [x.right_map[k - 1] if k else 0 for k in at], out)

    out: dict[str, list[str | None]] = {}
    walk(key, list(range(1, len(nodes[key].template) + 1)), out)
    return out
