"""The first fuses of large blocks, found without looking at all pairs.

Where one unlike character of a class is the least that two codes can differ by, the pairs at that cost are those
of equal length that differ in one place. A table of codes with one place left open finds them, so the work grows
with the codes' characters. Fuse costs never fall, so all these fuses come before any dearer one.

The next fuses are made limit by limit: all pairs within a limit are found by walking the templates as a tree of shared
beginnings, where partners are left behind once their cost so far is beyond the limit. A fused template can only be within
the limit of templates that both its parts were.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from heapq import heappop, heappush

import numpy as np

from .kernel import Pool, Template, leaf
from .metric import MANY_BIT, SCHEMES, CharMetric
from .tree import Fused, Node, counters, join, pair_fuse

#: Codes of a block whose table one worker holds.
MOST = 100_000
#: Templates that pairwise fusing takes over, and pairs within a limit that are held at once.
FEW, PAIRS = 1000, 4_000_000
#: Codes of a block from which on all this takes less time than intervals of all pairs.
FROM = 5000


def has_least(metric: CharMetric, max_cost: int | None) -> bool:
    """Whether one unlike character of a class is the least cost of two codes, and within the limit."""
    return metric.packed and 0 < metric.same < min(metric.cross, metric.gap) and (max_cost is None or metric.same <= max_cost)


def near_fuse(codes: list[str], metric: CharMetric, weights: list[int] | None = None) -> list[Node]:
    """Leaves and all fuses at the least cost, as pairwise fusing makes them.

    Templates in the order of their codes take the first live code that differs in one place, and then the others
    that differ in the same place: templates of a least cost vary in one column only, so no other fits any more.
    """
    order = sorted(range(len(codes)), key=codes.__getitem__)
    items: list[Template | None] = [leaf(codes[k], metric, weights[k] if weights else 1) for k in order]
    nodes, alike = [Node(t) for t in items], _alike([t.rep for t in items], SCHEMES[metric.scheme])
    for k, t in enumerate(items):
        if t is None:
            continue
        first = None
        for i, own in alike.pop(k, ()):
            b = next((x for x in own if x > k and items[x] is not None), None)
            if b is not None and (first is None or b < first[0]):
                first = b, i, own
        if first is None:
            continue
        _, i, own = first
        same = list(range(1, len(t) + 1))
        for x in own:
            q = items[x]
            if x <= k or q is None:
                continue
            cols, packed = list(t.cols), t.packed.copy()
            cols[i] = t.cols[i] | q.cols[i]
            packed[i] = metric.pack(cols[i]) | MANY_BIT
            made = Template(t.rep, t.card + q.card, cols, metric.same, packed, t.weight + q.weight)
            nodes.append(Node(made, (t.rep, t.card), (q.rep, q.card), same, same, len(nodes)))
            t, items[x] = made, None
        items[k] = t
    return nodes


def _alike(codes: list[str], of) -> dict[int, list[tuple[int, list[int]]]]:
    """For each code that is alike with others but for one place of a class: the places, and all that are alike there."""
    kinds, out = {ch: of(ch) for ch in set().union(*codes)}, {}
    for i in range(max(map(len, codes), default=0)):  # a table a place, as together they are as large as all codes' texts many times
        groups: dict[tuple, list[int]] = {}
        for k, c in enumerate(codes):
            if i < len(c):
                groups.setdefault((kinds[c[i]], c[:i], c[i + 1 :]), []).append(k)
        for own in groups.values():
            if len(own) > 1:
                for k in own:
                    out.setdefault(k, []).append((i, own))
    return out


def close_pairs(pool: Pool, limit: int, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(a, b, cost), a < b, of all pairs of templates whose fuse cost is within a limit; None if there are more than so many.

    A pair's running costs are kept where the two places are at most limit / gap apart, as each place more takes a gap.
    Templates that begin alike share these costs up to there.
    """
    n, seen, gap = len(pool.items), pool.seen, pool.metric.gap
    apart, far, grown = limit // gap, limit + 1, seen.grown
    wide, kind = 2 * apart + 1, np.uint8 if 2 * limit + 2 < 256 else np.int32
    both = np.minimum(seen.step[:grown, :grown].astype(np.int32) + seen.gap[:grown], far).astype(kind)
    alone = np.minimum(seen.gap[:grown], far).astype(kind)
    both[:, 0] = alone[0] = far  # no column goes beyond a template's last
    plain = pool.plain()
    owns = [plain[:m, k].tolist() for k, m in enumerate(pool.length.tolist())]
    order = np.array(sorted(range(n), key=owns.__getitem__), np.intp)
    size = pool.length[order]
    rows = np.zeros((int(size.max(initial=0)) + wide, n), np.uint16 if grown < 1 << 16 else np.int32)
    rows[apart : apart + int(size.max(initial=0))] = plain[: int(size.max(initial=0)), order]
    begin = np.full((wide, n), far, kind)
    begin[apart] = 0
    for d in range(1, apart + 1):
        begin[apart + d] = np.minimum(begin[apart + d - 1] + alone[rows[apart + d - 1]], far)
    stack, last, out, found = [(np.arange(n), begin)], [], [], 0
    for k, pivot in enumerate(order.tolist()):
        own = owns[pivot]
        alike = next((i for i, (x, y) in enumerate(zip(own, last)) if x != y), min(len(own), len(last)))
        last = own
        del stack[alike + 1 :]
        while len(stack) <= len(own) and len(stack[-1][0]):
            i = len(stack) - 1
            stack.append(_walk(*stack[-1], k, rows[i : i + wide], both[own[i]], alone, alone[own[i]], limit))
        if len(stack) <= len(own):
            continue
        partners, costs = stack[-1]
        at = size[partners] - len(own) + apart
        ends = np.flatnonzero((at >= 0) & (at < wide) & (partners > k))
        cost = costs[at[ends], ends]
        ends, cost = ends[cost <= limit], cost[cost <= limit]
        if len(ends):
            other = order[partners[ends]]
            out.append((np.minimum(other, pivot), np.maximum(other, pivot), cost))
            found += len(ends)
            if found > most:
                return None
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    return tuple(np.concatenate(x).astype(np.int64) for x in zip(*out))


def _walk(partners: np.ndarray, costs: np.ndarray, k: int, cols: np.ndarray, pair: np.ndarray, alone: np.ndarray, gap: int, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Running costs after one more pivot column, of the partners behind place k that are still within the limit."""
    if len(partners) < cols.shape[1]:
        behind = int(np.searchsorted(partners, k, side="right"))
        partners, costs = partners[behind:], costs[:, behind:]
        cols = np.take(cols, partners, axis=1, mode="clip")
    now = costs + np.take(pair, cols, mode="clip")
    np.minimum(now[:-1], costs[1:] + gap, out=now[:-1])
    right = np.take(alone, cols, mode="clip")
    for d in range(1, len(now)):
        np.minimum(now[d], now[d - 1] + right[d], out=now[d])
    near = np.flatnonzero(now.min(axis=0) <= limit)
    if len(near) < len(partners):
        partners, now = partners[near], np.take(now, near, axis=1)
    return partners, np.minimum(now, limit + 1, out=now)


def close_star(pool: Pool, pivot: Template, at: np.ndarray, limit: int) -> np.ndarray:
    """Fuse costs of a pivot with the templates at the given places; those beyond the limit are only known to be so."""
    apart, far, n = limit // pool.metric.gap, limit + 1, len(pivot)
    if not len(at) or len(at) > FEW or 4 * apart > n:
        return pool.star(pivot, at)
    seen, wide, size = pool.seen, 2 * apart + 1, pool.length[at]
    own = seen.of(pivot.packed)
    rows = pool.rows[:, :, pool.place[at]].transpose(1, 0, 2).reshape(-1, len(at))[: n + apart]
    held = np.zeros((n + wide, len(at)), np.intp)
    held[apart : apart + len(rows)] = rows
    alone = seen.gap[held]
    alone[held == 0] = far  # no column goes beyond a template's last
    cols = np.arange(n)[:, None] + np.arange(wide)
    pair = (seen.step[own[:, None, None], held[cols]] + alone[cols]).astype(np.int32)
    gaps, alone = seen.gap[own].tolist(), alone.astype(np.int32)
    now = np.full((wide + 1, len(at)), far, np.int32)  # a row more, as none comes from beyond the band
    now[apart] = 0
    for d in range(apart + 1, wide):
        now[d] = now[d - 1] + alone[d - 1]
    for i in range(n):
        np.minimum(now[:-1] + pair[i], now[1:] + gaps[i], out=now[:-1])
        for d in range(1, wide):
            np.minimum(now[d], now[d - 1] + alone[i + d], out=now[d])
        now[-1] = far
    end = size - n + apart
    inside = (end >= 0) & (end < wide)
    return np.where(inside, np.minimum(now[np.where(inside, end, 0), np.arange(len(at))], far), far).astype(np.int64)


def fuse_close(templates: list[Template], nodes: list[Node], metric: CharMetric, tie: str, limit: int, most: int) -> tuple[list[Template], int] | None:
    """Makes all fuses within a cost limit, in the order of pairwise fusing; gives what is left and the costs found, None if too many pairs are that close."""
    pool = Pool(sorted(templates, key=lambda t: t.rep), metric)
    pool.KEPT = 0
    pairs = close_pairs(pool, limit, most)
    if pairs is None:
        return None
    n = len(templates)
    bits = n.bit_length()
    a, b, cost = pairs
    first = np.sort((cost << bits | a) << bits | b)
    ends, other = np.concatenate((a, b)), np.concatenate((b, a))
    order = np.argsort(ends * n + other)
    near = np.split(other[order], np.searchsorted(ends[order], np.arange(1, n)))
    evals = len(first)
    del a, b, cost, pairs, ends, other, order
    known = _each(first)
    mask, end = (1 << bits) - 1, 1 << 62
    turn, live, made = [0] * n, np.ones(n, bool), []  # turn: how often a slot was fused, -1 once it is dead
    head = next(known, end)
    while made or head < end:
        if made and made[0][0] < head:
            key, own, theirs = heappop(made)
        else:
            key, own, theirs, head = head, 0, 0, next(known, end)
        x, y = key >> bits & mask, key & mask
        if turn[x] != own or turn[y] != theirs:
            continue
        t = join(pool, x, y, nodes, tie, key >> 2 * bits)
        turn[x], turn[y], live[y] = turn[x] + 1, -1, False
        both = np.intersect1d(near[x], near[y], assume_unique=True)
        both = both[live[both]]
        cost = close_star(pool, t, both, limit)
        evals += len(both)
        both, cost = both[cost <= limit], cost[cost <= limit]
        near[x], near[y] = both, None
        for z, c in zip(both.tolist(), cost.tolist()):
            one, two = (x, z) if x < z else (z, x)
            heappush(made, ((c << bits | one) << bits | two, turn[one], turn[two]))
    return [pool.items[k] for k in np.flatnonzero(live)], evals


def _each(keys: np.ndarray) -> Iterator[int]:
    for at in range(0, len(keys), 1 << 16):
        yield from keys[at : at + (1 << 16)].tolist()


def fuse_levels(rest: list[Template], nodes: list[Node], metric: CharMetric, tie: str, max_cost: int | None) -> tuple[list[Template], int]:
    """Raises the limit until few templates are left, or too many pairs are within the next limit; gives what is left and the costs found."""
    done, by, evals = metric.same, 3 * metric.same, 0
    while len(rest) > FEW and (max_cost is None or done < max_cost):
        limit = done + by if max_cost is None else min(done + by, max_cost)
        left = fuse_close(rest, nodes, metric, tie, limit, PAIRS)
        if left is not None:
            rest, done, evals = left[0], limit, evals + left[1]
        elif limit == done + 1:
            break
        else:
            by = (limit - done) // 2
    return rest, evals


def fuse_large(codes: list[str], metric: CharMetric, weights: list[int] | None, tie: str, max_cost: int | None, most: int) -> Fused | None:
    """The whole tree: the cheapest fuses first, then pairwise fusing of what is left if that is at most so many templates."""
    began = time.perf_counter()
    nodes = near_fuse(codes, metric, weights)
    held = {side for x in nodes for side in (x.left, x.right)}
    rest, evals = fuse_levels([x.template for x in nodes if (x.template.rep, x.template.card) not in held], nodes, metric, tie, max_cost)
    if len(rest) > most:
        return None
    more = pair_fuse([], metric, tie=tie, max_cost=max_cost, templates=rest)
    for x in more.nodes:
        x.round += len(nodes)
    nodes += more.nodes
    return Fused(nodes, counters("near", len(codes), evals + more.counters["fuse_evals"], nodes, 0, 0, began), {})
