"""Fusing with cost intervals instead of costs: the pruned searches.

Every live pair of templates has an interval for its fuse cost. Only pairs that may still be the next one
are measured, and only as many as it takes to be sure; the tree is that of pairwise fusing.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np

from .kernel import Pool, Template
from .metric import CharMetric
from .tree import FAR, Fused, counters, join, start

#: Costs below this, and sums of two, fit half words.
SMALL = 6_000
#: Cells of the intervals that are looked at together; they stay in a core's cache.
AT_ONCE = 1 << 16


def _places(mask: np.ndarray) -> np.ndarray:
    """Places of the set bytes of a mask of which few are set: eight bytes are passed over at a time."""
    flat = mask.reshape(-1)
    whole = len(flat) // 8 * 8
    words = np.flatnonzero(flat[:whole].view(np.uint64) != 0)
    k = np.flatnonzero(flat[:whole].reshape(-1, 8)[words])
    last = np.flatnonzero(flat[whole:]) + whole
    return np.concatenate((words[k >> 3] * 8 + (k & 7), last))


class Bounds:
    """Intervals [lb, ub] of all pairs of places, with each place's best partner by upper bound kept up to date.

    A place is a slot of the pool at first; once a quarter of them is dead, the others move together in their order.
    """

    def __init__(self, n: int, low: np.ndarray | None = None, high: np.ndarray | None = None):
        first = max((int(x.max(initial=0)) for x in (low, high) if x is not None), default=0)
        self.kind, self.far = (np.int16, 20_000) if first < SMALL else (np.int32, FAR)
        self.off = self.far + 1  # dead places and the diagonal
        self.lb = np.zeros((n, n), self.kind) if low is None else np.ascontiguousarray(low, self.kind)
        self.ub = np.full((n, n), self.far, self.kind) if high is None else np.ascontiguousarray(high, self.kind)
        np.fill_diagonal(self.lb, self.off)
        np.fill_diagonal(self.ub, self.off)
        self.live, self.slot = np.ones(n, bool), np.arange(n)
        #: (upper bound, partner) of every place's best pair in one number
        self.best = np.full(n, self._pair(self.off, 0))
        #: at most the least lower bound of every place with those behind it, once asked for
        self.floor: np.ndarray | None = None
        self.evals = self.refines = self.tightenings = 0
        self.rescan(np.arange(n))

    @staticmethod
    def _pair(upper, partner):
        return (np.int64(upper) if np.isscalar(upper) else upper.astype(np.int64)) << 32 | partner

    def room_for(self, cost: int) -> None:
        """Half words hold costs below SMALL and sums of two; the first dearer one moves all to whole words."""
        if cost >= SMALL and self.far < FAR:
            for name in ("lb", "ub"):
                m = getattr(self, name).astype(np.int32)
                m[m >= self.far] += FAR - self.far
                setattr(self, name, m)
            self.kind, self.far, self.off = np.int32, FAR, FAR + 1
            self.floor = None
            self.rescan(np.arange(len(self.live)))

    def rescan(self, rows: np.ndarray) -> None:
        for at in range(0, len(rows), 256):  # some at a time, as picked rows are copied
            own = rows[at : at + 256]
            upper = self.ub[own]
            self.best[own] = self._pair(upper.min(axis=1), upper.argmin(axis=1))

    def best_upper(self) -> tuple[int, int]:
        """The pair that sorts first by (ub, rep, rep)."""
        a = int(self.best.argmin())
        b = int(self.best[a] & 0xFFFFFFFF)
        return min(a, b), max(a, b)

    def critical(self, a: int, b: int, independence: bool = True) -> np.ndarray:
        """Pairs (x < y) other than (a, b) whose (lb, x, y) sorts before (ub of the best, a, b).

        With independence only pairs that share a template with the best one are looked at.
        """
        return np.concatenate([np.zeros((0, 2), np.int64), *self._critical(a, b, independence)])

    def _critical(self, a: int, b: int, independence: bool) -> Iterator[np.ndarray]:
        """The same, some at a time, as all pairs can be critical at first."""
        top = int(self.ub[a, b])
        if independence:
            for k in (a, b):
                other = np.flatnonzero(self.lb[k] <= top)
                other = other[self.live[other] & (other != a) & (other != b)]
                x, y = np.minimum(other, k), np.maximum(other, k)
                first = (self.lb[k, other] < top) | (x < a) | ((x == a) & (y < b))
                yield np.stack((x[first], y[first]), axis=1)
            return
        n = len(self.live)
        if self.floor is None:
            self.floor = np.zeros(n, np.int64)
        places = np.arange(n)
        rows = np.flatnonzero(self.live & ((self.floor < top) | ((self.floor == top) & (places <= a))))
        for own in np.split(rows, range(AT_ONCE // n or 1, len(rows), AT_ONCE // n or 1)):
            if not len(own):
                continue
            begin = int(own[0]) + 1
            lower = self.lb[own, begin:]
            lower[places[begin:] <= own[:, None]] = self.off
            self.floor[own] = lower.min(axis=1, initial=self.off)
            k = np.flatnonzero(lower <= top)
            x, y = own[k // (n - begin)] if n > begin else k, k % max(1, n - begin) + begin
            first = (self.live[y]) & ((lower.ravel()[k] < top) | (x < a) | ((x == a) & (y < b))) & ~((x == a) & (y == b))
            yield np.stack((x[first], y[first]), axis=1)

    def pick_pivot(self, pairs: np.ndarray) -> tuple[int, np.ndarray]:
        """The template whose critical intervals are widest in sum (endless ones count first), and all involved."""
        return self._heaviest([pairs])

    def _heaviest(self, parts: Iterable[np.ndarray]) -> tuple[int, np.ndarray]:
        n = len(self.live)
        many, score, involved = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, bool)
        for pairs in parts:
            upper = self.ub[pairs[:, 0], pairs[:, 1]]
            endless = upper >= self.far
            wide = np.where(endless, 0, upper.astype(np.int64) - self.lb[pairs[:, 0], pairs[:, 1]])
            for side in pairs.T:
                if len(side) < n // 8:
                    np.add.at(many, side, endless)
                    np.add.at(score, side, wide)
                else:
                    many += np.bincount(side[endless], minlength=n)
                    score += np.bincount(side, wide, n).astype(np.int64)
                involved[side] = True
        members = np.flatnonzero(involved)
        pivot = int(members[np.lexsort((members, -score[members], -many[members]))[0]])
        if not many[pivot] and not score[pivot]:
            raise AssertionError("a pivot without width makes no progress")
        return pivot, members

    def next_star(self, a: int, b: int, independence: bool) -> tuple[int, np.ndarray] | None:
        """Pivot and members of the star to measure before (a, b) may be fused; None if no pair is critical."""
        parts = (x for x in self._critical(a, b, independence) if len(x))
        one = next(parts, None)
        return None if one is None else self._heaviest(chain([one], parts, [np.array([[a, b]])]))

    def refine_star(self, pool, pivot: int, members: np.ndarray) -> None:
        """Measures the pivot against all others and tightens the rest by both triangle inequalities."""
        rest = members[members != pivot]
        ask = rest[self.lb[pivot, rest] != self.ub[pivot, rest]]
        cost = pool.star(pool.items[self.slot[pivot]], self.slot[ask])
        self.evals += len(ask)
        self.room_for(int(cost.max(initial=0)))
        for m in (self.lb, self.ub):
            m[pivot, ask] = cost
            m[ask, pivot] = cost
        if len(ask):
            self.best[ask] = np.minimum(self.best[ask], self._pair(cost, pivot))
            self.best[pivot] = min(self.best[pivot], self._pair(cost, ask).min())
        self.tightenings += self._tighten(rest, self.lb[pivot, rest])
        self.refines += 1

    def _tighten(self, rest: np.ndarray, exact: np.ndarray) -> int:
        """Bounds among the members from their exact costs to the pivot; gives the number of pairs that changed.

        Every pair is looked at once, some rows at a time, and only changed ones are written. Few members are picked
        out of the rows; of many, whole rows are looked at.
        """
        n, changed = len(self.live), 0
        every = 2 * len(rest) > n
        places, cost, mine = (np.arange(n), np.zeros(n, self.kind), np.zeros(n, bool)) if every else (rest, exact, np.ones(len(rest), bool))
        if every:
            cost[rest], mine[rest] = exact, True
        lb, ub, at, room = self.lb.reshape(-1), self.ub.reshape(-1), 0, max(AT_ONCE, n)
        work, less, more = np.empty(room, self.kind), np.empty(room, bool), np.empty(room, bool)
        while at < len(rest):
            begin = int(rest[at]) if every else at  # partners in front have been looked at
            own = rest[at : at + max(1, AT_ONCE // (len(places) - begin))]
            e, cols = exact[at : at + len(own), None], places[begin:]
            at += len(own)
            shape = len(own), len(cols)
            d, m, moved = (x[: shape[0] * shape[1]].reshape(shape) for x in (work, less, more))
            if every:
                rows = slice(int(own[0]), int(own[-1]) + 1) if own[-1] - own[0] == len(own) - 1 else own
                lower, upper = self.lb[rows, begin:], self.ub[rows, begin:]
            else:
                k = own[:, None] * n + cols
                lower, upper = np.take(lb, k, mode="clip"), np.take(ub, k, mode="clip")
            np.abs(np.subtract(e, cost[begin:], out=d), out=d)
            np.greater(d, lower, out=moved)
            np.less(np.add(e, cost[begin:], out=d), upper, out=m)
            moved |= m
            moved &= mine[begin:]
            first = int(own[-1]) - int(cols[0]) + 1
            moved[:, :first] &= cols[:first] > own[:, None]
            k = _places(moved)
            if not len(k):
                continue
            changed += len(k)
            i = np.repeat(np.arange(len(own)), np.diff(np.searchsorted(k, np.arange(len(own) + 1) * len(cols))))
            j = k - i * len(cols)
            x, y, one, two = own[i], cols[j], e[:, 0][i], cost[begin:][j]
            there, back = x * n + y, y * n + x
            lb[there] = lb[back] = np.maximum(lb[there], np.abs(one - two))
            high = one + two
            fell = np.flatnonzero(high < ub[there])
            if len(fell):
                x, y, high, there, back = x[fell], y[fell], high[fell], there[fell], back[fell]
                ub[there] = ub[back] = high
                np.minimum.at(self.best, x, self._pair(high, y))
                np.minimum.at(self.best, y, self._pair(high, x))
        return changed

    def inherit(self, a: int, b: int, cost: int) -> tuple[np.ndarray, np.ndarray]:
        """Bounds of the fused template from those of its parts."""
        self.room_for(cost)
        low = np.maximum(np.maximum(self.lb[a], self.lb[b]), self.kind(cost))
        return low, np.minimum(np.minimum(self.ub[a], self.ub[b]) + self.kind(cost), self.far)

    def replace(self, a: int, b: int, low: np.ndarray, high: np.ndarray) -> None:
        """Place a holds the fused template from now on, place b none."""
        self.live[b] = False
        low[a] = high[a] = self.off
        low[~self.live], high[~self.live] = self.off, self.off
        self.lb[a], self.lb[:, a], self.ub[a], self.ub[:, a] = low, low, high, high
        self.lb[b] = self.lb[:, b] = self.ub[b] = self.ub[:, b] = self.off
        if self.floor is not None:
            self.floor[:a] = np.minimum(self.floor[:a], low[:a])
            self.floor[a] = low[a:].min()
        partner = self.best & 0xFFFFFFFF
        stale = self.live & ((partner == a) | (partner == b))
        stale[[a, b]] = True
        mine = np.flatnonzero(~stale)
        self.best[mine] = np.minimum(self.best[mine], self._pair(high[mine], a))
        self.rescan(np.flatnonzero(stale))
        if 4 * np.count_nonzero(self.live) < 3 * len(self.live):
            self._close_up()

    def _close_up(self) -> None:
        """Moves the live places together, without a second copy."""
        own, n = np.flatnonzero(self.live), np.count_nonzero(self.live)
        for name in ("lb", "ub"):
            m = getattr(self, name)
            flat = m.reshape(-1)
            for to, k in enumerate(own):  # a row never moves behind one that is still to come
                flat[to * n : (to + 1) * n] = m[k][own]
            setattr(self, name, flat[: n * n].reshape(n, n))
        self.live, self.slot, self.floor = self.live[own], self.slot[own], None if self.floor is None else self.floor[own]
        self.best = self.best[own]
        partner = np.searchsorted(own, self.best & 0xFFFFFFFF)  # all live, as replace has seen to the others
        self.best = self.best >> 32 << 32 | np.minimum(partner, n - 1)


def bounded_fuse(
    codes: list[str], metric: CharMetric, weights: list[int] | None = None, tie: str = "gap_late", max_cost: int | None = None,
    profile: str = "star+inherit", independence: bool = True, lower: str = "zero", templates: list[Template] | None = None,
) -> Fused:
    """The tree of pairwise fusing from intervals.

    profile 'star': a fused template's pairs start anew at [0, FAR); 'star+inherit': they take over what its
    parts' pairs imply. lower 'cheap': pairs start at the gap cost of their length difference instead of 0;
    'profile': pairs of codes start from Pool.intervals(), which aligns nothing.
    The best pair and the critical set are found anew after every star. templates: goes on from these, whose nodes
    are known elsewhere, instead of codes.
    """
    if metric.kind != "diameter":
        raise ValueError("bounds hold for diameter spreads only")
    began = time.perf_counter()
    if templates is None:
        pool, nodes = start(codes, weights, metric)
    else:
        pool, nodes, lower = Pool(sorted(templates, key=lambda t: t.rep), metric), [], "zero"
    n = len(pool.items)
    low = high = None
    if lower == "profile" and metric.packed and n:
        low, high = pool.intervals()
    elif lower == "cheap" and metric.packed:
        low = np.abs(pool.length[:, None] - pool.length[None, :]) * metric.gap
    bounds = Bounds(n, low, high)
    hist: Counter[int] = Counter()
    for _ in range(n - 1):
        stars = 0
        while True:
            a, b = bounds.best_upper()
            star = bounds.next_star(a, b, independence)
            if star is None:
                break
            bounds.refine_star(pool, *star)
            stars += 1
        hist[stars] += 1
        if max_cost is not None and bounds.lb[a, b] > max_cost:
            break
        bounds.evals += bounds.lb[a, b] != bounds.ub[a, b]
        t = join(pool, int(bounds.slot[a]), int(bounds.slot[b]), nodes, tie)
        if max_cost is not None and t.spread > max_cost:
            nodes.pop()
            break
        m = len(bounds.live)
        bounds.replace(a, b, *(bounds.inherit(a, b, t.spread) if profile == "star+inherit" else (np.zeros(m, bounds.kind), np.full(m, bounds.far, bounds.kind))))
    name = ("bounded_profile" if lower == "profile" else "bounded_inherit") if profile == "star+inherit" else "bounded_star"
    return Fused(nodes, counters(name, n, int(bounds.evals), nodes, bounds.refines, bounds.tightenings, began), dict(hist))
