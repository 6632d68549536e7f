"""Alignment kernel: fuse costs of one template against many, and single fuses with their column maps.

Costs of a star run column by column of the pivot for all partners at once, as what pairing columns saves
over leaving them all beside gaps. Savings are small whole numbers from 0 up, a byte each for codes of usual
length, and what a pivot column saves with every partner's columns is kept between stars.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from .metric import GAP, GAP_BIT, SCHEMES, CharMetric, union

TIES = ("gap_late", "gap_early")


@dataclass
class Template:
    """Aligned columns as character sets, with packed summaries where the metric has them."""

    rep: str
    card: int
    cols: list[frozenset]
    spread: int
    packed: np.ndarray | None = field(default=None, repr=False)
    weight: int = 1

    def __len__(self) -> int:
        return len(self.cols)


@lru_cache(maxsize=4096)
def _single(ch: str) -> frozenset:
    return frozenset((ch,))


def leaf(code: str, metric: CharMetric, weight: int = 1) -> Template:
    return Template(code, 1, [_single(c) for c in code], 0, metric.pack_code(code) if metric.packed else None, weight)


def _moves(p: Template, q: Template, metric: CharMetric) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Costs of pairing columns, of a column of p with a gap, of a column of q with a gap."""
    if metric.packed:
        a, b = p.packed, q.packed
        return metric.spread_of(union(a[:, None], b[None, :])), metric.spread_of(a | GAP_BIT), metric.spread_of(b | GAP_BIT)
    spread, gap = metric.column_spread, frozenset((GAP,))
    pair = np.array([[spread(x | y) for y in q.cols] for x in p.cols], np.int32).reshape(len(p), len(q))
    return pair, np.array([spread(x | gap) for x in p.cols], np.int32), np.array([spread(y | gap) for y in q.cols], np.int32)


def _table(pair: np.ndarray, down: np.ndarray, right: np.ndarray) -> np.ndarray:
    n, m = pair.shape
    walked = np.concatenate(([0], np.cumsum(right)))
    out = np.empty((n + 1, m + 1), np.int64)
    out[0] = walked
    for i in range(n):
        t = out[i] + down[i]
        np.minimum(t[1:], out[i, :-1] + pair[i], out=t[1:])
        out[i + 1] = np.minimum.accumulate(t - walked) + walked
    return out


def fuse_cost(p: Template, q: Template, metric: CharMetric) -> int:
    """Spread of the fused template."""
    return int(_table(*_moves(p, q, metric))[-1, -1])


#: Partner columns lie in groups, place by place of their group, so that a running maximum takes few operations.
GROUP = 8
#: Partners that are worked on place by place, as their columns need no groups.
FEW = 128


def _groups(length: int) -> int:
    return max(1, -(-length // GROUP))


def _absorb(before: np.ndarray, saved: np.ndarray, after: np.ndarray, paired: np.ndarray) -> None:
    """Savings after one more pivot column, [place, group, partner], from those before it; both may be the same."""
    np.add(before[:-1], saved[1:], out=paired[1:])
    np.add(before[-1, :-1], saved[0, 1:], out=paired[0, 1:])
    paired[0, 0] = saved[0, 0]
    np.maximum(before, paired, out=after)
    places = list(after)
    for x, y in zip(places, places[1:]):
        np.maximum(x, y, out=y)
    ends = list(places[-1])
    for x, y in zip(ends, ends[1:]):
        np.maximum(x, y, out=y)
    np.maximum(after[:-1, 1:], after[-1, :-1], out=after[:-1, 1:])


class Summaries:
    """Column summaries by small numbers, with the spreads of all their unions in one table; 0 is the empty column."""

    def __init__(self, metric: CharMetric):
        self.metric, self.number, self.packed = metric, {0: 0}, np.zeros(64, np.int64)
        self.grown = 0
        #: what pairing two columns saves over leaving both beside gaps, in bytes where they hold it
        self.kind = np.uint8 if 2 * max(metric.same, metric.cross, metric.gap) < 256 else np.int64
        self._room(64)
        self._fill()

    def _room(self, n: int) -> None:
        #: spread of the union of two columns, less the second one's spread beside a gap; and the spread beside a gap
        self.step, self.gap, self.saved = np.zeros((n, n), np.int16), np.zeros(n, np.int16), np.zeros((n, n), self.kind)
        #: the most that pairing a column with any other may save
        self.worth = np.zeros(n, np.int64)

    def of(self, packed: np.ndarray) -> np.ndarray:
        number, out = self.number, np.empty(len(packed), np.intp)
        for k, x in enumerate(packed.tolist()):
            at = number.get(x)
            if at is None:
                at = number[x] = len(number)
                if at == len(self.packed):
                    self.packed = np.concatenate((self.packed, np.zeros(at, np.int64)))
                    self._room(2 * at)
                    self.grown = 0
                self.packed[at] = x
            out[k] = at
        self._fill()
        return out

    def moves(self, p: Template, q: Template) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """As _moves, from the table."""
        a, b = self.of(p.packed), self.of(q.packed)
        return self.step[a[:, None], b] + self.gap[b], self.gap[a], self.gap[b]

    def _fill(self) -> None:
        n, own = len(self.number), self.packed[: len(self.number)]
        if n > self.grown:
            fresh, spread_of = own[self.grown :], self.metric.spread_of
            self.gap[self.grown : n] = spread_of(fresh | GAP_BIT)
            self.worth[self.grown : n] = self.gap[self.grown : n] + np.maximum(self.metric.gap - spread_of(fresh), 0)
            both = spread_of(union(fresh[:, None], own[None, :]))
            self.step[self.grown : n, :n] = both - self.gap[None, :n]
            self.step[:n, self.grown : n] = both.T - self.gap[None, self.grown : n]
            saved = np.maximum(self.gap[self.grown : n, None].astype(np.int64) + self.gap[None, :n] - both, 0)
            self.saved[self.grown : n, :n], self.saved[:n, self.grown : n] = saved, saved.T
            self.saved[0], self.saved[:, 0], self.worth[0] = 0, 0, 0
            self.grown = n


class Pool:
    """Templates with their columns by number, one template a column of the matrix, for stars.

    Dropped templates leave the matrix once a quarter of it is theirs; slots keep their numbers.
    """

    #: Partners of a star that are worked on at once, and bytes that kept savings may take.
    AT_ONCE, KEPT = 4096, 1 << 28

    def __init__(self, templates: list[Template], metric: CharMetric):
        self.metric, self.items = metric, list(templates)
        self.length = np.array([len(t) for t in templates], np.int64)
        if metric.packed:
            self.seen = Summaries(metric)
            self.rows = np.zeros((GROUP, _groups(int(self.length.max(initial=1))), len(templates)), np.intp)
            for k, t in enumerate(templates):
                self.rows[:, :, k] = self._grouped(self.seen.of(t.packed))
            self.most = 2 * max(metric.same, metric.cross, metric.gap)
            self.alone = self.seen.gap[self.rows].sum(axis=(0, 1), dtype=np.int64)  # costs of all columns beside gaps
            self.worth = self.seen.worth[self.rows].sum(axis=(0, 1))
            self.slots, self.place, self.live = np.arange(len(templates)), np.arange(len(templates)), np.ones(len(templates), bool)
            self._forget()

    def _forget(self) -> None:
        self.kept: dict[int, int] = {}
        self.saved = np.zeros((0, *self.rows.shape), self.seen.kind)

    def _grouped(self, own: np.ndarray) -> np.ndarray:
        out = np.zeros((self.rows.shape[1], GROUP), np.intp)
        out.ravel()[: len(own)] = own
        return out.T

    def plain(self) -> np.ndarray:
        """Numbers of the columns, one after the other."""
        return self.rows.transpose(1, 0, 2).reshape(-1, self.rows.shape[2])

    def put(self, k: int, t: Template) -> None:
        self.items[k], self.length[k] = t, len(t)
        if self.metric.packed:
            at = self.place[k]
            if len(t) > GROUP * self.rows.shape[1]:
                more = _groups(len(t)) - self.rows.shape[1]
                self.rows = np.concatenate((self.rows, np.zeros((GROUP, more, self.rows.shape[2]), np.intp)), axis=1)
                self.saved = np.concatenate((self.saved, np.zeros((len(self.saved), GROUP, more, self.rows.shape[2]), self.saved.dtype)), axis=2)
            own = self.seen.of(t.packed)
            self.rows[:, :, at] = self._grouped(own)
            self.alone[k], self.worth[k] = self.seen.gap[own].sum(dtype=np.int64), self.seen.worth[own].sum()
            if self.kept:
                self.saved[: len(self.kept), :, :, at] = self.seen.saved[list(self.kept)][:, self.rows[:, :, at]]

    def drop(self, k: int) -> None:
        """No star asks for this slot any more."""
        if self.metric.packed:
            self.live[k] = False
            own = self.live[self.slots]
            if 4 * np.count_nonzero(own) < 3 * len(own):
                self.slots, self.rows, self.saved = self.slots[own], np.compress(own, self.rows, axis=2), np.compress(own, self.saved, axis=3)
                self.place[self.slots] = np.arange(len(self.slots))

    def _savings(self, col: int) -> np.ndarray | None:
        """What a column saves with each column of every template, kept as long as there is room."""
        at = self.kept.get(col)
        if at is None:
            at = len(self.kept)
            if at == len(self.saved):
                more = max(16, at)
                if (at + more) * self.rows.size * self.saved.itemsize > self.KEPT:
                    return None
                self.saved = np.concatenate((self.saved, np.zeros((more, *self.rows.shape), self.saved.dtype)))
            self.kept[col] = at
            np.take(self.seen.saved[col], self.rows, out=self.saved[at], mode="clip")
        return self.saved[at]

    def _kind(self, most: int):
        return next(k for k in (np.uint8, np.uint16, np.int64) if most <= np.iinfo(k).max and np.can_cast(self.seen.kind, k))

    def star(self, pivot: Template, at: np.ndarray) -> np.ndarray:
        """Fuse costs of a pivot with the templates at the given places.

        Costs are those of all columns beside gaps less the most that pairing saves. Empty columns behind a
        template's last save nothing, so the last row holds the savings of partners of any length.
        """
        if not self.metric.packed:
            return np.array([fuse_cost(pivot, self.items[k], self.metric) for k in at], np.int64)
        if not len(at):
            return np.zeros(0, np.int64)
        place, own = self.place[at], self.seen.of(pivot.packed).tolist()
        width, low, high = int(self.length[at].max()), int(place.min()), int(place.max()) + 1
        kind = self._kind(min(int(self.worth[at].max()), int(self.seen.worth[own].sum())))
        if 3 * len(at) > high - low > FEW:  # most of a range: all of it, without picking
            kept = {c: self._savings(c) for c in set(own)}
            out = np.concatenate([self._saved(own, width, slice(x, min(x + self.AT_ONCE, high)), kept, kind) for x in range(low, high, self.AT_ONCE)])[place - low]
        else:
            out = np.concatenate([self._saved(own, width, place[x : x + self.AT_ONCE], {}, kind) for x in range(0, len(at), self.AT_ONCE)])
        return int(self.seen.gap[own].sum(dtype=np.int64)) + self.alone[at] - out

    def _saved(self, own: list[int], width: int, part, kept: dict[int, np.ndarray | None], kind) -> np.ndarray:
        """The most that pairing a pivot's columns with those of some templates saves."""
        rows, made = self.rows[:, : _groups(width)], {}
        rows = rows[:, :, part] if isinstance(part, slice) else np.take(rows, part, axis=2)
        few = rows.shape[2] <= FEW
        if few:
            rows = rows.transpose(1, 0, 2).reshape(-1, rows.shape[2])[:width]
        for c in set(own):
            x = None if few else kept.get(c)
            made[c] = (np.take(self.seen.saved[c], rows, mode="clip") if x is None else x[:, : rows.shape[1], part]).astype(kind, copy=False)
        if few:
            best = np.zeros((width + 1, rows.shape[1]), kind)
            for c in own:
                np.maximum(best[1:], best[:-1] + made[c], out=best[1:])
                np.maximum.accumulate(best[1:], axis=0, out=best[1:])
            return best[-1].astype(np.int64)
        best, paired = np.zeros(rows.shape, kind), np.empty(rows.shape, kind)
        for c in own:
            _absorb(best, made[c], best, paired)
        return best[-1, -1].astype(np.int64)

    def triangle(self) -> Iterator[tuple[int, int, np.ndarray]]:
        """(k, first, costs) of every template k with all behind it, some at a time; nothing may be put or dropped yet.

        What the first columns of k save is taken over from the template before, as far as both begin alike.
        """
        n, plain = len(self.items), self.plain()
        owns = [plain[: self.length[k], k].tolist() for k in range(n)]
        alike = [0] + [next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b))) for a, b in zip(owns, owns[1:])]
        kind = self._kind(int(self.worth.max(initial=0)))
        for low in range(0, n, self.AT_ONCE // 2):
            high = min(low + self.AT_ONCE // 2, n)
            rows, made = self.rows[:, :, low:high], {}
            stack, paired = [np.zeros(rows.shape, kind)], np.empty(rows.shape, kind)
            for k in range(high - 1):
                begin = max(0, k + 1 - low)  # partners in front of k are done with
                for i, c in enumerate(owns[k][alike[k] :], alike[k]):
                    if c not in made:
                        made[c] = np.take(self.seen.saved[c], rows, mode="clip").astype(kind, copy=False)
                    if len(stack) == i + 1:
                        stack.append(np.empty_like(paired))
                    _absorb(*(x[:, :, begin:] for x in (stack[i], made[c], stack[i + 1], paired)))
                at = low + begin
                yield k, at, self.alone[k] + self.alone[at:high] - stack[len(owns[k])][-1, -1, begin:].astype(np.int64)

    def intervals(self) -> tuple[np.ndarray, np.ndarray]:
        """Bounds of the costs of all pairs of codes without aligning any, by profiles.

        Below: of the shorter code's characters at most as many find their equal, or one of their class, as both
        multisets share. Above: the cheapest alignment with all gaps in one place.
        """
        n, m = len(self.items), self.metric
        codes, size = [t.rep for t in self.items], self.length
        kind = np.int16 if int(size.max(initial=0)) * self.most < 6_000 else np.int32
        low, high = np.empty((n, n), kind), np.empty((n, n), kind)
        plain, classed = _marks(codes, lambda c: c), _marks(codes, SCHEMES[m.scheme])
        for at in range(0, n, 256):
            own = slice(at, at + 256)
            apart, shorter = np.abs(size[own, None] - size), np.minimum(size[own, None], size)
            low[own] = m.gap * apart
            if m.same <= m.cross <= 2 * m.gap:
                shared, related = plain[own] @ plain.T, classed[own] @ classed.T
                low[own] += (m.same * (related - shared) + m.cross * (shorter - related)).astype(kind)
        order = np.argsort(size, kind="stable")  # by length: all that stand behind a code are no shorter
        rows = self.plain()[: max(1, int(size.max(initial=1))), order]
        back, spans = np.zeros_like(rows), size[order].tolist()
        for k, length in enumerate(spans):  # codes from their ends
            back[:length, k] = rows[:length, k][::-1]
        paired = self.seen.step[: self.seen.grown, : self.seen.grown] + self.seen.gap[: self.seen.grown]
        room, costs, least = np.zeros((2, len(rows) + 1, n), kind), np.empty(n, paired.dtype), np.empty(n, kind)
        for k, length in enumerate(spans):
            for side, own in zip(room, (rows, back)):  # running costs of pairing columns place by place
                for i, row in enumerate(paired[own[:length, k]]):
                    np.take(row, own[i, k:], out=costs[k:], mode="clip")
                    np.add(side[i, k:], costs[k:], out=side[i + 1, k:], casting="unsafe")
            np.copyto(least[k:], room[1, length, k:])
            for i in range(1, length + 1):
                np.minimum(least[k:], room[0, i, k:] + room[1, length - i, k:], out=least[k:])
            high[order[k], order[k:]] = high[order[k:], order[k]] = least[k:] + (m.gap * (size[order[k:]] - length)).astype(kind)
        return low, high


def _marks(codes: list[str], kind) -> np.ndarray:
    """0/1 rows, one place for each k-th occurrence of a kind; products of rows are sizes of multiset intersections."""
    place: dict[tuple, int] = {}
    marks = [[place.setdefault((c, kinds[:k].count(c)), len(place)) for k, c in enumerate(kinds)] for kinds in ([kind(c) for c in code] for code in codes)]
    has = np.zeros((len(codes), max(1, len(place))), np.float32)
    for k, at in enumerate(marks):
        has[k, at] = 1
    return has


def _either(x: frozenset, y: frozenset) -> frozenset:
    """The union; one of the two where it holds the other, so that templates share their columns."""
    return x if y <= x else y if x <= y else x | y


def _band(pair: list[list[int]], down: list[int], right: list[int], cost: int, apart: int) -> list[list[int]]:
    """The table where rows and columns are at most so many places apart; other cells and costs are beyond the given one."""
    n, m, far = len(down), len(right), cost + 1
    out, before = [], [far] * (m + 1)
    for i in range(n + 1):
        row, low = [far] * (m + 1), max(0, i - apart)
        left = far
        for j in range(low, min(m, i + apart) + 1):
            least = 0 if not (i or j) else far
            if i:
                least = min(least, before[j] + down[i - 1])
                if j:
                    least = min(least, before[j - 1] + pair[i - 1][j - 1])
            if j and left + right[j - 1] < least:
                least = left + right[j - 1]
            row[j] = left = least
        out.append(row)
        before = row
    return out


def fuse(p: Template, q: Template, metric: CharMetric, tie: str = "gap_late", cost: int | None = None, seen: Summaries | None = None) -> tuple[Template, list[int], list[int]]:
    """The fused template and, for each of its columns, the 1-based column of p and of q in it (0: gap).

    The operand with the smaller rep is the first one. On ties a trace prefers gap moves, the first
    operand's before the second's ('gap_late'), or pairing before both ('gap_early'). cost: the fuse cost if it is known;
    each place that columns are apart takes a gap, so less of the table is looked at. seen: the spreads of their columns' unions.
    """
    if q.rep < p.rep:
        t, right, left = fuse(q, p, metric, tie, cost, seen)
        return t, left, right
    pair, down, right = _moves(p, q, metric) if seen is None else seen.moves(p, q)
    both, alone_p, alone_q = pair.tolist(), down.tolist(), right.tolist()
    near = cost is not None and metric.packed and metric.gap > 0 and 4 * (cost // metric.gap) < min(len(p), len(q))
    at = _band(both, alone_p, alone_q, cost, cost // metric.gap) if near else _table(pair, down, right).tolist()
    i, j = len(p), len(q)
    a, b = [], []
    while i or j:
        pairs = i > 0 and j > 0 and at[i][j] == at[i - 1][j - 1] + both[i - 1][j - 1]
        if pairs and tie != "gap_late":
            move = "both"
        elif i > 0 and at[i][j] == at[i - 1][j] + alone_p[i - 1]:
            move = "p"
        elif j > 0 and at[i][j] == at[i][j - 1] + alone_q[j - 1]:
            move = "q"
        else:
            move = "both"
        a.append(i if move != "q" else 0), b.append(j if move != "p" else 0)
        i, j = i - (move != "q"), j - (move != "p")
    a, b = a[::-1], b[::-1]
    gap = frozenset((GAP,))
    cols = [_either(p.cols[x - 1] if x else gap, q.cols[y - 1] if y else gap) for x, y in zip(a, b)]
    packed = None
    if metric.packed:
        of = lambda t, at: np.where(np.array(at) > 0, t.packed[np.maximum(np.array(at) - 1, 0)], GAP_BIT) if len(t) else np.full(len(at), GAP_BIT, np.int64)
        packed = union(of(p, a), of(q, b))
    return Template(p.rep, p.card + q.card, cols, at[-1][-1], packed, p.weight + q.weight), a, b


def align_pair(x: str, y: str, metric: CharMetric, tie: str = "gap_late") -> tuple[int, list[str | None], list[str | None]]:
    """Cost and both gap-padded codes."""
    t, a, b = fuse(leaf(x, metric), leaf(y, metric), metric, tie) if x <= y else (lambda r: (r[0], r[2], r[1]))(fuse(leaf(y, metric), leaf(x, metric), metric, tie))
    return t.spread, [x[k - 1] if k else GAP for k in a], [y[k - 1] if k else GAP for k in b]


def align_costs(xs: list[str], ys: list[str], metric: CharMetric) -> np.ndarray:
    """Costs of many pairs of codes at once: the recurrence runs over cells, each a vector over the pairs."""
    n = len(xs)
    lx, ly = np.array([len(x) for x in xs]), np.array([len(y) for y in ys])
    a, b = (np.zeros((n, max(1, int(m.max(initial=1)))), np.int64) for m in (lx, ly))
    for k, (x, y) in enumerate(zip(xs, ys)):
        a[k, : len(x)], b[k, : len(y)] = metric.pack_code(x), metric.pack_code(y)
    right = metric.spread_of(b | GAP_BIT) * (np.arange(b.shape[1]) < ly[:, None])
    walked = np.concatenate((np.zeros((n, 1), np.int64), np.cumsum(right, axis=1)), axis=1)
    row, out = walked.copy(), np.where(lx == 0, walked[np.arange(n), ly], 0)
    for i in range(a.shape[1]):
        t = row + metric.spread_of(a[:, i] | GAP_BIT)[:, None]
        np.minimum(t[:, 1:], row[:, :-1] + metric.spread_of(union(a[:, i : i + 1], b)), out=t[:, 1:])
        row = np.minimum.accumulate(t - walked, axis=1) + walked
        out = np.where(lx == i + 1, row[np.arange(n), ly], out)
    return out
