"""Costs of stars and of all pairs at once, against single alignments."""

import random

import numpy as np
import pytest

from alignforge.operators import bounded, kernel
from alignforge.operators.align import compare_searches
from alignforge.operators.bounded import Bounds
from alignforge.operators.kernel import Pool, fuse_cost, leaf
from alignforge.operators.metric import CharMetric

METRIC = CharMetric.classes()


@pytest.mark.parametrize("metric", [METRIC, CharMetric.unit(), CharMetric.classes(same=70.0, cross=90.0, gap=100.0)])
def test_stars_and_triangle_equal_single_costs(metric, monkeypatch):
    """Many partners of many lengths, some fused or dropped, also where savings exceed a byte."""
    r = random.Random(3)
    some = sorted({"".join(r.choice("abcXY12-/") for _ in range(r.choice((1, 3, 20, 70, 90)))) for _ in range(400)})
    monkeypatch.setattr(Pool, "AT_ONCE", 150)
    pool = Pool([leaf(c, metric) for c in some], metric)
    want = lambda t, at: [fuse_cost(t, pool.items[k], metric) for k in at]
    got = {k: [] for k in range(len(some) - 1)}
    for k, at, c in pool.triangle():
        assert at == k + 1 + len(got[k])
        got[k] += c.tolist()
    assert all(len(got[k]) == len(some) - 1 - k for k in got)
    for k in r.sample(range(len(some) - 1), 8):
        assert got[k] == want(pool.items[k], range(k + 1, len(some)))
    live = list(range(len(some)))
    for turn in range(150):
        a, b = sorted(r.sample(live, 2))
        pool.put(a, kernel.fuse(pool.items[a], pool.items[b], metric)[0]), pool.drop(b)
        live.remove(b)
        if turn % 30 == 0:
            for at in (live, sorted(r.sample(live, 20)), sorted(r.sample(live, 140))):
                assert pool.star(pool.items[a], np.array(at)).tolist() == want(pool.items[a], at)


def test_first_costs_share_beginnings(monkeypatch):
    """The baseline's first costs take one step a distinct beginning, not one a character."""
    steps = []
    own = kernel._absorb
    monkeypatch.setattr(kernel, "_absorb", lambda *a: (steps.append(1), own(*a)))
    some = sorted(f"https://www.example.com/en/{k}" for k in range(100, 200))
    pool = Pool([leaf(c, METRIC) for c in some], METRIC)
    assert sum(len(c) for _, _, c in pool.triangle()) == 100 * 99 // 2
    assert len(steps) <= len({c[:k] for c in some for k in range(1, len(c) + 1)}) < sum(map(len, some)) / 10


def intervals(n, seed=5):
    """Symmetric random intervals of n places."""
    r = np.random.default_rng(seed)
    low = r.integers(0, 9, (n, n))
    low = np.minimum(low, low.T)
    wide = r.integers(0, 5, (n, n))
    return Bounds(n, low.astype(np.int16), (low + np.minimum(wide, wide.T)).astype(np.int16))


def test_critical_pairs_of_all_come_some_at_a_time(monkeypatch):
    """Without independence too no step holds all pairs."""
    monkeypatch.setattr(bounded, "AT_ONCE", 200)
    b = intervals(60)
    for _ in range(6):
        x, y = b.best_upper()
        want = [[i, j] for i in range(60) for j in range(i + 1, 60) if b.live[i] and b.live[j] and (i, j) != (x, y) and (b.lb[i, j], i, j) < (b.ub[x, y], x, y)]
        parts = list(b._critical(x, y, False))
        assert b.critical(x, y, False).tolist() == want and all(len(p) <= 200 for p in parts)
        star = b.next_star(x, y, False)
        assert star is None if not want else star[1].tolist() == b.pick_pivot(np.array([*want, [x, y]]))[1].tolist()
        b.replace(x, y, *b.inherit(x, y, 3))


@pytest.mark.parametrize("many", [5, 30, 47])
def test_tightening_looks_at_every_pair_once(many, monkeypatch):
    """Few members and many, before and after dead places are left out: as by the formula, best partners included."""
    monkeypatch.setattr(bounded, "AT_ONCE", 300)
    b = intervals(64)
    for turn in range(20):
        k = len(b.live)
        members = np.sort(np.random.default_rng(turn).choice(np.flatnonzero(b.live), min(many, int(b.live.sum())), replace=False))
        exact = np.random.default_rng(turn).integers(0, 12, len(members)).astype(np.int16)
        low, high = b.lb.copy(), b.ub.copy()
        apart, both = np.abs(exact[:, None] - exact), exact[:, None] + exact
        at = np.ix_(members, members)
        low[at], high[at] = np.maximum(low[at], apart), np.minimum(high[at], both)
        np.fill_diagonal(low, b.off), np.fill_diagonal(high, b.off)
        changed = np.count_nonzero((low != b.lb) | (high != b.ub)) // 2
        assert b._tighten(members, exact) == changed
        assert (b.lb == low).all() and (b.ub == high).all()
        assert (b.best[b.live] >> 32 == high.min(axis=1)[b.live]).all() and ((b.best & 0xFFFFFFFF) == high.argmin(axis=1))[b.live].all()
        x, y = b.best_upper()
        b.replace(x, y, np.zeros(k, b.kind), np.full(k, b.far, b.kind))
    assert len(b.live) == 47 and b.slot.tolist() == sorted(b.slot.tolist())


def test_places_of_set_bytes():
    """Also where the mask is no whole number of words."""
    for shape in ((1, 3), (3, 7), (13, 40)):
        mask = np.random.default_rng(2).random(shape) < 0.1
        assert bounded._places(mask).tolist() == np.flatnonzero(mask).tolist()


def test_repeats_are_tasks_of_their_own(spark):
    """Repeats give the same figures as one run, and none waits for another in its task."""
    codes = spark.createDataFrame([(f"A{k}-{k % 7}", 1) for k in range(40)], "code string, weight long")
    one, three = (compare_searches(codes, repeats=r) for r in (1, 3))
    assert "turn" in three._jdf.queryExecution().toString()
    figures = lambda df: sorted((r.method, r.n, r.fuse_evals, r.refines, r.tightenings, sorted(r.refine_hist.items()), r.wall_ms >= 0) for r in df.collect())
    assert len(figures(one)) == 4 and figures(one) == figures(three) and one.columns == three.columns
