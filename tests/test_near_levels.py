"""Fusing limit by limit: pairs within a limit, stars of near partners, and the tree of pairwise fusing."""

import random

import numpy as np
import pytest

from alignforge.operators import near
from alignforge.operators.align import block_by, learn_tree
from alignforge.operators.kernel import Pool, fuse, fuse_cost, leaf
from alignforge.operators.metric import CharMetric
from alignforge.operators.tree import pair_fuse
from test_methods import shape

METRIC = CharMetric.classes()


def addresses(n, seed):
    r = random.Random(seed)
    hosts = ["example.com", "m.example.org", "blog.exomple.net", "a-b.example.com"]
    some = {f"http{r.choice(('', 's'))}://{r.choice(hosts)}/{r.choice(('en', 'de', 'es'))}/{r.randrange(30000)}{r.choice(('', '/', '.html', '#top'))}" for _ in range(n)}
    return sorted(some | {"".join(r.choice("ab12-/") for _ in range(r.randint(1, 5))) for _ in range(n // 4)})


@pytest.mark.parametrize("metric", [METRIC, CharMetric.classes(same=1.0, cross=2.0, gap=1.5), CharMetric.classes(same=0.5, cross=3.0, gap=40.0)])
def test_pairs_within_a_limit_are_all_pairs_of_that_cost(metric):
    """Of codes and of fused templates; more than asked for give None."""
    r = random.Random(1)
    items = [leaf(c, metric) for c in addresses(90, 2)]
    for _ in range(40):
        p, q = (items.pop(r.randrange(len(items))) for _ in range(2))
        items.append(fuse(p, q, metric)[0])
    pool = Pool(sorted(items, key=lambda t: t.rep), metric)
    n = len(items)
    costs = {(a, b): fuse_cost(pool.items[a], pool.items[b], metric) for a in range(n) for b in range(a + 1, n)}
    for limit in (1, 2, 5, 9, 20, 90, 200):
        want = {k: c for k, c in costs.items() if c <= limit}
        got = near.close_pairs(pool, limit, len(want))
        assert {(a, b): c for a, b, c in zip(*(x.tolist() for x in got))} == want and len(got[0]) == len(want)
        assert not want or near.close_pairs(pool, limit, len(want) - 1) is None
        for k in r.sample(range(n), 10):
            at = np.array(sorted(set(range(n)) - {k}))
            star, known = near.close_star(pool, pool.items[k], at, limit), pool.star(pool.items[k], at)
            assert ((star <= limit) == (known <= limit)).all() and (star[known <= limit] == known[known <= limit]).all()


@pytest.mark.parametrize("tie", ["gap_late", "gap_early"])
@pytest.mark.parametrize("seed", range(3))
def test_blocks_that_few_cheapest_fuses_leave_large_stay_on_one_worker(seed, tie, monkeypatch):
    """Before, such a block had to go on in rounds over all its pairs."""
    monkeypatch.setattr(near, "FEW", 20)
    some = addresses(220, seed)
    rest = [x for x in near.near_fuse(some, METRIC) if x.left is None]
    assert len(rest) > 100
    got = near.fuse_large(some, METRIC, None, tie, None, 100)
    assert shape(got) == shape(pair_fuse(some, METRIC, tie=tie))
    assert [x.round for x in got.nodes if x.left] == sorted(x.round for x in got.nodes if x.left)
    assert shape(near.fuse_large(some, METRIC, None, tie, 6, 1000)) == shape(pair_fuse(some, METRIC, tie=tie, max_cost=6))
    monkeypatch.setattr(near, "PAIRS", 300)  # smaller steps, or none
    assert shape(near.fuse_large(some, METRIC, None, tie, None, 1000)) == shape(pair_fuse(some, METRIC, tie=tie))


def test_known_costs_give_the_same_fuse():
    """A band of the table is enough for a fuse whose cost is known."""
    r = random.Random(4)
    items = [leaf(c, METRIC) for c in addresses(60, 5)]
    for _ in range(300):
        p, q = r.sample(items, 2)
        for tie in ("gap_late", "gap_early"):
            want = fuse(p, q, METRIC, tie)
            got = fuse(p, q, METRIC, tie, want[0].spread)
            assert got[1:] == want[1:] and got[0].cols == want[0].cols and got[0].spread == want[0].spread
        if want[0].spread < 25:
            items.append(want[0])


def test_a_search_that_was_asked_for_is_not_replaced(spark):
    """Large blocks of both searches of independence_pages were fused by a third one, without refines to compare."""
    codes = block_by(spark.createDataFrame([(c,) for c in addresses(40, 1)], "code string"))
    for independence in (True, False):
        assert learn_tree(codes, lower="zero", independence=independence).counters.first()["refine_hist"]
        with pytest.raises(ValueError, match="no other one takes its place"):
            learn_tree(codes, lower="zero", independence=independence, max_block=20)
