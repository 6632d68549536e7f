"""Searches of large blocks by their cheapest fuses first, and rules over them."""

import random

import pytest

from alignforge.operators.align import block_by, dedupe, learn_tree
from alignforge.operators.metric import CharMetric
from alignforge.operators.near import fuse_large, near_fuse
from alignforge.operators.rules import Thresholds, discover
from alignforge.operators.tree import pair_fuse
from test_methods import shape

METRIC = CharMetric.classes()


@pytest.mark.parametrize("seed", range(6))
def test_cheapest_fuses_first_give_the_same_tree(seed):
    r = random.Random(seed)
    some = sorted({f"S#{r.randrange(300):04d}" for _ in range(60)} | {"".join(r.choice("ab12-") for _ in range(r.randint(1, 4))) for _ in range(40)})
    base = pair_fuse(some, METRIC)
    near = near_fuse(some, METRIC)
    assert shape(fuse_large(some, METRIC, None, "gap_late", None, 1000)) == shape(base)
    assert [(x.left, x.right, x.left_map, x.right_map) for x in near if x.left] == [(x.left, x.right, x.left_map, x.right_map) for x in base.nodes if x.left and x.template.spread == METRIC.same]
    assert fuse_large(some, METRIC, None, "gap_late", None, 1) is None
    assert shape(fuse_large(some, METRIC, None, "gap_late", 3, 1000)) == shape(pair_fuse(some, METRIC, max_cost=3))


def test_large_blocks_learn_without_all_pairs(spark, monkeypatch):
    """Names beyond a worker's block neither meet in rounds nor change their tree or rules."""
    from alignforge.operators import rounds

    rows = [(f"Supplier#{k:09d}", str(k * 7 % 25 if k % 3 else k % 10)) for k in range(600)]
    df = spark.createDataFrame(rows, "code string, nation string")
    monkeypatch.setattr(rounds, "round_fuse", lambda *a: pytest.fail("all pairs of the block were asked for"))
    got, want = learn_tree(dedupe(df), max_block=100), learn_tree(dedupe(df))
    cols = ["block", "rep", "card", "weight", "cost_u", "pattern", "left_rep", "left_card", "right_rep", "right_card", "left_map", "right_map"]
    assert sorted(map(str, got.all.select(*cols).collect())) == sorted(map(str, want.all.select(*cols).collect()))
    loose = Thresholds(3, 0.3, 2, 1)
    a, b = (sorted(map(str, discover(df, "code", ["nation"], t, loose).collect())) for t in (got, want))
    c = sorted(map(str, discover(df, "code", ["nation"], want, loose, strategy="explode").collect()))
    assert a and a == b == c


def test_blocks_that_stay_large_go_in_rounds(spark):
    """Codes with few cheap fuses leave more templates than a worker may have."""
    r = random.Random(2)
    some = sorted({"".join(r.choice("ab12-/x") for _ in range(r.randint(3, 9))) for _ in range(60)})
    codes = block_by(spark.createDataFrame([(c,) for c in some], "code string"))
    got = learn_tree(codes, max_block=20)
    assert sorted((x.rep, x.card, x.cost_u) for x in got.nodes.collect()) == sorted((x.template.rep, x.template.card, x.template.spread) for x in pair_fuse(some, METRIC).nodes if x.left)
