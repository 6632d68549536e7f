"""Worked examples, bounds, identities of the searches, patterns and measures, against brute force."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from alignforge.operators.align import align_exact, scs_instance
from alignforge.operators.kernel import Pool, align_costs, align_pair, fuse, fuse_cost, leaf
from alignforge.operators.metric import CharMetric
from alignforge.operators.pattern import fit_to, key_of, parse_display, to_display, to_regex
from alignforge.operators.bounded import Bounds, bounded_fuse
from alignforge.operators.tree import aligned_members, chain_fuse, pair_fuse

METRIC = CharMetric.classes()
codes = st.text("ab12-", min_size=1, max_size=5)


def shape(fused):
    return sorted((x.template.rep, x.template.card, x.template.spread, to_display(x.template.cols)) for x in fused.nodes)


def test_t1_alignment():
    fused = pair_fuse(["SL410", "T520i", "T560", "New S1 2016", "New S1 2017"], METRIC)
    assert [x.template.spread / 2 for x in fused.nodes if x.left] == [0.5, 1.5, 3.5, 9.0]
    assert fused.counters["fuse_evals"] == 16
    three = next(x for x in fused.nodes if x.template.card == 3)
    rows = {k: "".join(c or "_" for c in v) for k, v in aligned_members(fused, (three.template.rep, 3)).items()}
    assert rows == {"SL410": "SL410_", "T520i": "T_520i", "T560": "T_560_"}
    assert to_display(three.template.cols) == "{ST}[L]{45}{126}0[i]"


def test_gap_cost_decides_the_law():
    """At 1.5 a gap costs as much as leaving unlike characters in line, so only the tie rule keeps the law."""
    some = ["SL410", "T520i", "T560"]
    assert pair_fuse(some, METRIC).nodes[-1].template.spread == 7 and pair_fuse(some, CharMetric.classes(gap=1.5)).nodes[-1].template.spread == 9
    assert to_display(pair_fuse(some, CharMetric.classes(gap=1.5), tie="gap_early").nodes[-1].template.cols) != "{ST}[L]{45}{126}0[i]"


def test_shared_letters():
    cost, a, b = align_pair("ab1c", "ab9c", METRIC)
    assert cost == 1 and a == list("ab1c") and b == list("ab9c")


def test_metric_check_and_table():
    assert METRIC.check("a1-B") == [] and CharMetric.unit().check("abc") == []
    assert CharMetric.classes(gap=0.5).check("a1")  # a way through the gap would be shorter
    assert CharMetric.filler("ab", "x").check("abx") == []
    assert CharMetric.classes(spread="pairsum").column_spread("123") == 3 and METRIC.column_spread("123") == 1
    table = CharMetric.from_table({("a", "b"): 1.0}, gap=1.0)
    assert fuse_cost(leaf("ab", table), leaf("b", table), table) == 2


@settings(max_examples=60, deadline=None)
@given(st.lists(codes, min_size=1, max_size=6), codes)
def test_star_equals_single_costs(many, one):
    pool = Pool([leaf(c, METRIC) for c in many], METRIC)
    import numpy as np

    assert pool.star(leaf(one, METRIC), np.arange(len(many))).tolist() == [fuse_cost(leaf(one, METRIC), leaf(c, METRIC), METRIC) for c in many]
    assert align_costs([one] * len(many), many, METRIC).tolist() == [fuse_cost(leaf(one, METRIC), leaf(c, METRIC), METRIC) for c in many]


@settings(max_examples=60, deadline=None)
@given(codes, codes, codes)
def test_bounds(x, y, z):
    """Growth, growth against a super-template, and both triangle inequalities, also for a fused template."""
    p, q, r = (leaf(c, METRIC) for c in sorted((x, y, z)))
    pq, _, _ = fuse(p, q, METRIC)
    c = lambda a, b: fuse_cost(a, b, METRIC)
    assert pq.spread >= max(p.spread, q.spread)
    assert c(pq, r) >= c(p, r)
    assert c(pq, r) <= c(p, r) + c(p, q)
    assert abs(c(p, q) - c(q, r)) <= c(p, r) <= c(p, q) + c(q, r)


@settings(max_examples=30, deadline=None)
@given(codes, codes)
def test_two_codes_are_optimal(x, y):
    assert fuse_cost(leaf(x, METRIC), leaf(y, METRIC), METRIC) == align_exact([x, y], METRIC)


@settings(max_examples=25, deadline=None)
@given(st.sets(codes, min_size=3, max_size=4))
def test_greedy_never_beats_the_optimum(some):
    some = sorted(some)
    best = align_exact(some, METRIC)
    assert pair_fuse(some, METRIC).nodes[-1].template.spread >= best and chain_fuse(some, METRIC).nodes[-1].template.spread >= best


def test_scs_reduction():
    """A common supersequence of length k exists iff the instance aligns within its threshold."""
    for strings, shortest in ((["ab", "ba"], 3), (["abc", "acb"], 4), (["aa", "a"], 2)):
        for k in (shortest - 1, shortest):
            made, metric, threshold = scs_instance(strings, k)
            assert align_exact(made, metric, threshold) == (k >= shortest)


@pytest.mark.parametrize("seed", range(12))
@pytest.mark.parametrize("tie", ["gap_late", "gap_early"])
def test_all_searches_give_one_tree(seed, tie):
    """Also where costs tie and where the first best pair loses its place while it is refined."""
    r = random.Random(seed)
    some = sorted({"".join(r.choice("ab12-") for _ in range(r.randint(1, 6))) for _ in range(14)})
    base = pair_fuse(some, METRIC, tie=tie)
    assert base.counters["fuse_evals"] == (len(some) - 1) ** 2
    for options in ({"profile": "star"}, {}, {"independence": False}, {"lower": "cheap"}):
        other = bounded_fuse(some, METRIC, tie=tie, **options)
        assert shape(other) == shape(base), options
        assert other.counters["fuse_evals"] <= base.counters["fuse_evals"]


def test_degap_and_filled_columns():
    r = random.Random(5)
    some = sorted({"".join(r.choice("abc123") for _ in range(r.randint(1, 7))) for _ in range(30)})
    fused = bounded_fuse(some, METRIC)
    for x in fused.nodes:
        if x.left:
            rows = aligned_members(fused, (x.template.rep, x.template.card))
            assert len(rows) == x.template.card
            assert all("".join(c for c in v if c) == k for k, v in rows.items())
            assert all(any(v[i] for v in rows.values()) for i in range(len(x.template)))


@pytest.mark.parametrize("text", ["{ST}[L]{45}{126}0[i]", "Q\\-1{2-46-8}[XYZ]", "AB {0-9}[a-f]\\{x", "{1-35-8}[TEKUX]"])
def test_display_ranges(text):
    cols = parse_display(text)
    assert parse_display(to_display(cols)) == cols
    assert to_display(parse_display("{123}{12}{1356}")) == "{1-3}{12}{1356}"


def test_marked_column():
    assert to_display(parse_display("a{12}[b]"), mark=2) == "a<{12}>[b]"


def test_unseen_match_and_keys():
    import re

    t = pair_fuse(["SL410", "T520i", "T560"], METRIC).nodes[-1].template
    assert re.match(to_regex(t.cols), "TL510i") and not re.match(to_regex(t.cols), "X520")
    assert key_of("TL510i", t, 3, METRIC) == "5" and key_of("T520", t, 2, METRIC) is None
    assert key_of("TL510i", t, 3, METRIC, how="regex") == "5"
    assert fit_to("X520", t, METRIC) is None


def test_cost_limit_stops():
    fused = pair_fuse(["SL410", "T520i", "T560", "New S1 2016", "New S1 2017"], METRIC, max_cost=7)
    assert max(x.template.spread for x in fused.nodes) == 7
    assert shape(bounded_fuse(["SL410", "T520i", "T560", "New S1 2016", "New S1 2017"], METRIC, max_cost=7)) == shape(fused)


def test_single_and_repeated_codes():
    assert len(pair_fuse(["a"], METRIC).nodes) == 1 and len(bounded_fuse(["a"], METRIC).nodes) == 1 and len(chain_fuse(["a"], METRIC).nodes) == 1


def test_golden_counts():
    """Counts of the smallest part codes, as worked out beforehand."""
    import duckdb

    from alignforge.sources.codes import with_relations

    con = duckdb.connect()
    con.execute("CREATE VIEW part AS SELECT * FROM '/root/testdata/sf0.001/part.parquet'")
    some = sorted(r[0] for r in con.execute(with_relations("SELECT DISTINCT code FROM part_code")).fetchall())
    assert len(some) == 185
    star, both = bounded_fuse(some, METRIC, profile="star"), bounded_fuse(some, METRIC)
    assert (pair_fuse(some, METRIC).counters["fuse_evals"], star.counters["fuse_evals"], both.counters["fuse_evals"]) == (33856, 17130, 3416)
    assert (star.counters["refines"], both.counters["refines"]) == (479, 256)
    assert both.refine_hist == {0: 10, 1: 109, 2: 51, 3: 11, 4: 3}


class Costs:
    """Stands in for a pool: fuse costs by table."""

    def __init__(self, cost):
        self.cost, self.items = cost, list(range(len(cost)))

    def star(self, pivot, at):
        import numpy as np

        return np.array([self.cost[pivot][k] for k in at], np.int64)


def test_star_bounds():
    """Five templates, the first the pivot at 1.5, 2, 2 and 1: intervals of all other pairs, in half-units."""
    import numpy as np

    cost = np.zeros((5, 5), int)
    cost[0, 1:] = cost[1:, 0] = (3, 4, 4, 2)
    b = Bounds(5)
    b.refine_star(Costs(cost), 0, np.arange(5))
    got = {(x, y): (int(b.lb[x, y]), int(b.ub[x, y])) for x in range(1, 5) for y in range(x + 1, 5)}
    assert got == {(1, 2): (1, 7), (1, 3): (1, 7), (1, 4): (1, 5), (2, 3): (0, 8), (2, 4): (2, 6), (3, 4): (2, 6)}
    assert b.evals == 4 and b.tightenings == 6


def test_critical_pairs_and_independence():
    """A pair above the best upper bound is pruned; one that shares no template with the best pair is left for later."""
    b = Bounds(4)
    for (x, y), (lo, hi) in {(0, 1): (2, 5), (2, 3): (3, 8), (1, 2): (4, 9), (0, 2): (7, 9), (0, 3): (6, 9), (1, 3): (6, 9)}.items():
        b.lb[x, y] = b.lb[y, x] = lo
        b.ub[x, y] = b.ub[y, x] = hi
    import numpy as np

    b.rescan(np.arange(4))
    assert b.best_upper() == (0, 1)
    assert b.critical(0, 1, independence=False).tolist() == [[1, 2], [2, 3]]
    assert b.critical(0, 1).tolist() == [[1, 2]]
    assert b.pick_pivot(np.array([[1, 2], [0, 1]]))[0] == 1


def test_tie_total_order():
    """Among equal costs the pair of the smaller codes goes first."""
    fused = pair_fuse(["a1", "a2", "a3", "a4"], METRIC)
    assert [(x.left, x.right) for x in fused.nodes if x.left] == [(("a1", 1), ("a2", 1)), (("a1", 2), ("a3", 1)), (("a1", 3), ("a4", 1))]


def test_x4_recompute():
    """The search looks again after each star; on these codes the first best pair is not the one that is fused."""
    r = random.Random(11)
    some = sorted({"".join(r.choice("abc12-/") for _ in range(r.randint(3, 8))) for _ in range(40)})
    assert shape(bounded_fuse(some, METRIC)) == shape(bounded_fuse(some, METRIC, profile="star")) == shape(pair_fuse(some, METRIC))


@settings(max_examples=40, deadline=None)
@given(st.lists(codes, min_size=1, max_size=12, unique=True), st.sampled_from([CharMetric.classes(), CharMetric.unit(), CharMetric.classes(same=1.0, cross=1.0, gap=2.0)]))
def test_profile_intervals_hold_the_costs(some, metric):
    pool = Pool([leaf(c, metric) for c in some], metric)
    low, high = pool.intervals()
    for a in range(len(some)):
        exact = [fuse_cost(pool.items[a], x, metric) for x in pool.items]
        assert pool.star(pool.items[a], np.arange(len(some))).tolist() == exact
        assert all(x <= c <= y for x, c, y in zip(low[a], exact, high[a]))


@settings(max_examples=30, deadline=None)
@given(st.lists(codes, min_size=2, max_size=14, unique=True))
def test_profile_search_builds_the_same_tree(some):
    assert shape(bounded_fuse(some, METRIC, lower="profile")) == shape(pair_fuse(some, METRIC))


def test_wide_costs_move_to_whole_words():
    b = Bounds(3)
    b.lb[0, 1] = b.lb[1, 0] = 7
    b.room_for(10_000)
    assert b.lb.dtype == np.int32 and b.lb[0, 1] == 7 and b.ub[0, 1] == b.far == b.off - 1
    long = ["a" * 3000, "1" * 2990, "a" * 2980 + "1" * 15]
    assert shape(bounded_fuse(long, METRIC)) == shape(pair_fuse(long, METRIC))
