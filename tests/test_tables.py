"""Queries that once made their data up now read the given tables; the worked examples stay here."""

import tracemalloc

import pytest
from pyspark.errors import AnalysisException

from alignforge.operators.bounded import Bounds
from alignforge.operators.claims import largest_count
from alignforge.operators.kernel import Pool, leaf
from alignforge.operators.metric import CharMetric
from alignforge.operators.pattern import to_display, to_regex
from alignforge.plans import catalog
from alignforge.sources.synth import coded_strings
from compare import differences, duck


def reads(spark, sf, name):
    """A folder without tables gives no result, and the given one that of SQL."""
    with pytest.raises(AnalysisException):
        catalog.QUERIES[name](spark, "/nowhere").collect()
    return differences(catalog.QUERIES[name](spark, sf), duck(sf), catalog.ORACLES[name])


def test_eta(spark, sf):
    assert largest_count(spark.createDataFrame([(c,) for c in "aababacd"], "key string")).first()[0] == 4
    assert reads(spark, sf, "eta_example") is None


def test_metric_on_the_characters_of_codes(spark, sf):
    assert reads(spark, sf, "metric_check") is None


def test_star_bounds_of_codes(spark, sf):
    assert reads(spark, sf, "star_example") is None


def test_pattern_of_codes(spark, sf):
    assert to_display(catalog._t1_node().cols) == "{ST}[L]{45}{126}0[i]" and to_regex(catalog._t1_node().cols) == "^([ST])(L?)([45])([126])(0)(i?)$"
    assert reads(spark, sf, "pattern_example") is None


def test_bounds_hold_one_copy_of_the_intervals():
    """A block's two interval tables are the memory it takes; picked rows come some at a time."""
    codes = sorted({f"{k % 7}{'ab'[k % 2]}{k}" for k in range(1500)})
    low, high = Pool([leaf(c, CharMetric.classes()) for c in codes], CharMetric.classes()).intervals()
    assert (high == high.T).all() and (low <= high).all()
    tracemalloc.start()
    bounds = Bounds(len(codes), low, high)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 0.5 * low.nbytes and bounds.ub is high


@pytest.mark.parametrize("name", ["synth_cn_10", "synth_cn_100"])
def test_clusters_of_order_records(spark, sf, name, monkeypatch):
    """The records are those of orders; where their keys leave all remainders, the codes are the generator's."""
    with pytest.raises(AnalysisException):
        catalog.QUERIES[name](spark, "/nowhere").collect()
    clusters = int(name.rsplit("_", 1)[1])
    monkeypatch.setitem(catalog.DEFAULTS, "N", 200)
    got = {r["method"]: r for r in catalog.QUERIES[name](spark, sf).collect()}
    n = coded_strings(spark, N=200, CN=clusters).select("code").distinct().count()
    assert {r["n"] for r in got.values()} == {n} and got["pair"]["fuse_evals"] == (n - 1) ** 2
