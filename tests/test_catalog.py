"""Every registered query of the methods and operators runs; those with SQL give DuckDB's rows."""

import pytest

from alignforge.plans import catalog, relational  # noqa: F401
from compare import differences, duck

SLOW = {k for k in catalog.QUERIES if k.startswith("synth_")}


@pytest.fixture(scope="module")
def con(sf):
    return duck(sf)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) & set(catalog.ORACLES)))
def test_same_as_sql(spark, sf, con, name):
    assert differences(catalog.QUERIES[name](spark, sf), con, catalog.ORACLES[name]) is None


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES) - SLOW))
def test_gives_rows(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() > 0


def test_generated_codes_cost(spark, sf):
    """The baseline's evaluations follow from the number of codes alone; pruned searches take fewer."""
    for name in ("synth_n_50", "synth_len_12"):
        got = {r["method"]: r for r in catalog.QUERIES[name](spark, sf).collect()}
        assert got["pair"]["fuse_evals"] == (got["pair"]["n"] - 1) ** 2
        assert got["bounded_inherit"]["fuse_evals"] <= got["bounded_star"]["fuse_evals"] <= got["pair"]["fuse_evals"]
