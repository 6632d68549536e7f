"""Methods that once ran on part of their input."""

import pytest

from alignforge.plans import catalog
from compare import differences, duck


@pytest.mark.parametrize("name", ["two_positions_laws_part", "chain_laws_part", "chain_rules_laws_part", "chain_rules_part_law0"])
def test_all_laws_are_learned(spark, sf, name):
    got = catalog.QUERIES[name](spark, sf)
    assert differences(got, duck(sf), catalog.ORACLES[name]) is None
    want = {"two_positions_laws_part": {0, 1, 2}, "chain_laws_part": {0, 1, 2}, "chain_rules_laws_part": {1, 2}, "chain_rules_part_law0": {0}}
    assert {r["law"] for r in got.select("law").collect()} == want[name]


def test_generated_workloads_have_the_whole_ranges(monkeypatch):
    """Numbers up to 5000, and 5000 codes wherever another parameter varies."""
    asked = []
    monkeypatch.setattr(catalog, "dedupe", lambda df: df)
    monkeypatch.setattr(catalog, "coded_strings", lambda spark, **o: asked.append(o))
    monkeypatch.setattr(catalog, "compare_searches", lambda df, searches: type("None_", (), {"select": lambda *a: None}))
    for name in catalog.QUERIES:
        if name.startswith("synth_"):
            catalog.QUERIES[name](None, "")
    assert {o["N"] for o in asked} == {50, 100, 200, 1000, 2000, 3000, 4000, 5000}
    for key, values in (("l", {10, 12, 14, 16, 18, 20}), ("CN", {10, 25, 50, 75, 100}), ("sigma", {0.01, 0.03, 0.05, 0.07, 0.1})):
        assert {o[key] for o in asked if o["N"] == 5000} == values
