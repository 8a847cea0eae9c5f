"""The ideal model tries every order."""

from cutloom.operators import baselines
from cutloom.patterns import tailed_triangle
from cutloom.queries import QUERIES


def test_every_order(spark, monkeypatch):
    tried, run = [], baselines.enumerate_matchings
    monkeypatch.setattr(baselines, "enumerate_matchings", lambda g, p, order, *a, **b: tried.append(tuple(order)) or run(g, p, order, *a, **b))
    assert QUERIES["baseline_perfect"](spark, "/root/testdata/sf0.001").first()["cnt"] == 127  # FIXTURES
    assert set(tried) == {tuple(o) for o in baselines.all_orders(tailed_triangle())} and len(tried) == 14
