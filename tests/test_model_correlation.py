"""Random plans of the applications that the models are held against."""

import pytest

from cutloom import measure, queries
from cutloom.operators.graph import Graph


def test_applications(spark):
    assert queries.PLANS == 100 and [len(x) for x in queries.APPLICATIONS.values()] == [20, 1, 1]
    assert [(p.n, p.m) for x in ("ladder6", "chord6") for p in queries.APPLICATIONS[x]] == [(6, 7), (6, 7)]
    g = queries.graph(spark, "/root/testdata/sf0.001", "bulk45")
    some = {"two": queries.APPLICATIONS["motif5"][:2], "chord6": queries.APPLICATIONS["chord6"]}
    got = {r["application"]: r["n"] for r in queries.correlations(g, some, 3).collect()}
    assert got == {"two": 3, "chord6": 3}


def test_a_piece_that_fails_has_no_time(spark, monkeypatch):
    """model_correlation: it used to take 0 seconds, which a correlation can't be told from."""
    def fail(*_, **__):
        raise MemoryError("of a piece")

    monkeypatch.setattr(measure, "count_matchings", fail)
    monkeypatch.setattr(Graph, "fits", lambda g: False)
    g = Graph(spark.createDataFrame([(1, 2), (2, 3), (1, 3)], "src long, dst long"))
    plan = queries.random_plans(queries.APPLICATIONS["chord6"][0], 1, 1)[0]
    with pytest.raises(MemoryError, match="of a piece"):
        measure.PieceTimes(g).plan(plan)
    assert measure.run(fail, 1).status == "failed"
