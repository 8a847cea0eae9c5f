"""The fit of the quality rules: against a plain Python version, on planted accuracies, and with clashing columns."""

import collections
import math
import random

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
from cutloom.llm import quality  # noqa: E402


def plain_fit(counts, rules, rounds=quality.ROUNDS):
    """Posterior of each vote pattern by the same model, written out."""
    share = [[list(r.starts[k]) for r in rules] for k in (0, 1)]
    first, prior = [[list(x) for x in side] for side in share], quality.PRIOR
    posterior = {}
    for it in range(rounds + 1):
        for votes in counts:
            odds = prior / (1 - prior)
            for j, v in enumerate(votes):
                odds *= share[0][j][v + 1] / share[1][j][v + 1]
            posterior[votes] = odds / (1 + odds)
        if it == rounds:
            break
        mass = [{v: n * (posterior[v] if k == 0 else 1 - posterior[v]) for v, n in counts.items()} for k in (0, 1)]
        whole = [sum(m.values()) + quality.STRENGTH for m in mass]
        prior = whole[0] / sum(whole)
        share = [[[(sum(x for v, x in mass[k].items() if v[j] == c - 1) + quality.STRENGTH * first[k][j][c]) / whole[k] for c in range(3)] for j in range(len(rules))] for k in (0, 1)]
    j = quality.ANCHOR
    return {v: 1 - q for v, q in posterior.items()} if share[0][j][0] > share[1][j][0] else posterior


def test_fit_and_kept_against_plain_python(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = quality.judged(docs).select("__q.votes", "__q.base_failed", "__posterior", "__kept").collect()
    want = plain_fit(collections.Counter(tuple(r["votes"]) for r in rows), quality.RULES)
    for r in rows:
        assert r["__posterior"] == pytest.approx(want[tuple(r["votes"])], abs=1e-9)
        assert r["__kept"] == (not r["base_failed"] and want[tuple(r["votes"])] >= 0.5)


def planted(rates, share, n, seed):
    """Vote patterns of n documents; ``rates`` gives each rule's shares of (bad, none, good) votes in good and in bad ones."""
    rng, rows, right, cast = random.Random(seed), collections.Counter(), [0] * len(rates), [0] * len(rates)
    for _ in range(n):
        good = rng.random() < share
        votes = tuple(rng.choices((-1, 0, 1), rates[j][0 if good else 1])[0] for j in range(len(rates)))
        rows[votes] += 1
        for j, v in enumerate(votes):
            cast[j] += v != 0
            right[j] += v == (1 if good else -1)
    return rows, [r / c for r, c in zip(right, cast)]


def test_planted_accuracies_are_recovered(spark):
    rules = quality.RULES[:6]
    sure, wrong, fair = ((0.03, 0.57, 0.4), (0.5, 0.45, 0.05)), ((0.3, 0.65, 0.05), (0.05, 0.9, 0.05)), ((0.1, 0.5, 0.4), (0.35, 0.45, 0.2))
    rows, accuracy = planted([sure, sure, fair, wrong, ((0.02, 0.98, 0.0), (0.4, 0.6, 0.0)), sure], 0.7, 20_000, 4)
    patterns = spark.createDataFrame([(list(v), n) for v, n in rows.items()], "votes array<int>, n long")
    found = {r["rule"]: r["accuracy"] for r in quality.accuracies(patterns, rules).collect()}
    for r, a in zip(rules, accuracy):
        assert found[r.name] == pytest.approx(a, abs=0.05), (r.name, a)
    assert found[rules[3].name] < 0.25  # a rule that starts as a good one and is mostly wrong
    fit = quality.fitted(patterns, rules).first()["p"]
    assert fit["prior"] == pytest.approx(0.7, abs=0.03)


def test_no_patterns_and_one(spark):
    empty = spark.createDataFrame([], "votes array<int>, n long")
    assert quality.posteriors(empty).count() == 0
    assert all(r["cast"] == 0 and r["accuracy"] is None for r in quality.accuracies(empty).collect())
    one = spark.createDataFrame([([0] * len(quality.RULES), 5)], "votes array<int>, n long")
    assert math.isfinite(quality.posteriors(one).first()["posterior"])


def test_columns_that_clash_stay(spark):
    good = " ".join(["the of and to in a word"] + [f"w{i}" for i in range(50)])
    df = spark.createDataFrame([(i, good, i, "x", "y") for i in range(30)] + [(99, "!! ## $$", 0, "x", "y")], "doc_id long, text string, __q int, __kept string, row string")
    out = quality.quality_filtered(df)
    assert out.columns == df.columns
    assert sorted((r["doc_id"], r["__q"], r["__kept"], r["row"]) for r in out.collect()) == [(i, i, "x", "y") for i in range(30)]
    huge = spark.createDataFrame([(1, good * 2_000)], "doc_id long, text string")
    assert quality.judged(huge).select(F.col("__q.m.n_words")).first()[0] > 100_000
