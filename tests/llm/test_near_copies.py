"""The near-dedup stage of the pipeline against all pairs of exact shingle similarity."""

import random
import re

import pytest

pytest.importorskip("cutloom.llm")
corpus_pipeline = pytest.importorskip("corpus_pipeline")

SF = "/root/testdata/sf0.001"


def shingles(text, size=5):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(b"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    return frozenset(tuple(w[i: i + size]) for i in range(len(w) - size + 1)) or frozenset([tuple(w)] if w else [])


def kept_ids(rows):
    """Smallest ids of the components of all pairs of similarity 0.8 or more; rows are (id, text)."""
    sets = [(i, shingles(t)) for i, t in rows if i is not None]
    up = {i: i for i, _ in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            common = len(a & b)
            if a == b or (common and 5 * common >= 4 * (len(a) + len(b) - common)):
                x, y = root(i), root(j)
                up[max(x, y)] = min(x, y)
    return sorted({root(i) for i in up})


def test_near_dedup_against_all_pairs(spark):
    rng = random.Random(11)
    texts = [None, "", "one two", "One  two", "solo"]
    for _ in range(12):
        base = [f"w{rng.randrange(5000)}" for _ in range(300)]
        for changes in (0, 2, 4, 6, 8, 10, 13, 16, 30):  # similarities from 1 to about 0.4
            words = list(base)
            for at in rng.sample(range(300), changes):
                words[at] = f"v{rng.randrange(10**6)}"
            texts.append(" ".join(words))
    rng.shuffle(texts)
    rows = [(i, t, "en", "src1", 0) for i, t in enumerate(texts)] + [(None, texts[0], "en", "src1", 0), (7, texts[7], "en", "src1", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    out = corpus_pipeline.dedup_stage(spark, docs, SF).collect()
    assert sorted(r["doc_id"] for r in out if r["doc_id"] is not None) == kept_ids([r[:2] for r in rows])
    assert sum(r["doc_id"] is None for r in out) == 1


def test_near_dedup_of_the_small_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = corpus_pipeline.dedup_stage(spark, docs, SF).collect()
    rows = {r["doc_id"]: r for r in docs.collect()}
    assert sorted(r["doc_id"] for r in out) == kept_ids([(i, r["text"]) for i, r in rows.items()])
    assert all(r == rows[r["doc_id"]] for r in out)


@pytest.mark.parametrize("group, block, pivots", [(0, 700, 1), (0, 1, 2), (2000, 5000, 8)])
def test_large_groups_in_blocks(spark, group, block, pivots):
    """Groups cut into blocks, with chains that no pivot reaches, sets of all sizes and repeated rows."""
    from cutloom.llm.near_copies import near_copies

    rng = random.Random(5)
    texts, walk = ["", "a b", "a  b"], [f"w{i}" for i in range(60)]
    for step in range(60):  # a chain: neighbours are alike, ends are not
        texts.append(" ".join(walk))
        walk[rng.randrange(60)] = f"c{step}"
    base = [f"x{i}" for i in range(90)]
    for cut in range(40):  # copies of one text, shorter and shorter
        texts.append(" ".join(base[: 90 - 2 * cut]))
    rows = list(enumerate(texts)) + [(5, texts[5]), (40, texts[70]), (None, texts[3])]
    got = near_copies(spark.createDataFrame(rows, "doc_id long, text string"), group=group, block=block, pivots=pivots).collect()
    assert {r["id"] for r in got if r["component"] is None} == {None}
    assert sorted({r["component"] for r in got if r["id"] is not None}) == kept_ids(rows)


def test_hot_joins_keep_every_row(spark, monkeypatch):
    from cutloom.llm import common, simhash
    from pyspark.sql import functions as F

    monkeypatch.setattr(common, "HOT", 3)
    pairs = [(i, 0) for i in range(1, 30)] + [(i, i - 1) for i in range(101, 130)] + [(7, 200), (200, 201)]
    found = {r["node"]: r["root"] for r in simhash.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert found == {**{i: 0 for i in [*range(1, 30), 200, 201]}, **{i: 100 for i in range(101, 130)}}
    rows = spark.createDataFrame([(k, i) for k in range(5) for i in range(10 ** (k % 2 + 1))] + [(9, 9)], "k long, i long")
    table = rows.where("k <> 9").groupBy("k").agg(F.max("i").alias("top"), F.count("*").alias("n"))
    out = common.joined_hot(rows, table, "k", rows.count()).collect()
    want = [(k, i, 10 ** (k % 2 + 1) - 1) for k in range(5) for i in range(10 ** (k % 2 + 1))] + [(9, 9, -1)]
    assert sorted((r["k"], r["i"], -1 if r["top"] is None else r["top"]) for r in out) == want
