"""Each stage of the pipeline, as the pipeline calls it, against plain Python over the small table."""

import collections

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
corpus_pipeline = pytest.importorskip("corpus_pipeline")
from cutloom.llm import mixing, quality, secrets  # noqa: E402
from cutloom.llm.queries import tokenizer_path  # noqa: E402
from tests.llm.test_near_copies import kept_ids  # noqa: E402
from tests.llm.test_operators import _base, _plain_scan  # noqa: E402
from tests.llm.test_quality_fit import plain_fit  # noqa: E402

SF = "/root/testdata/sf0.001"


def stage(name):
    return next(f for n, f in corpus_pipeline.STAGES if n == name)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").persist()


def test_quality_stage(spark, docs):
    votes = {r["doc_id"]: (tuple(r["votes"]), r["text"]) for r in quality.voted(docs).select("doc_id", "text", "__q.votes").collect()}
    fit = plain_fit(collections.Counter(v for v, _ in votes.values()), quality.RULES)
    want = []
    for i, (v, text) in votes.items():
        n, *_, repeated = _base(text)
        if n >= 10 and 100 * repeated <= 20 * n and fit[v] >= 0.5:
            want.append(i)
    rows = {r["doc_id"]: r for r in docs.collect()}
    out = stage("quality rules")(spark, docs, SF).collect()
    assert sorted(r["doc_id"] for r in out) == sorted(want) and all(r == rows[r["doc_id"]] for r in out)
    assert 0 < len(want) < len(rows)


def test_dedup_stage(spark, docs):
    out = stage("simhash near-dedup")(spark, docs, SF)
    assert sorted(r["doc_id"] for r in out.collect()) == kept_ids([(r["doc_id"], r["text"]) for r in docs.collect()])


def cleaned(text):
    """The text with each group of touching spans replaced by the name of its first."""
    names, out, at = [f"[{p.kind}]" for p in secrets.PATTERNS] + ["[entropy]"], [], 0
    for a, k, b in _plain_scan(text)[1]:
        if a >= at:
            out += [text[at:a], names[k]]
        at = max(at, b)
    return "".join(out) + text[at:]


def test_secret_stage(spark, docs):
    extra = spark.createDataFrame([(10**9 + i, t, "en", "src1", len(t)) for i, t in enumerate(["token=abcdefg1 x", "Q7xK2mV9pL4nR8tW1zYc5Ha3 y", "AKIA" + "A" * 16 + " passwd: 0123456789abcdef0123456789 z", ""])], docs.schema)
    both = docs.unionByName(extra)
    rows = {r["doc_id"]: r for r in both.collect()}
    out = stage("secret scans")(spark, both, SF).collect()
    assert len(out) == len(rows)
    changed = 0
    for r in out:
        before = rows[r["doc_id"]]
        want = before["text"] if before["text"] is None else cleaned(before["text"])
        assert r["text"] == want
        assert r["n_chars"] == (before["n_chars"] if want == before["text"] else len(want))
        changed += want != before["text"]
    assert changed >= 3


def test_mixing_stage(spark, docs):
    out = stage("mixing sources")(spark, docs, SF).collect()
    times = {r["doc_id"]: r["__copies"] for r in mixing.copies(docs, mixing.decisions(docs)).select("row.doc_id", "__copies").collect()}
    rows = {r["doc_id"]: r for r in docs.collect()}
    assert collections.Counter(r["doc_id"] for r in out) == {i: n for i, n in times.items() if n}
    assert all(r == rows[r["doc_id"]] for r in out)
    words = sum(len((rows[i]["text"] or "").split()) for i in rows)
    assert 0.5 * mixing.SHARE / 1000 * words < sum(len((r["text"] or "").split()) for r in out) <= mixing.SHARE / 1000 * words


def test_encoding_stage(spark, docs):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=tokenizer_path("piece_bpe_32k.model"))
    out = stage("sentencepiece")(spark, docs.where(F.col("doc_id") < 60), SF).collect()
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    assert len(out) == sum(i < 60 for i in texts)
    for r in out:
        assert list(r["ids"]) == library.encode(texts[r["doc_id"]])
