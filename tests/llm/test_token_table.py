"""The pre-token table against the library: every settled character, special strings, rare and hot parts, odd inputs."""

import collections
import random
import sys

import pytest

pytest.importorskip("cutloom.llm")
from cutloom.llm import token_count  # noqa: E402
from cutloom.llm.queries import tokenizer_path  # noqa: E402

PATH = tokenizer_path("byte_bpe_50k.json")


def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(PATH)


def test_settled_characters_are_cut_as_the_library_cuts_them():
    tokenizer = library()
    settled = [chr(c) for c in range(sys.maxunicode + 1) if not 0xD800 <= c < 0xE000 and token_count._settled.fullmatch(chr(c))]
    assert len(settled) > 1300
    for c in settled:
        text = f"a{c}b {c}1{c}{c} '{c}s  {c}"
        assert token_count.pre_tokens(PATH, text)[0] == [text[a:b] for _, (a, b) in tokenizer.pre_tokenizer.pre_tokenize_str(text)], hex(ord(c))


TEXTS = [None, "", " ", "\n\n  x", "<|endoftext|>", "a<|endoftext|><|endoftext|> b <|endoftext", "it's we'll 'sx ''s  '", "x   y\x1cz \x85", "日本語 テキスト 😀😀  ▁", "0" * 700 + "-" * 900, "q" * 5000, "aA1\t\r\n \n", "größe été naïve", "\U0001fae8 new Ᲊ"]


def test_counts(spark):
    rng = random.Random(2)
    words = ["alpha", " ", "beta", "12", "'s", "!", "\n", "größe", "日本", "zz9"]
    texts = TEXTS + ["".join(rng.choice(words) for _ in range(rng.randint(1, 80))) for _ in range(60)]
    rows = [(i, t, "x", "y") for i, t in enumerate(texts)] + [(3, texts[3], "x", "y")] * 3 + [(None, "no id", "x", "y")]
    df = spark.createDataFrame(rows, "doc_id long, text string, piece string, row string").repartition(3)
    tokenizer = library()
    want = collections.Counter((i, len((t or "").encode()), len(tokenizer.encode(t or "", add_special_tokens=False).ids)) for i, t, *_ in rows)
    for hot in (token_count.HOT, 4, 0):
        assert collections.Counter(map(tuple, token_count.token_counts(df, PATH, hot=hot).collect())) == want
    assert token_count.token_counts(df.limit(0), PATH).count() == 0


def test_each_pre_token_is_counted_once(spark):
    df = spark.createDataFrame([(i, "one two two three" if i % 2 else "one four") for i in range(50)], "doc_id long, text string").repartition(5)
    rows = token_count.vocabulary(df, PATH).collect()
    assert {r["piece"]: r["n"] for r in rows} == {"one": 50, " two": 50, " three": 25, " four": 25} and len(rows) == 4
