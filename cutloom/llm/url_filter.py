"""URL filtering: host and path rules first, then a logistic regression on hashed character n-grams.

The model is trained on the driver from a small labelled table of URLs (at most
``most`` rows, a documented bound) and is a vector of 2^bits weights, so what
goes to the tasks has a fixed size.  Scoring hashes all n-grams of a batch of
hosts and paths at once.

Defined results: a null url, or one without ``://``, has an empty host and path,
fits no rule and is judged by the model on empty strings (its intercept);
repeated rows are judged alike; a very long url is hashed whole; an empty table
gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import mix, text_bytes

#: Fixed values: (verdict, host, path prefix).
RULES = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]

#: The small labelled URL table; 1 is to be blocked.  Its hosts are none of the given pages'.
LABELLED = [
    ("http://spam-links.example.com/en/12", 1), ("https://www.spam-mill.example.org/de/904?page=2", 1), ("http://m.spam-links.example.com/fr/31.html", 1), ("http://link-farm.example.com/es/8", 1), ("http://farm-of-links.example.org/en/66", 1),
    ("http://cheap-meds.example.com/en/77", 1), ("https://blog.buy-pills.example.org/es/5/", 1), ("http://cheap-meds.example.com/en/2", 1), ("http://pills-now.example.org/fr/81", 1), ("http://cheap-loans.example.com/en/40", 1),
    ("http://casino-royal.example.com/en/450", 1), ("https://www.online-casino.example.org/fr/7.html", 1), ("http://casino-royal.example.com/es/19", 1), ("https://big-win.example.org/en/3", 1), ("http://win-money.example.com/de/21", 1),
    ("http://best-bets.example.com/de/90", 1), ("https://m.sure-bets.example.org/en/61#top", 1), ("http://free-spins.example.com/en/1", 1), ("http://free-gifts.example.org/fr/17.html", 1), ("http://bets-today.example.com/en/88", 1),
    ("http://click-ads.example.com/en/5", 1), ("https://www.ads-serve.example.org/es/88", 1), ("http://click-track.example.com/fr/4", 1), ("http://track-pixel.example.org/en/6", 1), ("http://ads-pixel.example.com/de/13", 1),
    ("http://adult-chat.example.com/en/14", 1), ("https://blog.adult-cams.example.org/fr/23", 1), ("http://xxx-adult.example.com/en/9", 1), ("http://x-cams.example.org/es/2", 1),
    ("http://news.example.org/en/1", 0), ("https://library.example.com/fr/20", 0), ("http://garden.example.org/es/300/", 0), ("https://www.museum.example.com/en/41.html", 0), ("http://school.example.org/de/52", 0),
    ("https://weather.example.com/en/7", 0), ("http://travel-notes.example.org/en/18", 0), ("https://open-data.example.com/fr/5", 0), ("https://m.history.example.org/en/25#top", 0), ("http://the-theatre.example.com/en/676", 0),
    ("https://nothing.example.org/en/685", 0), ("https://other-things.example.com/en/770#top", 0), ("https://blog.station.example.com/fr/853/", 0), ("http://blog.nation.example.org/en/960", 0), ("https://m.health.example.com/en/474.html", 0),
    ("https://earth.example.com/en/671?utm_source=feed", 0), ("https://blog.author.example.org/es/533/", 0), ("https://www.north.example.com/en/148.html", 0), ("https://blog.together.example.org/es/978?page=2", 0), ("https://question.example.com/en/81", 0),
    ("http://reader.example.org/de/90", 0), ("https://month.example.com/es/17", 0), ("https://table.example.org/fr/63", 0), ("https://mother.example.com/fr/12", 0), ("http://within.example.org/en/99", 0), ("https://www.southern.example.com/de/71", 0),
    ("http://fashion.example.org/es/45", 0), ("https://thousand.example.com/en/3", 0), ("http://father.example.org/de/6/", 0), ("https://blog.method.example.com/en/58", 0), ("http://what-and-when.example.org/fr/37.html", 0),
]

_ASCII = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
URL_PARTS = r"(?s)^(.*?)://([^/?#]*)([^?#]*)"


def parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; empty without ``://``."""
    url = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(url, URL_PARTS, 2), *_ASCII), F.regexp_extract(url, URL_PARTS, 3)


def ruled(host: Column, path: Column, rules: list[tuple[str, str, str]] = RULES) -> tuple[Column, Column]:
    """The longest fitting rule and its verdict, or nulls."""
    rule = verdict = None
    for says, h, p in sorted(rules, key=lambda r: -len(r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule = (F.when if rule is None else rule.when)(fits, h + p)
        verdict = (F.when if verdict is None else verdict.when)(fits, says)
    if rule is None:
        return F.lit(None).cast("string"), F.lit(None).cast("string")
    return rule.otherwise(F.lit(None).cast("string")), verdict.otherwise(F.lit(None).cast("string"))


def slots(texts: pa.Array, sizes: tuple[int, ...], bits: int, salt: int) -> tuple[np.ndarray, np.ndarray]:
    """For all n-grams of all texts: the text's index and the n-gram's slot."""
    data, offsets = text_bytes(texts)
    owner = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    rows, hashes = [], []
    for n in sizes:
        if len(data) < n:
            continue
        h = np.full(len(data) - n + 1, np.uint64(salt * 31 + n))
        for k in range(n):
            h = h * np.uint64(0x100000001B3) + data[k: len(data) - n + 1 + k].astype(np.uint64) + np.uint64(1)
        inside = owner[: len(h)] == owner[n - 1:]
        rows.append(owner[: len(h)][inside])
        hashes.append((mix(h[inside]) >> np.uint64(64 - bits)).astype(np.int64))
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(rows), np.concatenate(hashes)


class Model:
    """Weights of hashed n-grams; a text's features are n-gram counts over the root of their sum of squares per part."""

    def __init__(self, sizes: tuple[int, ...] = (2, 3, 4), bits: int = 14):
        self.sizes, self.bits = sizes, bits
        self.weights, self.intercept = np.zeros(1 << bits), 0.0

    def features(self, hosts: list[str] | pa.Array, paths: list[str] | pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, slot, value) of all features."""
        out = []
        for salt, texts in ((1, hosts), (2, paths)):
            framed = pa.array([f"^{t}$" if t else "" for t in (texts.to_pylist() if isinstance(texts, pa.Array) else texts)], pa.string())
            row, slot = slots(framed, self.sizes, self.bits, salt)
            n = np.bincount(row, minlength=len(framed))
            out.append((row, slot, 1 / np.sqrt(np.maximum(n, 1))[row]))
        return tuple(np.concatenate(x) for x in zip(*out))

    def fit(self, hosts: list[str], paths: list[str], labels: list[int], rounds: int = 400, rate: float = 10.0, ridge: float = 1e-4) -> Model:
        row, slot, value = self.features(hosts, paths)
        y = np.asarray(labels, np.float64)
        for _ in range(rounds):
            z = np.bincount(row, self.weights[slot] * value, len(y)) + self.intercept
            gap = (1 / (1 + np.exp(-z)) - y) / max(1, len(y))
            self.weights -= rate * (np.bincount(slot, gap[row] * value, 1 << self.bits) + ridge * self.weights)
            self.intercept -= rate * gap.sum()
        return self

    def margins(self, hosts, paths) -> np.ndarray:
        row, slot, value = self.features(hosts, paths)
        return np.bincount(row, self.weights[slot] * value, len(hosts)) + self.intercept


def split_url(url: str | None) -> tuple[str, str]:
    """parts() for one URL on the driver."""
    import re

    m = re.match(URL_PARTS, url or "")
    return (m[2].translate(str.maketrans(*_ASCII)), m[3]) if m else ("", "")


def trained(labelled: DataFrame | list[tuple[str, int]], most: int = 10_000) -> Model:
    """A model from (url, label) rows; more than ``most`` rows are refused."""
    rows = labelled if isinstance(labelled, list) else [tuple(r) for r in labelled.select("url", "label").limit(most + 1).collect()]
    if len(rows) > most:
        raise ValueError(f"the labelled table is to have at most {most} rows")
    hosts, paths = zip(*(split_url(u) for u, _ in rows))
    return Model().fit(list(hosts), list(paths), [y for _, y in rows])


def judged(pages: DataFrame, model: Model, rules: list[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """(id, host, path, rule, verdict, margin) for each row."""
    host, path = parts(F.col(url_col))
    rule, verdict = ruled(F.col("host"), F.col("path"), rules)
    cut = pages.select(F.col(id_col).cast("long").alias("id"), host.alias("host"), path.alias("path")).select("*", rule.alias("rule"), verdict.alias("said"))
    shared = pages.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            margins = shared.value.margins(batch.column("host"), batch.column("path"))
            said = [s or ("block" if m >= 0 else "allow") for s, m in zip(batch.column("said").to_pylist(), margins.tolist())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(said, pa.string()), pa.array(margins)], ["id", "host", "path", "rule", "verdict", "margin"])

    return cut.mapInArrow(run, "id long, host string, path string, rule string, verdict string, margin double")
