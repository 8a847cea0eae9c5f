"""Quality filtering by weak supervision, in DataFrame functions only.

Rules vote good (1), bad (-1) or abstain (0) on measures of the whole text: a
defect rule votes bad or abstains, since lacking one defect says little, and an
evidence rule may also vote good.  Expectation-maximisation over the distinct
vote patterns (at most 3^rules, so one bounded row) estimates how often each
rule votes bad, abstains or votes good in either class, hence each rule's
accuracy (how often its vote is right), and the share of good documents; a
document's posterior then replaces passing every rule.  The start counts as
``STRENGTH`` pseudo-documents of each class, a fixed few, so the corpus decides
where an estimate ends; the class in which the anchor rule votes bad less often
is the good one.  The estimation is one SQL expression, folded over the rounds;
documents meet their pattern's posterior in a broadcast join whose size is
bounded by 3^rules.

Defined results: null and empty texts have no words, so they fail the base; an
empty table gives no rows; repeated rows are judged alike; a very long text is
judged whole, in one row; columns of the input may have any names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import SPACE_PATTERN, WORD_PATTERN, let

#: Very common words of four languages.
COMMON_WORDS = "the of and to in a is that for it with as was on be at by der die und in den von zu das mit sich auf ist im dem nicht ein de la le et les des en un du une que est pour qui dans el y los se del las por con para".split()

WINDOW = 5


#: Start shares of (bad, none, good) votes in good and in bad documents: of defect rules, and of evidence rules.
DEFECT = ((0.02, 0.97, 0.01), (0.30, 0.69, 0.01))
EVIDENCE = ((0.05, 0.25, 0.70), (0.30, 0.40, 0.30))


@dataclass(frozen=True)
class Rule:
    """Bad from ``bad`` thousandths of numerator / denominator on; good up to ``good``, if that is given.

    With ``more_is_better`` the senses swap.  ``starts`` is where the estimate
    starts: the shares of bad votes, abstentions and good votes in good documents
    and in bad ones.
    """

    name: str
    numerator: str
    denominator: str
    bad: int
    good: int | None = None
    more_is_better: bool = False
    starts: tuple[tuple[float, float, float], tuple[float, float, float]] = DEFECT

    def sql(self) -> str:
        x, bad = f"1000 * {self.numerator}", f"{self.bad} * {self.denominator}"
        worse, better = ("<", ">=") if self.more_is_better else (">", "<=")
        good = "" if self.good is None else f" WHEN {x} {better} {self.good} * {self.denominator} THEN 1"
        return f"CASE WHEN {x} {worse} {bad} THEN -1{good} ELSE 0 END"


#: Thresholds in thousandths.
RULES = [
    Rule("length", "n_words", "1", 3_000, 10_000, True, EVIDENCE),
    Rule("symbols", "n_symbols", "n_words", 150),
    Rule("marks", "n_symbols", "word_chars", 40),
    Rule("repeats", "n_repeat_words", "n_words", 120),
    Rule("lines", "n_dup_lines", "n_lines", 300),
    Rule("word_size", "word_chars", "n_words", 16_000),
    Rule("capitals", "n_capitals", "word_chars", 300),
    Rule("calls", "n_calls", "n_words", 200),
    Rule("common", "n_common", "n_words", 0, 50, True, EVIDENCE),
]

#: Rounds of the fit, pseudo-documents of each class, and the rule that tells the classes apart.
PRIOR, ROUNDS, STRENGTH, ANCHOR = 0.8, 40, 20, 1


def measures(text: Column) -> Column:
    """One struct of all measures of a text; words and windows are made once."""
    def repeated(h: Column) -> Column:
        def covered(p: Column) -> Column:
            hits = F.filter(F.transform(p, lambda x, k: F.when((F.get(p, k - 1)["h"] == x["h"]) | (F.get(p, k + 1)["h"] == x["h"]), x["i"])), lambda i: i.isNotNull())
            return let(F.sort_array(hits), lambda d: F.aggregate(F.transform(d, lambda i, k: F.least(F.lit(WINDOW), F.coalesce(F.get(d, k + 1), i + WINDOW) - i)), F.lit(0), lambda a, x: a + x))

        return F.when(F.size(F.array_distinct(h)) == F.size(h), 0).otherwise(let(F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), covered))

    def of_words(w: Column) -> Column:
        windows = F.when(F.size(w) >= WINDOW, F.transform(F.sequence(F.lit(0), F.size(w) - WINDOW), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WINDOW)]))).otherwise(F.array().cast("array<bigint>"))
        return F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
            let(windows, repeated).cast("long").alias("n_repeat_words"),
            F.size(F.array_intersect(w, F.array(*[F.lit(x) for x in dict.fromkeys(COMMON_WORDS)]))).cast("long").alias("n_common"),
        )

    def of_lines(lines: Column) -> Column:
        return F.struct(F.size(lines).cast("long").alias("n_lines"), (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"))

    words = F.filter(F.split(text, SPACE_PATTERN), lambda w: w != "")
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD_PATTERN))
    return F.struct(
        let(words, of_words).alias("w"), let(lines, of_lines).alias("l"),
        F.regexp_count(text, F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        F.regexp_count(text, F.lit("[A-Z]")).cast("long").alias("n_capitals"),
        F.regexp_count(text, F.lit("!")).cast("long").alias("n_calls"),
    )


BASE = "n_words < 10 OR 100 * n_repeat_words > 20 * n_words"


def voted(docs: DataFrame, rules: list[Rule] = RULES, text_col: str = "text") -> DataFrame:
    """``docs`` with a struct column __q: measures, base_failed and the array of votes."""
    names = ["w.n_words", "w.word_chars", "n_symbols", "l.n_dup_lines", "w.n_repeat_words", "l.n_lines", "w.n_common", "n_capitals", "n_calls"]

    def judged(m: Column) -> Column:
        flat = F.struct(*[_path(m, n).alias(n.split(".")[-1]) for n in names])
        return let(flat, lambda x: F.struct(x.alias("m"), _on(BASE, x).alias("base_failed"), F.array(*[_on(r.sql(), x) for r in rules]).alias("votes")))

    return docs.withColumn("__q", let(measures(F.coalesce(F.col(text_col), F.lit(""))), judged))


def _path(m: Column, name: str) -> Column:
    for part in name.split("."):
        m = m[part]
    return m


def _on(sql: str, x: Column) -> Column:
    """The small grammar of Rule.sql and BASE, as a Column over the fields of the struct ``x``."""
    def term(t: str) -> Column:
        out = None
        for f in t.split("*"):
            f = f.strip()
            c = F.lit(int(f)).cast("long") if f.lstrip("-").isdigit() else x[f]
            out = c if out is None else out * c
        return out

    def test(t: str) -> Column:
        for sign in ("<=", ">=", "<", ">"):
            if sign in t:
                a, b = map(term, t.split(sign))
                return {"<=": a <= b, ">=": a >= b, "<": a < b, ">": a > b}[sign]
        raise ValueError(t)

    if not sql.startswith("CASE"):
        out = None
        for part in sql.split(" OR "):
            out = test(part) if out is None else out | test(part)
        return out
    body, other = sql[len("CASE WHEN "): -len(" END")].split(" ELSE ")
    result = None
    for when in body.split(" WHEN "):
        condition, value = when.split(" THEN ")
        result = (F.when if result is None else result.when)(test(condition), F.lit(int(value)))
    return result.otherwise(F.lit(int(other)))


_PARAMS = "struct<prior:double,good:array<double>,bad:array<double>>"


def _shares(rules: list[Rule], k: int) -> list[float]:
    """Start shares of class ``k``, flat: three for each rule."""
    return [x for r in rules for x in r.starts[k]]


def _odds(p: Column, votes: Column) -> Column:
    """The posterior of a vote pattern under the parameters ``p``."""
    weights = F.transform(votes, lambda x, j: F.log(p["good"][3 * j + x + 1] / p["bad"][3 * j + x + 1]))
    return 1 / (1 + F.exp(-F.aggregate(weights, F.log(p["prior"] / (1 - p["prior"])), lambda a, x: a + x)))


def fitted(patterns: DataFrame, rules: list[Rule] = RULES, rounds: int = ROUNDS, anchor: int = ANCHOR) -> DataFrame:
    """One row (v array<struct<votes, n>>, p struct<prior, good, bad>) from (votes, n); none without patterns.

    good and bad hold, flat, each rule's shares of bad votes, abstentions and
    good votes in that class.
    """
    row = patterns.agg(F.sort_array(F.collect_list(F.struct("votes", "n"))).alias("v"))

    def step(p: Column, _: Column) -> Column:
        def refit(q: Column) -> Column:
            masses = F.transform("v", lambda x, k: F.struct(x["votes"].alias("votes"), (x["n"] * q[k]).alias("g"), (x["n"] * (1 - q[k])).alias("b")))

            def shares(m: Column) -> Column:
                def of(side: str, start: list[float]) -> tuple[Column, Column]:
                    whole = F.aggregate(m, F.lit(float(STRENGTH)), lambda a, x: a + x[side])
                    part = F.transform(F.array(*map(F.lit, start)), lambda s, i: F.aggregate(m, s * STRENGTH, lambda a, x: a + F.when(x["votes"][F.floor(i / 3).cast("int")] == i % 3 - 1, x[side]).otherwise(0.0)))
                    return whole, let(whole, lambda w: F.transform(part, lambda x: x / w))

                (ng, good), (nb, bad) = of("g", _shares(rules, 0)), of("b", _shares(rules, 1))
                return F.struct((ng / (ng + nb)).alias("prior"), good.alias("good"), bad.alias("bad")).cast(_PARAMS)

            return let(masses, shares)

        return let(F.transform("v", lambda x: _odds(p, x["votes"])), refit)

    first = F.struct(F.lit(PRIOR).alias("prior"), F.array(*map(F.lit, _shares(rules, 0))).alias("good"), F.array(*map(F.lit, _shares(rules, 1))).alias("bad")).cast(_PARAMS)

    def named(p: Column) -> Column:
        swapped = F.struct((1 - p["prior"]).alias("prior"), p["bad"].alias("good"), p["good"].alias("bad")).cast(_PARAMS)
        return F.when(p["good"][3 * anchor] > p["bad"][3 * anchor], swapped).otherwise(p)

    return row.where(F.size("v") > 0).select("v", let(F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), first, step), named).alias("p"))


def posteriors(patterns: DataFrame, rules: list[Rule] = RULES, rounds: int = ROUNDS, anchor: int = ANCHOR) -> DataFrame:
    """(votes, posterior) from (votes, n)."""
    each = let(F.col("p"), lambda p: F.transform("v", lambda x: F.struct(x["votes"].alias("votes"), _odds(p, x["votes"]).alias("posterior"))))
    return fitted(patterns, rules, rounds, anchor).select(F.explode(each).alias("x")).select("x.votes", "x.posterior")


def accuracies(patterns: DataFrame, rules: list[Rule] = RULES, rounds: int = ROUNDS, anchor: int = ANCHOR) -> DataFrame:
    """(rule, cast, accuracy): how many votes each rule cast and the expected share of right ones (null without votes)."""
    each = let(F.col("p"), lambda p: F.transform("v", lambda x: F.struct(x["votes"].alias("votes"), x["n"].alias("n"), _odds(p, x["votes"]).alias("q"))))
    rows = fitted(patterns, rules, rounds, anchor).select(F.explode(each).alias("x")).select("x.n", "x.q", F.posexplode("x.votes").alias("j", "vote")).where("vote <> 0")
    sums = rows.groupBy("j").agg(F.sum("n").alias("cast"), (F.sum(F.col("n") * F.when(F.col("vote") == 1, F.col("q")).otherwise(1 - F.col("q"))) / F.sum("n")).alias("accuracy"))
    names = patterns.sparkSession.createDataFrame([(j, r.name) for j, r in enumerate(rules)], "j int, rule string")
    return names.join(F.broadcast(sums), "j", "left").select("rule", F.coalesce("cast", F.lit(0)).cast("long").alias("cast"), "accuracy")


def judged(docs: DataFrame, rules: list[Rule] = RULES, text_col: str = "text") -> DataFrame:
    """``docs`` with __q (measures, base_failed, votes), __posterior and __kept."""
    marked = voted(docs, rules, text_col)
    known = posteriors(marked.groupBy(F.col("__q.votes").alias("votes")).agg(F.count(F.lit(1)).alias("n")), rules)
    known = known.select(F.col("votes").alias("__votes"), F.col("posterior").alias("__posterior"))
    joined = marked.join(F.broadcast(known), F.col("__q.votes") == F.col("__votes"), "left").drop("__votes")
    return joined.withColumn("__kept", ~F.col("__q.base_failed") & (F.coalesce("__posterior", F.lit(0.0)) >= 0.5))


def quality_filtered(docs: DataFrame, rules: list[Rule] = RULES) -> DataFrame:
    """The rows of ``docs`` that pass the base and whose posterior is at least one half."""
    packed = docs.select(F.struct(*docs.columns).alias("row"), F.col("text"))
    return judged(packed, rules).where("__kept").select("row.*")


def oracle(rules: list[Rule] = RULES) -> str:
    """The same in DuckDB SQL, with a recursive fit."""
    m = range(1, len(rules) + 1)
    logit = " + ".join(f"ln(g[{3 * j - 1} + v[{j}]] / b[{3 * j - 1} + v[{j}]])" for j in m)
    side = lambda k, mass: ", ".join(f"(coalesce(sum({mass}) FILTER (v[{i // 3 + 1}] = {i % 3 - 1}), 0) + {STRENGTH} * {x}) / (sum({mass}) + {STRENGTH})" for i, x in enumerate(_shares(rules, k)))
    start = lambda k: ", ".join(f"{x}::DOUBLE" for x in _shares(rules, k))
    swap = f"g[{3 * ANCHOR + 1}] > b[{3 * ANCHOR + 1}]"
    words = ", ".join(f"'{w}'" for w in dict.fromkeys(COMMON_WORDS))
    return f"""
WITH RECURSIVE t AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT *, regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+') AS w, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS l FROM t),
win AS (SELECT r, i, count(*) OVER (PARTITION BY r, w[i], w[i + 1], w[i + 2], w[i + 3], w[i + 4]) AS c FROM (SELECT r, w, unnest(generate_series(1, len(w) - {WINDOW - 1})) AS i FROM w)),
rep AS (SELECT r, count(DISTINCT i + k) AS n FROM win, generate_series(0, {WINDOW - 1}) AS g(k) WHERE c > 1 GROUP BY r),
m AS (SELECT w.r, doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
  (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(rep.n, 0)::BIGINT AS n_repeat_words, len(l)::BIGINT AS n_lines,
  len(list_intersect(w, [{words}]))::BIGINT AS n_common, length(regexp_replace(text, '[^A-Z]', '', 'g'))::BIGINT AS n_capitals, length(regexp_replace(text, '[^!]', '', 'g'))::BIGINT AS n_calls
  FROM w LEFT JOIN rep ON rep.r = w.r),
d AS (SELECT *, ({BASE}) AS base_failed, [{", ".join(r.sql() for r in rules)}] AS v FROM m),
pat AS (SELECT v, count(*)::DOUBLE AS n FROM d GROUP BY v),
em(it, prior, g, b) AS (
  SELECT 0, {PRIOR}::DOUBLE, [{start(0)}], [{start(1)}]
  UNION ALL
  SELECT it + 1, (sum(n * q) + {STRENGTH}) / (sum(n) + 2 * {STRENGTH}), [{side(0, "n * q")}], [{side(1, "n * (1 - q)")}]
  FROM (SELECT it, n, v, 1 / (1 + exp(-(ln(prior / (1 - prior)) + {logit}))) AS q FROM em, pat WHERE it < {ROUNDS}) AS e GROUP BY it),
z AS (SELECT v, CASE WHEN {swap} THEN 1 - q ELSE q END AS q FROM (SELECT v, g, b, 1 / (1 + exp(-(ln(prior / (1 - prior)) + {logit}))) AS q FROM em, pat WHERE it = {ROUNDS}) AS f)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND q >= 0.5) AS kept FROM d JOIN z ON z.v = d.v"""
