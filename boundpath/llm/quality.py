"""Quality rules as a short-circuit cascade, in DataFrame functions alone.

Every rule is a pair of a name and a rejection expression over the text.  Cost (seconds over a sample) and selectivity
(share of the sample rejected) are estimated rule by rule; the cascade asks the rules in falling order of rejections per
second, and a row leaves at the first rule that rejects it.  The order changes the work, never the verdict.  The rule on repeated
windows takes its place in that order like any other, though it needs columns of its own: it is computed from the texts that the rules before it kept.

Defined cases: null and blank texts have no words and are rejected (too few words); a text of fewer than five words
has no repeated windows; lines compare as they are, blanks included; other columns, whatever their names, are untouched.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import BLANK_RUN, count_words, drop_materialised, materialise, read_table, split_words

MIN_WORDS = 10
REPEAT_PERCENT = 20
SYMBOL_PERCENT = 10
DUP_LINE_PERCENT = 40
LETTER_WORD_PERCENT = 70
MEAN_WORD = (3, 10)
SAMPLE_ROWS = 2000


def whole(text: Column) -> Column:
    return F.coalesce(text, F.lit(""))


def n_symbols(text: Column) -> Column:
    return F.regexp_count(whole(text), F.lit(r"[#*$%&|<>]")).cast("bigint")


def word_chars(text: Column) -> Column:
    return (F.char_length(whole(text)) - F.regexp_count(whole(text), F.lit(r"[\x20\x09-\x0D]"))).cast("bigint")


def letter_words(text: Column) -> Column:
    """Words with a letter in them."""
    return F.regexp_count(whole(text), F.lit(r"[^\x20\x09-\x0D\p{L}]*+\p{L}[^\x20\x09-\x0D]*+")).cast("bigint")


def worded_lines(text: Column) -> Column:
    return F.filter(F.split(whole(text), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))


def n_dup_lines(text: Column) -> Column:
    return (F.size(worded_lines(text)) - F.size(F.array_distinct(worded_lines(text)))).cast("bigint")


def with_repeat_words(df: DataFrame, text: str, out: str) -> DataFrame:
    """Adds the number of words inside five-word windows that the text holds twice or more.

    Only texts with a repeated window are sorted; each step is a column of its own, so it is computed once."""
    p = "__bp_"
    keep = df.columns
    df = df.withColumn(f"{p}words", F.transform(split_words(F.col(text)), lambda x: F.xxhash64(x)))
    n = F.size(f"{p}words")
    runs = F.transform(F.sequence(F.lit(1), n - 4), lambda i: F.xxhash64(F.slice(f"{p}words", i, 5)))
    df = df.withColumn(f"{p}runs", F.when(n < 5, F.array().cast("array<bigint>")).otherwise(runs))
    repeated = F.size(F.array_distinct(f"{p}runs")) < F.size(f"{p}runs")
    placed = F.sort_array(F.transform(f"{p}runs", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn(f"{p}sorted", F.when(repeated, placed).otherwise(F.array().cast("array<struct<h:bigint,i:int>>")))
    twice = F.filter(f"{p}sorted", lambda x, i: (F.get(f"{p}sorted", i - 1)["h"] == x["h"]) | (F.get(f"{p}sorted", i + 1)["h"] == x["h"]))
    df = df.withColumn(f"{p}at", F.sort_array(F.transform(twice, lambda x: x["i"])))
    start = F.struct(F.lit(-5).alias("last"), F.lit(0).cast("bigint").alias("words"))
    covered = F.aggregate(f"{p}at", start, lambda acc, i: F.struct(i.alias("last"), (acc["words"] + F.least(F.lit(5), i - acc["last"])).alias("words")), lambda acc: acc["words"])
    return df.select(*[F.col(f"`{c}`") for c in keep], covered.alias(out))


class Measures:
    """What rules look at: expressions over a text, or the columns that hold them already."""

    def __init__(self, text: Column, **known: Column):
        self._text, self._known = text, known

    def __getattr__(self, name: str) -> Column:
        if name.startswith("_") or (name not in self._known and name not in _EXPRESSIONS):
            raise AttributeError(name)
        return self._known[name] if name in self._known else _EXPRESSIONS[name](self._text)


_EXPRESSIONS: dict[str, Callable[[Column], Column]] = {
    "n_words": count_words,
    "n_symbols": n_symbols,
    "n_letter_words": letter_words,
    "word_chars": word_chars,
    "n_dup_lines": n_dup_lines,
    "n_lines": lambda t: F.size(worded_lines(t)),
}


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[Measures], Column]
    windows: bool = False  # needs n_repeat_words, which is no single expression


RULES = (
    Rule("few_words", lambda m: m.n_words < MIN_WORDS),
    Rule("symbols", lambda m: m.n_symbols * 100 > m.n_words * SYMBOL_PERCENT),
    Rule("letterless_words", lambda m: m.n_letter_words * 100 < m.n_words * LETTER_WORD_PERCENT),
    Rule("word_length", lambda m: (m.word_chars < m.n_words * MEAN_WORD[0]) | (m.word_chars > m.n_words * MEAN_WORD[1])),
    Rule("repeated_lines", lambda m: m.n_dup_lines * 100 > m.n_lines * DUP_LINE_PERCENT),
    Rule("repeated_windows", lambda m: m.n_repeat_words * 100 > m.n_words * REPEAT_PERCENT, windows=True),
)


@dataclass(frozen=True)
class Estimate:
    rule: Rule
    cost: float
    rejection: float

    @property
    def rank(self) -> float:
        return self.rejection / max(self.cost, 1e-6)


def estimate(docs: DataFrame, text: str = "text", rules=RULES, sample_rows: int = SAMPLE_ROWS, seed: int = 17) -> list[Estimate]:
    """Cost and selectivity of each rule on a uniform sample of about ``sample_rows`` rows, best first."""
    total = docs.count()
    share = 1.0 if total <= sample_rows else sample_rows / total
    sample = materialise(docs.select(F.col(text).alias("t")).sample(False, share, seed).withColumn("n", count_words(F.col("t"))).repartition(1), "rule-sample")
    bare = _timed(sample, F.lit(True))[0]
    found = []
    for rule in rules:
        rows = with_repeat_words(sample, "t", "repeat") if rule.windows else sample
        known = {"n_words": F.col("n")} | ({"n_repeat_words": F.col("repeat")} if rule.windows else {})
        seconds, rate = _timed(rows, rule.rejects(Measures(F.col("t"), **known)))
        found.append(Estimate(rule, max(seconds - bare, 1e-4), rate))
    drop_materialised(sample)
    return sorted(found, key=lambda e: (-e.rank, e.rule.name))


def _timed(sample: DataFrame, test: Column) -> tuple[float, float]:
    began = time.perf_counter()
    rate = sample.agg(F.avg(F.when(test, 1.0).otherwise(0.0))).first()[0]
    return time.perf_counter() - began, rate or 0.0


def first_rejection(order: list[Estimate], m: Measures) -> Column:
    """The first rule in cascade order that rejects, null where none does; later rules are not evaluated."""
    out = None
    for e in order:
        test = e.rule.rejects(m)
        out = F.when(test, e.rule.name) if out is None else out.when(test, e.rule.name)
    return out if out is not None else F.lit(None).cast("string")


def judge(docs: DataFrame, text: str = "text", rules=RULES, sample_rows: int = SAMPLE_ROWS, out: str = "rejected_by", order: list[Estimate] | None = None) -> DataFrame:
    """``docs`` with the name of the first rule that rejects a row, in the estimated order (or the one given)."""
    order = estimate(docs, text, rules, sample_rows) if order is None else order
    at = next((i for i, e in enumerate(order) if e.rule.windows), len(order))
    marked = docs.withColumn("__bp_n", count_words(F.col(text)))
    why = first_rejection(order[:at], Measures(F.col(text), n_words=F.col("__bp_n")))
    if at < len(order):
        marked = marked.withColumn("__bp_why", why)
        marked = marked.withColumn("__bp_left", F.when(F.col("__bp_why").isNull(), F.col(text)))
        marked = with_repeat_words(marked, "__bp_left", "__bp_repeat")
        rest = Measures(F.col("__bp_left"), n_words=F.col("__bp_n"), n_repeat_words=F.col("__bp_repeat"))
        why = F.when(F.col("__bp_why").isNotNull(), F.col("__bp_why")).otherwise(first_rejection(order[at:], rest))
    return marked.select(*[F.col(f"`{c}`") for c in docs.columns if c != out], why.alias(out))


def filter_quality(docs: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that no rule rejects, all columns kept."""
    mark, fence = "__bp_verdict", "__bp_fence"
    # a filter pushed below would repeat whole array computations per element: a row number in the projection holds it
    judged = judge(docs, text, out=mark).withColumn(fence, F.monotonically_increasing_id())
    return judged.filter((F.col(fence) >= 0) & F.col(mark).isNull()).drop(mark, fence)


def op5_quality(spark, sf_dir: str) -> DataFrame:
    """All measures are asked for, so they are columns first; the cascade then runs over them in its estimated order."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    order = estimate(docs)
    t = F.col("text")
    measured = ("n_words", "word_chars", "n_symbols", "n_dup_lines")
    df = docs.withColumns({name: _EXPRESSIONS[name](t) for name in measured})
    df = with_repeat_words(df, "text", "n_repeat_words")
    known = Measures(t, **{name: F.col(name) for name in (*measured, "n_repeat_words")})
    by_name = {r.name: r.rejects(known) for r in RULES}
    df = df.withColumn("base_failed", by_name["few_words"] | by_name["repeated_windows"]).withColumn("kept", first_rejection(order, known).isNull())
    return df.select("doc_id", *measured, "n_repeat_words", "base_failed", "kept")


#: Measures of whole texts in DuckDB; {docs} is the relation to measure.
MEASURES_SQL = r"""
 numbered AS (SELECT row_number() OVER () AS row_id, doc_id, coalesce(text, '') AS text FROM {docs}),
 parts AS (SELECT row_id, doc_id, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
           list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM numbered),
 runs AS (SELECT row_id, unnest(range(1, len(w) - 3)) AS pos, w FROM parts WHERE len(w) >= 5),
 hashed AS (SELECT row_id, pos, array_to_string(w[pos:pos + 4], ' ') AS run FROM runs),
 twice AS (SELECT row_id, pos FROM (SELECT row_id, pos, count(*) OVER (PARTITION BY row_id, run) AS c FROM hashed) WHERE c > 1),
 cover AS (SELECT row_id, sum(least(5, pos - coalesce(prev, -9))) AS n
           FROM (SELECT row_id, pos, lag(pos) OVER (PARTITION BY row_id ORDER BY pos) AS prev FROM twice) GROUP BY row_id),
 measured AS (SELECT row_id, doc_id, CAST(len(w) AS BIGINT) AS n_words,
   CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
   CAST(len(regexp_extract_all(text, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
   CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, len(lines) AS n_lines,
   len(list_filter(w, lambda x: regexp_matches(x, '\p{L}'))) AS n_letter,
   CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words FROM parts LEFT JOIN cover USING (row_id)),
 judged AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
   n_symbols * 100 > n_words * 10 OR n_letter * 100 < n_words * 70 OR word_chars < n_words * 3 OR word_chars > n_words * 10
   OR n_dup_lines * 100 > n_lines * 40 AS rule_failed FROM measured)
"""

QUERIES = {"op5_quality": op5_quality}
ORACLES = {
    "op5_quality": "WITH "
    + MEASURES_SQL.replace("{docs}", "documents")
    + "SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT rule_failed AS kept FROM judged"
}
