"""Quality rules as a short-circuit cascade, in DataFrame functions only.

Base measures are computed for every document.  The further rules are ordered by rejections per cost, both estimated
on a sample, and evaluated as one CASE: a document that an early rule rejects never pays for a later one.  The order
changes the cost only, never the verdict, which is the disjunction of all rules.

Null texts have no words; with fewer than ``MIN_WORDS`` words they fail the base rules.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE_PATTERN

WINDOW = 8
MIN_WORDS, MAX_REPEATED = 20, 30
#: White space of the contract, and its symbols.
SPACES, SYMBOLS = " \t\n\x0b\x0c\r", "#*$%&|<>"
#: Rows of the sample on which cost and selectivity are estimated.
SAMPLE_ROWS = 400


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once: a lambda variable is never inlined into the loops that use it."""
    return F.transform(F.array(value), body)[0]


def words_of(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(SPACES))
    return F.when(F.length(trimmed) == 0, F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_PATTERN))


def repeated_words(words: Column, window: int = WINDOW) -> Column:
    """Words that lie in a window found twice or more.  Windows are compared by a 64-bit hash of their words' hashes."""

    def covered(hashes: Column) -> Column:
        # windows sorted with their positions: equal neighbours are repeats; then the union of their spans is measured
        def spans(ordered: Column) -> Column:
            n = F.size(ordered)
            same = F.transform(
                ordered,
                lambda e, i: F.when(((i > 0) & (F.get(ordered, F.greatest(i - 1, F.lit(0)))["h"] == e["h"])) | ((i + 1 < n) & (F.get(ordered, F.least(i + 1, n - 1))["h"] == e["h"])), e["at"]),
            )
            return let(F.array_sort(F.filter(same, lambda p: p.isNotNull())), lambda at: F.aggregate(at, F.struct(F.lit(0).alias("sum"), F.lit(-window).alias("last")), lambda s, p: F.struct((s["sum"] + F.least(F.lit(window), p - s["last"])).alias("sum"), p.alias("last")))["sum"])

        return let(F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("at")))), spans)

    def windows(coded: Column) -> Column:
        every = F.transform(F.sequence(F.lit(1), F.size(coded) - (window - 1)), lambda i: F.xxhash64(F.slice(coded, i, window)))
        return let(every, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(covered(w)))

    return let(words, lambda ws: F.when(F.size(ws) < window + 1, F.lit(0)).otherwise(let(F.transform(ws, lambda w: F.xxhash64(w)), windows))).cast("long")


def duplicate_lines(text: Column) -> Column:
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.btrim(x, F.lit(SPACES))) > 0)
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long")


def symbol_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit("[#*$%&|<>]")).cast("long")


def measures(docs: DataFrame) -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    text = F.coalesce(F.col("text"), F.lit(""))
    out = docs.withColumn("_words", words_of(text))
    out = out.withColumns(
        {
            "n_words": F.size("_words").cast("long"),
            "word_chars": F.length(F.translate(text, SPACES, "")).cast("long"),
            "n_symbols": symbol_count(text),
            "n_dup_lines": duplicate_lines(text),
            "n_repeat_words": repeated_words(F.col("_words")),
        }
    )
    return out.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEATED * F.col("n_words")))


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Column


def further_rules() -> list[Rule]:
    """Thresholds lie far from what well-formed prose shows; columns are those of ``measures``."""
    n, chars, words, text = F.col("n_words"), F.col("word_chars"), F.col("_words"), F.coalesce(F.col("text"), F.lit(""))
    return [
        Rule("symbols", 20 * F.col("n_symbols") > chars),
        Rule("repeated_lines", 2 * F.col("n_dup_lines") > F.size(F.split(text, "\n"))),
        Rule("word_length", (chars > 15 * n) | (2 * chars < 5 * n)),
        Rule("capitals", 2 * F.regexp_count(text, F.lit(r"\p{Lu}")) > chars),
        Rule("few_distinct_words", 10 * F.size(F.array_distinct(words)) < 3 * F.least(n, F.lit(1000))),
        Rule("words_without_letters", 2 * F.size(F.filter(words, lambda w: w.rlike(r"\p{L}"))) < n),
    ]


def ranked_rules(measured: DataFrame, rules: list[Rule], sample_rows: int = SAMPLE_ROWS) -> list[tuple[Rule, float, float]]:
    """Rules by rejections per cost, with (cost in seconds, share rejected) on a sample of ``sample_rows`` rows."""
    needed = measured.select("text", "_words", "n_words", "word_chars", "n_symbols", "n_dup_lines").limit(sample_rows)
    held = measured.sparkSession.createDataFrame(needed.collect(), needed.schema).coalesce(1).cache()  # bounded by sample_rows
    total = max(1, held.count())
    found = []
    for rule in rules:
        shares = []
        for _ in range(2):  # the first run compiles
            began = time.perf_counter()
            hits = held.agg(F.sum(F.when(rule.rejects, 1).otherwise(0))).first()[0] or 0
            shares.append(time.perf_counter() - began)
        found.append((rule, min(shares), hits / total))
    held.unpersist()
    return sorted(found, key=lambda x: (-(x[2] + 1e-6) / x[1], x[0].name))


def cascade(order: list[Rule]) -> Column:
    verdict = F.when(F.col("base_failed"), False)
    for rule in order:
        verdict = verdict.when(rule.rejects, False)
    return verdict.otherwise(True)


def judged(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """docs with the measures, ``base_failed`` and ``kept``."""
    measured = measures(docs)
    order = [rule for rule, _, _ in ranked_rules(measures(docs.limit(sample_rows)), further_rules(), sample_rows)]
    return measured.withColumn("kept", cascade(order)).drop("_words")


def kept(docs: DataFrame) -> DataFrame:
    """The rows of docs that pass, with the columns of docs, whatever their names."""
    held = docs.select(F.struct("*").alias("_document"), "text")
    return judged(held).where("kept").select("_document.*")


ORACLE_SQL = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
         string_split(coalesce(text, ''), chr(10)) AS lines FROM documents
), spans AS (
  SELECT doc_id, i, array_to_string(list_slice(w, i, i + 7), ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 6))) AS i FROM d)
), repeats AS (
  SELECT doc_id, i FROM spans QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1
), covered AS (
  SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM repeats) GROUP BY doc_id
), m AS (
  SELECT d.doc_id, d.text, d.w, CAST(len(w) AS BIGINT) AS n_words,
         CAST(length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
         CAST(length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(len(list_filter(lines, lambda x: regexp_matches(x, '[^\x20\x09-\x0D]'))) - len(list_distinct(list_filter(lines, lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))) AS BIGINT) AS n_dup_lines,
         len(lines) AS n_lines, CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words
  FROM d LEFT JOIN covered c ON c.doc_id = d.doc_id
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
       NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words OR 20 * n_symbols > word_chars OR 2 * n_dup_lines > n_lines
            OR word_chars > 15 * n_words OR 2 * word_chars < 5 * n_words
            OR 2 * length(regexp_replace(text, '\P{Lu}+', '', 'g')) > word_chars
            OR 10 * len(list_distinct(w)) < 3 * least(n_words, 1000)
            OR 2 * len(list_filter(w, lambda x: regexp_matches(x, '\p{L}'))) < n_words) AS kept
FROM m
"""
