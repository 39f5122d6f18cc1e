"""Quality rules: a threshold table compiled into one projection of built-in functions.

A rule names a measure of the text and the range it must stay in. Compiling
the table gives one struct column: measures are computed once a row, and every
rule is a comparison on them, so a scan of the text column is all there is.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.llm.common import SPACE, let, lower_ascii

WINDOW = 8
SYMBOLS = "#*$%&|<>"

#: Frequent function words of English, French, German and Spanish.
STOP_WORDS = (
    "the", "of", "and", "to", "in", "is", "it", "that", "for", "was", "on", "with", "as", "are", "be",
    "de", "la", "le", "les", "et", "des", "un", "une", "que", "du", "en", "pour", "par", "sur", "qui",
    "der", "die", "und", "den", "von", "zu", "das", "mit", "ist", "im", "auf", "ein", "dem", "nicht",
    "el", "los", "las", "del", "se", "con", "por", "su", "para", "al", "no", "una", "lo",
)


@dataclass(frozen=True)
class Rule:
    """The text passes if at least <= measure <= most (None: open)."""

    name: str
    measure: str
    at_least: float | None = None
    at_most: float | None = None


#: The production table. Measures: see measures().
TABLE: tuple[Rule, ...] = (
    Rule("words", "n_words", at_least=20),
    Rule("repeats", "repeat_percent", at_most=30),
    Rule("word_length", "mean_word_chars", 2.0, 12.0),
    Rule("symbols", "symbols_per_word", at_most=0.3),
    Rule("stop_words", "stop_word_share", at_least=0.02),
    Rule("duplicate_lines", "dup_line_share", at_most=0.5),
    Rule("capitals", "capital_share", at_most=0.5),
)
#: Of the table, those that the contract fixes.
BASE = ("words", "repeats")


def _repeat_words(words: Column) -> Column:
    """Words inside windows of WINDOW words that occur twice or more, by window hashes.

    A hash set tells whether any window repeats; only then are the hashes
    sorted with their places: O(n) for most texts, O(n log n) at worst.
    """
    hashes = F.transform(F.sequence(F.lit(0), F.size(words) - WINDOW), lambda i: F.xxhash64(F.slice(words, i + 1, F.lit(WINDOW))))
    twice = lambda a: F.filter(a, lambda x, i: (F.get(a, i - 1)["h"] == x["h"]) | F.coalesce(F.get(a, i + 1)["h"] == x["h"], F.lit(False)))
    covered = lambda p: F.aggregate(
        F.transform(p, lambda x, i: F.least(F.lit(WINDOW), F.coalesce(F.get(p, i + 1) - x, F.lit(WINDOW)))), F.lit(0), lambda a, x: a + x
    )
    placed = lambda h: F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("p"))))
    places = lambda h: let(placed(h), lambda a: F.array_sort(F.transform(twice(a), lambda x: x["p"])))
    counted = let(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(let(places(h), covered)))
    return F.when(F.size(words) <= WINDOW, F.lit(0)).otherwise(counted)


def _counts(text: Column) -> Column:
    """Struct of counts (bigint) from one text: words and lines are split once each."""
    def of_words(w: Column) -> Column:
        return F.struct(
            F.size(w).cast("bigint").alias("n_words"),
            F.char_length(F.translate(text, " \t\n\x0b\x0c\r", "")).cast("bigint").alias("word_chars"),
            (F.char_length(text) - F.char_length(F.translate(text, SYMBOLS, ""))).cast("bigint").alias("n_symbols"),
            _repeat_words(w).cast("bigint").alias("n_repeat_words"),
            F.size(F.filter(F.split(lower_ascii(text), "[^a-z\\x{80}-\\x{10FFFF}]+", -1), lambda x: x.isin(*STOP_WORDS))).cast("bigint").alias("n_stop_words"),
            F.regexp_count(text, F.lit(f"(?:^|[{SPACE}])[A-Z]{{2}}")).cast("bigint").alias("n_capital_words"),
            let(F.filter(F.split(text, "\n", -1), lambda x: x.rlike(f"[^{SPACE}]")), lambda n: F.struct(F.size(n).cast("bigint").alias("n"), (F.size(n) - F.size(F.array_distinct(n))).cast("bigint").alias("dup"))).alias("lines"),
        )

    return let(F.filter(F.split(text, f"[{SPACE}]+", -1), lambda x: x != ""), of_words)


def compile_rules(text: Column, table: Sequence[Rule] = TABLE) -> Column:
    """One struct column: the counts, the ratios, failed (names of failed rules, in table order)."""
    per = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))

    def with_ratios(c: Column) -> Column:
        return F.struct(
            *(c[x].alias(x) for x in ("n_words", "word_chars", "n_symbols", "n_repeat_words")), c["lines"]["dup"].alias("n_dup_lines"),
            per(100.0 * c["n_repeat_words"], c["n_words"]).alias("repeat_percent"), per(c["word_chars"], c["n_words"]).alias("mean_word_chars"),
            per(c["n_symbols"], c["n_words"]).alias("symbols_per_word"), per(c["n_stop_words"], c["n_words"]).alias("stop_word_share"),
            per(c["lines"]["dup"], c["lines"]["n"]).alias("dup_line_share"), per(c["n_capital_words"], c["n_words"]).alias("capital_share"),
        )

    def judged(m: Column) -> Column:
        fails = []
        for r in table:
            low = [m[r.measure] < F.lit(r.at_least)] if r.at_least is not None else []
            high = [m[r.measure] > F.lit(r.at_most)] if r.at_most is not None else []
            for bad in low + high:
                fails.append(F.when(bad, F.lit(r.name)))
        return F.struct(m.alias("m"), F.filter(F.array(*fails), lambda x: x.isNotNull()).alias("failed"))

    return let(let(_counts(F.coalesce(text, F.lit(""))), with_ratios), judged)


def judge_quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", table: Sequence[Rule] = TABLE) -> DataFrame:
    """Counts, base_failed, kept, failed (comma-joined names) for every row.

    Null and empty texts have no words and fail. Repeated rows give repeated
    rows. Hashes of equal windows are equal; that two different windows share
    all 64 bits is left out of account.
    """
    own = docs.select(docs[id_col].cast("bigint").alias("doc_id"), compile_rules(docs[text_col].cast("string"), table).alias("q"))
    m, names = F.col("q.m"), F.col("q.failed")
    base = (m["n_words"] < 20) | (100 * m["n_repeat_words"] > 30 * m["n_words"])
    return own.select(
        "doc_id", *(m[c].alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")),
        base.alias("base_failed"), (~base & (F.size(names) == 0)).alias("kept"), F.array_join(names, ",").alias("failed"),
    )


def oracle(table: Sequence[Rule] = TABLE) -> str:
    """The same by DuckDB SQL over unnested words and lines."""
    fails = []
    for r in table:
        for bound, sign in ((r.at_least, "<"), (r.at_most, ">")):
            if bound is not None:
                fails.append(f"CASE WHEN {r.measure} {sign} {float(bound)} THEN '{r.name}' END")
    stops = ", ".join(f"'{w}'" for w in STOP_WORDS)
    az = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
    ratio = lambda a, b: f"CASE WHEN {b} > 0 THEN {a}::DOUBLE / {b} ELSE 0 END"
    return f"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT k, w, p FROM (SELECT k, unnest(l) AS w, unnest(range(len(l))) AS p FROM (SELECT k, regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+') AS l FROM d))),
g AS (SELECT k, p, string_agg(w, ' ') OVER (PARTITION BY k ORDER BY p ROWS BETWEEN CURRENT ROW AND {WINDOW - 1} FOLLOWING) AS gram,
  count(*) OVER (PARTITION BY k ORDER BY p ROWS BETWEEN CURRENT ROW AND {WINDOW - 1} FOLLOWING) AS n FROM w),
r AS (SELECT k, p, count(*) OVER (PARTITION BY k, gram) AS c FROM g WHERE n = {WINDOW}),
v AS (SELECT k, p, max(CASE WHEN c > 1 THEN 1 ELSE 0 END) OVER (PARTITION BY k ORDER BY p RANGE BETWEEN {WINDOW - 1} PRECEDING AND CURRENT ROW) AS hit FROM (SELECT w.k, w.p, coalesce(r.c, 0) AS c FROM w LEFT JOIN r USING (k, p))),
rep AS (SELECT k, sum(hit)::BIGINT AS n_repeat_words FROM v GROUP BY k),
ws AS (SELECT k, count(*) AS n_words, sum(length(w))::BIGINT AS word_chars, sum(length(regexp_replace(w, '[^#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
  sum(regexp_matches(w, '^[A-Z]{{2}}')::INT)::BIGINT AS n_capital_words FROM w GROUP BY k),
sw AS (SELECT k, count(*) AS n_stop_words FROM (SELECT k, unnest(regexp_extract_all(translate(text, {az}), '[a-z\\x{{80}}-\\x{{10FFFF}}]+')) AS x FROM d) WHERE x IN ({stops}) GROUP BY k),
ls AS (SELECT k, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT k, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]') GROUP BY k),
m AS (SELECT doc_id, coalesce(n_words, 0) AS n_words, coalesce(word_chars, 0) AS word_chars, coalesce(n_symbols, 0) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words,
  {ratio('100.0 * n_repeat_words', 'n_words')} AS repeat_percent, {ratio('word_chars', 'n_words')} AS mean_word_chars, {ratio('n_symbols', 'n_words')} AS symbols_per_word,
  {ratio('coalesce(n_stop_words, 0)', 'n_words')} AS stop_word_share, {ratio('n_dup_lines', 'n_lines')} AS dup_line_share, {ratio('n_capital_words', 'n_words')} AS capital_share
  FROM d LEFT JOIN ws USING (k) LEFT JOIN ls USING (k) LEFT JOIN sw USING (k) LEFT JOIN rep USING (k)),
j AS (SELECT *, (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed, concat_ws(',', {', '.join(fails)}) AS failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND failed = '') AS kept, failed FROM j"""
