"""Shingles, words, bags, sets and token weights; all row-local but idf."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.functions.hashing import WIDTH, base32


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(v) with v computed once a row."""
    return F.transform(F.array(value), body)[0]


def char_grams(text: Column, k: int) -> Column:
    """Bag of contiguous k-character substrings, in order; shorter texts have none."""
    grams = F.transform(F.sequence(F.lit(1), F.length(text) - (k - 1)), lambda i: F.substring(text, i, F.lit(k)))
    return F.when(F.length(text) >= k, grams).otherwise(F.array().cast("array<string>"))


def words(text: Column) -> Column:
    """Runs of letters and digits of the lower-cased text."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[\\p{L}\\p{N}]+"), F.lit(0))


def word_grams(text: Column, n: int) -> Column:
    """Bag of n consecutive words joined by blanks."""
    return let(words(text), lambda w: F.when(
        F.size(w) >= n, F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, F.lit(n)), " "))
    ).otherwise(F.array().cast("array<string>")))


def counts(bag: Column) -> Column:
    """array<struct<tok, cnt>> by token, from runs of the sorted bag."""
    def runs(s: Column) -> Column:
        starts = F.filter(F.transform(s, lambda x, i: F.when((i == 0) | (F.get(s, i - 1) != x), i)), lambda i: i.isNotNull())
        return let(starts, lambda at: F.transform(at, lambda i, j: F.struct(F.get(s, i).alias("tok"), (F.coalesce(F.get(at, j + 1), F.size(s)) - i).alias("cnt"))))

    return let(F.array_sort(bag), runs)


def distinct_hashes(bag: Column, hash_of: Callable[[Column], Column] = base32) -> Column:
    """Sorted distinct token hashes: the record as a set."""
    return F.array_sort(F.array_distinct(F.transform(F.array_distinct(bag), hash_of)))


def hashed_counts(bag: Column, hash_of: Callable[[Column], Column] = base32) -> Column:
    """array<struct<h, cnt>>: the record as a weighted set."""
    return F.transform(counts(bag), lambda e: F.struct(hash_of(e["tok"]).alias("h"), e["cnt"].alias("cnt")))


def gram_keys(text: Column, n: int) -> Column:
    """array<bigint>: 64-bit hashes of the word n-grams, with repeats; words are hashed together, so no gram is ever built as text."""
    return let(words(text), lambda w: F.when(
        F.size(w) >= n, F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.xxhash64(*(F.get(w, i + j) for j in range(n))))
    ).otherwise(F.array().cast("array<bigint>")))


def fast_gram_counts(text: Column, n: int) -> Column:
    """array<struct<h, cnt>> of word n-grams by the fast hash: words are hashed together, so no gram is ever built as text."""
    grams = let(words(text), lambda w: F.when(
        F.size(w) >= n, F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.xxhash64(*(F.get(w, i + j) for j in range(n))).bitwiseAND(F.lit(WIDTH - 1)))
    ).otherwise(F.array().cast("array<bigint>")))
    return F.transform(counts(grams), lambda e: F.struct(e["tok"].alias("h"), e["cnt"].alias("cnt")))


def tagged(parts: Sequence[tuple[str, Column]]) -> Column:
    """One bag of field-tagged tokens; parts: (tag, array of tokens)."""
    none = F.array().cast("array<string>")
    marked = lambda tag: lambda x: F.concat(F.lit(tag + ":"), x)  # noqa: E731  one parameter: a second would be the index
    return F.concat(*(F.transform(F.coalesce(bag, none), marked(tag)) for tag, bag in parts))


def report_tokens(k: int = 2) -> Column:
    """Tagged tokens of a report: character grams of both names, month and day of the event, place."""
    day = F.col("event_date")
    single = lambda c: F.when(c.isNotNull(), F.array(c.cast("string")))
    return tagged((
        ("g", char_grams(F.col("given"), k)), ("f", char_grams(F.col("family"), k)),
        ("m", single(F.date_format(day, "yyyy-MM"))), ("d", single(F.dayofmonth(day))), ("p", single(F.col("place"))),
    ))


def long_form(df: DataFrame, id_col: str, bag: Column) -> DataFrame:
    """(rec_id, tok, cnt), one row a record and token."""
    return df.select(F.col(id_col).alias("rec_id"), F.explode(counts(bag)).alias("e")).select("rec_id", "e.tok", "e.cnt")


def idf(long: DataFrame, n: int | Column) -> DataFrame:
    """(tok, df, idf) with idf = ln((n+1)/(df+1)); one shuffle over distinct tokens, with partial sums before it."""
    n = F.lit(n) if isinstance(n, int) else n
    return long.groupBy("tok").agg(F.count("*").alias("df")).select("tok", "df", F.log((n + 1) / (F.col("df") + 1)).alias("idf"))
