"""Shingles, options of multiple-choice items, format measures."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Lines such as "A) text" or "(B) text", or three or more cells between bars.
OPTION_LINE = r"(?m)^[ \t]*\(?([A-H])[).:][ \t]+(.+?)[ \t]*$"


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once: a lambda variable, which the optimizer cannot copy into inner lambdas."""
    return F.transform(F.array(value), body)[0]


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[ \t\r\n]+"), lambda w: w != "")


def shingles(text: Column, n: int) -> Column:
    """Distinct runs of n words; the whole sequence if it is shorter, none if it is empty."""
    def of(w: Column) -> Column:
        full = F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, n), " "))
        return F.when(F.size(w) >= n, F.array_distinct(full)).when(F.size(w) > 0, F.array(F.array_join(w, " "))).otherwise(F.array().cast("array<string>"))

    return let(words(text), of)


def hashed_shingles(text: Column, n: int) -> Column:
    """The same as 64-bit hashes of word hashes: joins and distinct sets move eight bytes for each."""
    def of(w: Column) -> Column:
        full = F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.xxhash64(F.slice(w, i, n)))
        return F.when(F.size(w) >= n, F.array_distinct(full)).when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))

    return let(F.transform(words(text), lambda x: F.xxhash64(x)), of)


def placed_runs(text: Column, n: int) -> Column:
    """(at, g, size) of each run of n words: its place, a hash of it, and the text's number of words; the whole sequence if it is shorter.

    The number is part of each entry: as a column beside a generator it would be computed anew for every row that comes out.
    """
    def of(w: Column) -> Column:
        entry = lambda at, run: F.struct(at.alias("at"), F.xxhash64(run).alias("g"), F.size(w).alias("size"))
        full = F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: entry(i, F.slice(w, i + 1, n)))
        return F.when(F.size(w) >= n, full).when(F.size(w) > 0, F.array(entry(F.lit(0), w)))

    return let(F.transform(words(text), lambda x: F.xxhash64(x)), of)


def count_cosine(a: Column, b: Column) -> Column:
    """Cosine of the counts of two short arrays' elements."""
    times = lambda x, e: F.size(F.filter(x, lambda y: y == e))
    product = lambda x, y: F.aggregate(F.array_distinct(x), F.lit(0), lambda s, e: s + times(x, e) * times(y, e))
    return product(a, b) / (F.sqrt(product(a, a)) * F.sqrt(product(b, b)))


def char_grams(text: Column, n: int) -> Column:
    return F.when(F.length(text) >= n, F.transform(F.sequence(F.lit(1), F.length(text) - (n - 1)), lambda i: F.substring(text, i, n))).otherwise(F.array().cast("array<string>"))


def option_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(OPTION_LINE))


def bar_cells(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit("|"), F.lit("")))


def is_multi_option(text: Column) -> Column:
    """Two or more option lines, or cells between bars."""
    return F.coalesce((option_count(text) >= 2) | (bar_cells(text) >= 2), F.lit(False))


def option_letters(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(OPTION_LINE), F.lit(1))


def option_texts(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(OPTION_LINE), F.lit(2))
