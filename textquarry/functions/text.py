"""Text pieces as Column expressions: words, sentences, n-grams, hashes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, use) -> Column:
    """Bind a value to a variable, so that lambdas inside *use* do not compute it for every element."""
    return F.element_at(F.transform(F.array(value), use), 1)


def words(text: Column) -> Column:
    """Non-empty pieces between white space."""
    return F.filter(F.split(text, r"\s+"), lambda w: w != "")


def folded_words(text: Column) -> Column:
    """Lower-case runs of letters, digits and underscore."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}_]+"), lambda w: w != "")


def sentences(text: Column) -> Column:
    """Pieces that end at a line break or after a final mark."""
    broken = F.regexp_replace(text, r"([.!?…।])\s+", "$1\n")
    return F.filter(F.transform(F.split(broken, "\n"), lambda s: F.trim(s)), lambda s: s != "")


def lines(text: Column) -> Column:
    return F.split(text, "\n")


def ngrams(items: Column, n: int, joiner: str = " ") -> Column:
    """All n-grams as joined strings; shorter inputs give one gram of everything, empty ones none."""

    def make(a: Column) -> Column:
        many = F.transform(F.sequence(F.lit(1), F.size(a) - n + 1), lambda i: F.array_join(F.slice(a, i, F.lit(n)), joiner))
        return F.when(F.size(a) >= n, many).when(F.size(a) > 0, F.array(F.array_join(a, joiner))).otherwise(F.array().cast("array<string>"))

    return let(items, make)


def repeated_share(items: Column, least: int = 2) -> Column:
    """Occurrences of items seen *least* times or more over all occurrences; 0 without items.

    Works on the sorted array, so it costs n log n per document instead of a look-up per item.
    """

    def share(s: Column) -> Column:
        n = F.size(s)
        at = lambda i: F.get(s, i - 1)  # noqa: E731  null outside the array

        def often(i: Column) -> Column:
            hit = F.lit(False)
            for k in range(least):
                hit = hit | F.coalesce(at(i - k) == at(i - k + least - 1), F.lit(False))
            return hit

        return F.when(n > 0, F.size(F.filter(F.sequence(F.lit(1), n), often)) / n).otherwise(F.lit(0.0))

    return let(F.array_sort(items), share)


def md5_int(value: Column) -> Column:
    """First 8 hex digits of md5 as a number; equal in other SQL engines."""
    return F.conv(F.substring(F.md5(value.cast("string").cast("binary")), 1, 8), 16, 10).cast("long")


def char_grams(text: Column, n: int) -> Column:
    """All runs of n characters."""
    return F.when(F.length(text) >= n, ngrams(F.filter(F.split(text, ""), lambda c: c != ""), n, "")).otherwise(F.array().cast("array<string>"))
