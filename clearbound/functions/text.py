"""Text normalisation, tokens and shingles as built-in expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}_]+"


def normalize(text: Column) -> Column:
    """Lower case, LaTeX commands and delimiters to blanks, single blanks."""
    x = F.regexp_replace(F.lower(text), r"\\[a-z]+", " ")
    x = F.regexp_replace(x, r"[$(){}\[\],]", " ")
    return F.trim(F.regexp_replace(x, r"[ \t\n\r\f]+", " "))


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(WORD), F.lit(0))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once: inside a lambda a plain reference would
    be computed for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def grams(words: Column, k: int = 5) -> Column:
    """All k-grams in order; none where there are fewer than k words."""

    def body(w: Column) -> Column:
        some = F.transform(F.sequence(F.lit(1), F.size(w) - (k - 1)), lambda i: F.array_join(F.slice(w, i, k), " "))
        return F.when(F.size(w) >= k, some).otherwise(F.array().cast("array<string>"))

    return let(words, body)


def shingles(words: Column, k: int = 5) -> Column:
    return F.array_distinct(grams(words, k))


def shingle_hashes(words: Column, k: int = 5) -> Column:
    """Distinct k-grams as 64-bit hashes: a third of the bytes of the strings in a shuffle."""

    def body(w: Column) -> Column:
        some = F.transform(F.sequence(F.lit(1), F.size(w) - (k - 1)), lambda i: F.xxhash64(F.slice(w, i, k)))
        return F.when(F.size(w) >= k, some).otherwise(F.array().cast("array<bigint>"))

    return F.array_distinct(let(words, body))


def jaccard(a: Column, b: Column) -> Column:
    """|A n B| / |A u B| of two arrays without repeats; 0 if either is empty."""

    def body(s: Column) -> Column:
        inter = F.size(F.array_intersect(s["a"], s["b"]))
        return F.when((F.size(s["a"]) == 0) | (F.size(s["b"]) == 0), 0.0).otherwise(inter / (F.size(s["a"]) + F.size(s["b"]) - inter))

    return let(F.struct(a.alias("a"), b.alias("b")), body)


def lines(text: Column) -> Column:
    return F.split(text, "\n")


def md5_int(x: Column, digits: int = 8) -> Column:
    return F.conv(F.substring(F.md5(x), 1, digits), 16, 10).cast("bigint")
