"""Column expressions shared by the operators that run without Python on the executors."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What separates words: ASCII characters other than letters and digits. With capitals left alone, words break at the same places.
SEPARATOR = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    """The words of a text as they stand; none for null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SEPARATOR, -1), "")


def lower_ascii(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def word_hashes(list_of_words: Column) -> Column:
    """A hash of each word without regard to case. Only a filter: lower() folds more than A-Z, and hits are compared anew."""
    return F.transform(list_of_words, lambda w: F.xxhash64(F.lower(w)))


def gram(hashes: Column, at: Column, k: int) -> Column:
    """Hash of the k words from place `at` (from 0)."""
    return F.xxhash64(*[F.get(hashes, at + i) for i in range(k)])


def run_of(list_of_words: Column, at: Column, k: int | Column) -> Column:
    """The k words from place `at`, ASCII lower case, with blanks between."""
    return lower_ascii(F.array_join(F.slice(list_of_words, at + 1, k), " "))


def fixed(value: Column) -> Column:
    """The value, made so that the optimizer cannot look through it. It and costly expressions beside it in a projection stay where
    they are, sharing their parts; else they would be copied into filters and branches and computed there again and again."""
    return F.when(F.rand(0) < 2, value)
