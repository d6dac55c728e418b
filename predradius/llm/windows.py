"""Word windows and their hashes, built from SQL functions only."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once per row: the optimizer would copy it into every lambda that names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def starts(n_words: Column, width: int) -> Column:
    """0, 1, … of every window of `width` words; an empty array if there is none."""
    return F.when(n_words >= width, F.sequence(F.lit(0), n_words - width)).otherwise(F.array().cast("array<int>"))


def window_hashes(words: Column, width: int) -> Column:
    """One 64-bit hash per window of `width` consecutive elements."""
    return let(words, lambda own: F.transform(starts(F.size(own), width), lambda i: F.xxhash64(F.slice(own, i + 1, width))))


def plain_words(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    spaced = F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " "))
    return F.when(spaced == "", F.array().cast("array<string>")).otherwise(F.split(spaced, " "))
