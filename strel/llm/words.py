"""Words and shingles of texts in DataFrame expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What stands between words: every ASCII character but digits and letters (lower-cased text).
SEPARATORS = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"
#: The same where A-Z are letters too.
SEPARATORS_ANY_CASE = "[\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+"


def words(text: Column) -> Column:
    """Lower-cased words of a text; null gives none."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda w: w != "")


def window_hashes(hashes: Column, width: int) -> Column:
    """Hashes of all runs of ``width`` neighbours of an array of word hashes; none if too short."""
    run = lambda i: F.xxhash64(F.lit(width), *[F.get(hashes, i + j) for j in range(width)])
    return F.when(F.size(hashes) >= width, F.transform(F.sequence(F.lit(0), F.size(hashes) - width), run)).otherwise(F.array().cast("array<long>"))


def window_texts(ws: Column, width: int) -> Column:
    """The runs themselves, words joined by a space."""
    run = lambda i: F.array_join(F.slice(ws, i + 1, width), " ")
    return F.when(F.size(ws) >= width, F.transform(F.sequence(F.lit(0), F.size(ws) - width), run)).otherwise(F.array().cast("array<string>"))
