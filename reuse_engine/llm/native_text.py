"""Column expressions on whole texts: words, five-word windows, lines (built-in functions only)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WIDTH = 5
#: White space of the contracts.
SPACE = r"[\x20\x09-\x0D]"
NON_SPACE = r"[^\x20\x09-\x0D]"


def words(text: Column, separators: str = SPACE + "+") -> Column:
    """Words of a text in order; null or wordless gives an empty array."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), separators), "")


def window_hashes(words_col: str) -> Column:
    """A 64-bit hash for each window of five words, in order, repeats included.

    One to four words give one hash of the whole sequence; no word gives none.
    """
    w = F.col(words_col)
    n = F.size(w)
    at = F.transform(
        F.sequence(F.lit(0), n - WIDTH),
        lambda i: F.xxhash64(*[F.get(F.col(words_col), i + k) for k in range(WIDTH)]),
    )
    return F.when(n >= WIDTH, at).when(n > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))


def lines(text: Column) -> Column:
    """``\\n``-split lines that hold a word."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda line: line.rlike(NON_SPACE))
