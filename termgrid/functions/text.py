"""Tokens, bags of terms and keyword masks."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Characters between tokens (a fixed value of the default tokenizer).
BETWEEN = r"[^\p{L}\p{N}_#]+"


def tokenize(text: Column, kind: str | Callable[[Column], Column] = "alnum") -> Column:
    """Array of tokens in lower case; null texts give an empty array.

    ``alnum`` splits at anything but letters, digits, ``_`` and ``#``; ``whitespace`` at white space; ``sentences`` uses
    the built-in sentence splitter; a callable is any other tokenizer as a column expression (or an Arrow UDF).
    """
    low = F.lower(F.coalesce(text, F.lit("")))
    if callable(kind):
        return kind(low)
    if kind == "sentences":
        return F.flatten(F.sentences(low))
    parts = F.split(low, BETWEEN if kind == "alnum" else r"\s+")
    return F.filter(parts, lambda t: t != "")


def text_of(columns: Sequence[str]) -> Column:
    """The text of a tuple: its text attributes in a row."""
    return F.concat_ws(" ", *[F.col(c).cast("string") for c in columns])


def without(terms: Column, words: Sequence[str]) -> Column:
    """A bag of terms less every occurrence of ``words``."""
    if not words:
        return terms
    gone = F.array(*[F.lit(w) for w in words])
    return F.filter(terms, lambda t: ~F.array_contains(gone, t))


def count_in(terms: Column, word: str) -> Column:
    """Occurrences of a word in a bag."""
    return F.size(F.filter(terms, lambda t: t == word)).cast("long")


def keyword_mask(terms: Column, keywords: Sequence[str]) -> Column:
    """Bit i is set if the bag holds keyword i."""
    if len(keywords) > 62:
        raise ValueError("at most 62 keywords")
    mask = F.lit(0).cast("long")
    for i, word in enumerate(keywords):
        mask = mask + F.array_contains(terms, word).cast("long") * F.lit(1 << i).cast("long")
    return mask


def term_counts(terms: Column) -> Column:
    """A bag as a map of counts: terms are sorted, and each run of equal ones counts, n log n in the length of the bag."""
    def counted(s: Column) -> Column:
        starts = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda i: (i == 0) | (F.get(s, i) != F.get(s, i - 1)))
        runs = lambda b: F.map_from_arrays(F.transform(b, lambda i: F.get(s, i)), F.transform(b, lambda i, k: (F.coalesce(F.get(b, k + 1), F.size(s)) - i).cast("long")))
        return F.get(F.transform(F.array(starts), runs), F.lit(0))

    # arrays of one element bind the sorted bag and the starts, so that lambdas index values
    bag = F.get(F.transform(F.array(F.array_sort(terms)), counted), F.lit(0))
    return F.when(F.size(terms) > 0, bag).otherwise(F.create_map().cast("map<string,bigint>"))
