"""Similarities of strings as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..sources.corpus import NOT_TOKEN


def tokens(col: Column) -> Column:
    """Lower-case tokens of letters and digits."""
    return F.filter(F.split(F.lower(col), NOT_TOKEN), lambda x: x != "")


def edit_ratio(a: Column, b: Column) -> Column:
    """One minus the edit distance over the longer length; two empty strings are equal."""
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longest)


def jaccard(a: Column, b: Column) -> Column:
    """Shared tokens over all tokens."""
    return set_jaccard(token_set(a), token_set(b))


def token_set(col: Column) -> Column:
    """Tokens, each once."""
    return F.array_distinct(tokens(col))


def set_jaccard(x: Column, y: Column) -> Column:
    """The same of two token sets, where they are made once and compared often."""
    shared = F.size(F.array_intersect(x, y))
    n = F.size(x) + F.size(y) - shared
    return F.when(n == 0, 0.0).otherwise(shared / n)
