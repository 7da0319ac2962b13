"""Token tags and the similarity of two foods, as Column functions on token arrays."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from pantry.functions import lexicons as lx

NUMBER = r"^[0-9./%]+$"


def _adjective(t: Column) -> Column:
    return t.isin(*lx.ADJECTIVES) | (~t.isin(*lx.NOUNS) & ~t.isin(*lx.VERBS) & t.rlike(r"^\p{L}{3,}(?:ous|al|y)$"))


def _verb(t: Column) -> Column:
    return t.isin(*lx.VERBS) | (~t.isin(*lx.NOUNS) & ~t.isin(*lx.ADJECTIVES) & t.rlike(r"^\p{L}{3,}(?:ed|ing)$"))


def tag(t: Column) -> Column:
    """number, verb, adjective or noun: lexicon first, then endings, else noun."""
    return F.when(t.rlike(NUMBER), "number").when(_verb(t), "verb").when(_adjective(t), "adjective").otherwise("noun")


def tagged(tokens: Column, kind: str) -> Column:
    """Sorted set of the tokens of a kind."""
    return F.array_sort(F.array_distinct(F.filter(tokens, lambda t: tag(t) == kind)))


def jaccard(a: Column, b: Column) -> Column:
    """Common over all; NULL where both are empty."""
    return F.try_divide(F.size(F.array_intersect(a, b)).cast("double"), F.size(F.array_union(a, b)))


def smoothed(a: Column, b: Column) -> Column:
    return (F.size(F.array_intersect(a, b)) + 1) / (F.size(F.array_union(a, b)) + 2)


def other_ratio(verbs: Column, adjectives: Column, numbers: Column, verbs_j: Column, adjectives_j: Column, numbers_j: Column, mode: str = "symmetric") -> Column:
    """Smoothed ratio of verbs, adjectives and numbers; ``as_printed`` takes the item's adjectives on both sides."""
    own = adjectives if mode == "symmetric" else adjectives_j
    return smoothed(F.array_union(F.array_union(verbs, own), numbers), F.array_union(F.array_union(verbs_j, adjectives_j), numbers_j))


def similarity_index(nouns: Column, nouns_j: Column, other: Column) -> Column:
    return jaccard(nouns, nouns_j) * other
