"""Similarity of sets as column expressions, and the bounds that follow from the triangle inequality."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def jaccard(a: Column, b: Column) -> Column:
    """Shared over total elements of two sets; two empty sets have 0."""
    shared = F.size(F.array_intersect(a, b))
    total = F.size(a) + F.size(b) - shared
    return F.when(total > 0, shared / total).otherwise(F.lit(0.0))


def distance(a: Column, b: Column) -> Column:
    return 1 - jaccard(a, b)


def chain3(ab: Column, bc: Column) -> Column:
    """The least similarity of A and C that those of A, B and B, C allow."""
    return ab + bc - 1


def path_bound(sims: Column) -> Column:
    """The least similarity of the ends of a path, from those along it (an array)."""
    return F.aggregate(sims, F.lit(1.0), lambda acc, s: acc - (1 - s))


def candidate_probability(s: Column, b: int | Column, r: int | Column) -> Column:
    """Chance that two sets of similarity s agree in all r rows of one of b bands."""
    b, r = (F.lit(x) if isinstance(x, int) else x for x in (b, r))
    return 1 - F.pow(1 - F.pow(s, r), b)


def contained(a: Column, b: Column) -> Column:
    """Share of a's elements that b has too."""
    return F.when(F.size(a) > 0, F.size(F.array_intersect(a, b)) / F.size(a)).otherwise(F.lit(0.0))
