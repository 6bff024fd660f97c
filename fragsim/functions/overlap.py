"""Overlap of action bags and the integer predicates on it."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bag_overlap(a: Column, b: Column, element: str = "bag") -> Column:
    """Shared actions of two maps action -> frequency.

    ``bag`` sums the smaller frequencies, ``pair`` counts actions with equal frequency, ``set`` counts
    common actions.
    """
    value = {
        "bag": lambda k, x, y: F.least(F.coalesce(x, F.lit(0)), F.coalesce(y, F.lit(0))).cast("long"),
        "pair": lambda k, x, y: F.when(x == y, 1).otherwise(0).cast("long"),
        "set": lambda k, x, y: F.when(x.isNotNull() & y.isNotNull(), 1).otherwise(0).cast("long"),
    }[element]
    return F.aggregate(F.map_values(F.map_zip_with(a, b, value)), F.lit(0).cast("long"), lambda s, v: s + v)


def denominator(total_q: Column, total_c: Column, overlap: Column, denom: str) -> Column:
    return {
        "min": lambda: F.least(total_q, total_c),
        "max": lambda: F.greatest(total_q, total_c),
        "query": lambda: total_q,
        "union": lambda: total_q + total_c - overlap,
        "count": lambda: F.lit(100).cast("long"),
    }[denom]()


def above(overlap: Column, denom: Column, theta_pct: int, inclusive: bool = False) -> Column:
    """Share of ``denom`` strictly above (or at least) theta percent."""
    left, right = overlap * 100, denom * theta_pct
    return left >= right if inclusive else left > right


def size_compatible(n1: Column, n2: Column, gamma_pct: int) -> Column:
    """Sizes within a factor of gamma of each other."""
    return F.least(n1, n2) * 100 >= F.greatest(n1, n2) * gamma_pct


def sequence_similarity(a: Column, b: Column) -> Column:
    """Longest common subsequence of two arrays over the longer length (0 where both are empty)."""
    width = F.size(b)
    zero = F.transform(F.sequence(F.lit(0), width), lambda i: F.lit(0))
    # One row of the table per element of a; each row is built left to right.
    row = lambda above_, x: F.aggregate(
        F.sequence(F.lit(1), width),
        F.array(F.lit(0)),
        lambda acc, j: F.concat(acc, F.array(F.when(F.get(b, j - 1) == x, F.get(above_, j - 1) + 1).otherwise(F.greatest(F.get(above_, j), F.element_at(acc, -1))))),
    )
    table = F.aggregate(a, zero, lambda acc, x: F.when(width > 0, row(acc, x)).otherwise(acc))
    longest = F.greatest(F.size(a), width)
    return F.when(longest == 0, F.lit(0.0)).otherwise(F.element_at(table, -1) / longest)
