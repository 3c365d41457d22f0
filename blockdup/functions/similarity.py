"""Similarity measures over multisets as exact integer arithmetic.

A threshold is an integer per mille. Every test is a comparison of integers, so a value exactly on the
threshold counts and no ceiling of a rounded product can go wrong.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MEASURES = ("overlap", "jaccard", "cosine")


def _long(x) -> Column:
    return x.cast("long") if isinstance(x, Column) else F.lit(x).cast("long")


def check(theta_pm: int, measure: str) -> None:
    if not 0 < theta_pm <= 1000:
        raise ValueError("the threshold is a per mille value from 1 to 1000")
    if measure not in MEASURES:
        raise ValueError(f"measure is one of {MEASURES}")


def meets(overlap: Column, x: Column, y: Column, theta_pm: int, measure: str = "overlap", strict: bool = False) -> Column:
    """Whether an overlap of blocks of x and y elements reaches (strict: passes the ceiling of) the threshold."""
    o, a, b = _long(overlap), _long(x), _long(y)
    if measure == "overlap":
        return o > required_overlap(x, y, theta_pm) if strict else o * 1000 >= F.greatest(a, b) * theta_pm
    if measure == "jaccard":
        left, right = o * (1000 + theta_pm), (a + b) * theta_pm
    else:
        left, right = o * o * 1_000_000, a * b * (theta_pm * theta_pm)
    return left > right if strict else left >= right


def required_overlap(x: Column, y: Column, theta_pm: int, measure: str = "overlap") -> Column:
    """Least overlap that reaches the threshold."""
    a, b = _long(x), _long(y)
    if measure == "overlap":
        return ceil_div(F.greatest(a, b) * theta_pm, 1000)
    if measure == "jaccard":
        return ceil_div((a + b) * theta_pm, 1000 + theta_pm)
    guess = F.floor(F.sqrt(a * b * float(theta_pm * theta_pm)) / 1000).cast("long")
    low = F.greatest(guess - 1, F.lit(0).cast("long"))
    fits = lambda o: o * o * 1_000_000 >= a * b * (theta_pm * theta_pm)
    return F.when(fits(low), low).when(fits(low + 1), low + 1).when(fits(low + 2), low + 2).otherwise(low + 3)


def ceil_div(x: Column, by: int) -> Column:
    """Integer ceiling of x / by for x >= 0, without leaving bigint."""
    up = x + (by - 1)
    return ((up - F.pmod(up, F.lit(by).cast("long"))) / by).cast("long")


def least_partner(n: Column, theta_pm: int, measure: str = "overlap") -> Column:
    """Size of the smallest block that can still match one of n elements."""
    scale = 1000 if measure != "cosine" else 1_000_000
    share = theta_pm if measure != "cosine" else theta_pm * theta_pm
    return ceil_div(_long(n) * share, scale)


def prefix_length(n: Column, theta_pm: int, measure: str = "overlap", min_shared: int = 1) -> Column:
    """Elements of the sub-block: two blocks that match share min_shared of them (or all they need to share)."""
    return F.least(_long(n), _long(n) - least_partner(n, theta_pm, measure) + min_shared).cast("int")


def similarity(overlap: Column, x: Column, y: Column, measure: str = "overlap") -> Column:
    o, a, b = overlap.cast("double"), x.cast("double"), y.cast("double")
    if measure == "overlap":
        return o / F.greatest(a, b)
    return o / (a + b - o) if measure == "jaccard" else o / F.sqrt(a * b)
