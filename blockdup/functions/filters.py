"""Filters over pairs of postings and candidates, as predicates."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .similarity import meets

#: prefix: only sub-blocks are indexed; size: partner large enough; position: bound from places in the order.
FILTERS = frozenset({"prefix", "size", "position"})


def size_filter(n_large: Column, n_small: Column, theta_pm: int, measure: str) -> Column:
    """The smaller block lies wholly inside the larger one at best."""
    return meets(n_small, n_large, n_small, theta_pm, measure)


def upper_bound(seen: Column, pos_b: Column, pos_c: Column, n_b: Column, n_c: Column) -> Column:
    """Largest overlap still possible when the last shared element stands at these places (from 1)."""
    return seen + F.least(n_b - pos_b, n_c - pos_c)


def position_filter(seen: Column, pos_b: Column, pos_c: Column, n_b: Column, n_c: Column, theta_pm: int, measure: str) -> Column:
    """The bound only falls from one shared element to the next, so testing it after the last one is enough."""
    return meets(upper_bound(seen, pos_b, pos_c, n_b, n_c), n_b, n_c, theta_pm, measure)


def posting_filter(pos_b: Column, pos_c: Column, n_b: Column, n_c: Column, theta_pm: int, measure: str) -> Column:
    """The same bound for one shared element alone; true clones pass at each of theirs. Used before the shuffle."""
    return meets(F.least(pos_b, pos_c) + F.least(n_b - pos_b, n_c - pos_c), n_b, n_c, theta_pm, measure)
