"""Positions as closed forms of the rank: no list is ever moved, each is one projection.

``k`` is the rank by length, 1 for the longest, ``d`` the number of items; positions run from 1 to d.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The same forms as SQL text, for registered functions.
INTERLEAVE_SQL = "CASE WHEN 2 * k <= d + 1 THEN 2 * k - 1 ELSE 2 * (d - k + 1) END"
MIRROR_SQL = "CASE WHEN k % 2 = 0 AND 2 * k < d THEN d + 1 - k WHEN (d + 1 - k) % 2 = 0 AND 2 * (d + 1 - k) < d THEN d + 1 - k ELSE k END"


def interleave(k: Column, d: Column) -> Column:
    """Longest, shortest, second longest, second shortest, and so on from the front."""
    return F.when(2 * k <= d + 1, 2 * k - 1).otherwise(2 * (d - k + 1))


def mirror_swap(k: Column, d: Column) -> Column:
    """Every second item of the front half trades places with its mirror image."""
    q = d + 1 - k
    traded = ((k % 2 == 0) & (2 * k < d)) | ((q % 2 == 0) & (2 * q < d))
    return F.when(traded, q).otherwise(k)


def mirror_alternate(k: Column, d: Column) -> Column:
    """Longest and shortest at the front, the next two at the back, and so on inward."""
    s = d + 1 - k
    long_half = F.when(k % 2 == 1, k).otherwise(d + 2 - k)
    short_half = F.when(s % 2 == 1, s + 1).otherwise(d + 1 - s)
    return F.when(2 * k <= d + 1, long_half).otherwise(short_half)


def reflected(pos: Column, d: Column) -> Column:
    """The list read from its end."""
    return d + 1 - pos
