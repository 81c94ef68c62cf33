"""Rank formulas as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def teleport(n: int, alpha: float) -> Column:
    """What every vertex gets without any link."""
    return F.lit((1 - alpha) / n)


def plain_rank(share_sum: Column, n: int, alpha: float) -> Column:
    """Teleport plus the damped sum of shares that come in."""
    return teleport(n, alpha) + F.lit(alpha) * share_sum


def loopfree_rank(share_sum: Column, own: Column, deg: Column, n: int, alpha: float) -> Column:
    """The rank that a vertex with a self-loop converges to while the shares of others stay: the loop's geometric series, summed.

    ``share_sum`` includes the vertex's own share ``own``, which is taken out first.
    """
    return (F.lit(alpha) * (share_sum - own) + teleport(n, alpha)) / (F.lit(1.0) - F.lit(alpha) / deg)


def change(old: Column, new: Column) -> Column:
    return F.abs(new - old)


def relative_change(old: Column, new: Column) -> Column:
    return change(old, new) / F.greatest(old, new)


def spread_measure(kind: str, old: Column, new: Column, deg: Column) -> Column:
    """What is compared with the spread tolerance."""
    return {"rel": relative_change(old, new), "abs": change(old, new), "share": change(old, new) / deg}[kind]


def rank_e9(rank: Column) -> Column:
    """Fixed-point form, in which results of different summation orders agree."""
    return F.floor(rank * F.lit(1e9) + F.lit(0.5)).cast("bigint")
