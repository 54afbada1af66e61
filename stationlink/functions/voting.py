"""Threshold rescaling, decisions and votes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def rescale(sim, t) -> Column:
    """Piecewise linear: 0 to 0, the threshold to a half, 1 to 1; 0 if both similarity and threshold are 0."""
    sim, t = (x if isinstance(x, Column) else F.lit(float(x)) for x in (sim, t))
    low = F.when(t > 0, F.try_divide(sim, 2 * t)).otherwise(F.lit(0.0))
    return F.when(sim <= t, low).otherwise(0.5 + F.try_divide(sim - t, 2 * (1 - t)))


def decide(score) -> Column:
    return (score > 0.5).cast("int")


def soft(*scores, weights=None) -> Column:
    """Mean of the members' scores."""
    weights = weights or [1.0] * len(scores)
    total = F.lit(0.0)
    for s, w in zip(scores, weights):
        total = total + s * w
    return total / sum(weights)


def hard(*decisions, tie: int = 0) -> Column:
    """Majority of the members' decisions."""
    yes = F.lit(0)
    for d in decisions:
        yes = yes + d
    n = len(decisions)
    return F.when(yes * 2 > n, 1).when(yes * 2 == n, tie).otherwise(0)
