"""Naive equalities and the distance score."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def same_position(dist, eps_m: float = 1.0) -> Column:
    return (dist < eps_m).cast("int")


def same_label(a, b) -> Column:
    return (a == b).cast("int")


def within(dist, d_hat: float) -> Column:
    return (dist < d_hat).cast("int")


def decay(dist, d_hat: float) -> Column:
    """1 at no distance, a half at ``d_hat``, halved again with each further one."""
    if d_hat <= 0:
        raise ValueError("the half distance must be above 0")
    return F.exp(dist * (-math.log(2) / d_hat))
