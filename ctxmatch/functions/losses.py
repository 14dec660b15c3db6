"""Losses for soft multi-label targets, as column expressions; the numpy forms are in ``models.mlp``."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def clipped(p: Column) -> Column:
    return F.greatest(F.least(p, F.lit(1 - 1e-7)), F.lit(1e-7))


def focal(p: Column, y: Column, alpha: float = 0.9, gamma: float = 2.0) -> Column:
    q = clipped(p)
    return F.lit(alpha) * y * F.pow(1 - q, F.lit(gamma)) * -F.log(q) + F.lit(1 - alpha) * (1 - y) * F.pow(q, F.lit(gamma)) * -F.log(1 - q)


def bce(p: Column, y: Column) -> Column:
    q = clipped(p)
    return -(y * F.log(q) + (1 - y) * F.log(1 - q))


def masked(loss: Column, own: Column) -> Column:
    """Null outside the row's own outputs, so that averages leave those cells out."""
    return F.when(own, loss)
