"""Labels of augmented columns: which tables a column speaks of, and how strongly."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def soft(path: Column, position: Column, decay: float = 0.5) -> Column:
    """map table -> exp(-decay * distance along the path); the origin gets 1, tables off the path are absent."""
    return F.map_from_arrays(path, F.transform(path, lambda _, i: F.exp(F.lit(-decay) * F.abs(i - position))))


def multihot(path: Column) -> Column:
    """1 for every table of the view: the limit of no decay."""
    return F.map_from_arrays(path, F.transform(path, lambda _: F.lit(1.0)))


def onehot(path: Column, position: Column) -> Column:
    """1 for the origin alone: the limit of infinite decay."""
    return F.map_from_arrays(F.array(F.element_at(path, position + 1)), F.array(F.lit(1.0)))


def weight(distance: int, decay: float = 0.5) -> float:
    return math.exp(-decay * distance)
