"""Student's t upper tail as a Column: with t = sqrt(v) tan(x) the density goes as cos(x)^(v-1), integrated by Simpson's rule."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PANELS = 2000


def _integral(lo: Column, power: Column) -> Column:
    step = (F.lit(3.141592653589793 / 2) - lo) / PANELS
    weight = lambda i: F.when((i == 0) | (i == PANELS), 1.0).when(i % 2 == 1, 4.0).otherwise(2.0)
    add = lambda acc, i: acc + weight(i) * F.pow(F.greatest(F.lit(0.0), F.cos(lo + step * i)), power)
    return F.aggregate(F.sequence(F.lit(0), F.lit(PANELS)), F.lit(0.0), add) * step / 3


def t_upper(t: Column, v: Column) -> Column:
    """P(T > t) for v degrees of freedom."""
    tail = 0.5 * _integral(F.atan(F.abs(t) / F.sqrt(v)), v - 1) / _integral(F.lit(0.0), v - 1)
    return F.when(t >= 0, tail).otherwise(1 - tail)
