"""Pairs of places within a distance, by grid cells."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geopat.functions.geo import haversine

_DEGREE_M = 111195.0


def near_pairs(left: DataFrame, right: DataFrame, metres: float) -> DataFrame:
    """Rows of both place tables (columns a_*, b_*) within `metres`, the same place included, with `dist`.

    Grid cells are at least that wide, and twice as many degrees of longitude (good to 60 degrees of latitude); a left place is sent to 3 x 3 of them.
    """
    size = metres / _DEGREE_M * 1.001
    cell = lambda t: (F.floor(F.col(f"{t}_lat") / size), F.floor(F.col(f"{t}_lon") / (2 * size)))
    named = lambda df, t: df.select(*[F.col(c).alias(f"{t}_{c}") for c in df.columns])
    a, b = named(left, "a"), named(right, "b")
    around = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    x, y = cell("a")
    a = a.withColumn("n", F.explode(around)).withColumns({"a_x": x + F.col("n.i"), "a_y": y + F.col("n.j")}).drop("n")
    x, y = cell("b")
    b = b.withColumns({"b_x": x, "b_y": y})
    dist = haversine(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon"))
    return a.join(b, (F.col("a_x") == F.col("b_x")) & (F.col("a_y") == F.col("b_y"))).withColumn("dist", dist).where(F.col("dist") <= metres).drop("a_x", "a_y", "b_x", "b_y")
