"""The generic neighbourhood, and where it disagrees with weak dependencies."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geopat.functions.geo import haversine
from geopat.plans.rangejoin import buckets

_DEGREE_M, MID_LAT = 111195.0, 36.0
_WIDTH = 6 * 3_600_000_000


def generic_pairs(df: DataFrame, metres: float = 300.0, mid_lat: float = MID_LAT) -> DataFrame:
    """(a, b) with a < b: planar distance at most `metres` and intervals that meet; no street, side or lag.

    Weather stands at its station, so weather columns lat and lon must hold its position.
    Planar metres take one length of a degree of longitude, that of `mid_lat`.
    """
    across = F.lit(_DEGREE_M) * F.cos(F.radians(F.lit(mid_lat)))
    x, y = F.floor(F.col("lat") * _DEGREE_M / metres), F.floor(F.col("lon") * across / metres)
    base = df.select("entity_id", "start_us", "end_us", "lat", "lon", x.alias("x"), y.alias("y")).withColumn("day", F.explode(buckets(F.col("start_us"), F.col("end_us"), _WIDTH)))
    a, b = (base.select(*[F.col(c).alias(f"{t}_{c}") for c in base.columns]) for t in "ab")
    around = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    a = a.withColumn("n", F.explode(around)).withColumns({"a_x": F.col("a_x") + F.col("n.i"), "a_y": F.col("a_y") + F.col("n.j")})
    dy, dx = (F.col("a_lat") - F.col("b_lat")) * _DEGREE_M, (F.col("a_lon") - F.col("b_lon")) * across
    meets = (F.col("a_start_us") <= F.col("b_end_us")) & (F.col("b_start_us") <= F.col("a_end_us")) & (F.col("a_day") == F.floor(F.greatest("a_start_us", "b_start_us") / _WIDTH))
    on = (F.col("a_x") == F.col("b_x")) & (F.col("a_y") == F.col("b_y")) & (F.col("a_day") == F.col("b_day")) & meets
    return a.join(b, on & (F.col("a_entity_id") < F.col("b_entity_id")) & (dx * dx + dy * dy <= metres * metres)).select(F.col("a_entity_id").alias("a"), F.col("b_entity_id").alias("b"))


def compare(strict: DataFrame, generic: DataFrame, df: DataFrame) -> DataFrame:
    """One row: pairs both find, pairs of one only; of the generic ones on opposite sides of a street, of the strict ones that start after the other's end."""
    pairs = strict.withColumn("s", F.lit(1)).join(generic.withColumn("g", F.lit(1)), ["a", "b"], "full")
    side = lambda t: df.select(F.col("entity_id").alias(t), *[F.col(c).alias(f"{t}_{c}") for c in ("kind", "street", "side", "start_us", "end_us")])
    rows = pairs.join(side("a"), "a").join(side("b"), "b")
    only_g, only_s = F.col("s").isNull(), F.col("g").isNull()
    road = (F.col("a_kind") == "traffic") & (F.col("b_kind") == "traffic")
    opposite = road & (F.col("a_street") == F.col("b_street")) & (F.col("a_side") != F.col("b_side"))
    lags = (F.col("a_end_us") < F.col("b_start_us")) | (F.col("b_end_us") < F.col("a_start_us"))
    return rows.agg(F.count_if(~only_g & ~only_s).alias("both"), F.count_if(only_s).alias("only_strict"), F.count_if(only_g).alias("only_generic"), F.count_if(only_g & opposite).alias("opposite_side"), F.count_if(only_s & lags).alias("lagging"))


def generic_sql(metres: int = 300) -> str:
    """WITH-list items `ep` (weather at its station) and `gp2` (a, b) for DuckDB, after `e`."""
    across = f"111195.0::double * cos(radians({MID_LAT}::double))"
    return f"""
ep as (select e.* replace (case when kind = 'weather' then slat else lat end as lat, case when kind = 'weather' then slon else lon end as lon) from e join st on st.code = e.station),
gp2 as (select p.entity_id a, c.entity_id b from ep p join ep c on p.entity_id < c.entity_id and p.start_us <= c.end_us and c.start_us <= p.end_us
  and abs(p.lat - c.lat) < 0.01 and pow((p.lon - c.lon) * {across}, 2) + pow((p.lat - c.lat) * 111195.0::double, 2) <= {metres * metres})
"""


def loop_pairs(df: DataFrame, minutes: int = 10, snow_minutes: int = 40, metres: float = 300.0) -> DataFrame:
    """Weak pairs (a, b) by comparing every row with every other: what the bucketed join is held against, for small tables only."""
    a, b = (df.select(*[F.col(c).alias(f"{t}_{c}") for c in df.columns]) for t in "ab")
    gap = F.abs(F.col("a_start_us") - F.col("b_start_us"))
    road = (F.col("a_kind") == "traffic") & (F.col("b_kind") == "traffic")
    for c in ("state", "city", "zip", "street", "side"):
        road &= F.col(f"a_{c}") == F.col(f"b_{c}")
    road &= (gap <= minutes * 60_000_000) & (haversine(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon")) <= metres)
    wet = F.when(F.col("a_kind") == "weather", F.col("a_type")).otherwise(F.col("b_type"))
    near = (F.col("a_kind") != F.col("b_kind")) & (F.col("a_station") == F.col("b_station")) & (gap <= F.when(wet == "snow", F.lit(snow_minutes * 60_000_000)).otherwise(F.lit(minutes * 60_000_000)))
    return a.crossJoin(b).where((F.col("a_entity_id") < F.col("b_entity_id")) & (road | near)).select(F.col("a_entity_id").alias("a"), F.col("b_entity_id").alias("b"))
