"""Weak dependencies and parent-child links between entities."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geopat.functions.geo import haversine
from geopat.plans.rangejoin import within_after

MINUTE = 60_000_000
_ADDRESS = ("state", "city", "zip", "street", "side")


def _side(df: DataFrame, prefix: str) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{prefix}_{c}") for c in ("entity_id", "type", "kind", "start_us", "lat", "lon", "station", *_ADDRESS)])


def candidates(df: DataFrame, minutes: int, snow_minutes: int, metres: float = 300.0) -> DataFrame:
    """(parent_id, child_id, gap_us, via): collocated pairs with the second starting 0 to T later.

    Traffic pairs share the whole address and lie within `metres`; weather pairs with traffic by station.
    Snow has a time threshold of its own; each threshold gets a join with buckets of its width.
    """
    traffic, weather = df.where("kind = 'traffic'"), df.where("kind = 'weather'")
    near = haversine(F.col("p_lat"), F.col("p_lon"), F.col("c_lat"), F.col("c_lon")) <= metres
    road = within_after(_side(traffic, "p"), _side(traffic, "c"), [(f"p_{a}", f"c_{a}") for a in _ADDRESS], ("p_start_us", "c_start_us"), minutes * MINUTE).where(near & (F.col("p_entity_id") != F.col("c_entity_id")))
    parts = [road.withColumn("via", F.lit("road"))]
    for rows, width in ((weather.where("type <> 'snow'"), minutes), (weather.where("type = 'snow'"), snow_minutes)):
        parts.append(within_after(_side(rows, "p"), _side(traffic, "c"), [("p_station", "c_station")], ("p_start_us", "c_start_us"), width * MINUTE).withColumn("via", F.lit("station")))
    out = parts[0].unionByName(parts[1]).unionByName(parts[2])
    return out.select(F.col("p_entity_id").alias("parent_id"), F.col("c_entity_id").alias("child_id"), (F.col("c_start_us") - F.col("p_start_us")).alias("gap_us"), "via")


def weak_pairs(df: DataFrame, minutes: int = 10, snow_minutes: int = 40, metres: float = 300.0) -> DataFrame:
    """(a, b) with a < b: collocated pairs that start within T of each other, in either order; weather pairs with traffic only."""
    forward = candidates(df, minutes, snow_minutes, metres).where("gap_us > 0 or via = 'station' or parent_id < child_id").select("parent_id", "child_id")
    traffic, weather = df.where("kind = 'traffic'"), df.where("kind = 'weather'")
    for rows, width in ((weather.where("type <> 'snow'"), minutes), (weather.where("type = 'snow'"), snow_minutes)):
        late = within_after(_side(traffic, "p"), _side(rows, "c"), [("p_station", "c_station")], ("p_start_us", "c_start_us"), width * MINUTE)
        forward = forward.union(late.where("c_start_us > p_start_us").select("p_entity_id", "c_entity_id"))
    return forward.select(F.least("parent_id", "child_id").alias("a"), F.greatest("parent_id", "child_id").alias("b"))


def links(df: DataFrame, minutes: int = 10, snow_minutes: int = 40, metres: float = 300.0) -> DataFrame:
    """Child-parent links: the parent starts strictly earlier; weather is only ever a parent."""
    return candidates(df, minutes, snow_minutes, metres).where("gap_us > 0")


def coverage(df: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row per kind: entities, those in a weak pair (a, b), and the share in percent."""
    touched = pairs.select(F.col("a").alias("entity_id")).union(pairs.select("b")).distinct().withColumn("hit", F.lit(1))
    return df.join(touched, "entity_id", "left").groupBy("kind").agg(F.count("*").alias("n"), F.count("hit").alias("n_linked")).withColumn("percent", F.round(100.0 * F.col("n_linked") / F.col("n"), 6))


_PAIR = "p.state = c.state and p.city = c.city and p.zip = c.zip and p.street = c.street and p.side = c.side"
_NEAR = "2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians(c.lat - p.lat) / 2), 2) + cos(radians(p.lat)) * cos(radians(c.lat)) * pow(sin(radians(c.lon - p.lon) / 2), 2)))) <= 300"


def link_sql(minutes: int, snow_minutes: int) -> str:
    """WITH-list item `l` for DuckDB."""
    t, s = minutes * MINUTE, snow_minutes * MINUTE
    return f"""l as (
  select p.entity_id parent_id, c.entity_id child_id, c.start_us - p.start_us gap_us, 'road' via from e p join e c on {_PAIR}
    where p.kind = 'traffic' and c.kind = 'traffic' and c.start_us > p.start_us and c.start_us - p.start_us <= {t}::bigint and {_NEAR}
  union all
  select p.entity_id, c.entity_id, c.start_us - p.start_us, 'station' from e p join e c on p.station = c.station
    where p.kind = 'weather' and c.kind = 'traffic' and c.start_us > p.start_us and c.start_us - p.start_us <= case when p.type = 'snow' then {s}::bigint else {t}::bigint end)"""


def weak_sql(minutes: int, snow_minutes: int) -> str:
    """WITH-list item `wp` (a, b) for DuckDB."""
    t, s = minutes * MINUTE, snow_minutes * MINUTE
    return f"""wp as (
  select p.entity_id a, c.entity_id b from e p join e c on {_PAIR} where p.kind = 'traffic' and c.kind = 'traffic' and p.entity_id < c.entity_id and abs(c.start_us - p.start_us) <= {t}::bigint and {_NEAR}
  union all
  select least(p.entity_id, c.entity_id), greatest(p.entity_id, c.entity_id) from e p join e c on p.station = c.station
    where p.kind = 'weather' and c.kind = 'traffic' and abs(c.start_us - p.start_us) <= case when p.type = 'snow' then {s}::bigint else {t}::bigint end)"""
