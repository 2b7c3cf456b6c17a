"""Typed, located time intervals from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geopat.functions.geo import haversine
from geopat.plans.nearby import near_pairs
from geopat.plans.scratch import written

#: Unified types by the first code that is past them.
TAXONOMY = (
    (50, "congestion"), (60, "accident"), (65, "flow_incident"), (69, "broken_vehicle"), (73, "lane_blocked"), (78, "construction"), (80, "event"),
    (81, "hail"), (90, "rain"), (94, "fog"), (97, "snow"), (98, "severe_cold"), (99, "storm"), (100, "precipitation"),
)
FIRST_WEATHER = 80
SECOND = 1_000_000


def read(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def unified_type(code: Column) -> Column:
    """Type of a message code; codes outside the taxonomy are `other`."""
    out = None
    for past, name in TAXONOMY:
        out = F.when((code >= 0) & (code < past), name) if out is None else out.when(code < past, name)
    return out.otherwise("other")


def stations(spark: SparkSession, folder: str) -> DataFrame:
    """(code, lat, lon, state) of weather stations."""
    s, n = F.col("s_suppkey"), F.col("s_nationkey")
    return read(spark, folder, "supplier").select(
        s.cast("long").alias("code"), (28 + 4 * F.floor(n / 5) + 0.1 * (s % 7)).alias("slat"), (-120 + 10 * (n % 5) + 0.1 * (s % 5)).alias("slon"), n.cast("long").alias("sstate")
    )


#: Pairs of a place and a station that may be compared without a grid.
MOST_PAIRS = 50_000_000


def nearest_station(places: DataFrame, directory: DataFrame, start_metres: float = 50_000.0) -> DataFrame:
    """(city, station): station nearest to each place, by whole metres, then code.

    Of stations at one position only the first code can be it.  A directory of a checked size is broadcast.  Beyond it
    places meet the stations of the grid cells around, in a radius that doubles until all have one within it.
    """
    metres = F.round(haversine(F.col("clat"), F.col("clon"), F.col("slat"), F.col("slon")), 0)
    directory = written(directory.groupBy("slat", "slon").agg(F.min("code").alias("code")))
    if places.count() * directory.count() <= MOST_PAIRS:
        spread = places.repartition(places.sparkSession.sparkContext.defaultParallelism)  # few rows, but each meets the whole directory
        return spread.crossJoin(F.broadcast(directory)).groupBy("city").agg(F.min_by("code", F.struct(metres, "code")).alias("station"))
    at = written(directory.select(F.col("code").alias("place"), F.col("slat").alias("lat"), F.col("slon").alias("lon")))
    todo = written(places.select(F.col("city").alias("place"), F.col("clat").alias("lat"), F.col("clon").alias("lon")))
    done, radius = None, start_metres
    while not todo.isEmpty() and radius < 3e7:
        hits = near_pairs(todo, at, radius).withColumn("m", F.round("dist", 0)).where(F.col("m") < radius - 1)  # what rounds to the radius might have company beyond it
        best = written(hits.groupBy(F.col("a_place").alias("city")).agg(F.min_by("b_place", F.struct("m", "b_place")).alias("station")))
        done = best if done is None else done.union(best)
        todo, radius = written(todo.join(best.select(F.col("city").alias("place")), "place", "left_anti")), radius * 2
    return done


def nearest_stations(places: DataFrame, directory: DataFrame, k: int, start_metres: float = 50_000.0, most_pairs: int = MOST_PAIRS) -> DataFrame:
    """(city, r, code): the k stations nearest to each place, by whole metres, then code.

    Of stations at one position only the first k codes can be among them.  Beyond a checked size places meet the
    positions of the grid cells around, in a radius that doubles until all have k within it.
    """
    spot = directory.groupBy("slat", "slon").agg(F.array_sort(F.collect_set("code")).alias("codes"))
    spot = written(spot.select("slat", "slon", F.slice("codes", 1, k).alias("codes")))
    todo = written(places.select("city", "clat", "clon"))
    found, radius = [], start_metres
    while todo.count() * spot.count() > most_pairs and radius < 3e7:
        a = todo.select(F.col("city").alias("place"), F.col("clat").alias("lat"), F.col("clon").alias("lon"))
        hits = near_pairs(a, spot.select(F.col("slat").alias("lat"), F.col("slon").alias("lon"), "codes"), radius).withColumn("m", F.round("dist", 0))
        within = hits.where(F.col("m") < radius - 1)  # what rounds to the radius might have company beyond it
        best = written(_first(within.select(F.col("a_place").alias("city"), "m", F.col("b_codes").alias("codes")), k).where(F.size("best") == k))
        found.append(best)
        todo, radius = written(todo.join(best.select("city"), "city", "left_anti")), radius * 2
    metres = F.round(haversine(F.col("clat"), F.col("clon"), F.col("slat"), F.col("slon")), 0)
    out = _first(todo.crossJoin(F.broadcast(spot)).select("city", metres.alias("m"), "codes"), k)
    for best in found:
        out = out.unionByName(best)
    return out.select("city", F.posexplode("best").alias("i", "s")).select("city", (F.col("i") + 1).cast("long").alias("r"), "s.code")


def _first(near: DataFrame, k: int) -> DataFrame:
    """(city, best): the first k (m, code) of each city from (city, m, codes)."""
    each = near.select("city", "m", F.explode("codes").alias("code"))
    ranked = each.withColumn("i", F.row_number().over(Window.partitionBy("city").orderBy("m", "code"))).where(F.col("i") <= k)
    return ranked.groupBy("city").agg(F.array_sort(F.collect_list(F.struct("m", "code"))).alias("best"))


def _placed(rows: DataFrame) -> DataFrame:
    """Rows with the street, city and state of user `u`, and the city's position."""
    c = F.col("city")
    return (
        rows.withColumn("street", F.floor(F.col("u") / 5)).withColumn("city", F.floor(F.col("street") / 2)).withColumn("state", c % 25)
        .withColumn("clat", 28 + 4 * F.floor(F.col("state") / 5) + 0.2 * (F.floor(c / 25) % 10))
        .withColumn("clon", -120 + 10 * (F.col("state") % 5) + 0.2 * F.floor(c / 250))
    )


def spread(rows: DataFrame, key: str) -> DataFrame:
    """The rows over all cores, where their files are split into fewer parts."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores, key) if rows.rdd.getNumPartitions() < cores else rows


def entities(spark: SparkSession, folder: str) -> DataFrame:
    """One row per event: id, type, kind, start and end (microseconds), address, position, road class, station."""
    k = F.get_json_object("props", "$.k").cast("int")
    events = read(spark, folder, "events").select("event_id", "event_type", "user_id", "ts", "value", "props")
    base = spread(events, "event_id").select(
        F.col("event_id").cast("long").alias("entity_id"), F.col("event_type").alias("provider_type"), k.alias("code"), F.col("user_id").cast("long").alias("u"),
        F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(ts as timestamp_ntz))").alias("start_us"), F.round(F.col("value") * 60, 0).cast("long").alias("seconds"),
    )
    placed, c = _placed(base), F.col("city")
    users = events.select(F.col("user_id").cast("long").alias("u")).distinct()
    cities = written(_placed(users).select("city", "clat", "clon").distinct())
    near = written(nearest_station(cities, stations(spark, folder)))  # so that its size is known where it is joined
    return placed.join(near, "city", "left").select(
        "entity_id", unified_type(F.col("code")).alias("type"), F.when(F.col("code") >= FIRST_WEATHER, "weather").otherwise("traffic").alias("kind"), "provider_type", "code",
        "start_us", (F.col("start_us") + F.col("seconds") * SECOND).alias("end_us"), "street", F.when(F.col("entity_id") % 2 == 0, "R").otherwise("L").alias("side"),
        (90000 + c).alias("zip"), "city", "state", F.when(F.col("street") % 3 == 0, "interstate").otherwise("city").alias("road"),
        (F.col("clat") + ((F.col("u") % 5) * 100 + F.col("code")) / 111195.0).alias("lat"), (F.col("clon") + 0.01 * (F.col("street") % 2)).alias("lon"), "station",
    )


_CASE = "case " + " ".join(f"when k < {past} then '{name}'" for past, name in TAXONOMY) + " else 'other' end"

#: The same view for DuckDB, as a WITH list.
ENTITY_SQL = f"""
e0 as (select event_id::bigint entity_id, event_type provider_type, json_extract_string(props, '$.k')::int k, user_id::bigint u, epoch_us(ts) start_us, round(value * 60)::bigint secs from events),
e1 as (select *, (u // 5) // 2 city, u // 5 street, ((u // 5) // 2) % 25 state from e0),
e2 as (select *, 28 + 4 * (state // 5) + 0.2::double * ((city // 25) % 10) clat, -120 + 10 * (state % 5) + 0.2::double * (city // 250) clon from e1),
st as (select s_suppkey::bigint code, 28 + 4 * (s_nationkey // 5) + 0.1::double * (s_suppkey % 7) slat, -120 + 10 * (s_nationkey % 5) + 0.1::double * (s_suppkey % 5) slon from supplier),
ct as (select distinct city, clat, clon from e2),
nr as (select city, arg_min(code, [round(2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians(slat - clat) / 2), 2) + cos(radians(clat)) * cos(radians(slat)) * pow(sin(radians(slon - clon) / 2), 2))))), code]) station from ct, st group by city),
e as (select entity_id, {_CASE} as type, case when k >= 80 then 'weather' else 'traffic' end kind, provider_type, k code, start_us, start_us + secs * 1000000 end_us, street,
  case when entity_id % 2 = 0 then 'R' else 'L' end side, 90000 + city zip, e2.city, state, case when street % 3 = 0 then 'interstate' else 'city' end road,
  clat + ((u % 5) * 100 + k) / 111195.0::double lat, clon + 0.01::double * (street % 2) lon, station from e2 join nr using (city))
"""
