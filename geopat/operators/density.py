"""Density of points: nearest neighbours, neighbour counts, clusters and their radius.

Points that share a place are one weighted place, so repeated coordinates make no pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geopat.functions.geo import haversine
from geopat.operators.lasting import quantile
from geopat.plans.components import connected
from geopat.plans.nearby import near_pairs
from geopat.plans.scratch import written


def places(points: DataFrame) -> DataFrame:
    """(place, lat, lon, weight): distinct coordinates, named by their smallest point id."""
    return points.where("lat is not null and lon is not null").groupBy("lat", "lon").agg(F.min("id").alias("place"), F.count("*").alias("weight"))


def nearest(points: DataFrame, start_metres: float = 50.0, most_rounds: int = 20) -> DataFrame:
    """(place, weight, dist): distance from a place's points to their nearest other point.

    Shared places have 0.  The rest search a radius that doubles; a round keeps only places still without
    a neighbour.  Places without any after the last round (or with no other place) have null.
    """
    every = written(places(points))
    done = [every.where("weight > 1").select("place", "weight", F.lit(0.0).alias("dist"))]
    todo, radius = every.where("weight = 1"), start_metres
    for _ in range(most_rounds):
        hits = near_pairs(todo, every, radius).where("a_place <> b_place").groupBy("a_place").agg(F.min("dist").alias("dist"))
        tried = written(todo.join(hits, F.col("place") == F.col("a_place"), "left").drop("a_place"))
        done.append(tried.where("dist is not null").select("place", "weight", "dist"))
        todo, radius = tried.where("dist is null").drop("dist"), radius * 2
        if todo.isEmpty():
            break
    else:
        done.append(todo.select("place", "weight", F.lit(None).cast("double").alias("dist")))
    out = done[0]
    for part in done[1:]:
        out = out.union(part)
    return out


def neighbour_counts(points: DataFrame, metres: float) -> DataFrame:
    """(place, lat, lon, weight, n): other points within `metres` of each of a place's points."""
    every = places(points)
    n = near_pairs(every, every, metres).groupBy("a_place").agg((F.sum("b_weight") - 1).alias("n"))
    return every.join(n, F.col("place") == F.col("a_place")).drop("a_place")


def parameters(points: DataFrame, p: float = 0.99) -> DataFrame:
    """One row: eps_m, the p-quantile of nearest-neighbour distances, and min_pts, that of neighbour counts within it."""
    points = written(points)
    eps = quantile(written(nearest(points)), F.col("dist"), p, F.col("weight"))
    least = None if eps is None else quantile(written(neighbour_counts(points, eps + 1e-6)), F.col("n"), p, F.col("weight"))
    return points.sparkSession.createDataFrame([(eps, least)], "eps_m double, min_pts double")


def dbscan(points: DataFrame, eps_m: float, min_pts: int, count_self: bool = False) -> DataFrame:
    """(id, lat, lon, cluster, core): cluster is its smallest core place, -1 for noise; a border point takes the smallest adjacent cluster."""
    counted = written(neighbour_counts(points, eps_m).withColumn("core", F.col("n") + (1 if count_self else 0) >= min_pts))
    cores = counted.where("core").select("place", "lat", "lon")
    edges = near_pairs(cores, cores, eps_m).where("a_place <= b_place").select(F.col("a_place").alias("a"), F.col("b_place").alias("b"))
    label = written(connected(edges))
    heads = cores.join(label, F.col("place") == F.col("node")).select("place", "lat", "lon", "component")
    rest = counted.where("not core").select("place", "lat", "lon")
    border = near_pairs(rest, heads, eps_m).groupBy(F.col("a_place").alias("place")).agg(F.min("b_component").alias("component"))
    found = heads.select("place", "component").union(border)
    labelled = counted.join(found, "place", "left").select("lat", "lon", F.coalesce("component", F.lit(-1)).alias("cluster"), "core")
    return points.join(labelled, ["lat", "lon"]).select("id", "lat", "lon", "cluster", "core")


def radius(clusters: DataFrame) -> DataFrame:
    """One row: clusters, and the mean over them of the greatest distance to the mean position, in metres."""
    real = clusters.where("cluster >= 0")
    centre = real.groupBy("cluster").agg(F.avg("lat").alias("clat"), F.avg("lon").alias("clon"))
    far: Column = F.max(haversine(F.col("lat"), F.col("lon"), F.col("clat"), F.col("clon")))
    return real.join(centre, "cluster").groupBy("cluster").agg(far.alias("r")).agg(F.count("*").alias("clusters"), F.round(F.avg("r"), 3).alias("radius_m"))
