"""The nearest few stations, and reports of a table through the Python source."""

import random

import pytest

from geopat.sources import entities


@pytest.mark.parametrize("most_pairs", [0, 10**9])
def test_nearest_few_by_rings_and_by_pairs(spark, monkeypatch, most_pairs):
    """Many stations at few positions, ties in whole metres, and a place far from all."""
    rng = random.Random(5)
    at = [(i, 30 + 0.1 * rng.randrange(12), -100 + 0.1 * rng.randrange(6), 0) for i in range(300)]
    towns = [(c, 30 + rng.random(), -100 + rng.random()) for c in range(20)] + [(99, 34.0, -93.0)]
    sent = []
    monkeypatch.setattr(entities, "_first", lambda near, k, first=entities._first: sent.append(near.count()) or first(near, k))
    found = entities.nearest_stations(spark.createDataFrame(towns, "city long, clat double, clon double"), spark.createDataFrame(at, "code long, slat double, slon double, sstate long"), 3, most_pairs=most_pairs)

    got = {(r.city, r.r): r.code for r in found.collect()}
    town, some = spark.createDataFrame(towns, "city long, clat double, clon double"), spark.createDataFrame(at, "code long, slat double, slon double, sstate long")
    far = town.crossJoin(some).select("city", "code", entities.F.round(entities.haversine(*[entities.F.col(c) for c in ("clat", "clon", "slat", "slon")]), 0).alias("m")).collect()
    want = {(c, i + 1): code for c in {t[0] for t in towns} for i, (_, code) in enumerate(sorted((r.m, r.code) for r in far if r.city == c)[:3])}
    assert got == want
    assert max(sent) < len(towns) * len(at)  # fewer rows are compared than there are pairs


def test_feed_source_replays_a_table(spark, tmp_path):
    """Reports come from the events of the folder, all of them and in time order."""
    from geopat import surface_more

    rows = [(i, f"2024-01-01 00:{(i * 7) % 60:02d}:00", "abc"[i % 3]) for i in range(50)] + [(50, None, "a")]
    spark.createDataFrame(rows, "event_id long, ts string, event_type string").withColumn("ts", entities.F.to_timestamp_ntz("ts")).repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    found = [(r.id, r.at_us, r.type) for r in surface_more.op_feed_source(spark, str(tmp_path)).collect()]
    start = 1_704_067_200_000_000
    assert found == [(50, None, "a"), *sorted(((i, start + (i * 7) % 60 * 60_000_000, "abc"[i % 3]) for i in range(50)), key=lambda r: (r[1], r[0]))]


def test_recursion_reads_a_table(spark, tmp_path):
    """Levels and their running totals come from the table's line numbers."""
    from geopat.workloads import QUERIES

    spark.createDataFrame([(1,), (1,), (2,), (3,), (3,), (5,)], "l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert sorted(tuple(r) for r in QUERIES["op_cte_recursive"](spark, str(tmp_path)).collect()) == [(1, 1, 2), (2, 2, 3), (3, 6, 5)]


def test_events_of_one_file_are_read_by_all_cores_and_stay_there(spark):
    """One small file is dealt out before its rows are parsed, and the few cities come to the rows by broadcast."""
    plan = entities.entities(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "REPARTITION_BY_NUM" in plan and "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan
    rows = spark.range(100).repartition(spark.sparkContext.defaultParallelism)
    assert entities.spread(rows, "id") is rows
