"""Quantiles, baselines, enumeration, nearest stations, the radius chain's pieces and the data source, against independent versions."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from geopat import studies
from geopat.operators import baseline, influence, lasting, mine, relate
from geopat.sources import entities, feed_source
from tests.test_core import COLUMNS, MIN, entity


def test_quantile_is_exact(spark):
    rng = np.random.default_rng(3)
    for values in (rng.normal(size=400), rng.integers(0, 9, 300).astype(float), np.array([5.0]), np.concatenate((rng.exponential(size=300) ** 6, [1e12]))):
        df = spark.createDataFrame([(float(v),) for v in values], "v double")
        for p in (0.0, 0.5, 0.95, 0.99, 1.0):
            assert lasting.quantile(df, F.col("v"), p, cells=16) == pytest.approx(np.quantile(values, p), rel=1e-12)
    weighted = spark.createDataFrame([(1.0, 3), (2.0, 1), (7.0, 6), (None, 5), (9.0, 0)], "v double, w long")
    assert lasting.quantile(weighted, F.col("v"), 0.35, F.col("w")) == pytest.approx(np.quantile([1, 1, 1, 2] + [7] * 6, 0.35))
    assert lasting.quantile(weighted.where("false"), F.col("v"), 0.5) is None


def test_bucketed_join_is_the_nested_loop(spark):
    rng = random.Random(4)
    rows = [entity(i, rng.choice(("traffic", "traffic", "weather")), rng.choice(("congestion", "snow", "rain")), rng.randrange(90) * MIN, street=rng.choice((1, 2)), side=rng.choice("RL"), lat=30 + rng.randrange(5) * 0.001, station=rng.choice((1, 2))) for i in range(120)]
    df = spark.createDataFrame(rows, COLUMNS)
    pairs = lambda x: {(r.a, r.b) for r in x.collect()}
    assert pairs(relate.weak_pairs(df, 10, 40)) == pairs(baseline.loop_pairs(df, 10, 40))


def test_miner_is_enumeration(spark):
    rng = random.Random(9)
    rows = []
    for tree in range(40):
        parents = {0: None}
        for n in range(1, rng.choice((2, 4, 6))):
            parents[n] = rng.randrange(n)
        rows += [(1, tree, tree * 100 + n, None if up is None else tree * 100 + up, rng.choice("abc"), n) for n, up in parents.items()]
    nodes = spark.createDataFrame(rows, "state long, tree long, node long, parent long, label string, start_us long")
    key = lambda df: {(r.shape, r.support_count) for r in df.collect()}
    assert key(mine.frequent(nodes, ["state"], 0.1, max_nodes=4)) == key(studies.enumerated(nodes, ["state"], 0.1))


def test_nearest_station_by_rings(spark, monkeypatch):
    rng = random.Random(2)
    places = spark.createDataFrame([(i, 28 + rng.random() * 10, -110 + rng.random() * 20) for i in range(30)], "city long, clat double, clon double")
    stations = spark.createDataFrame([(i, 28 + rng.random() * 10, -110 + rng.random() * 20, 0) for i in range(12)], "code long, slat double, slon double, sstate long")
    near = lambda: {r.city: r.station for r in entities.nearest_station(places, stations).collect()}
    whole = near()
    monkeypatch.setattr(entities, "MOST_PAIRS", 0)
    assert near() == whole and len(whole) == 30


def test_stations_at_one_position_are_one(spark, monkeypatch):
    """Five hundred stations at two positions make two pairs with a place, and the first code of the nearer position is the nearest."""
    places = spark.createDataFrame([(1, 30.0, -100.0)], "city long, clat double, clon double")
    stations = spark.createDataFrame([(i, 30.0 + i % 2, -100.0, 0) for i in range(1, 501)], "code long, slat double, slon double, sstate long")
    monkeypatch.setattr(entities, "MOST_PAIRS", 2)
    monkeypatch.setattr(entities, "near_pairs", None)
    assert [tuple(r) for r in entities.nearest_station(places, stations).collect()] == [(1, 2)]


def test_one_sided_windows(spark):
    """A window outside the data is left out, and the average is that of the other side."""
    week = 7 * 24 * 60 * MIN
    rows = [entity(1, start=0, end=100 * MIN), entity(2, start=10 * MIN, end=11 * MIN), entity(3, start=week + 110 * MIN, end=week + 111 * MIN), entity(4, start=2 * week, end=2 * week + 300 * MIN)]
    df = spark.createDataFrame(rows, COLUMNS)
    owner = df.where("entity_id = 1")
    got = {edge: lasting.halo_counts(owner, df, edge=edge).collect() for edge in ("keep", "one_sided", "complete")}
    assert [(r.n_during, r.n_before, r.n_after) for r in got["one_sided"]] == [(1, None, 1)]
    assert [(r.n_during, r.n_before, r.n_after) for r in got["keep"]] == [(1, 0, 1)] and got["complete"] == []
    m = influence.means(lasting.halo_counts(owner, df, edge="one_sided"), [F.lit(1).alias("bucket")]).first()
    assert (m.size_before, m.size_after, m.mean_avg) == (0, 1, 1.0)


def test_fused_members_are_not_counted(spark):
    rows = [entity(1, start=0, end=100 * MIN), entity(2, start=50 * MIN, end=200 * MIN), entity(3, start=60 * MIN, end=61 * MIN)]
    df = spark.createDataFrame(rows, COLUMNS)
    found = df.where("entity_id < 3")
    owners = lasting.fused_windows(found)
    assert [(r.long_id, r.n_during) for r in lasting.halo_counts(owners, df, excluded=found).collect()] == [(1, 1)]


def test_feed_source_as_stream(spark, tmp_path):
    spark.dataSource.register(feed_source.ReportFeed)
    stream = spark.readStream.format("report_feed").option("reports", 120).option("step", 50).load()
    query = stream.writeStream.format("memory").queryName("reports_seen").option("checkpointLocation", str(tmp_path)).start()
    query.processAllAvailable()
    query.stop()
    assert sorted(r.id for r in spark.table("reports_seen").collect()) == list(range(120))


def test_markup_trees(spark):
    pages = spark.createDataFrame([(1, "<html><body><p>a<br>b</p><p>c</body></html>"), (2, None)], "page_id long, html string")
    assert [(r.node, r.parent, r.label) for r in studies.markup(pages).orderBy("node").collect()] == [(0, None, "html"), (1, 0, "body"), (2, 1, "p"), (3, 2, "br"), (4, 1, "p")]
