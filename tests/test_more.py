"""Density, fusion by order and to a fixpoint, containment and reduced lists, weather intervals and streams, against brute force."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from geopat import experiments, surface_more, workloads
from geopat.operators import cluster, density, influence, lasting, shapes, weather
from geopat.streaming import feeds
from tests.test_core import COLUMNS, MIN, entity

HOUR = 60 * MIN


def metres(a, b):
    h = math.sin(math.radians(b[0] - a[0]) / 2) ** 2 + math.cos(math.radians(a[0])) * math.cos(math.radians(b[0])) * math.sin(math.radians(b[1] - a[1]) / 2) ** 2
    return 2 * 6371008.8 * math.asin(math.sqrt(min(1.0, h)))


def scattered(n, seed):
    pick = random.Random(seed)
    return [(i, 30 + pick.randrange(40) * 0.0004, -100 + pick.randrange(20) * 0.0005) for i in range(n)]


@pytest.mark.parametrize("count_self", [False, True])
def test_dbscan_is_brute_force(spark, count_self):
    pts = scattered(160, 3)
    eps, least = 75.0, 5
    near = {i: [j for j, b, c in pts if j != i and metres((x, y), (b, c)) <= eps] for i, x, y in pts}
    core = {i for i in near if len(near[i]) + count_self >= least}
    label = {}
    for i in sorted(core):
        todo = [i] if i not in label else []
        while todo:
            j = todo.pop()
            if j not in label:
                label[j] = i
                todo += [k for k in near[j] if k in core]
    want = {i: label[i] if i in core else min((label[j] for j in near[i] if j in core), default=-1) for i in near}
    got = density.dbscan(spark.createDataFrame(pts, "id long, lat double, lon double"), eps, least, count_self).collect()
    assert {r.id: r.cluster for r in got} == want
    assert {r.id for r in got if r.core} == core
    assert len(set(want.values())) > 2 and -1 in want.values()


def test_nearest_is_brute_force(spark):
    pts = [*scattered(60, 5), (999, 31.5, -101.0)]
    got = {r.place: (r.weight, r.dist) for r in density.nearest(spark.createDataFrame(pts, "id long, lat double, lon double"), 20.0).collect()}
    assert sum(w for w, _ in got.values()) == len(pts)
    for i, (_, dist) in got.items():
        at = next((x, y) for j, x, y in pts if j == i)
        assert dist == pytest.approx(min(metres(at, (x, y)) for j, x, y in pts if j != i), abs=1e-6)


def test_nearest_of_one_point(spark):
    one = spark.createDataFrame([(1, 30.0, -100.0)], "id long, lat double, lon double")
    assert [(r.weight, r.dist) for r in density.nearest(one, most_rounds=3).collect()] == [(1, None)]


def crowd(n, seed):
    pick = random.Random(seed)
    out = []
    for i in range(n):
        start = pick.randrange(200) * HOUR
        kind, type_ = pick.choice([("traffic", "event"), ("traffic", "flow_incident"), ("weather", "rain")])
        out.append(entity(i, kind, type_, start, start + pick.randrange(1, 12) * HOUR, lat=30 + pick.randrange(6) * 0.15, station=pick.randrange(3)))
    return out


def clash(a, b):
    meets = a[3] <= b[4] and b[3] <= a[4]
    return meets and (a[12] == b[12] if "weather" in (a[2], b[2]) else metres((a[10], a[11]), (b[10], b[11])) <= lasting.RADIUS)


def test_greedy_is_one_ordered_pass(spark):
    rows = crowd(150, 7)
    df = spark.createDataFrame(rows, COLUMNS)
    taken, want = set(), {}
    for a in sorted(rows, key=lambda r: (r[3], r[0])):
        if a[0] in taken:
            continue
        group = [b for b in rows if b[0] not in taken and (b[0] == a[0] or ((b[3], b[0]) > (a[3], a[0]) and clash(a, b)))]
        taken |= {b[0] for b in group}
        want[a[0]] = len(group)
    got = {r.id: r.members for r in lasting.fuse_greedy(df, lasting.conflicts(df)).collect()}
    assert got == want
    assert max(want.values()) > 2


def test_fixpoint_leaves_no_conflict(spark):
    df = spark.createDataFrame(crowd(150, 11), COLUMNS)
    fused = lasting.fuse_fixpoint(df)
    assert fused.agg(F.sum("members")).first()[0] == 150
    assert lasting.conflicts(fused.withColumnRenamed("id", "entity_id")).isEmpty()
    assert fused.count() <= lasting.fuse_components(df, lasting.conflicts(df)).count()


def test_fusion_of_nothing(spark):
    df = spark.createDataFrame([], COLUMNS)
    for fused in (lasting.fuse_greedy(df, lasting.conflicts(df)), lasting.fuse_fixpoint(df)):
        assert fused.count() == 0


def test_containment():
    tree = shapes.tree_of(shapes.parse("a(x(b),c(d,d))"))
    assert shapes.contains(tree, shapes.parse("a(b)"))
    assert not shapes.contains(tree, shapes.parse("a(b)"), kind="induced")
    assert shapes.contains(tree, shapes.parse("c(d,d)"))
    assert not shapes.contains(tree, shapes.parse("a(x,b)"))
    assert shapes.contains(tree, shapes.parse("a(x,b)"), siblings="any")
    assert shapes.contains(tree, shapes.parse("a(d,b)"))
    assert not shapes.contains(tree, shapes.parse("a(d,b)"), ordered=True)


def test_reduced_lists(spark):
    rows = [(1, "a(b)", 2, 5), (1, "a(c)", 2, 9), (1, "a(b,c)", 3, 5), (2, "a(b)", 2, 4)]
    df = spark.createDataFrame(rows, "city int, shape string, size long, support_count long")
    names = lambda out: {(r.city, r.shape) for r in out.collect()}
    assert names(shapes.reduced(df, ["city"])) == {(1, "a(b,c)"), (2, "a(b)")}
    assert names(shapes.reduced(df, ["city"], closed=True)) == {(1, "a(b,c)"), (1, "a(c)"), (2, "a(b)")}


def test_weather_intervals(spark):
    gap = 10 * HOUR
    rows = [(1, t, 10.0, 10.0, p, "rain") for t, p in ((0, 1.0), (gap, 12.0), (2 * gap + 1, 1.0))]
    df = spark.createDataFrame([*rows, (1, 3 * gap, 10.0, 10.0, 0.0, "clear")], "station long, time_us long, temperature double, wind double, precipitation double, condition string")
    got = {(r.start_us, r.end_us, r.records, r.intensity) for r in weather.extract(df, gap).collect()}
    assert got == {(0, gap, 2, "heavy"), (2 * gap + 1, 2 * gap + 1, 1, "light")}
    assert {r.end_us for r in weather.extract(df, gap, "next").collect()} == {2 * gap + 1, 3 * gap}


def islands(times, gap):
    """(first, last, count) of runs of sorted times without a gap over `gap`."""
    out = []
    for t in sorted(times):
        if out and t - out[-1][1] <= gap:
            out[-1] = (out[-1][0], t, out[-1][2] + 1)
        else:
            out.append((t, t, 1))
    return out


@pytest.mark.parametrize("rule", ["last", "next"])
def test_tied_weather_records_stay_together(spark, rule):
    """Every time is held by several records, so each interval opens and ends with a tie; none may be cut by it."""
    pick, gap = random.Random(21), 20 * weather.DAY
    at = {(s, kind): [t for t in pick.sample(range(0, 400 * weather.DAY, weather.DAY), 25) for _ in range(pick.randrange(2, 6))] for s in range(6) for kind in ("rain", "fog")}
    rows = [(s, t, 10.0, 10.0, 1.0, kind) for (s, kind), times in at.items() for t in times]
    pick.shuffle(rows)
    df = spark.createDataFrame(rows, "station long, time_us long, temperature double, wind double, precipitation double, condition string").repartition(7)

    def end(s, kind, first, last):
        later = [[u for u in at[s, "rain"] + at[s, "fog"] if u > t] for t in at[s, kind] if first <= t <= last]
        return max((min(us) for us in later if us), default=last) if rule == "next" else last

    want = sorted((s, kind, first, end(s, kind, first, last), n) for (s, kind), times in at.items() for first, last, n in islands(times, gap))
    assert sorted((r.station, r.type, r.start_us, r.end_us, r.records) for r in weather.extract(df, gap, rule).collect()) == want


def test_two_samples(spark):
    df = spark.createDataFrame([(1, float(v)) for v in (3, 4, 5, 6, 7)] + [(0, float(v)) for v in (1, 2, 3, 4, 5)], "g int, v double")
    for r in influence.two_sample(df, "v", F.col("g") == 1, F.col("g") == 0).collect():
        assert (r.t, r.df, r.p) == (2.0, 8.0, pytest.approx(0.040258, abs=1e-6))


def test_sessions_of_a_stream(spark, tmp_path):
    rows = [(u, f"2024-01-{d:02d} {h:02d}:00:00", "click") for u, d, h in ((1, 1, 0), (1, 1, 5), (1, 1, 12), (2, 1, 3), (1, 20, 0))]
    df = spark.createDataFrame(rows, "user_id long, ts string, event_type string").withColumn("ts", F.to_timestamp("ts"))
    df.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    out = feeds.upsert(feeds.sessions(spark.readStream.schema(df.schema).parquet(f"{tmp_path}/events.parquet")), ["user_id", "start"], "complete")
    assert {(r.user_id, r.n) for r in out.where("start < '2024-01-10'").collect()} == {(1, 2), (1, 1), (2, 1)}


def test_tied_records_of_a_stream_stay_together(spark, tmp_path):
    """Several records a day, dealt over the files of a folder: an interval takes all records of its first and last day."""
    pick, day = random.Random(20), 24 * HOUR
    at = {s: [t for t in pick.sample(range(0, 400 * day, day), 40) for _ in range(pick.randrange(2, 6))] for s in range(6)}
    rows = [(s, t) for s, times in at.items() for t in times]
    pick.shuffle(rows)
    df = spark.createDataFrame(rows, "l_suppkey long, us long").select("l_suppkey", F.timestamp_micros("us").cast("timestamp_ntz").alias("l_shipdate"))
    df.repartition(5).write.parquet(f"{tmp_path}/lineitem.parquet")
    want = sorted((s, *span) for s, times in at.items() for span in islands(times, 10 * day))
    assert sorted((r.station, r.start_us, r.end_us, r.records) for r in surface_more.st_weather(spark, str(tmp_path)).collect()) == want


def test_description_length():
    points, labels, centres = np.array([[0.0], [2.0], [10.0], [14.0]]), np.array([0, 0, 1, 1]), np.array([[1.0], [12.0]])
    # Distances 1, 1, 2, 2: mean 3/2, deviation 1/2.  Parameters cost log 4, two centres 2 log 4.
    expected = 4 * (0.5 + math.log(0.5 * math.sqrt(2 * math.pi))) + 3 * math.log(4)
    length, degenerate = cluster.description_length(points, labels, centres)
    assert abs(length - expected) < 1e-9 and not degenerate


def chains(spark):
    """Ten equal chains of five nodes a, b, c, d, e in one city."""
    rows = [(1, 1, tree, 10 * tree + i, 10 * tree + i - 1 if i else None, "abcde"[i], i) for tree in range(10) for i in range(5)]
    return spark.createDataFrame(rows, "state long, city long, tree long, node long, parent long, label string, start_us long")


@pytest.mark.parametrize("kind", ["maximal", "closed"])
def test_reduced_queries_read_all_sizes(spark, monkeypatch, kind):
    monkeypatch.setattr(experiments, "entities", lambda *_: None)
    monkeypatch.setattr(experiments, "nodes_of", lambda *_: chains(spark))
    assert [r["shape"] for r in workloads.QUERIES[f"w_shapes_{kind}_fixed02"](spark, "").collect()] == ["a(b(c(d(e))))"]


def test_queries_over_all_sizes(spark, monkeypatch):
    nodes = chains(spark)
    for module in (workloads, experiments):
        monkeypatch.setattr(module, "entities", lambda *_: nodes.select("state"))
        monkeypatch.setattr(module, "nodes_of", lambda *_: nodes)
    run = lambda name: workloads.QUERIES[f"{name}_fixed02"](spark, "").collect()
    # A chain of five nodes holds 26 subsets of two nodes or more.
    assert [tuple(r) for r in run("w_shape_catalogue_all")] == [(26, 26, 2, 5)]
    assert {r["root_label"]: r["shapes"] for r in run("w_initiators_all")} == {"a": 15, "b": 7, "c": 3, "d": 1}
    assert len(run("w_state_vectors_all")) == 26 and len(run("w_shape_top12_all")) == 12 and run("w_shapes_lost_all") == []
    assert max(r["size"] for r in run("w_shapes_city_ordered")) == 5
