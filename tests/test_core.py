"""Worked cases of the propagation and influence operators."""

import math
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from geopat.functions.stats import t_upper
from geopat.operators import cluster, forest, lasting, mine, relate
from geopat.plans import components, scratch

MIN = 60_000_000
COLUMNS = "entity_id long, type string, kind string, start_us long, end_us long, street long, side string, zip long, city long, state long, lat double, lon double, station long"


def entity(i, kind="traffic", type_="congestion", start=0, end=None, street=1, side="R", lat=30.0, station=1):
    return (i, type_, kind, start, start + MIN if end is None else end, street, side, 9, 1, 1, lat, -100.0, station)


def linked(spark, *rows):
    return {(r.parent_id, r.child_id) for r in relate.links(spark.createDataFrame(list(rows), COLUMNS)).collect()}


def test_gap_edges(spark):
    assert linked(spark, entity(1), entity(2)) == set()
    assert linked(spark, entity(1), entity(2, start=1)) == {(1, 2)}
    assert linked(spark, entity(1), entity(2, start=10 * MIN)) == {(1, 2)}
    assert linked(spark, entity(1), entity(2, start=10 * MIN + 1)) == set()


def test_place_edges(spark):
    assert linked(spark, entity(1), entity(2, start=MIN, side="L")) == set()
    assert linked(spark, entity(1, street=None), entity(2, start=MIN, street=None)) == set()
    assert linked(spark, entity(1), entity(2, start=MIN, lat=30 + 299 / 111195.0)) == {(1, 2)}
    assert linked(spark, entity(1), entity(2, start=MIN, lat=30 + 301 / 111195.0)) == set()


def test_weather_rules(spark):
    snow, rain = entity(1, "weather", "snow"), entity(2, "weather", "rain")
    assert linked(spark, snow, rain, entity(3, start=39 * MIN), entity(4, start=41 * MIN, side="L")) == {(1, 3)}
    assert linked(spark, entity(1), entity(2, "weather", "rain", start=MIN)) == set()


def trees(spark, *parents):
    """Nodes of trees given as lists of (label, parent place)."""
    rows, at = [], 0
    for tree, nodes in enumerate(parents):
        for i, (label, up) in enumerate(nodes):
            rows.append((1, tree, at + i, None if up is None else at + up, label, i))
        at += len(nodes)
    return spark.createDataFrame(rows, "g long, tree long, node long, parent long, label string, start_us long")


FOUR = ([("a", None), ("b", 0)], [("a", None), ("c", 0), ("b", 1)], [("a", None), ("b", 0), ("c", 0)], [("b", None), ("a", 0), ("c", 1)])


def test_four_trees(spark):
    found = {r["shape"]: r.support_count for r in mine.frequent(trees(spark, *FOUR), ["g"], 0.75).collect()}
    assert found == {"a(b)": 3, "a(c)": 3}


def test_variants(spark):
    def count(shape, *nodes, **options):
        return {r["shape"]: r.support_count for r in mine.frequent(trees(spark, *nodes), ["g"], 0.01, **options).collect()}.get(shape, 0)

    chain = [("a", None), ("x", 0), ("b", 1)]
    assert count("a(b)", chain) == 1 and count("a(b)", chain, kind="induced") == 0
    line = [("a", None), ("b", 0), ("c", 1)]
    assert count("a(b,c)", line) == 0 and count("a(b,c)", line, siblings="any") == 1
    assert count("a(a,a)", [("a", None), ("a", 0), ("a", 0)]) == 1


def brute(nodes):
    """All embedded shapes of a tree with disjoint siblings, by choosing node sets."""
    up = [p for _, p in nodes]

    def above(x):
        while up[x] is not None:
            x = up[x]
            yield x

    out = set()
    for size in range(1, len(nodes) + 1):
        for chosen in combinations(range(len(nodes)), size):
            parent = {x: next((a for a in above(x) if a in chosen), None) for x in chosen}
            if sum(p is None for p in parent.values()) == 1:
                def name(x, parent=parent):
                    kids = sorted(name(c) for c in parent if parent[c] == x)
                    return nodes[x][0] + (f"({','.join(kids)})" if kids else "")

                out.add(name(next(x for x, p in parent.items() if p is None)))
    return out


def test_miner_is_enumeration(spark):
    nodes = [("a", None), ("b", 0), ("a", 0), ("b", 2), ("c", 2), ("b", 1)]
    found = {r["shape"] for r in mine.frequent(trees(spark, nodes), ["g"], 0.01, max_nodes=6).collect()}
    assert found == {x for x in brute(nodes) if "(" in x}


def test_chain_forest(spark):
    parents = spark.createDataFrame([(i, i - 1) for i in range(1, 25)], "node long, parent long")
    nodes = forest.build(parents).collect()
    assert len(nodes) == 25 and {r.tree for r in nodes} == {0} and max(r.depth for r in nodes) == 24


def test_minimum_support(spark):
    rows = spark.createDataFrame([(1,), (100,), (1000,)], "x long").select(F.round(mine.adaptive_support(F.col("x")), 6)).collect()
    assert [r[0] for r in rows] == [round(math.exp(-(0.004 * x + 1.5)) + 0.05, 6) for x in (1, 100, 1000)]


def test_t_tail(spark):
    p = spark.range(1).select(t_upper(F.lit(2.0), F.lit(8.0)), t_upper(F.lit(-2.0), F.lit(8.0))).first()
    assert math.isclose(p[0], 0.0402581190, abs_tol=1e-9) and math.isclose(p[0] + p[1], 1)


def test_fuse_chain(spark):
    rows = spark.createDataFrame([entity(1, end=10), entity(2, start=5, end=20, type_="accident"), entity(3, start=15, end=30)], COLUMNS)
    pairs = lasting.conflicts(rows)
    assert {tuple(r) for r in pairs.collect()} == {(1, 2), (2, 3)}
    fused = lasting.fuse_components(rows, pairs).collect()
    assert [(r.id, r.start_us, r.end_us, r.type, r.members) for r in fused] == [(1, 0, 30, "accident_congestion", 3)]


def test_kmeans_line(spark):
    rows = spark.createDataFrame([(float(x),) for x in (1, 2, 3, 11, 12, 13)], "v double")
    assert cluster.lloyd_1d(rows, "v", 2) == [2.0, 12.0]


def test_plans_have_no_nested_loop(spark):
    rows = spark.createDataFrame([entity(1), entity(2, start=5)], COLUMNS)
    for df in (relate.links(rows), lasting.conflicts(rows)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_components(spark, monkeypatch):
    chain = [(i, i + 1) for i in range(40)] + [(100, 200), (200, 300), (7, 7), (500, 500), (None, 3)] + [(1000, 1001 + i) for i in range(60)] + [(5000 - i, 6000) for i in range(60)]
    links = spark.createDataFrame(chain, "a long, b long").repartition(8)
    expected = {**dict.fromkeys(range(41), 0), 100: 100, 200: 100, 300: 100, 500: 500, **dict.fromkeys(range(1000, 1061), 1000), **dict.fromkeys([*range(4941, 5001), 6000], 4941)}
    for few in (20_000, 0):  # with and without a join of their own for hubs
        monkeypatch.setattr(scratch, "FEW_ROWS", few)
        monkeypatch.setattr(components, "FEW_ROWS", few)
        monkeypatch.setattr(scratch, "HOT_SHARE", 0.1)
        assert {r.node: r.component for r in components.connected(links).collect()} == expected
    with pytest.raises(RuntimeError):
        components.connected(links, most_rounds=1)


def test_no_folder_of_its_own_on_a_cluster(spark):
    class Elsewhere:
        master = "spark://host:7077"

    class Session:
        conf, sparkContext = type("C", (), {"get": staticmethod(lambda *_: None)}), Elsewhere

    with pytest.raises(RuntimeError):
        scratch.folder(Session)
