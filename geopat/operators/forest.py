"""Relation trees from links: one parent per child, roots by pointer doubling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geopat.plans.scratch import written


def pick_parent(linked: DataFrame, rule: str = "hash", seed: int = 0) -> DataFrame:
    """(node, parent): one parent of each child, by a seeded hash, an arithmetic rule, or the nearest start."""
    p, c = F.col("parent_id"), F.col("child_id")
    order = {"hash": F.xxhash64(F.lit(seed), c, p), "arith": (7919 * p + 104729 * c) % 1000003, "nearest_time": F.col("gap_us")}[rule]
    return linked.groupBy("child_id").agg(F.min_by(p, F.struct(order, p)).alias("parent")).select(F.col("child_id").alias("node"), "parent")


def build(parents: DataFrame) -> DataFrame:
    """(tree, node, parent, depth) of every node in a tree of two or more.  Links run forward in time, so there are no cycles."""
    parents = written(parents)
    roots = parents.select(F.col("parent").alias("node")).distinct().join(parents.select("node"), "node", "left_anti").select("node", F.col("node").alias("up"), F.lit(0).cast("long").alias("hops"))
    table = written(parents.select("node", F.col("parent").alias("up"), F.lit(1).cast("long").alias("hops")).union(roots))
    for doubled in range(1, 65):
        above = table.select(F.col("node").alias("up"), F.col("up").alias("up2"), F.col("hops").alias("hops2"))
        table = written(table.join(above, "up").select("node", F.col("up2").alias("up"), (F.col("hops") + F.col("hops2")).alias("hops")))
        if (table.agg(F.max("hops")).first()[0] or 0) < 2**doubled:
            break
    return table.join(parents, "node", "left").select(F.col("up").alias("tree"), "node", "parent", F.col("hops").alias("depth"))


def places(nodes: DataFrame, df: DataFrame) -> DataFrame:
    """Nodes with label and start, and the tree's state and city: the root's, or under weather that of the smallest traffic id."""
    full = nodes.join(df.select(F.col("entity_id").alias("node"), F.col("type").alias("label"), "kind", "state", "city", "start_us"), "node")
    where = full.groupBy("tree").agg(
        F.min_by(F.struct("state", "city"), F.struct(F.when((F.col("node") == F.col("tree")) & (F.col("kind") == "traffic"), 0).when(F.col("kind") == "traffic", 1).otherwise(2), "node")).alias("at")
    )
    return full.drop("state", "city").join(where, "tree").select("tree", "node", "parent", "depth", "label", "kind", "start_us", F.col("at.state").alias("state"), F.col("at.city").alias("city"))


def stats(nodes: DataFrame) -> DataFrame:
    """One row: trees, nodes, largest tree, greatest depth."""
    sizes = nodes.groupBy("tree").agg(F.count("*").alias("n"), F.max("depth").alias("d"))
    return sizes.agg(F.count("*").alias("trees"), F.sum("n").alias("nodes"), F.max("n").alias("largest"), F.max("d").alias("deepest"))


#: WITH-list items `f` (tree, node, parent, depth) and `g` (with label and place) for DuckDB, after `e` and `l`.
FOREST_SQL = """
pp as (select child_id node, arg_min(parent_id, [(7919 * parent_id + 104729 * child_id) % 1000003, parent_id]) parent from l group by 1),
f as (
  select distinct parent tree, parent node, null::bigint parent, 0::bigint depth from pp where parent not in (select node from pp)
  union all select f.tree, pp.node, pp.parent, f.depth + 1 from f join pp on pp.parent = f.node),
g0 as (select f.*, e.type as label, e.kind, e.state, e.city, e.start_us from f join e on e.entity_id = f.node),
gp as (select tree, arg_min([state, city], [case when node = tree and kind = 'traffic' then 0 when kind = 'traffic' then 1 else 2 end, node]) spot from g0 group by 1),
g as (select g0.tree, node, parent, depth, label, kind, spot[1] state, spot[2] city from g0 join gp on gp.tree = g0.tree)
"""
