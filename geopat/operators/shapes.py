"""Containment, support and reduced lists of shapes."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geopat.operators.mine import Shape, Tree, _grow, text
from geopat.plans.ship import ship


@lru_cache(maxsize=100_000)
def parse(shape: str) -> Shape:
    """Preorder (depth, label) of a shape's text."""
    out, depth, word = [], 0, ""
    for ch in shape + ",":
        if ch not in "(),":
            word += ch
            continue
        if word:
            out.append((depth, word))
            word = ""
        depth += (ch == "(") - (ch == ")")
    return tuple(out)


def tree_of(shape: Shape) -> Tree:
    """The shape as a tree of its own."""
    path: list[int] = []
    parents: list[int | None] = []
    for i, (depth, _) in enumerate(shape):
        parents.append(path[depth - 1] if depth else None)
        path = [*path[:depth], i]
    return Tree(list(range(len(shape))), parents, [x for _, x in shape], list(range(len(shape))))


def contains(tree: Tree, shape: Shape, kind: str = "embedded", siblings: str = "disjoint", ordered: bool = False) -> bool:
    """Whether the shape lies in the tree; images grow along the shape's own preorder."""
    images = [(i,) for i, label in enumerate(tree.label) if label == shape[0][1]]
    for size in range(1, len(shape)):
        images = list(dict.fromkeys(_grow(tree, shape[:size], images, kind, siblings, ordered).get(shape[: size + 1], [])))
    return bool(images)


def support(packed: DataFrame, group: list[str], shape: str, **options: object) -> DataFrame:
    """(group, trees, support_count, support) of one shape over packed trees: one scan."""
    ship(packed.sparkSession)
    wanted = parse(shape)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in packed.select(*group).schema) + ", hit boolean"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            hits = []
            for n in batch["nodes"]:
                tree = Tree([x["node"] for x in n], [None if pd.isna(x["parent"]) else x["parent"] for x in n], [x["label"] for x in n], [x["start_us"] for x in n])
                hits.append(contains(tree, wanted, **options))
            yield batch[group].assign(hit=hits)

    counted = packed.select(*group, "nodes").mapInPandas(run, schema).groupBy(*group).agg(F.count("*").alias("trees"), F.count_if("hit").alias("support_count"))
    return counted.withColumn("support", F.round(F.col("support_count") / F.col("trees"), 6))


@lru_cache(maxsize=100_000)
def fewer(shape: str) -> tuple[str, ...]:
    """The shapes of one node less in a shape: without a leaf, without an inner node, whose children go to its parent, or without a root of one child."""
    nodes, out = parse(shape), set()
    for i, (depth, _) in enumerate(nodes):
        end = next((j for j in range(i + 1, len(nodes)) if nodes[j][0] <= depth), len(nodes))
        if i or sum(d == 1 for d, _ in nodes) == 1:
            lifted = [(d - 1, x) for d, x in nodes[i + 1 : end]]
            out.add(text((*nodes[:i], *lifted, *nodes[end:])))
    return tuple(sorted(out))


def reduced(shapes: DataFrame, group: list[str], closed: bool = False) -> DataFrame:
    """Shapes in no larger shape of their group's list (maximal), or in none of the same support count (closed).

    The list is one of `frequent`: it holds a shape's smaller shapes too, so of the larger ones those of one node more
    decide.  Nodes that an image leaves out go one at a time, and support only grows on the way.
    """
    ship(shapes.sparkSession)

    @F.pandas_udf("array<string>")
    def smaller(one: pd.Series) -> pd.Series:
        return one.map(lambda x: list(fewer(x)))

    count = ["support_count"] if closed else []
    within = shapes.select(*group, *count, F.explode(smaller("shape")).alias("shape")).distinct()
    # Never by broadcast: Spark takes the list to be as small as the file of shapes, which holds each text once.
    return shapes.join(within.hint("merge"), [*group, *count, "shape"], "left_anti").select(*shapes.columns)


def pairs(nodes: DataFrame, deepest: int | None = None) -> DataFrame:
    """(tree, state, city, top, low): each node with each of its ancestors; the loop runs to the greatest depth."""
    base = nodes.select("tree", "state", "city", F.col("node").alias("low"), F.col("parent").alias("top")).where("top is not null")
    deepest = deepest or nodes.agg(F.max("depth")).first()[0] or 0
    up = nodes.select(F.col("node").alias("top"), F.col("parent").alias("further")).where("further is not null")
    out, step = base, base
    for _ in range(int(deepest) - 1):
        step = step.join(up, "top").select("tree", "state", "city", "low", F.col("further").alias("top"))
        out = out.union(step)
    return out.select("tree", "state", "city", "top", "low")


def profile(found: DataFrame, nodes: DataFrame, df: DataFrame, width: int = 2) -> DataFrame:
    """Two-node shapes: states, mean support, hours with most roots (a window of `width` hours round the clock, earliest on a tie), road class."""
    label = nodes.select(F.col("node").alias("n"), "label")
    root = df.select(F.col("entity_id").alias("top"), (F.floor(F.col("start_us") / 3_600_000_000) % 24).alias("hour"), "road", F.col("type").alias("root"))
    each = pairs(nodes).join(root, "top").join(label, F.col("low") == F.col("n")).withColumn("shape", F.concat("root", F.lit("("), "label", F.lit(")")))
    kept = each.join(found.select("state", "city", "shape"), ["state", "city", "shape"], "left_semi")
    hours = kept.groupBy("shape", "hour").agg(F.count("*").alias("n"), F.count_if(F.col("road") == "interstate").alias("fast"))
    starts = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: (F.col("hour") - i + 24) % 24)
    windows = hours.withColumn("start", F.explode(starts)).groupBy("shape", "start").agg(F.sum("n").alias("n"))
    peak = windows.groupBy("shape").agg(F.max_by("start", F.struct("n", -F.col("start"))).cast("long").alias("peak_hour"))
    share = F.sum("fast") / F.sum("n")
    road = hours.groupBy("shape").agg(F.sum("n").alias("instances"), F.when(share >= 2 / 3, "interstate").when(share <= 1 / 3, "city").otherwise("mixture").alias("road_class"))
    of_state = found.groupBy("shape", "root_label", "state").agg(F.avg(F.col("support_count") / F.col("trees")).alias("s"), F.sum(F.col("support_count") / F.col("trees")).alias("t"), F.count("*").alias("c"))
    mean = of_state.groupBy("shape", "root_label").agg(F.count("*").alias("states"), F.round(F.sum("t") / F.sum("c"), 6).alias("avg_support_city"), F.round(F.avg("s"), 6).alias("avg_support_state"))
    return mean.join(peak, "shape").join(road, "shape")
