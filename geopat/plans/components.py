"""Connected components of links between ids, without gathering them anywhere."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import FEW_ROWS, hot_join, written
from .ship import ship


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node reachable) for the nodes of the links (a, b) that are not smallest themselves."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, root[i], low)
        np.minimum.at(new, root[j], low)
        new = new[new]
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            break
        root = new
    moved = root != np.arange(len(nodes))
    return nodes[moved], nodes[root[moved]]


def _thin(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of a task, batch by batch, reduced to stars around each piece's smallest id; an id linked with itself gives (id, id)."""

    def stars(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        hi, lo = forest(a, b)
        alone = np.setdiff1d(a[a == b], hi)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate((hi, alone))), pa.array(np.concatenate((lo, alone)))], names=["hi", "lo"])

    a, b = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for batch in rows:
        a = np.concatenate((a, batch["a"].to_numpy()))
        b = np.concatenate((b, batch["b"].to_numpy()))
        if len(a) > 500_000:
            thin = stars(a, b)
            if thin.num_rows > 250_000:
                yield thin
                a, b = a[:0], b[:0]
            else:
                a, b = thin["hi"].to_numpy(), thin["lo"].to_numpy()
    if len(a):
        yield stars(a, b)


def connected(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component) for every id in the links (a, b); component is the smallest id reachable.

    Tasks first thin their own links to stars.  Then, in rounds, larger neighbours and
    smaller neighbours of each node are hung on its smallest neighbour in turn, until
    the stars stay as they are.  The smallest neighbour is an aggregate that tasks
    combine before the shuffle, and hubs get theirs by broadcast, so their links stay in
    place.  An id linked with itself alone is a component.  Links of null are left out.
    """
    ship(links.sparkSession)
    plain = links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a is not null and b is not null")
    thin = written(plain.mapInArrow(_thin, "hi long, lo long"))
    stars = thin.where("hi <> lo")
    size, before = thin.count(), None
    if size < FEW_ROWS:  # checked: one task can settle these
        once = written(thin.select(F.col("hi").alias("a"), F.col("lo").alias("b")).coalesce(1).mapInArrow(_thin, "hi long, lo long"))
        return once.where("hi <> lo").select(F.col("hi").alias("node"), F.col("lo").alias("component")).union(once.select("lo", "lo").distinct())
    for _ in range(most_rounds):
        both = stars.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(stars.select("lo", "hi"))
        least = written(both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")))
        large = written(hot_join(both.where("v > u"), least, "u", "n", 2 * size).select(F.col("v").alias("hi"), F.least("u", "m").alias("lo")).distinct())
        lowest = written(large.groupBy("hi").agg(F.min("lo").alias("m"), F.count("*").alias("n")))
        small = hot_join(large, lowest, "hi", "n", size).select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi <> lo")
        stars = written(small.union(lowest.select("hi", "m")).distinct())
        now = stars.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if before is not None and tuple(now) == before:
            break
        size, before = now[0], tuple(now)
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    alone = thin.where("hi = lo").join(stars.select("hi"), "hi", "left_anti")
    return stars.select(F.col("hi").alias("node"), F.col("lo").alias("component")).union(stars.select("lo", "lo").union(alone.select("hi", "lo")).distinct())

