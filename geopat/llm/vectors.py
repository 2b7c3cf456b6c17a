"""Near-duplicate vectors by PCA-ordered tiled comparison.

Vectors of one label are compared, all against all, in tiles.  Coordinates are rotated
so that leading ones hold most of the variance; a tile adds them up a few at a time and
bounds what is left of each pair's product by the norms of the remaining coordinates.
Rows and columns in which no pair can reach the threshold drop out; pairs that stay to the
end get their cosine in double precision from the vectors as given.  The first two coordinates
also cut space into cells as wide as linked unit vectors can be apart, so that only
neighbouring cells meet; cells are cut into blocks, so no label or cell fills a task.

The rotation is fitted on at most MOST_ROTATION vectors picked by a hash (a documented
bound); it changes only the speed.  Equal vectors of a label are one class whose size
counts as so many links.  Vectors that are null, zero, or hold null, NaN or infinite
components, and rows with a null label or id, link with nothing; so do vectors of other lengths.
An empty table gives no rows.  Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, ship, table
from geopat.plans.components import connected, forest

MOST_ROTATION = 10_000
BLOCK = 1024
STRIDE = 8


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _matrix(rows: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(rows), np.float64).reshape(len(rows), -1)


def rotation(classes: DataFrame, most: int) -> dict[int, np.ndarray]:
    """Principal axes by vector length, from a bounded sample."""
    sample = classes.orderBy(F.xxhash64("rep"), "rep").limit(most).select("dims", "v").toPandas()
    axes = {}
    for dims, group in sample.groupby("dims"):
        x = _unit(np.array(group["v"].tolist(), np.float64))
        axes[int(dims)] = np.linalg.eigh(x.T @ x)[1][:, ::-1].copy()
    return axes


def tile(left: np.ndarray, right: np.ndarray, axes: np.ndarray, threshold: float, same: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Places (i, j) with cosine(left[i], right[j]) >= threshold."""
    a, b = _unit(left) @ axes, _unit(right) @ axes
    rest_a = np.sqrt(np.maximum(np.cumsum((a * a)[:, ::-1], axis=1)[:, ::-1], 0))
    rest_b = np.sqrt(np.maximum(np.cumsum((b * b)[:, ::-1], axis=1)[:, ::-1], 0))
    rows, columns = np.arange(len(a)), np.arange(len(b))
    product = np.zeros((len(a), len(b)))
    done, dims = 0, a.shape[1]
    while done < dims and len(rows) and len(columns):
        upto = min(dims, done + STRIDE)
        product += a[rows, done:upto] @ b[columns, done:upto].T
        done = upto
        bound = product if done == dims else product + rest_a[rows, done][:, None] * rest_b[columns, done][None, :]
        may = bound >= threshold - 1e-9
        if same is not None:
            may &= same[rows[:, None], columns[None, :]]
        keep_rows, keep_columns = may.any(axis=1), may.any(axis=0)
        if may.sum() * 8 < may.size or done == dims:
            i, j = np.nonzero(may)
            i, j = rows[i], columns[j]
            x, y = left[i], right[j]
            cosine = (x * y).sum(axis=1) / (np.sqrt((x * x).sum(axis=1)) * np.sqrt((y * y).sum(axis=1)))
            good = cosine >= threshold
            return i[good], j[good]
        rows, columns, product = rows[keep_rows], columns[keep_columns], product[np.ix_(keep_rows, keep_columns)]
    return np.zeros(0, np.int64), np.zeros(0, np.int64)


def near_vectors(rows: DataFrame, threshold: float = 0.98, most_rotation: int = MOST_ROTATION) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row of `rows` (vec_id, embedding, label)."""
    ship(rows.sparkSession)
    v = F.transform("embedding", lambda x: x.cast("double") + 0.0)
    given = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "label", v.alias("v"))
    sound = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    keyed = materialise(given.withColumn("sound", F.coalesce(sound, F.lit(False))).withColumns({"h1": F.xxhash64("label", "v"), "h2": F.xxhash64("v", F.lit(7), "label")}))
    groups = keyed.where("sound").groupBy("label", "h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"))
    first = keyed.where("sound").select(F.col("vec_id").alias("rep"), "label", "h1", "h2", "v", F.size("v").alias("dims"))
    classes = materialise(groups.join(first, ["rep", "label", "h1", "h2"]).dropDuplicates(["rep", "label", "h1", "h2"]))
    axes = rotation(classes, most_rotation)
    width = float(np.sqrt(max(2 - 2 * threshold, 0)) + 1e-9)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            dims = batch["dims"].to_numpy()
            cell = np.zeros((len(dims), 2), np.int64)
            held = batch["v"].to_pylist()
            for d in np.unique(dims):
                at = np.flatnonzero(dims == d)
                x = _unit(np.array([held[i] for i in at])) @ axes.get(int(d), np.eye(int(d)))[:, :2]
                cell[at, : x.shape[1]] = np.floor(x / width)
            raw = [np.array(x).tobytes() for x in held]
            yield pa.RecordBatch.from_arrays([batch["rep"], batch["label"], batch["dims"], batch["weight"], pa.array(raw, pa.binary()), pa.array(cell[:, 0]), pa.array(cell[:, 1])], names=["rep", "label", "dims", "weight", "v", "c1", "c2"])

    label = classes.schema["label"].dataType.simpleString()
    placed = materialise(classes.select("rep", "label", "dims", "weight", "v").mapInArrow(cells, f"rep long, label {label}, dims int, weight long, v binary, c1 long, c2 long"))
    forward = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in ((0, 0), (0, 1), (1, -1), (1, 0), (1, 1))])
    left = placed.withColumn("to", F.explode(forward)).select("rep", "label", "dims", "weight", "v", (F.col("c1") + F.col("to.a")).alias("c1"), (F.col("c2") + F.col("to.b")).alias("c2"), ((F.col("to.a") == 0) & (F.col("to.b") == 0)).alias("home"), F.lit(True).alias("first"))
    both = left.union(placed.select("rep", "label", "dims", "weight", "v", "c1", "c2", F.lit(True).alias("home"), F.lit(False).alias("first")))
    where = ["label", "dims", "c1", "c2"]
    count = lambda c: F.ceil(F.sum(c.cast("int")) / BLOCK).cast("int")
    shape = both.groupBy(*where).agg(count(F.col("first")).alias("lefts"), count(~F.col("first")).alias("rights")).where("lefts > 0 and rights > 0")
    own, other = F.when(F.col("first"), F.col("lefts")).otherwise(F.col("rights")), F.when(F.col("first"), F.col("rights")).otherwise(F.col("lefts"))
    dealt = (
        both.join(shape, where)
        .withColumn("own", F.pmod(F.xxhash64("rep"), own).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), other - 1)))
        .withColumns({"i": F.when(F.col("first"), F.col("own")).otherwise(F.col("other")), "j": F.when(F.col("first"), F.col("other")).otherwise(F.col("own"))})
        .select(*where, "i", "j", "rep", "weight", "v", "home", "first")
    )

    def run(group: pa.Table) -> pa.Table:
        first, home = (group[c].to_numpy(zero_copy_only=False) for c in ("first", "home"))
        ids, weight = group["rep"].to_numpy(), group["weight"].to_numpy()
        x = _matrix(group["v"].to_pylist())
        l, r = np.flatnonzero(first), np.flatnonzero(~first)
        order = ~home[l][:, None] | (ids[l][:, None] < ids[r][None, :])
        i, j = tile(x[l], x[r], axes.get(x.shape[1], np.eye(x.shape[1])), threshold, order) if len(l) and len(r) else (l[:0], r[:0])
        i, j = l[i], r[j]
        touched, at = np.unique(np.concatenate((ids[i], ids[j])), return_inverse=True)
        links = np.bincount(at, np.concatenate((weight[j], weight[i])), len(touched)).astype(np.int64)
        hi, lo = forest(ids[i], ids[j]) if len(i) else (touched, touched)
        a = np.concatenate((touched, hi))
        return pa.table([pa.array(a), pa.array(np.concatenate((touched, lo))), pa.array(np.concatenate((links, np.zeros(len(hi), np.int64))))], names=["a", "b", "n"])

    found = materialise(dealt.groupBy(*where, "i", "j").applyInArrow(run, "a long, b long, n long"))
    links = found.groupBy("a").agg(F.sum("n").alias("n")).withColumnRenamed("a", "of")
    component = connected(found.select("a", "b"))
    labelled = (
        groups.join(links, F.col("rep") == F.col("of"), "left")
        .join(component, F.col("rep") == F.col("node"), "left")
        .select(F.col("label").alias("l"), F.col("h1").alias("g1"), F.col("h2").alias("g2"), (F.col("weight") - 1 + F.coalesce("n", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component"))
    )
    return (
        keyed.select("vec_id", "label", "h1", "h2", "sound")
        .join(labelled, F.col("sound") & (F.col("h1") == F.col("g1")) & (F.col("h2") == F.col("g2")) & (F.col("label") == F.col("l")), "left")
        .select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
    )


def op7_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))
