"""K-Means with fixed starts, and the description length that chooses K."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geopat.plans.ship import ship


def lloyd_1d(df: DataFrame, column: str, k: int, rounds: int = 12) -> list[float]:
    """Sorted centres of a column.  Starts are the (i + 1/2)/k quantiles; ties go to the lower centre.

    A round is one aggregation of k sums; only the k centres come back.
    """
    centres = df.agg(F.percentile(column, F.array(*[F.lit((i + 0.5) / k) for i in range(k)]))).first()[0]
    for _ in range(rounds):
        label = nearest_1d(F.col(column), centres)
        got = {r[0]: r[1] for r in df.where(F.col(column).isNotNull()).groupBy(label.alias("c")).agg(F.avg(column)).collect()}  # k rows
        centres = [got.get(i, c) for i, c in enumerate(centres)]
    return sorted(centres)


def nearest_1d(value: Column, centres: list[float]) -> Column:
    gaps = F.array(*[F.struct(F.abs(value - F.lit(float(c))).alias("d"), F.lit(i).alias("i")) for i, c in enumerate(centres)])
    return F.array_min(gaps)["i"]


def lloyd_sql(source: str, column: str, k: int, rounds: int = 12) -> str:
    """The same rounds as a chain of WITH-list items c0 .. c<rounds> (i, c) for DuckDB."""
    parts = [f"c0 as (select i, quantile_cont({column}, (i + 0.5) / {k}) c from {source}, range(0, {k}) r(i) group by i)"]
    quantiles = " union all ".join(f"select {i} i, (select quantile_cont({column}, {(i + 0.5) / k}) from {source}) c" for i in range(k))
    parts = [f"c0 as ({quantiles})"]
    for r in range(rounds):
        parts.append(f"c{r + 1} as (select c{r}.i, coalesce(m.c, c{r}.c) c from c{r} left join (select i, avg(v) c from (select v, (select arg_min(i, [abs(v - c), i]) from c{r}) i from (select {column} v from {source})) group by i) m on m.i = c{r}.i)")
    return ",\n".join(parts)


def kmeans(points: np.ndarray, k: int, rounds: int = 100) -> tuple[np.ndarray, np.ndarray]:
    """(labels, centres) of a small table by Lloyd rounds from farthest-first starts; ties, to nine decimals, go to the lower index."""
    picked = [0]
    gap = ((points - points[0]) ** 2).sum(axis=1)
    while len(picked) < k:
        picked.append(int(np.argmax(gap)))
        gap = np.minimum(gap, ((points - points[picked[-1]]) ** 2).sum(axis=1))
    centres = points[picked].astype(float)
    labels = np.full(len(points), -1)
    for _ in range(rounds):
        new = ((points[:, None, :] - centres[None, :, :]) ** 2).sum(axis=2).round(9).argmin(axis=1)
        if (new == labels).all():
            break
        labels = new
        for i in range(k):
            if (labels == i).any():
                centres[i] = points[labels == i].mean(axis=0)
    return labels, centres


def description_length(points: np.ndarray, labels: np.ndarray, centres: np.ndarray, floor: float = 1e-6) -> tuple[float, bool]:
    """(bits-like length in natural logs, degenerate): Gaussian code of the distances, plus its two parameters, plus centres."""
    d = np.sqrt(((points - centres[labels]) ** 2).sum(axis=1))
    sd = max(float(d.std()), floor)
    code = float((0.5 * ((d - d.mean()) / sd) ** 2 + math.log(sd * math.sqrt(2 * math.pi))).sum())
    n, k = len(points), len(centres)
    return code + math.log(n) + k * math.log(n), bool(d.std() < floor)


def state_vectors(core: DataFrame, states: DataFrame) -> DataFrame:
    """(state, shape, present): every state with every shape of the national list; both lists are small."""
    shapes = core.select("shape").distinct()
    return states.crossJoin(F.broadcast(shapes)).join(core.select("state", "shape", F.lit(1).alias("present")).distinct(), ["state", "shape"], "left").fillna(0, ["present"])


def state_groups(vectors: DataFrame, ks: range = range(2, 11)) -> DataFrame:
    """(k, state, cluster, length, degenerate, best) for each K; states are few, their table is small."""
    spark = vectors.sparkSession
    wide = vectors.toPandas().pivot(index="state", columns="shape", values="present").sort_index()
    points, rows = wide.to_numpy(float), []
    if points.size:
        runs = {}
        for k in [k for k in ks if k < len(points)]:
            labels, centres = kmeans(points, k)
            runs[k] = (labels, *description_length(points, labels, centres))
        sound = {k: v[1] for k, v in runs.items() if not v[2]}
        best = min(sound, key=lambda k: (sound[k], k)) if sound else None
        rows = [(k, int(s), int(c), round(length, 6), bad, k == best) for k, (labels, length, bad) in runs.items() for s, c in zip(wide.index, labels, strict=True)]
    return spark.createDataFrame(rows, "k int, state long, cluster int, length double, degenerate boolean, best boolean")


def groups_sql(core: str, rounds: int = 12, ks: tuple[int, int] = (2, 10)) -> str:
    """WITH-list items up to `kl` (k, state, cluster) and `dl` (k, length, degenerate, best) for DuckDB, after `e` and the list `core` (state, shape); the same starts and rounds."""
    first, last = ks
    picks = []
    for j in range(1, last):
        picks.append(f"g{j} as materialized (select state, {'d' if j == 1 else f'least(g{j - 1}.gap, d)'} gap from (select v.state, sum(pow(v.x - p.x, 2)) d from v join v p using (shape) where p.state = (select spot from p{j - 1}) group by 1){'' if j == 1 else f' join g{j - 1} using (state)'})")
        picks.append(f"p{j} as materialized (select arg_min(state, [-gap, state]) spot from g{j})")
    starts = " union all ".join(f"select {j} j, spot from p{j}" for j in range(last))
    near = "select c.k, v.state, c.i, {0} d from {1} c join v using (shape) group by c.k, v.state, c.i"
    labels = "select k, state, arg_min(i, [d, i]) i from ({}) group by k, state"
    return f"""
v as materialized (select su.state, sl.shape, case when exists (select 1 from {core} c where c.state = su.state and c.shape = sl.shape) then 1.0::double else 0 end x from (select distinct state from e) su, (select distinct shape from {core}) sl),
p0 as materialized (select min(state) spot from v),
{", ".join(picks)},
lc as (
  select 0 r, k, s.j i, v.shape, v.x from (select unnest(range({first}, {last + 1})) k) kk join ({starts}) s on s.j < k join v on v.state = s.spot where k < (select count(distinct state) from v)
  union all
  select c.r + 1, c.k, c.i, c.shape, coalesce(a.m, c.x) from lc c left join (
    select l.k, l.i, v.shape, avg(v.x) m from ({labels.format(near.format("round(sum(pow(v.x - c.x, 2)), 9)", "lc"))}) l join v using (state) group by l.k, l.i, v.shape) a on a.k = c.k and a.i = c.i and a.shape = c.shape
  where c.r < {rounds}),
le as materialized (select * from lc where r = {rounds}),
kl as materialized (select k, state, i "cluster" from ({labels.format(near.format("round(sum(pow(v.x - c.x, 2)), 9)", "le"))})),
kd as (select kl.k, kl.state, sqrt(sum(pow(v.x - le.x, 2))) d from kl join v using (state) join le on le.k = kl.k and le.i = kl."cluster" and le.shape = v.shape group by kl.k, kl.state),
ks as (select k, count(*) n, stddev_pop(d) s, greatest(stddev_pop(d), 1e-6) sd from kd group by k),
dk as (select k, 0.5 * n * pow(s / sd, 2) + n * ln(sd * sqrt(2 * pi())) + ln(n) + k * ln(n) length, s < 1e-6 degenerate from ks),
dl as (select k, length, degenerate, coalesce(k = (select arg_min(k, [length, k]) from dk where not degenerate), false) best from dk)
"""


def vector_kmeans(df: DataFrame, id_col: str, vector: str, k: int, rounds: int = 8) -> DataFrame:
    """(id, cluster) by Lloyd rounds from the vectors of the k smallest ids; ties go to the lower centre.

    A round sends back one row of sums per batch and centre, combined in Spark; k centres reach the driver.
    """
    ship(df.sparkSession)
    rows = df.select(F.col(id_col).alias("id"), F.col(vector).alias("v"))
    centres = np.array([r.v for r in rows.orderBy("id").limit(k).collect()], dtype=float)
    if not len(centres):
        return rows.select("id", F.lit(0).alias("cluster"))

    def nearest(block: np.ndarray, c: np.ndarray) -> np.ndarray:
        return ((c * c).sum(axis=1)[None, :] - 2 * block @ c.T).argmin(axis=1)

    for _ in range(rounds):
        def sums(batches, c=centres):  # noqa: ANN001, ANN202
            for b in batches:
                block = np.array(b["v"].tolist(), dtype=float).reshape(len(b), c.shape[1])
                at = nearest(block, c)
                yield pd.DataFrame([(int(i), int((at == i).sum()), block[at == i].sum(axis=0).tolist()) for i in np.unique(at)], columns=["c", "n", "s"])

        part = rows.mapInPandas(sums, "c int, n long, s array<double>").select("c", "n", F.posexplode("s").alias("i", "x")).groupBy("c", "i").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
        for r in part.collect():  # k x d sums
            centres[r.c, r.i] = r.x / r.n

    def assign(batches, c=centres):  # noqa: ANN001, ANN202
        for b in batches:
            yield pd.DataFrame({"id": b["id"], "cluster": nearest(np.array(b["v"].tolist(), dtype=float).reshape(len(b), c.shape[1]), c)})

    return rows.mapInPandas(assign, f"id {dict(rows.dtypes)['id']}, cluster int")


def vector_length(df: DataFrame, id_col: str, vector: str, k: int, rounds: int = 8) -> DataFrame:
    """(k, n, length): description length of `vector_kmeans`, from sums of distances; centres are averages per cluster and place of the vector."""
    at = df.select(F.col(id_col).alias("id"), F.posexplode(vector).alias("i", "x")).join(vector_kmeans(df, id_col, vector, k, rounds), "id")
    centre = at.groupBy("cluster", "i").agg(F.avg("x").alias("c"))
    apart = at.join(centre, ["cluster", "i"]).groupBy("id").agg(F.sqrt(F.sum(F.pow(F.col("x") - F.col("c"), 2))).alias("d"))
    s = apart.agg(F.count("*").alias("n"), F.stddev_pop("d").alias("s")).withColumn("sd", F.greatest("s", F.lit(1e-6)))
    n = F.col("n")
    length = 0.5 * n * F.pow(F.col("s") / F.col("sd"), 2) + n * F.log(F.col("sd") * F.sqrt(2 * F.pi())) + F.log(n) + k * F.log(n)
    return s.select(F.lit(k).alias("k"), "n", F.round(length, 6).alias("length"))


def distinctive(vectors: DataFrame) -> DataFrame:
    """(cluster, shape, states): shapes that only states of one of the best groups have."""
    best = state_groups(vectors).where("best").select("state", "cluster")
    in_one = vectors.where("present = 1").join(best, "state").groupBy("shape").agg(F.countDistinct("cluster").alias("clusters"), F.min("cluster").alias("cluster"), F.count("*").alias("states"))
    return in_one.where("clusters = 1").select("cluster", "shape", "states")


def library_kmeans(df: DataFrame, id_col: str, vector: str, k: int, rounds: int = 8) -> DataFrame:
    """(id, cluster) by the library's K-Means, the alternative to the rounds above."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = df.select(F.col(id_col).alias("id"), array_to_vector(vector).alias("features"))
    return KMeans(k=k, maxIter=rounds, seed=1).fit(rows).transform(rows).select("id", F.col("prediction").alias("cluster"))
