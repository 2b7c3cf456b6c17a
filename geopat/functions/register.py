"""Functions of this package for SQL, and Python functions over Arrow and Pandas batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geopat.functions.geo import RADIUS_M


def sql_functions(spark: SparkSession) -> None:
    """Temporary SQL functions: great-circle metres, and the least support of a number of trees."""
    arc = "pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)"
    spark.sql(f"create or replace temporary function geopat_metres(lat1 double, lon1 double, lat2 double, lon2 double) returns double return 2 * {RADIUS_M}d * asin(sqrt(least(1d, {arc})))")
    spark.sql("create or replace temporary function geopat_least_support(trees double) returns double return exp(-(0.004d * trees + 1.5d)) + 0.05d")


def views(spark: SparkSession, folder: str) -> None:
    """Temporary views of the main tables: geopat_entities, geopat_links, geopat_lasting."""
    from geopat.operators import lasting, relate
    from geopat.plans.scratch import written
    from geopat.sources.entities import entities

    e = written(entities(spark, folder))
    e.createOrReplaceTempView("geopat_entities")
    relate.links(e).createOrReplaceTempView("geopat_links")
    lasting.extract(e).createOrReplaceTempView("geopat_lasting")


@F.udf(T.StringType())
def shape_label(root, child):  # noqa: ANN001, ANN201
    return f"{root}({child})"


@F.pandas_udf(T.DoubleType())
def t_tail(t: pd.Series, v: pd.Series) -> pd.Series:
    """P(T > t), integrated over the angle whose tangent is t / sqrt(v)."""
    x = np.linspace(0, 1, 4001)

    def one(t: float, v: float) -> float:
        lo = np.arctan(abs(t) / np.sqrt(v))
        area = lambda a: np.trapezoid(np.cos(a + (np.pi / 2 - a) * x).clip(0) ** (v - 1), dx=(np.pi / 2 - a) / 4000)
        tail = 0.5 * area(lo) / area(0.0)
        return tail if t >= 0 else 1 - tail

    return pd.Series([one(a, b) for a, b in zip(t, v, strict=True)], dtype=float)


@F.arrow_udf(T.LongType())
def grid_cell(lat: pa.Array, lon: pa.Array) -> pa.Array:
    y, x = (np.floor(c.to_numpy(zero_copy_only=False) * 10).astype(np.int64) for c in (lat, lon))
    return pa.array(y * 100_000 + x)


@F.pandas_udf(T.DoubleType())
def mean_gap(value: pd.Series, against: pd.Series) -> float:
    return float(value.mean() - against.iloc[0])


@F.udtf(returnType=T.StructType([T.StructField("which", T.StringType()), T.StructField("lo", T.LongType()), T.StructField("hi", T.LongType())]))
class ProbeWindows:
    """The three windows of an owner: during, and a week and its duration before and after."""

    def eval(self, start_us: int, end_us: int) -> Iterator[tuple[str, int, int]]:
        away = 604_800_000_000 + end_us - start_us
        for which, k in (("during", 0), ("before", -1), ("after", 1)):
            yield which, start_us + k * away, end_us + k * away


def role_path(turns: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"conv_id": [turns["conv_id"].iloc[0]], "path": [">".join(turns.sort_values("turn")["role"].dropna())]})


def text_sizes(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        yield pd.DataFrame({"item_id": b["item_id"], "n": b["text"].map(len, na_action="ignore").astype("Int64")})


def side_by_side(key: tuple, before: pd.DataFrame, after: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"k": [key[0]], "n_before": [int(before["n"].sum())], "n_after": [int(after["n"].sum())]})
