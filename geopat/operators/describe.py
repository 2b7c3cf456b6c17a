"""Frequency tables and cleaning."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def type_table(df: DataFrame) -> DataFrame:
    """(type, n, percent) with a total row."""
    n = df.groupBy("type").agg(F.count("*").alias("n"))
    whole = F.sum("n").over(Window.partitionBy(F.lit(1)))
    shares = n.withColumn("percent", F.round(100.0 * F.col("n") / whole, 6))
    return shares.union(n.agg(F.lit("total").alias("type"), F.sum("n").alias("n"), F.lit(100.0).alias("percent")))


def calendar(df: DataFrame, unit: str) -> DataFrame:
    """(kind, unit, n, percent): relative frequency by month, weekday (Sunday 1) or hour of the start, in UTC."""
    day = F.floor(F.col("start_us") / 86_400_000_000)
    date = F.date_add(F.lit("1970-01-01").cast("date"), day.cast("int"))
    part = {"month": F.month(date), "weekday": F.dayofweek(date), "hour": F.floor(F.col("start_us") / 3_600_000_000) % 24}[unit].cast("long")
    n = df.groupBy("kind", part.alias(unit)).agg(F.count("*").alias("n"))
    return n.withColumn("percent", F.round(100.0 * F.col("n") / F.sum("n").over(Window.partitionBy("kind")), 6))


def drop_same_id(df: DataFrame, id_col: str, order: list[str]) -> DataFrame:
    """One row per id, the first by `order`."""
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(id_col).orderBy(*order))).where("_r = 1").drop("_r")


def drop_same_content(df: DataFrame, keys: list[str], id_col: str) -> DataFrame:
    """One row per content, that of the smallest id."""
    first = df.groupBy(*keys).agg(F.min(id_col).alias(id_col))
    return df.join(first.select(id_col), id_col, "left_semi")


def type_mismatch(df: DataFrame) -> DataFrame:
    """(provider_type, n, changed, percent): rows whose unified type differs from the provider's."""
    other = F.count_if(F.col("type") != F.col("provider_type"))
    return df.groupBy("provider_type").agg(F.count("*").alias("n"), other.alias("changed"), F.round(100.0 * other / F.count("*"), 6).alias("percent"))
