"""Shared pieces: table reading, written intermediate tables, column hygiene."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.plans import ship as code
from geopat.plans.scratch import written

#: A word, as every contract of this folder defines it (Java and Python regular expressions agree on it).
WORD = r"[^\x20\x09-\x0D]+"


#: Rows of a batch sent to Python, in place of Spark's default: rows here are whole texts or sets.
BATCH_ROWS = 1000


def ship(spark: SparkSession) -> None:
    """Give the executors' Python this package, and small Arrow batches unless the session sets their size itself."""
    code.ship(spark)
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{folder}/{name}.parquet")


def materialise(df: DataFrame) -> DataFrame:
    """Cut lineage: write the rows as Parquet in the shared folder and read them back.

    Unlike a block in an executor's memory, the table outlives lost executors.
    """
    return written(df)


def parts_for(rows: int, room: int) -> int:
    """Parts of at most about `room` rows each, by what there is and not by the session's settings."""
    return max(1, -(-rows // room))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))
