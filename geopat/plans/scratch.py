"""Tables written between steps, in the cluster's shared folder, so that a lost executor loses nothing."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from urllib.parse import urlparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: str | None = None

#: Keys that meet over this share of all rows are joined by broadcast; there can be no more of them than its inverse.
HOT_SHARE = 1 / 2000
#: Below so many rows in all, no key is worth a join of its own.
FEW_ROWS = 20_000


def folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir.  Where it is unset, a temporary one of this process, on a local master alone."""
    global _own
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if _own is None:
        _own = tempfile.mkdtemp(prefix="geopat-")
        atexit.register(shutil.rmtree, _own, ignore_errors=True)
    return _own


def place(spark: SparkSession) -> str:
    """A new path in the shared folder, removed when the session's process ends."""
    path = f"{folder(spark)}/geopat-{uuid.uuid4().hex}"
    if urlparse(path).scheme in ("", "file"):
        for end in ("", "-state"):
            atexit.register(shutil.rmtree, urlparse(path).path + end, ignore_errors=True)
    else:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    return path


def written(df: DataFrame) -> DataFrame:
    """The same rows, from a Parquet table at a new place."""
    path = place(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def hot_join(rows: DataFrame, found: DataFrame, key: str, n: str, total: int) -> DataFrame:
    """Inner join of `rows` with `found` on `key`; `found` has one row per key and `n`, of `total` rows those that it meets.

    Keys that meet over HOT_SHARE of all rows are broadcast (2000 at most), so they stay where they are; the rest is shuffled.
    """
    if total < FEW_ROWS:
        return rows.join(found, key)
    limit = total * HOT_SHARE
    hot, cool = found.where(F.col(n) > limit), found.where(F.col(n) <= limit)
    apart = rows.join(F.broadcast(hot.select(key)), key, "left_anti")
    return rows.join(F.broadcast(hot), key).unionByName(apart.join(cool, key))
