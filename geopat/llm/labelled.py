"""Bounded samples of labelled rows, and the split by document id that keeps rows for tests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise


def held_out(doc_id: Column) -> Column:
    """True for the third of ids whose labels are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, columns: list[str], most: int, seed: int = 17) -> DataFrame:
    """Texts with their labels, at most `most` of them, picked by a hash of the id outside the held-out third.

    The picked labels are bounded by `most`, so they are broadcast; the texts are read once.
    Labels that are null, or that contradict each other for one id, are not used.
    """
    named = labels.select(F.col("doc_id").alias("_id"), *columns).where(F.col("_id").isNotNull() & ~held_out(F.col("_id")))
    agreed = named.dropna().groupBy("_id").agg(*[F.min(c).alias(c) for c in columns], *[F.max(c).alias(f"_{c}") for c in columns])
    for c in columns:
        agreed = agreed.where(F.col(c) == F.col(f"_{c}")).drop(f"_{c}")
    picked = materialise(agreed.orderBy(F.xxhash64("_id", F.lit(seed)), "_id").limit(most))
    return docs.select("doc_id", "text").join(F.broadcast(picked), F.col("_id") == F.col("doc_id")).drop("_id")
