"""Streams over a table's files, run to the end of what is there and read back as a batch table.

Every query checkpoints under the shared folder, takes the files with the availableNow
trigger, and may be restarted from where it stopped.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from geopat.plans.scratch import place


def feed(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """The table as a stream of its files, with times as timestamps (watermarks want them).

    The path is a pattern that fits the table alone: a stream's plain path has to be a folder.
    """
    schema = spark.read.parquet(f"{folder}/{name}.parquet").schema
    rows = spark.readStream.schema(schema).parquet(f"{folder}/{name}[.]parquet")
    return rows.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema if f.dataType.typeName() == "timestamp_ntz"})


def drain(stream: DataFrame) -> DataFrame:
    """Append mode to Parquet, to the end of the input."""
    spark, out = stream.sparkSession, place(stream.sparkSession)
    query = stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start(out)
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def upsert(stream: DataFrame, keys: list[str], mode: str = "update") -> DataFrame:
    """Update or complete mode: each batch's rows are written under its number; the last row of a key counts."""
    spark, out = stream.sparkSession, place(stream.sparkSession)

    def save(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/batch={number}")

    query = stream.writeStream.foreachBatch(save).outputMode(mode).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.option("basePath", out).parquet(f"{out}/batch=*").drop("batch")
    rest = [c for c in stream.columns if c not in keys]
    last = F.max_by(F.struct(*rest), "_batch").alias("_last")
    return rows.groupBy(*keys).agg(last).select(*keys, *[F.col(f"_last.{c}").alias(c) for c in rest])


def tumbling(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, event_type, n) of windows; sliding ones with `slide`."""
    at = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", "1 day").groupBy(at.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(user_id, start, end, n) of a user's events with no gap of that length."""
    spans = events.withWatermark("ts", "1 day").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return spans.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def online_links(parents: DataFrame, children: DataFrame, keys: list[str], minutes: int) -> DataFrame:
    """Stream-stream interval join: (parent_id, child_id) of entities that share keys, the child up to `minutes` later.

    Inputs have entity_id, at (timestamp, watermarked) and the keys; state older than the interval is dropped.
    """
    p = parents.select(F.col("entity_id").alias("parent_id"), F.col("at").alias("p_at"), *[F.col(k).alias(f"p_{k}") for k in keys])
    c = children.select(F.col("entity_id").alias("child_id"), F.col("at").alias("c_at"), *[F.col(k).alias(f"c_{k}") for k in keys])
    on = (F.col("c_at") > F.col("p_at")) & (F.col("c_at") <= F.col("p_at") + F.make_dt_interval(mins=F.lit(minutes)))
    for k in keys:
        on &= F.col(f"p_{k}") == F.col(f"c_{k}")
    return p.join(c, on).select("parent_id", "child_id")



def days(events: DataFrame) -> DataFrame:
    """(day_us, n) of whole days, with a watermark a day behind."""
    counted = events.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return counted.select(F.unix_micros("w.start").alias("day_us"), "n")


def append_then_late(stream: DataFrame, source: str, late: DataFrame) -> DataFrame:
    """Append mode over the files of `source`; then again after `late` rows were added there, which the watermark drops."""
    spark, out = stream.sparkSession, place(stream.sparkSession)
    for more in (None, late):
        if more is not None:
            more.coalesce(1).write.mode("append").parquet(source)
        stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start(out).awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def fused_intervals(records: DataFrame, gap_us: int) -> DataFrame:
    """(station, start_us, end_us, records, open) from records (station, time_us): intervals without a gap over `gap_us`.

    State is the station's open intervals; a batch adds its records to them.  Closed ones that a later batch may still
    join stay in the state, so every batch gives a station's intervals anew and the last counts.
    """

    def fuse(key, batches, state):  # noqa: ANN001, ANN202
        held = list(zip(*state.get, strict=True)) if state.exists else []
        for b in batches:
            held += [(int(t), int(t), 1) for t in b["time_us"].dropna()]
        out: list[list[int]] = []
        for start, end, n in sorted(held):
            if out and start - out[-1][1] <= gap_us:
                out[-1] = [out[-1][0], max(out[-1][1], end), out[-1][2] + n]
            else:
                out.append([start, end, n])
        starts, ends, counts = (list(c) for c in zip(*out, strict=True)) if out else ([], [], [])
        state.update((starts, ends, counts))
        yield pd.DataFrame({"station": [key[0]] * len(out), "start_us": starts, "end_us": ends, "records": counts})

    kinds = "starts array<long>, ends array<long>, counts array<long>"
    return records.groupBy("station").applyInPandasWithState(fuse, "station long, start_us long, end_us long, records long", kinds, "update", GroupStateTimeout.NoTimeout)


def drain_state(stream: DataFrame) -> DataFrame:
    """Update mode, to the end of the input: the rows of each station's last batch."""
    spark, out = stream.sparkSession, place(stream.sparkSession)

    def save(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/batch={number}")

    stream.writeStream.foreachBatch(save).outputMode("update").option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.option("basePath", out).parquet(f"{out}/batch=*").drop("batch")
    last = rows.groupBy("station").agg(F.max("_batch").alias("_batch"))
    return rows.join(last, ["station", "_batch"]).drop("_batch")
