"""Weather records: intensity, types, and intervals of one type at one station."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Published centres, in degrees Celsius, km/h and mm.
PUBLISHED = {"temperature": (-23.7, -8.6, 6.7, 21.3, 35.8), "wind": (13.2, 36.2, 60.0), "rain": (2.5, 7.1, 11.6), "snow": (0.6, 1.7, 2.5)}
NAMES = {"temperature": ("severe_cold", "cold", "cool", "warm", "hot"), "wind": ("calm", "moderate", "storm"), "rain": ("light", "moderate", "heavy"), "snow": ("light", "moderate", "heavy")}
SEVERE_COLD, STORM = PUBLISHED["temperature"][0], PUBLISHED["wind"][-1]
DAY = 86_400_000_000


def intensity(value: Column, measure: str, centres: tuple[float, ...] | None = None) -> Column:
    """Name of the centre nearest to a value; on a midpoint, the lower one; null stays null."""
    centres, names = centres or PUBLISHED[measure], NAMES[measure]
    out = F.when(value.isNull(), None)
    for low, high, name in zip(centres, centres[1:], names, strict=False):
        out = out.when(value <= (low + high) / 2, name)
    return out.otherwise(names[-1])


def classify(records: DataFrame) -> DataFrame:
    """Records with `type`, one row per type that holds; clear weather has none."""
    deposit = (F.col("condition") == "thunderstorm") & (F.col("precipitation") > 0)
    kinds = [F.when(F.col("temperature") <= SEVERE_COLD, "severe_cold"), F.when(F.col("wind") >= STORM, "storm"), F.when(deposit, "precipitation"), *[F.when(F.col("condition") == c, c) for c in ("fog", "hail", "rain", "snow")]]
    return records.withColumn("type", F.explode(F.array_compact(F.array(*kinds))))


def extract(records: DataFrame, gap_us: int = 20 * DAY, end_rule: str = "last") -> DataFrame:
    """(station, type, start_us, end_us, records, intensity): records of a type at a station, merged where no gap is longer than `gap_us`.

    An interval ends with its last record, or by `end_rule` next with the station's next
    record of any type.  Intensity is the greatest of the records', for rain and snow.
    """
    by_time = Window.partitionBy("station").orderBy("time_us").rangeBetween(1, Window.unboundedFollowing)
    rows = records.withColumn("next_us", F.min("time_us").over(by_time)) if end_rule == "next" else records.withColumn("next_us", F.lit(None).cast("long"))
    level = F.when(F.col("type").isin("rain", "snow"), F.when(F.col("type") == "rain", _rank("rain")).otherwise(_rank("snow")))
    rows = classify(rows).withColumn("level", level)
    order = Window.partitionBy("station", "type").orderBy("time_us")
    opens = F.col("time_us") - F.lag("time_us").over(order) > gap_us
    island = F.sum(F.when(opens, 1).otherwise(0)).over(order.rowsBetween(Window.unboundedPreceding, 0))
    spans = rows.withColumn("opens", F.when(opens, 1).otherwise(0)).withColumn("island", island).groupBy("station", "type", "island")
    out = spans.agg(F.min("time_us").alias("start_us"), F.max("time_us").alias("last_us"), F.max("next_us").alias("next_us"), F.count("*").alias("records"), F.max("level").alias("level"))
    end = F.coalesce("next_us", "last_us") if end_rule == "next" else F.col("last_us")
    name = F.when(F.col("level") == 0, "light").when(F.col("level") == 1, "moderate").when(F.col("level") == 2, "heavy")
    return out.select("station", "type", "start_us", end.alias("end_us"), "records", name.alias("intensity"))


def _rank(measure: str) -> Column:
    a, b, c = PUBLISHED[measure]
    return F.when(F.col("precipitation") <= (a + b) / 2, 0).when(F.col("precipitation") <= (b + c) / 2, 1).otherwise(2)


def intensity_sql(value: str, measure: str) -> str:
    c, names = PUBLISHED[measure], NAMES[measure]
    steps = " ".join(f"when {value} <= {(a + b) / 2!r}::double then '{n}'" for a, b, n in zip(c, c[1:], names, strict=False))
    return f"case when {value} is null then null {steps} else '{names[-1]}' end"
