"""Mixing sources to target weights by entropy balancing.

Every document gets a rate, the expected number of its copies.  Among all rates between
0 and the cap that give each source its target of words, the mix takes those nearest to
1 in relative entropy.  The convex dual has one multiplier per source, and a document's
rate is min(cap, exp(multiplier * size / mean size of its source)).  The multipliers come
from safeguarded Newton steps, each one distributed aggregation over the table of
(source, size, documents of that size), which is all that the dual reads.

Rates become copies by dithered rounding: floor(rate + u) with u from the document's
id, then one small shift of all u of a source, found from a histogram of the places
where a copy would be won or lost, which brings the source's words to the target.

Targets: sources in code-point order (null last) weigh 5, 2, 1, 5, ... and share all
words by weight; none gets more than `cap` times its own words, and what exceeds that
is shared again by weight.  Sources without words take nothing.  Null and empty texts
have size 0 and take 0.  Documents with the same id are rounded alike.  An empty table
gives no rows.  Extra columns are not read.  The table of sources is ordered in one task, which
holds one row per source; sources are named pools of documents, not documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, materialise, ship, table

WEIGHTS = (5.0, 2.0, 1.0)
CAP = 3
BINS = 4096
STEPS = 40
TOLERANCE = 1e-7


def words_in(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def exact_sum(value: Column) -> Column:
    """A sum to six decimals that does not depend on the order of rows, so that reruns agree to the last bit."""
    return F.sum(value.cast("decimal(38,6)")).cast("double")


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """(source, source_size, weight, target) from (source, source_size).

    The shared-out level solves sum(min(weight * level, cap * size)) = total.  It is read
    off the sources ordered by the level at which each is full, so it takes one sort.
    """
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    ranked = sizes.withColumn("weight", F.get(cycle, (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)))
    full = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last())
    level = (
        ranked.withColumn("total", F.sum("source_size").over(everything))
        .withColumn("fill", cap * F.col("source_size") / F.col("weight"))
        .withColumn("spent", F.coalesce(F.sum(cap * F.col("source_size")).over(full.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("open", F.sum("weight").over(full.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", (F.col("total") - F.col("spent")) / F.col("open"))
        .withColumn("level", F.min(F.when(F.col("level") <= F.col("fill"), F.struct("fill", "level"))).over(everything)["level"])
    )
    target = F.least(F.col("weight") * F.coalesce(F.col("level"), F.lit(0.0)), (cap * F.col("source_size")).cast("double"))
    return level.select("source", "source_size", "weight", target.alias("target"))


def multipliers(by_size: DataFrame, aims: DataFrame, cap: int = CAP, steps: int = STEPS) -> DataFrame:
    """(source, source_size, target, mean_size, multiplier); null multiplier: take the cap of everything.

    `by_size` has (source, size, n).  A Newton step that leaves the bracket is replaced by
    its middle, so the iteration cannot diverge.
    """
    means = by_size.where("size > 0").groupBy("source").agg((F.sum(F.col("size") * F.col("n")) / F.sum("n")).alias("mean_size"))
    state = aims.join(means, aims["source"].eqNullSafe(means["source"]), "left").select(
        aims["source"], "source_size", "target", F.coalesce("mean_size", F.lit(1.0)).alias("mean_size"),
        F.lit(0.0).alias("m"), F.lit(-200.0).alias("low"), F.lit(200.0).alias("high"),
        (F.col("target") >= cap * F.col("source_size") * (1 - 1e-12)).alias("done"),
        (F.col("target") >= cap * F.col("source_size") * (1 - 1e-12)).alias("full"),
    )
    state = materialise(state)
    for _ in range(steps):
        moving = F.broadcast(state.where("not done")) if state.count() < 100_000 else state.where("not done")
        rate = F.exp(F.least(F.col("m") * F.col("size") / F.col("mean_size"), F.lit(50.0)))
        words = F.col("size") * F.col("n")
        sums = (
            by_size.withColumnRenamed("source", "of")
            .join(moving, F.col("of").eqNullSafe(F.col("source")))
            .groupBy("source")
            .agg(
                exact_sum(words * F.least(rate, F.lit(float(cap)))).alias("taken"),
                exact_sum(F.when(rate < cap, words * rate * F.col("size") / F.col("mean_size")).otherwise(0.0)).alias("slope"),
            )
            .withColumnRenamed("source", "of")
        )
        gap = F.col("taken") - F.col("target")
        low = F.when(gap < 0, F.col("m")).otherwise(F.col("low"))
        high = F.when(gap > 0, F.col("m")).otherwise(F.col("high"))
        step = F.col("m") - F.try_divide(gap, F.col("slope"))
        inside = F.when((step > low) & (step < high), step).otherwise((low + high) / 2)
        near = F.abs(gap) <= F.greatest(TOLERANCE * F.col("target"), F.lit(1e-3))
        stays = F.col("done") | F.col("taken").isNull() | near
        state = materialise(
            state.join(sums, F.col("of").eqNullSafe(F.col("source")), "left").select(
                "source", "source_size", "target", "mean_size",
                F.when(stays, F.col("m")).otherwise(inside).alias("m"),
                F.when(stays, F.col("low")).otherwise(low).alias("low"),
                F.when(stays, F.col("high")).otherwise(high).alias("high"),
                stays.alias("done"), "full",
            ).coalesce(1)
        )
        if state.where("not done").isEmpty():
            break
    else:
        raise RuntimeError(f"the dual did not settle in {steps} steps")
    return state.select("source", "source_size", "target", "mean_size", F.when(~F.col("full"), F.col("m")).alias("multiplier"))


def unit(key: Column, seed: int) -> Column:
    """A number in [0, 1) from a key, the same on every run."""
    return F.shiftrightunsigned(F.xxhash64(key, F.lit(seed)), 11) / F.lit(float(1 << 53))


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: int = CAP, seed: int = 11, carry: bool = False) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, rate, copies, taken; with `carry` also row, the whole row."""
    ship(docs.sparkSession)
    row = [F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")] if carry else []
    # Words are counted once: with whole rows carried along, counting them a second time costs less than writing these.
    sized = docs.select("doc_id", "source", words_in().alias("size"), *row)
    sized = sized if carry else materialise(sized)
    by_size = materialise(sized.groupBy("source", "size").agg(F.count("*").alias("n")))
    sizes = by_size.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    solved = materialise(multipliers(by_size, targets(sizes, weights, cap), cap).coalesce(1)).withColumnRenamed("source", "of")
    few = solved.count() < 100_000
    rate = F.when(F.col("multiplier").isNull(), float(cap)).otherwise(
        F.least(F.lit(float(cap)), F.exp(F.least(F.col("multiplier") * F.col("size") / F.col("mean_size"), F.lit(50.0))))
    )
    place = F.col("rate") + unit(F.col("doc_id"), seed)
    part = F.col("place") - F.floor("place")
    rated = (
        sized.join(F.broadcast(solved) if few else solved, F.col("of").eqNullSafe(F.col("source")), "left")
        .withColumn("rate", rate)
        .withColumn("place", place)
        .withColumn("turn", F.when(part >= 0.5, 1 - part).otherwise(-part))
        .withColumn("bin", F.least(F.floor((F.col("turn") + 0.5) * BINS), F.lit(BINS - 1)).cast("int"))
        .withColumn("least", F.floor(F.col("place") - F.when(part < 0.5, 1).otherwise(0)))
    )
    bound = lambda c: F.greatest(F.lit(0), F.least(F.lit(cap), c)).cast("long")
    fewest, most = bound(F.col("least")), bound(F.col("least") + 1)
    steps = materialise(
        rated.groupBy("of", "bin").agg(
            F.sum(F.col("size") * fewest).alias("base"), F.sum(F.col("size") * (most - fewest)).alias("gain"), F.first("target").alias("target")
        )
    )
    whole = Window.partitionBy("of")
    cut = (
        steps.withColumn("base", F.sum("base").over(whole))
        .withColumn("upto", F.col("base") + F.sum("gain").over(whole.orderBy("bin")))
        .groupBy("of")
        .agg(
            F.min_by(F.col("bin"), F.struct(F.abs(F.col("upto") - F.col("target")), F.col("bin"))).alias("last"),
            F.min(F.abs(F.col("upto") - F.col("target"))).alias("miss"),
            F.first(F.abs(F.col("base") - F.col("target"))).alias("bare"),
        )
        .select(F.col("of").alias("cut_of"), F.when(F.col("bare") < F.col("miss"), -1).otherwise(F.col("last")).alias("last"))
    )
    copies = F.when(F.col("bin") <= F.col("last"), most).otherwise(fewest)
    return (
        rated.join(F.broadcast(cut) if few else cut, F.col("cut_of").eqNullSafe(F.col("of")), "left")
        .withColumn("copies", copies)
        .select("doc_id", "source", "size", "source_size", "target", "rate", "copies", (F.col("copies") * F.col("size")).alias("taken"), *(["row"] if carry else []))
    )


def repeat_documents(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """The documents, each as often as the mix says; columns as in `docs`."""
    mixed = mix(docs, weights, cap, carry=True)
    return mixed.where("copies > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy")).select("row.*")


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "rate", "copies")
