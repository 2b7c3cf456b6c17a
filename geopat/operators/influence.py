"""Six one-sided two-sample t-tests per bucket of lasting entities."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geopat.functions.stats import PANELS, t_upper

#: Test: (reference sample, +1 where the alternative is "reference below during").
TESTS = {"T1": ("avg", 1), "T2": ("avg", -1), "T3": ("before", 1), "T4": ("before", -1), "T5": ("after", 1), "T6": ("after", -1)}
#: Lower edges of duration buckets, in hours: those of the study's kind of data, and those of the given tables, whose entities are shorter.
EDGES_H = (0, 10, 16, 22, 28, 34, 40)
SHORT_EDGES_H = (0, 3, 4, 5, 6)


def duration_bucket(span_us: Column, edges: tuple[int, ...] = EDGES_H) -> Column:
    """Lower edge, in hours, of the bucket of a duration."""
    out = F.lit(edges[0])
    for edge in edges[1:]:
        out = F.when(span_us >= edge * 3_600_000_000, edge).otherwise(out)
    return out


def means(counts: DataFrame, by: list[Column]) -> DataFrame:
    """Sizes, means and variances of the samples per bucket.  A window that was left out (null) counts in none; the average is then that of the other side."""
    one = F.coalesce((F.col("n_before") + F.col("n_after")) / 2, "n_before", "n_after")
    stats = [f(F.col(f"n_{w}")).alias(f"{n}_{w}") for w in ("during", "before", "after", "avg") for n, f in (("size", F.count), ("mean", F.avg), ("var", F.var_samp))]
    return counts.withColumn("n_avg", one).groupBy(*by).agg(F.count("*").alias("n"), *stats)


def tests(counts: DataFrame, by: list[Column], flavour: str = "pooled") -> DataFrame:
    """(bucket columns, test, n, t, df, p, tier): p is null where a sample has one row or no spread."""
    m = means(counts, by)
    names = [c for c in m.columns[: len(by)]]
    rows = []
    for name, (ref, sign) in TESTS.items():
        nx, ny, vx, vy = F.col("size_during"), F.col(f"size_{ref}"), F.col("var_during"), F.col(f"var_{ref}")
        a, b = vx / F.nullif(nx, F.lit(0)), vy / F.nullif(ny, F.lit(0))
        if flavour == "pooled":
            df = nx + ny - 2.0
            spread = ((nx - 1) * vx + (ny - 1) * vy) / F.nullif(df, F.lit(0.0)) * (1 / F.nullif(nx, F.lit(0)) + 1 / F.nullif(ny, F.lit(0)))
        else:
            df = (a + b) * (a + b) / F.nullif(a * a / F.nullif(nx - 1, F.lit(0)) + b * b / F.nullif(ny - 1, F.lit(0)), F.lit(0.0))
            spread = a + b
        t = sign * (F.col("mean_during") - F.col(f"mean_{ref}")) / F.sqrt(F.nullif(spread, F.lit(0.0)))
        rows.append(F.struct(F.lit(name).alias("test"), F.when(F.least(nx, ny) > 1, t).alias("t"), df.cast("double").alias("df")))
    flat = m.select(*names, "n", F.inline(F.array(*rows)))
    p = F.when(F.col("t").isNotNull(), t_upper(F.col("t"), F.col("df")))
    return flat.withColumn("p", p).withColumn("tier", _tier(F.col("p"))).select(*names, "test", "n", (F.round("t", 6) + 0.0).alias("t"), F.round("df", 6).alias("df"), F.round("p", 6).alias("p"), "tier")


def _tier(p: Column) -> Column:
    """Highest confidence (99, 95, 90 %) that a test reaches."""
    return F.when(p.isNull(), None).when(1 - p >= 0.99, "99").when(1 - p >= 0.95, "95").when(1 - p >= 0.9, "90").otherwise("none")


TIER_SQL = "case when p is null then null when 1 - p >= 0.99 then '99' when 1 - p >= 0.95 then '95' when 1 - p >= 0.9 then '90' else 'none' end"


def tally(tested: DataFrame) -> DataFrame:
    """(tier, buckets): buckets by the better of T1 and T2."""
    best = tested.where("test in ('T1', 'T2') and p is not null").groupBy(tested.columns[0]).agg(F.min("p").alias("p"))
    return best.groupBy(_tier(F.col("p")).alias("tier")).agg(F.count("*").alias("buckets"))


def test_sql(bucket: str, flavour: str = "pooled") -> str:
    """WITH-list items up to `t` for DuckDB, after `h`."""
    vx, vy = "var_during / nullif(size_during, 0)", "var_{r} / nullif(size_{r}, 0)"
    if flavour == "pooled":
        spread = "((size_during - 1) * var_during + (size_{r} - 1) * var_{r}) / nullif(size_during + size_{r} - 2, 0) * (1 / nullif(size_during, 0) + 1 / nullif(size_{r}, 0))"
        df = "(size_during + size_{r} - 2)::double"
    else:
        spread = f"({vx} + {vy})"
        df = f"pow({vx} + {vy}, 2) / nullif(pow({vx}, 2) / nullif(size_during - 1, 0) + pow({vy}, 2) / nullif(size_{{r}} - 1, 0), 0)"
    each = " union all ".join(
        f"select bucket, '{k}' test, n, case when size_during > 1 and size_{r} > 1 then {s} * (mean_during - mean_{r}) / sqrt(nullif({spread.format(r=r)}, 0)) end t, {df.format(r=r)} df from m" for k, (r, s) in TESTS.items()
    )
    stats = ", ".join(f"count({c}) size_{w}, avg({c}) mean_{w}, var_samp({c}) var_{w}" for w, c in (("during", "n_during"), ("before", "n_before"), ("after", "n_after"), ("avg", "coalesce((n_before + n_after) / 2.0::double, n_before, n_after)")))
    return f"""
m as (select {bucket} bucket, count(*) n, {stats} from h group by 1),
t0 as ({each}),
t1 as (select *, case when t is not null then 0.5 * {_part("atan(abs(t) / sqrt(df))")} / ({_part("0.0")}) end tail from t0),
t as (select bucket, test, n, t, df, case when t >= 0 then tail else 1 - tail end p from t1)
"""


def _part(lo: str) -> str:
    """Simpson's rule for the t distribution's tail, from an angle to the right one, in DuckDB."""
    return f"list_sum(list_transform(range(0, {PANELS + 1}), lambda i: (case when i = 0 or i = {PANELS} then 1.0 when i % 2 = 1 then 4.0 else 2.0 end) * pow(greatest(0, cos({lo} + (pi() / 2 - {lo}) / {PANELS} * i)), df - 1))) * (pi() / 2 - {lo})"


def contrast(counts: DataFrame, bucket: Column) -> DataFrame:
    """(bucket, t3 .. t6, construction): confidence of the before and after tests side by side, and the share of construction."""
    tested = tests(counts, [bucket.alias("bucket")]).groupBy("bucket").pivot("test", ["T3", "T4", "T5", "T6"]).agg(F.max(F.round(1 - F.col("p"), 6)))
    share = counts.groupBy(bucket.alias("bucket")).agg(F.round(F.avg(F.when(F.col("type") == "construction", 1.0).otherwise(0.0)), 6).alias("construction"))
    return tested.join(share, "bucket").select("bucket", *[F.col(t).alias(t.lower()) for t in ("T3", "T4", "T5", "T6")], "construction")


def sign(tested: DataFrame, least: float = 0.9) -> DataFrame:
    """(bucket, positive, negative): whether any test of that direction reaches the confidence."""
    reach = lambda names: F.coalesce(F.max(F.when(F.col("test").isin(*names), 1 - F.col("p"))) >= least, F.lit(False))
    return tested.groupBy("bucket").agg(reach(("T1", "T3", "T5")).alias("positive"), reach(("T2", "T4", "T6")).alias("negative"))


def two_sample(df: DataFrame, value: str, first: Column, second: Column) -> DataFrame:
    """(flavour, n_x, n_y, t, df, p) of one-sided tests that the first group's mean is above the second's, pooled and Welch."""
    v = F.col(value).cast("double")
    m = df.agg(*[f(F.when(g, v)).alias(f"{n}{s}") for s, g in (("x", first), ("y", second)) for n, f in (("n", F.count), ("m", F.avg), ("v", F.var_samp))])
    nx, ny, vx, vy = (F.col(c) for c in ("nx", "ny", "vx", "vy"))
    a, b = vx / nx, vy / ny
    pooled = ((nx - 1) * vx + (ny - 1) * vy) / (nx + ny - 2)
    kinds = [("pooled", pooled * (1 / nx + 1 / ny), (nx + ny - 2).cast("double")), ("welch", a + b, (a + b) * (a + b) / (a * a / (nx - 1) + b * b / (ny - 1)))]
    each = F.array(*[F.struct(F.lit(k).alias("flavour"), ((F.col("mx") - F.col("my")) / F.sqrt(s)).alias("t"), f.alias("df")) for k, s, f in kinds])
    return m.select("nx", "ny", F.inline(each)).select("flavour", F.col("nx").alias("n_x"), F.col("ny").alias("n_y"), F.round("t", 6).alias("t"), F.round("df", 4).alias("df"), F.round(t_upper(F.col("t"), F.col("df")), 6).alias("p"))


def two_sample_sql(source: str) -> str:
    """The same for DuckDB; `source` gives g (1 or 0) and v."""
    return f"""with m as (select count(v) filter (g = 1) nx, count(v) filter (g = 0) ny, avg(v) filter (g = 1) mx, avg(v) filter (g = 0) my, var_samp(v) filter (g = 1) vx, var_samp(v) filter (g = 0) vy from ({source})),
k as (select 'pooled' flavour, nx, ny, (mx - my) / sqrt(((nx - 1) * vx + (ny - 1) * vy) / (nx + ny - 2) * (1 / nx + 1 / ny)) t, (nx + ny - 2)::double df from m
union all select 'welch', nx, ny, (mx - my) / sqrt(vx / nx + vy / ny), pow(vx / nx + vy / ny, 2) / (pow(vx / nx, 2) / (nx - 1) + pow(vy / ny, 2) / (ny - 1)) from m),
q as (select *, 0.5 * {_part("atan(abs(t) / sqrt(df))")} / ({_part("0.0")}) tail from k)
select flavour, nx n_x, ny n_y, round(t, 6) t, round(df, 4) df, round(case when t >= 0 then tail else 1 - tail end, 6) p from q"""
