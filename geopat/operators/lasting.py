"""Lasting entities: threshold, conflicts, fusion, and counts in their surroundings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geopat.functions.geo import MILE_M, haversine
from geopat.plans.components import connected
from geopat.plans.rangejoin import buckets
from geopat.plans.scratch import written

RADIUS = 14.03 * MILE_M
DAY = 86_400_000_000
_DEGREE_M = 111195.0


def span() -> Column:
    """Duration of an entity, in microseconds."""
    return F.col("end_us") - F.col("start_us")


def quantile(df: DataFrame, value: Column, p: float, weight: Column | None = None, cells: int = 4096) -> float | None:
    """The p-quantile of a column, interpolated as the exact percentile is, without a task or map that holds all values.

    A pass counts the values of an interval by cell, and the cell with the wanted ranks is the next
    interval, until it holds one value or parts the two ranks.  A pass brings back `cells` rows at most.
    """
    rows = df.select(value.cast("double").alias("v"), (F.lit(1) if weight is None else weight).cast("long").alias("w")).where("v is not null and w > 0")
    ends = rows.agg(F.min("v"), F.max("v"), F.sum("w")).first()
    if ends[2] is None:
        return None
    lo, hi, before = ends[0], ends[1], 0
    place = p * (ends[2] - 1)
    first, second = int(place), min(int(place) + 1, ends[2] - 1)
    while lo < hi:
        cell = F.floor((F.col("v") - lo) / ((hi - lo) / cells))
        held = rows.where(F.col("v").between(lo, hi)).groupBy(cell.alias("c")).agg(F.sum("w").alias("n"), F.min("v").alias("lo"), F.max("v").alias("hi")).collect()
        for r in sorted(held, key=lambda r: r.lo):
            if first < before + r.n:
                break
            before += r.n
        if second >= before + r.n:
            return r.hi + (min(x.lo for x in held if x.lo > r.hi) - r.hi) * (place - first)
        lo, hi = r.lo, r.hi
    return lo


def threshold(df: DataFrame, p: float = 0.99, exact: bool = True, round_to_minutes: int | None = None) -> DataFrame:
    """One row: the p-quantile of durations, in microseconds, rounded down to so many minutes where that is given."""
    if exact:
        cut = df.sparkSession.createDataFrame([(quantile(df, span(), p),)], "threshold_us double")
    else:
        cut = df.agg(F.percentile_approx(span(), F.lit(p), F.lit(100_000)).cast("double").alias("threshold_us"))
    unit = (round_to_minutes or 0) * 60_000_000
    return cut.withColumn("threshold_us", F.floor(F.col("threshold_us") / unit) * float(unit)) if unit else cut


def extract(df: DataFrame, p: float = 0.99, inclusive: bool = False, round_to_minutes: int | None = None) -> DataFrame:
    """Entities that last longer than the threshold."""
    rows = df.crossJoin(F.broadcast(threshold(df, p, round_to_minutes=round_to_minutes)))  # one row
    return rows.where(span() >= F.col("threshold_us") if inclusive else span() > F.col("threshold_us")).drop("threshold_us")


def _cell(lat: Column, lon: Column, radius: float) -> tuple[Column, Column]:
    """Grid cell at least `radius` wide; longitude cells are widened for latitudes up to 60 degrees."""
    size = radius / _DEGREE_M * 1.001
    return F.floor(lat / size), F.floor(lon / (size * 2))


def conflicts(lasting: DataFrame, radius: float = RADIUS) -> DataFrame:
    """(a, b) with a < b: pairs that overlap in time, and in place by radius, or by station where weather is involved."""
    cols = ("entity_id", "kind", "start_us", "end_us", "lat", "lon", "station")
    x, y = _cell(F.col("lat"), F.col("lon"), radius)
    base = lasting.select(*cols, x.alias("x"), y.alias("y")).withColumn("day", F.explode(buckets(F.col("start_us"), F.col("end_us"), DAY)))
    near = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    a = base.select(*[F.col(c).alias(f"a_{c}") for c in (*cols, "x", "y", "day")])
    b = base.select(*[F.col(c).alias(f"b_{c}") for c in (*cols, "x", "y", "day")])
    same = (F.col("a_entity_id") < F.col("b_entity_id")) & (F.col("a_start_us") <= F.col("b_end_us")) & (F.col("b_start_us") <= F.col("a_end_us"))
    once = F.col("a_day") == F.floor(F.greatest("a_start_us", "b_start_us") / DAY)
    weather = (F.col("a_kind") == "weather") | (F.col("b_kind") == "weather")
    by_station = a.join(b, (F.col("a_station") == F.col("b_station")) & (F.col("a_day") == F.col("b_day")) & same & once & weather)
    wide = a.where("a_kind = 'traffic'").withColumn("n", F.explode(near)).withColumns({"a_x": F.col("a_x") + F.col("n.i"), "a_y": F.col("a_y") + F.col("n.j")})
    close = haversine(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon")) <= radius
    by_radius = wide.join(b.where("b_kind = 'traffic'"), (F.col("a_x") == F.col("b_x")) & (F.col("a_y") == F.col("b_y")) & (F.col("a_day") == F.col("b_day")) & same & once & close)
    out = [F.col("a_entity_id").alias("a"), F.col("b_entity_id").alias("b")]
    return by_station.select(*out).union(by_radius.select(*out))


def _fused(lasting: DataFrame, found: DataFrame) -> DataFrame:
    """Fused entities of the groups (node, component); entities in none stand alone."""
    rows = lasting.join(found, F.col("entity_id") == F.col("node"), "left").withColumn("id", F.coalesce("component", "entity_id"))
    return rows.groupBy("id").agg(
        F.min("start_us").alias("start_us"), F.max("end_us").alias("end_us"), F.array_join(F.array_sort(F.collect_set("type")), "_").alias("type"), F.count("*").alias("members"), F.max("kind").alias("kind"), (F.min("kind") != F.max("kind")).alias("mixed"),
        F.min_by("station", F.struct("start_us", "entity_id")).alias("station"), F.min_by("state", F.struct("start_us", "entity_id")).alias("state"),
        F.avg(F.when(F.col("kind") == "traffic", F.col("lat"))).alias("lat"), F.avg(F.when(F.col("kind") == "traffic", F.col("lon"))).alias("lon"),
    )


def fuse_components(lasting: DataFrame, pairs: DataFrame) -> DataFrame:
    """Fused entities: one per component of conflicts, with the union of times, the centre, and the sorted types joined.

    A fused entity with a weather member counts as weather, so it meets others by station.
    """
    return _fused(lasting, connected(pairs))


def fuse_fixpoint(lasting: DataFrame, radius: float = RADIUS, most_rounds: int = 20) -> DataFrame:
    """Components fused again, with their wider times and new centres, until no two fused entities conflict."""
    lasting = written(lasting)
    found = written(connected(conflicts(lasting, radius)))
    for _ in range(most_rounds):
        again = written(conflicts(_fused(lasting, found).withColumnRenamed("id", "entity_id"), radius))
        if again.isEmpty():
            return _fused(lasting, found)
        merged = connected(again).withColumnRenamed("node", "old").withColumnRenamed("component", "new")
        whole = lasting.select(F.col("entity_id").alias("node")).join(found, "node", "left").select("node", F.coalesce("component", "node").alias("old"))
        found = written(whole.join(merged, "old", "left").select("node", F.coalesce("new", "old").alias("component")))
    raise RuntimeError(f"fusion did not settle in {most_rounds} rounds")


def fuse_greedy(lasting: DataFrame, pairs: DataFrame, most_rounds: int = 1000) -> DataFrame:
    """One pass in order of start and id: an entity not yet taken is a seed, and takes its later conflicts that no earlier seed took.

    The pass is decided in parallel: a round settles every entity whose earlier conflicts are settled,
    or of which one is a seed; what is left of a chain of conflicts bounds the rounds, not the number of entities.
    """
    at = lasting.select("entity_id", F.struct("start_us", "entity_id").alias("at"))
    both = pairs.join(at.select(F.col("entity_id").alias("a"), F.col("at").alias("a_at")), "a").join(at.select(F.col("entity_id").alias("b"), F.col("at").alias("b_at")), "b")
    swap = F.col("a_at") > F.col("b_at")
    edges = written(both.select(F.when(swap, F.col("b")).otherwise(F.col("a")).alias("first"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("later"), F.least("a_at", "b_at").alias("first_at")))
    state = written(edges.select(F.col("first").alias("node")).union(edges.select("later")).distinct().withColumn("s", F.lit(0)))
    for _ in range(most_rounds):
        before = edges.join(state.select(F.col("node").alias("first"), F.col("s").alias("fs")), "first").groupBy(F.col("later").alias("node")).agg(F.count_if(F.col("fs") == 1).alias("seeds"), F.count_if(F.col("fs") == 0).alias("open"))
        settled = F.when(F.col("s") != 0, F.col("s")).when(F.coalesce("seeds", F.lit(0)) > 0, 2).when(F.coalesce("open", F.lit(0)) == 0, 1).otherwise(0)
        state = written(state.join(before, "node", "left").select("node", settled.alias("s")))
        if state.where("s = 0").isEmpty():
            break
    else:
        raise RuntimeError(f"the pass did not settle in {most_rounds} rounds")
    seeds = state.where("s = 1").select(F.col("node").alias("first"))
    taken = edges.join(seeds, "first", "left_semi").groupBy(F.col("later").alias("node")).agg(F.min_by("first", "first_at").alias("component"))
    return _fused(lasting, taken)


def type_table(before: DataFrame, after: DataFrame, top: int = 15) -> DataFrame:
    """(rank, type_before, n_before, type_after, n_after): the commonest types before and after fusion, side by side; ties by name."""
    order = Window.partitionBy(F.lit(1)).orderBy(F.desc("n"), "type")  # types are few
    ranked = lambda df, t: df.groupBy("type").agg(F.count("*").alias("n")).withColumn("rank", F.row_number().over(order).cast("long")).where(F.col("rank") <= top).select("rank", F.col("type").alias(f"type_{t}"), F.col("n").alias(f"n_{t}"))
    return ranked(before, "before").join(ranked(after, "after"), "rank", "full")


def fused_windows(lasting: DataFrame, radius: float = RADIUS, rule: str = "components") -> DataFrame:
    """Lasting entities with overlaps resolved, as owners of halo windows (entity_id is the fused entity's id)."""
    lasting = written(lasting)
    fused = fuse_fixpoint(lasting, radius) if rule == "fixpoint" else fuse_components(lasting, conflicts(lasting, radius))
    return fused.withColumnRenamed("id", "entity_id")


def _shift(week: int, rule: str) -> Column:
    """How far the windows before and after lie from the one during: a week and the duration, as it is or in whole days."""
    return week + {"exact": span(), "ceil": F.ceil(span() / DAY) * DAY, "floor": F.floor(span() / DAY) * DAY}[rule]


def _kept(lasting: DataFrame, df: DataFrame, shift: Column, edge: str) -> DataFrame:
    """Window owners with has_before and has_after: whether these windows lie within the data; which owners stay depends on `edge`."""
    if edge == "keep":
        return lasting.withColumns({"has_before": F.lit(True), "has_after": F.lit(True)})
    ends = df.agg(F.min("start_us").alias("first_us"), F.max("end_us").alias("last_us"))
    flagged = lasting.crossJoin(F.broadcast(ends)).withColumns({"has_before": F.col("start_us") - shift >= F.col("first_us"), "has_after": F.col("end_us") + shift <= F.col("last_us")})  # one row
    return flagged.where("has_before and has_after" if edge == "complete" else "has_before or has_after").drop("first_us", "last_us")


def halo_members(
    lasting: DataFrame, df: DataFrame, radius: float = RADIUS, week: int = 7 * DAY, edge: str = "keep", shift: str = "exact", counted: str = "traffic", excluded: DataFrame | None = None, mixed: str = "station"
) -> DataFrame:
    """(long_id, which, entity_id): entities that start after and end before the ends of a window (during, before, after).

    The three windows are one tagged table joined once, by cell or station and day of start.
    `edge` complete keeps owners whose shifted windows both lie within the data, one_sided those with one;
    `counted` all counts weather too, by station.  `excluded` (the owners themselves, or what was fused into them) is never counted.
    Owners fused of both kinds meet others by station, by radius, or by either (`mixed`).
    """
    s, e = F.col("start_us"), F.col("end_us")
    shift = _shift(week, shift)
    x, y = _cell(F.col("lat"), F.col("lon"), radius)
    both = F.col("mixed") if "mixed" in lasting.columns else F.lit(False)
    keep = _kept(lasting, df, shift, edge)
    tags = F.array(*[F.struct(F.lit(n).alias("which"), (s + k * shift).alias("lo"), (e + k * shift).alias("hi"), F.lit(has).alias("tag")) for n, k, has in (("during", 0, ""), ("before", -1, "b"), ("after", 1, "a"))])
    windows = keep.select(
        F.col("entity_id").alias("long_id"), F.col("kind").alias("w_kind"), both.alias("w_mixed"), F.col("lat").alias("w_lat"), F.col("lon").alias("w_lon"), F.col("station").alias("w_station"), x.alias("w_x"), y.alias("w_y"), "has_before", "has_after", F.inline(tags)
    ).where((F.col("tag") == "") | ((F.col("tag") == "b") & F.col("has_before")) | ((F.col("tag") == "a") & F.col("has_after")))
    windows = windows.drop("tag", "has_before", "has_after").withColumn("w_day", F.explode(buckets(F.col("lo"), F.col("hi"), DAY)))
    others = df if counted == "all" else df.where("kind = 'traffic'")
    gone = (lasting if excluded is None else excluded).select("entity_id")
    others = others.join(gone, "entity_id", "left_anti").select("entity_id", "kind", "start_us", "end_us", "lat", "lon", "station", x.alias("x"), y.alias("y"), F.floor(s / DAY).alias("day"))
    inside = (s > F.col("lo")) & (e < F.col("hi")) & (F.col("day") == F.col("w_day"))
    near = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    weather = F.col("w_kind") == "weather"
    by_place = ~weather if mixed == "station" else ~weather | F.col("w_mixed")
    at_station = weather & ~F.col("w_mixed") if mixed == "radius" else weather
    wide = windows.where(by_place).withColumn("n", F.explode(near)).withColumns({"w_x": F.col("w_x") + F.col("n.i"), "w_y": F.col("w_y") + F.col("n.j")})
    close = haversine(F.col("lat"), F.col("lon"), F.col("w_lat"), F.col("w_lon")) <= radius
    out = ("long_id", "which", "entity_id")
    hits = wide.join(others.where("kind = 'traffic'"), (F.col("w_x") == F.col("x")) & (F.col("w_y") == F.col("y")) & inside & close).select(*out)
    by_station = windows.where(at_station).join(others, (F.col("w_station") == F.col("station")) & inside).select(*out)
    if counted == "all":
        wet = windows.where(~at_station).join(others.where("kind = 'weather'"), (F.col("w_station") == F.col("station")) & inside)
        by_station = by_station.union(wet.select(*out))
    found = hits.union(by_station)
    return found.distinct() if mixed == "either" else found


def halo_counts(
    lasting: DataFrame, df: DataFrame, radius: float = RADIUS, week: int = 7 * DAY, edge: str = "keep", shift: str = "exact", counted: str = "traffic", excluded: DataFrame | None = None, mixed: str = "station"
) -> DataFrame:
    """(long_id, state, type, kind, span_us, n_during, n_before, n_after): sizes of `halo_members`, zeros kept; null for a window that `edge` leaves out."""
    hits = halo_members(lasting, df, radius, week, edge, shift, counted, excluded, mixed)
    keep = _kept(lasting, df, _shift(week, shift), edge)
    n = hits.groupBy("long_id").agg(*[F.count_if(F.col("which") == w).alias(f"n_{w}") for w in ("during", "before", "after")])

    def zero(w: str) -> Column:
        count = F.coalesce(F.col(f"n_{w}"), F.lit(0)).cast("long")
        return (count if w == "during" else F.when(F.col(f"has_{w}"), count)).alias(f"n_{w}")

    return keep.withColumnRenamed("entity_id", "long_id").join(n, "long_id", "left").select("long_id", "state", "type", "kind", span().alias("span_us"), zero("during"), zero("before"), zero("after"))


_APART = "2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians({b}.lat - {a}.lat) / 2), 2) + cos(radians({a}.lat)) * cos(radians({b}.lat)) * pow(sin(radians({b}.lon - {a}.lon) / 2), 2))))"


def lasting_sql(p: float) -> str:
    """WITH-list items `la` and `cf` for DuckDB, after `e`."""
    return f"""
la as (select * from e where end_us - start_us > (select quantile_cont(end_us - start_us, {p}) from e)),
cf as (select p.entity_id a, c.entity_id b from la p join la c on p.entity_id < c.entity_id and p.start_us <= c.end_us and c.start_us <= p.end_us
  where case when p.kind = 'weather' or c.kind = 'weather' then p.station = c.station else {_APART.format(a="p", b="c")} <= {RADIUS}::double end)
"""


#: WITH-list item `fu` for DuckDB, after `cf`: lasting entities fused by components, with the columns of `la` that halos read.
FUSED_SQL = """
rc as (select entity_id node, entity_id r from la union select case when rc.node = cf.a then cf.b else cf.a end, rc.r from rc join cf on rc.node in (cf.a, cf.b)),
cm as (select node, min(r) id from rc group by 1),
fu as (select id entity_id, min(start_us) start_us, max(end_us) end_us, array_to_string(list_sort(list(distinct type)), '_') "type", max(kind) kind, count(distinct kind) > 1 mixed, arg_min(station, [start_us, la.entity_id]) station,
  arg_min(state, [start_us, la.entity_id]) state, avg(lat) filter (kind = 'traffic') lat, avg(lon) filter (kind = 'traffic') lon from la join cm on node = la.entity_id group by id)
"""


def halo_sql(edge: str, span: str = "(end_us - start_us)", owners: str = "fu", mixed: str = "station", counted: str = "e") -> str:
    """WITH-list items `lk`, `tr` and `h` for DuckDB, after the owners (`la` or `fu`)."""
    stays = {"keep": "", "complete": "where b_ok and a_ok", "one_sided": "where b_ok or a_ok"}[edge]
    both = "mixed" if owners == "fu" else "false mixed"
    near = f"{_APART.format(a='lk', b='tr')} <= {RADIUS}::double"
    meets = {
        "station": f"case when lk.kind = 'weather' then lk.station = tr.station else {near} end",
        "radius": f"case when lk.kind = 'weather' and not lk.mixed then lk.station = tr.station else {near} end",
        "either": f"case when lk.mixed then lk.station = tr.station or {near} when lk.kind = 'weather' then lk.station = tr.station else {near} end",
    }[mixed]
    side = lambda ok, sign: f"(case when {'true' if edge != 'one_sided' else f'any_value({ok})'} then count_if(tr.start_us > lk.start_us {sign} sh and tr.end_us < lk.end_us {sign} sh) end)::bigint"
    return f"""
lk as (select * from (select entity_id, state, "type", kind, station, lat, lon, start_us, end_us, {both}, 604800000000 + {span} sh, start_us - (604800000000 + {span}) >= (select min(start_us) from e) b_ok,
  end_us + (604800000000 + {span}) <= (select max(end_us) from e) a_ok from {owners}) {stays}),
tr as (select * from {counted} where kind = 'traffic' and entity_id not in (select entity_id from la)),
h as (select lk.entity_id long_id, any_value(lk.state) state, any_value(lk.type) "type", any_value(lk.kind) kind, any_value(lk.end_us - lk.start_us) span_us,
  (count_if(tr.start_us > lk.start_us and tr.end_us < lk.end_us))::bigint n_during, {side("b_ok", "-")} n_before, {side("a_ok", "+")} n_after
  from lk left join tr on {meets} group by lk.entity_id)
"""
