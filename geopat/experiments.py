"""More of the workloads: weather intervals, three-node shapes and profiles, density, fusion by other rules, halo variants, baselines, measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.functions.geo import haversine
from geopat.operators import baseline, cluster, density, forest, influence, lasting, mine, relate, shapes, weather
from geopat.plans.scratch import written
from geopat.sources.entities import nearest_station, read, stations
from geopat.workloads import BUCKETS, DENSE, DENSER, EDGES, OWNERS_SQL, PAPER, entities, halo, nodes_of, query, with_e

# ---- preparation

_CONDITION = {"STANDARD": "clear", "ECONOMY": "rain", "MEDIUM": "snow", "PROMO": "fog", "LARGE": "hail", "SMALL": "thunderstorm"}
_RECORDS = (
    "r as (select l_suppkey::bigint station, epoch_us(l_shipdate) + 10800000000 * l_linenumber + (l_orderkey % 180) * 60000000 time_us, 1.3::double * l_quantity - 28 temperature, 700.0::double * l_discount wind, 150.0::double * l_tax precipitation, "
    "case split_part(p_type, ' ', 1) " + " ".join(f"when '{k}' then '{v}'" for k, v in _CONDITION.items()) + " end condition from lineitem join part on p_partkey = l_partkey)"
)
_TYPED = "y as (select *, unnest(list_filter([case when temperature <= -23.7::double then 'severe_cold' end, case when wind >= 60 then 'storm' end, case when condition = 'thunderstorm' and precipitation > 0 then 'precipitation' end, case when condition in ('fog', 'hail', 'rain', 'snow') then condition end], lambda x: x is not null)) \"type\" from n)"


def records(spark: SparkSession, d: str) -> DataFrame:
    """Weather records with a time, in microseconds."""
    names = F.create_map(*[F.lit(x) for kv in _CONDITION.items() for x in kv])
    rows = read(spark, d, "lineitem").join(read(spark, d, "part"), F.col("p_partkey") == F.col("l_partkey"))
    day = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(l_shipdate as timestamp_ntz))")
    return rows.select(
        F.col("l_suppkey").cast("long").alias("station"), (day + 10_800_000_000 * F.col("l_linenumber") + F.col("l_orderkey") % 180 * 60_000_000).alias("time_us"), (1.3 * F.col("l_quantity") - 28).alias("temperature"),
        (700.0 * F.col("l_discount")).alias("wind"), (150.0 * F.col("l_tax")).alias("precipitation"), names[F.split("p_type", " ")[0]].alias("condition"),
    )


@query("w_weather_intensity", f"with {_RECORDS} select condition, {weather.intensity_sql('temperature', 'temperature')} temperature, {weather.intensity_sql('wind', 'wind')} wind, case condition when 'rain' then {weather.intensity_sql('precipitation', 'rain')} when 'snow' then {weather.intensity_sql('precipitation', 'snow')} end deposit, count(*) n from r group by all")
def w_weather_intensity(spark: SparkSession, d: str) -> DataFrame:
    deposit = F.when(F.col("condition") == "rain", weather.intensity(F.col("precipitation"), "rain")).when(F.col("condition") == "snow", weather.intensity(F.col("precipitation"), "snow"))
    named = records(spark, d).select("condition", weather.intensity(F.col("temperature"), "temperature").alias("temperature"), weather.intensity(F.col("wind"), "wind").alias("wind"), deposit.alias("deposit"))
    return named.groupBy("condition", "temperature", "wind", "deposit").agg(F.count("*").alias("n"))


for _rule in ("last", "next"):
    _next = "(min(time_us) over (partition by station order by time_us range between 1 following and unbounded following))" if _rule == "next" else "null::bigint"
    _end = "coalesce(max(next_us), max(time_us))" if _rule == "next" else "max(time_us)"
    _level = "case when type = 'rain' then case when precipitation <= 4.8 then 0 when precipitation <= 9.35 then 1 else 2 end when type = 'snow' then case when precipitation <= 1.15 then 0 when precipitation <= 2.1 then 1 else 2 end end"

    @query(f"w_weather_entities{'_next' if _rule == 'next' else ''}", f"with {_RECORDS}, n as (select *, {_next} next_us from r), {_TYPED}, z as (select *, time_us - lag(time_us) over (partition by station, type order by time_us) > 1728000000000 opens from y), i as (select *, sum(case when opens then 1 else 0 end) over (partition by station, type order by time_us rows unbounded preceding) island from z) select station, type, min(time_us) start_us, {_end} end_us, count(*) records, ['light', 'moderate', 'heavy'][max({_level}) + 1] intensity from i group by station, type, island")
    def w_weather_entities(spark: SparkSession, d: str, rule: str = _rule) -> DataFrame:
        return weather.extract(records(spark, d), end_rule=rule)


@query("w_congestion_severity", with_e(then="select case when code < 17 then 'light' when code < 34 then 'moderate' else 'heavy' end severity, count(*) n from e where type = 'congestion' group by 1"))
def w_congestion_severity(spark: SparkSession, d: str) -> DataFrame:
    level = F.when(F.col("code") < 17, "light").when(F.col("code") < 34, "moderate").otherwise("heavy")
    return entities(spark, d).where("type = 'congestion'").groupBy(level.alias("severity")).agg(F.count("*").alias("n"))


_METRES = "2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians(slat - clat) / 2), 2) + cos(radians(clat)) * cos(radians(slat)) * pow(sin(radians(slon - clon) / 2), 2))))"


@query("w_zip_station", with_e("zc as (select zip, avg(lat) clat, avg(lon) clon from e where kind = 'traffic' group by 1)", then=f"select zip, arg_min(code, [round({_METRES}), code]) station from zc, st group by zip"))
def w_zip_station(spark: SparkSession, d: str) -> DataFrame:
    centre = entities(spark, d).where("kind = 'traffic'").groupBy(F.col("zip").alias("city")).agg(F.avg("lat").alias("clat"), F.avg("lon").alias("clon"))
    return nearest_station(centre, stations(spark, d)).withColumnRenamed("city", "zip")


@query("w_address", with_e(then="select entity_id, arg_min(ct.city, [round(2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians(clat - lat) / 2), 2) + cos(radians(lat)) * cos(radians(clat)) * pow(sin(radians(clon - lon) / 2), 2))))), ct.city]) city from e, ct where kind = 'traffic' group by 1"))
def w_address(spark: SparkSession, d: str) -> DataFrame:
    """City of each traffic entity by the nearest centre in a directory, found in the 3 x 3 cells (0.1 degrees) around."""
    e = entities(spark, d)
    c = F.col("city")
    directory = e.select("city", "state").distinct().select(c, (28 + 4 * F.floor(F.col("state") / 5) + 0.2 * (F.floor(c / 25) % 10)).alias("clat"), (-120 + 10 * (F.col("state") % 5) + 0.2 * F.floor(c / 250)).alias("clon"))
    around = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    spread = directory.withColumn("n", F.explode(around)).select("city", "clat", "clon", (F.floor(F.col("clat") * 10) + F.col("n.i")).alias("x"), (F.floor(F.col("clon") * 10) + F.col("n.j")).alias("y"))
    points = e.where("kind = 'traffic'").select("entity_id", "lat", "lon", F.floor(F.col("lat") * 10).alias("x"), F.floor(F.col("lon") * 10).alias("y"))
    metres = F.round(haversine(F.col("lat"), F.col("lon"), F.col("clat"), F.col("clon")), 0)
    return points.join(spread, ["x", "y"]).groupBy("entity_id").agg(F.min_by("city", F.struct(metres, "city")).alias("city"))


# ---- propagation

for _name, _t in (("paper", PAPER), ("dense", DENSE)):
    @query(f"w_weak_pairs_{_name}", with_e(relate.weak_sql(*_t), then="select a, b from wp"))
    def w_weak_pairs(spark: SparkSession, d: str, t: tuple = _t) -> DataFrame:
        return relate.weak_pairs(entities(spark, d), *t)


def _stationed(spark: SparkSession, d: str, e: DataFrame) -> DataFrame:
    """Entities with weather at its station's position."""
    at = stations(spark, d).select(F.col("code").alias("station"), "slat", "slon")
    wet = F.col("kind") == "weather"
    return e.join(at, "station", "left").withColumns({"lat": F.when(wet, F.col("slat")).otherwise(F.col("lat")), "lon": F.when(wet, F.col("slon")).otherwise(F.col("lon"))}).drop("slat", "slon")


@query("w_generic_pairs", with_e(baseline.generic_sql(), then="select a, b from gp2"))
def w_generic_pairs(spark: SparkSession, d: str) -> DataFrame:
    return baseline.generic_pairs(_stationed(spark, d, entities(spark, d)))


@query("w_generic_vs_strict", with_e(relate.weak_sql(*DENSE), baseline.generic_sql(), "cmp as (select coalesce(wp.a, gp2.a) a, coalesce(wp.b, gp2.b) b, wp.a is not null s, gp2.a is not null g from wp full join gp2 on wp.a = gp2.a and wp.b = gp2.b)", then="select count_if(s and g)::bigint \"both\", count_if(s and not g)::bigint only_strict, count_if(g and not s)::bigint only_generic, count_if(g and not s and p.kind = 'traffic' and c.kind = 'traffic' and p.street = c.street and p.side <> c.side)::bigint opposite_side, count_if(s and not g and (p.end_us < c.start_us or c.end_us < p.start_us))::bigint lagging from cmp join e p on p.entity_id = cmp.a join e c on c.entity_id = cmp.b"))
def w_generic_vs_strict(spark: SparkSession, d: str) -> DataFrame:
    e = entities(spark, d)
    return baseline.compare(relate.weak_pairs(e, *DENSE), baseline.generic_pairs(_stationed(spark, d, e)), e)


for _name, _t, _s in (("adaptive", DENSE, None), ("fixed02", DENSER, 0.02)):
    _base = (relate.link_sql(*_t), forest.FOREST_SQL, mine.shape_sql(_s is None))
    _city, _state = mine.three_sql(_s is None), mine.three_sql(_s is None, "state", "t3")

    @query(f"w_shapes3_city_{_name}", with_e(*_base, _city, then="select * from s3"))
    def w_shapes3(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s, max_nodes=3)

    @query(f"w_shapes_state_core_{_name}", with_e(*_base, _city, then="select distinct state, shape, size, root_label from s3"))
    def w_core(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_shapes3) -> DataFrame:
        return mine.state_core(get(spark, d, t, s))

    @query(f"w_shapes3_state_{_name}", with_e(*_base, _state, then="select * from t3"))
    def w_shapes3_state(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.frequent(nodes_of(entities(spark, d), t), ["state"], s, max_nodes=3)

    @query(f"w_shapes_lost_{_name}", with_e(*_base, _city, _state, then="select distinct state, shape from s3 where (state, shape) not in (select (state, shape) from t3)"))
    def w_lost(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        n = written(nodes_of(entities(spark, d), t))
        core = mine.state_core(mine.frequent(n, ["state", "city"], s, max_nodes=3))
        return core.join(mine.frequent(n, ["state"], s, max_nodes=3).select("state", "shape"), ["state", "shape"], "left_anti").select("state", "shape")

    @query(f"w_shape_top12_{_name}", with_e(*_base, _city, "tp as (select shape, count(distinct state) states, row_number() over (order by count(distinct state) desc, shape) rank from s3 group by 1)", then="select rank, shape, states from tp where rank <= 12"))
    def w_top12(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_shapes3) -> DataFrame:
        from pyspark.sql import Window

        n = get(spark, d, t, s).groupBy("shape").agg(F.countDistinct("state").alias("states"))
        return n.withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(1)).orderBy(F.desc("states"), "shape")).cast("long")).where("rank <= 12").select("rank", "shape", "states")

    @query(f"w_shape_top12_all_{_name}")
    def w_top12_all(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_top12) -> DataFrame:
        return get(spark, d, t, s, lambda spark, d, t, s: mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s))

    @query(f"w_shapes_lost_all_{_name}")
    def w_lost_all(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        n = written(nodes_of(entities(spark, d), t))
        core = mine.state_core(mine.frequent(n, ["state", "city"], s))
        return core.join(mine.frequent(n, ["state"], s).select("state", "shape"), ["state", "shape"], "left_anti").select("state", "shape")

    _profile = (
        "oc as (select an.state, an.city, top_label || '(' || low_label || ')' shape, hour(make_timestamp(x.start_us)) h, x.road from an join e x on x.entity_id = an.top where top <> low)",
        "ok as (select oc.* from oc join s2 using (state, city, shape))",
        "hw as (select shape, s.s, count(*) n from ok, (select unnest(range(0, 24)) s) s where h = s.s or h = (s.s + 1) % 24 group by all)",
        "pk as (select shape, arg_min(s, [-n, s]) peak_hour from hw group by 1)",
        "rd as (select shape, count(*) instances, case when avg(case when road = 'interstate' then 1.0 else 0 end) >= 2 / 3::double then 'interstate' when avg(case when road = 'interstate' then 1.0 else 0 end) <= 1 / 3::double then 'city' else 'mixture' end road_class from ok group by 1)",
        "ps as (select shape, root_label, state, avg(support_count / trees) s, sum(support_count / trees) t, count(*) c from s2 group by all)",
        "pf as (select shape, root_label, count(*) states, round(sum(t) / sum(c), 6) avg_support_city, round(avg(s), 6) avg_support_state, peak_hour, instances, road_class from ps join pk using (shape) join rd using (shape) group by all)",
    )

    @query(f"w_shape_profile_{_name}", with_e(*_base, *_profile, then="select * from pf"))
    def w_profile(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        e = entities(spark, d)
        n = written(nodes_of(e, t))
        return shapes.profile(mine.frequent(n, ["state", "city"], s, max_nodes=2), n, e)

    @query(f"w_initiators_by_road_{_name}", with_e(*_base, *_profile, then="select root_label, road_class, count(*) shapes from pf group by all"))
    def w_by_road(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_profile) -> DataFrame:
        return get(spark, d, t, s).groupBy("root_label", "road_class").agg(F.count("*").alias("shapes"))

    @query(f"w_state_vectors_{_name}", with_e(*_base, "sl as (select distinct shape from s2)", "su as (select distinct state from e)", then="select state, shape, case when exists (select 1 from s2 where s2.state = su.state and s2.shape = sl.shape) then 1 else 0 end present from su, sl"))
    def w_vectors(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        e = entities(spark, d)
        found = mine.frequent(nodes_of(e, t), ["state", "city"], s, max_nodes=2)
        return cluster.state_vectors(mine.state_core(found), e.select("state").distinct())

    @query(f"w_state_vectors_all_{_name}")
    def w_vectors_all(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        e = entities(spark, d)
        return cluster.state_vectors(mine.state_core(mine.frequent(nodes_of(e, t), ["state", "city"], s)), e.select("state").distinct())

    @query(f"w_state_distinctive_{_name}")
    def w_distinctive(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_vectors_all) -> DataFrame:
        return cluster.distinctive(written(get(spark, d, t, s)))

    for _kind in ("maximal", "closed"):
        @query(f"w_shapes_{_kind}_{_name}")
        def w_reduced(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, kind: str = _kind) -> DataFrame:
            return shapes.reduced(written(mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s)), ["state", "city"], kind == "closed")


@query("m_support", with_e(relate.link_sql(*DENSE), forest.FOREST_SQL, mine.shape_sql(True), then="select state, city, any_value(trees) trees, (count(distinct case when top_label = 'congestion' and low_label = 'congestion' and top <> low then tree end))::bigint support_count, round(count(distinct case when top_label = 'congestion' and low_label = 'congestion' and top <> low then tree end) / any_value(trees), 6) support from an join nt using (state, city) group by 1, 2"))
def m_support(spark: SparkSession, d: str) -> DataFrame:
    return shapes.support(mine.pack(nodes_of(entities(spark, d), DENSE), ["state", "city"]), ["state", "city"], "congestion(congestion)")


@query("m_link_count", with_e(relate.link_sql(*PAPER), then="select count(*) links, (select count(*) from e) entities, round(count(*) / (select count(*) from e), 6) per_entity from l"))
def m_link_count(spark: SparkSession, d: str) -> DataFrame:
    e = entities(spark, d)
    n = F.lit(e.count())
    return relate.links(e, *PAPER).agg(F.count("*").alias("links"), n.cast("long").alias("entities"), F.round(F.count("*") / n, 6).alias("per_entity"))


@query("m_tree_sizes", with_e(relate.link_sql(*DENSE), forest.FOREST_SQL, then="select nodes, count(*) trees from (select tree, count(*) nodes from f group by 1) group by 1"))
def m_tree_sizes(spark: SparkSession, d: str) -> DataFrame:
    sizes = forest.build(forest.pick_parent(relate.links(entities(spark, d), *DENSE), "arith")).groupBy("tree").agg(F.count("*").alias("nodes"))
    return sizes.groupBy("nodes").agg(F.count("*").alias("trees"))


@query("w_forest_conversations", "with n as (select count(distinct conv_id) trees from conversations), p as (select x.role || '(' || y.role || ')' shape, x.role root_label, count(distinct x.conv_id) support_count from conversations x join conversations y on x.conv_id = y.conv_id and x.turn < y.turn group by 1, 2) select 0::bigint state, shape, 2::bigint size, root_label, support_count, trees, round(support_count / trees, 6) support from p, n where support_count >= ceil(0.2 * trees - 1e-9)")
def w_forest_conversations(spark: SparkSession, d: str) -> DataFrame:
    """Two-node shapes of turn chains: a conversation is a tree, its roles are labels."""
    turns = read(spark, d, "conversations").select(F.lit(0).cast("long").alias("state"), F.col("conv_id").alias("tree"), F.col("turn").alias("node"), F.col("role").alias("label"), F.col("turn").alias("start_us"))
    first = turns.groupBy("tree").agg(F.min("node").alias("first"))
    chain = turns.join(first, "tree").withColumn("parent", F.when(F.col("node") > F.col("first"), F.col("node") - 1)).drop("first")
    return mine.frequent(chain, ["state"], 0.2, max_nodes=2)


# ---- influence

for _name, _p in (("p99", 0.99), ("p95", 0.95)):
    _cmp = "rc as (select entity_id node, entity_id r from la union select case when rc.node = cf.a then cf.b else cf.a end, rc.r from rc join cf on rc.node in (cf.a, cf.b))", "cm as (select node, min(r) id from rc group by 1)", "fu as (select id, array_to_string(list_sort(list(distinct type)), '_') \"type\", count(*) members from la join cm on node = entity_id group by id)"

    for _mode in ("greedy", "fixpoint"):
        @query(f"w_fused_{_mode}_{_name}")
        def w_fused(spark: SparkSession, d: str, p: float = _p, mode: str = _mode) -> DataFrame:
            found = written(lasting.extract(entities(spark, d), p))
            fused = lasting.fuse_fixpoint(found) if mode == "fixpoint" else lasting.fuse_greedy(found, lasting.conflicts(found))
            return fused.select("id", "start_us", "end_us", "type", "members")

    @query(f"w_lasting_types_{_name}", with_e(lasting.lasting_sql(_p), *_cmp, "kb as (select type, count(*) n, row_number() over (order by count(*) desc, type) rank from la group by 1)", "ka as (select type, count(*) n, row_number() over (order by count(*) desc, type) rank from fu group by 1)", then="select rank, b.type type_before, b.n n_before, a.type type_after, a.n n_after from (select * from kb where rank <= 15) b full join (select * from ka where rank <= 15) a using (rank)"))
    def w_lasting_types(spark: SparkSession, d: str, p: float = _p) -> DataFrame:
        found = written(lasting.extract(entities(spark, d), p))
        return lasting.type_table(found, lasting.fuse_components(found, lasting.conflicts(found)))

    @query(f"m_lasting_{_name}", with_e(lasting.lasting_sql(_p), *_cmp, then="select (select count(*) from la) lasting, count(*) fused from fu"))
    def m_lasting(spark: SparkSession, d: str, p: float = _p) -> DataFrame:
        found = written(lasting.extract(entities(spark, d), p))
        n = found.agg(F.count("*").alias("lasting"))
        return n.crossJoin(lasting.fuse_components(found, lasting.conflicts(found)).agg(F.count("*").alias("fused")))  # one row each


def traffic_points(spark: SparkSession, d: str) -> DataFrame:
    return entities(spark, d).where("kind = 'traffic'").select(F.col("entity_id").alias("id"), "lat", "lon")


_HAV = "2 * 6371008.8::double * asin(sqrt(least(1, pow(sin(radians(q.lat - p.lat) / 2), 2) + cos(radians(p.lat)) * cos(radians(q.lat)) * pow(sin(radians(q.lon - p.lon) / 2), 2))))"
_TP = "tp as (select entity_id id, street, lat, lon from e where kind = 'traffic')"


@query("w_nearest_traffic", with_e(_TP, f"pr as (select p.id, min(case when p.lat = q.lat and p.lon = q.lon then 0 else {_HAV} end) dist from tp p join tp q on p.id <> q.id and abs(p.lat - q.lat) < 0.05 group by 1)", then="select count(*) n, count_if(dist = 0)::bigint shared, round(quantile_cont(dist, 0.99), 4) p99, round(max(dist), 4) longest from pr"))
def w_nearest_traffic(spark: SparkSession, d: str) -> DataFrame:
    near = density.nearest(traffic_points(spark, d))
    return near.agg(F.sum("weight").alias("n"), F.sum(F.when(F.col("dist") == 0, F.col("weight")).otherwise(0)).alias("shared"), F.round(F.percentile("dist", F.lit(0.99), F.col("weight")), 4).alias("p99"), F.round(F.max("dist"), 4).alias("longest"))


@query("w_density_params", with_e(_TP, f"pr as (select p.id, min(case when p.lat = q.lat and p.lon = q.lon then 0 else {_HAV} end) dist from tp p join tp q on p.id <> q.id and abs(p.lat - q.lat) < 0.05 group by 1)", "ep1 as (select quantile_cont(dist, 0.99) eps from pr)", f"nc as (select p.id, count(*) - 1 n from tp p join tp q on abs(p.lat - q.lat) < 0.05 and {_HAV} <= (select eps from ep1) + 1e-6 group by 1)", then="select round((select eps from ep1), 4) eps_m, quantile_cont(n, 0.99) min_pts from nc"))
def w_density_params(spark: SparkSession, d: str) -> DataFrame:
    return density.parameters(traffic_points(spark, d)).withColumn("eps_m", F.round("eps_m", 4))


for _shift, _span in (("ceil", "ceil((end_us - start_us) / 86400000000)::bigint * 86400000000"), ("floor", "((end_us - start_us) // 86400000000) * 86400000000")):
    @query(f"w_halo_counts_shift_{_shift}", with_e(*OWNERS_SQL, lasting.halo_sql("complete", _span), then="select * from h"))
    def w_shift(spark: SparkSession, d: str, shift: str = _shift) -> DataFrame:
        return halo(entities(spark, d), edge="complete", shift=shift)

for _kind in ("traffic", "weather"):
    @query(f"w_halo_counts_{_kind}", with_e(*OWNERS_SQL, lasting.halo_sql("complete"), then=f"select * from h where kind = '{_kind}'"))
    def w_halo_kind(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        return halo(entities(spark, d), edge="complete").where(F.col("kind") == kind)

for _mixed in ("radius", "either"):
    @query(f"w_halo_counts_mixed_{_mixed}", with_e(*OWNERS_SQL, lasting.halo_sql("complete", mixed=_mixed), then="select * from h"))
    def w_halo_mixed(spark: SparkSession, d: str, mixed: str = _mixed) -> DataFrame:
        return halo(entities(spark, d), edge="complete", mixed=mixed)


@query("w_halo_counts_unfused", with_e(lasting.lasting_sql(0.95), lasting.halo_sql("complete", owners="la"), then="select * from h"))
def w_unfused(spark: SparkSession, d: str) -> DataFrame:
    """Counts without the fusion step, for comparison."""
    return halo(entities(spark, d), "none", edge="complete")


_ZIPS = (
    "zc as (select zip, avg(lat) clat, avg(lon) clon from e where kind = 'traffic' group by 1)",
    f"zs as (select zip, arg_min(code, [round({_METRES}), code]) zip_station from zc, st group by zip)",
    "ez as (select e.* replace (case when kind = 'traffic' then zip_station else station end as station) from e join zs using (zip))",
)


@query("w_halo_counts_zip", with_e(*OWNERS_SQL, *_ZIPS, lasting.halo_sql("complete", counted="ez"), then="select * from h"))
def w_halo_zip(spark: SparkSession, d: str) -> DataFrame:
    """Weather halos by the station that each zip code is mapped to, as the nearest to its traffic."""
    e = entities(spark, d)
    zips = w_zip_station(spark, d).select("zip", F.col("station").alias("zip_station"))
    mapped = e.join(zips, "zip").withColumn("station", F.when(F.col("kind") == "traffic", F.col("zip_station")).otherwise(F.col("station"))).drop("zip_station")
    found = written(lasting.extract(e, 0.95))
    return lasting.halo_counts(written(lasting.fused_windows(found)), written(mapped), edge="complete", excluded=found)


@query("w_halo_members", with_e(*OWNERS_SQL, lasting.halo_sql("keep"), then=f"select lk.entity_id long_id, w which, tr.entity_id from lk join (values ('during', 0), ('before', -1), ('after', 1)) v(w, k) on true join tr on tr.start_us > lk.start_us + k * sh and tr.end_us < lk.end_us + k * sh and case when lk.kind = 'weather' then lk.station = tr.station else {_HAV.replace('q.', 'tr.').replace('p.', 'lk.')} <= {lasting.RADIUS}::double end"))
def w_halo_members(spark: SparkSession, d: str) -> DataFrame:
    e = entities(spark, d)
    found = written(lasting.extract(e, 0.95))
    return lasting.halo_members(written(lasting.fused_windows(found)), e, excluded=found)


for _edge in EDGES:
    _hours = BUCKETS["duration"][0]
    _pivot = ", ".join(f"max(case when test = '{t}' then round(1 - p, 6) end) {t.lower()}" for t in ("T3", "T4", "T5", "T6"))

    @query(f"w_before_after_contrast_{_edge}", with_e(*OWNERS_SQL, lasting.halo_sql(_edge), influence.test_sql(_hours), f"cs as (select {_hours} bucket, round(avg(case when type = 'construction' then 1.0 else 0 end), 6) construction from h group by 1)", then=f"select bucket, {_pivot}, construction from t join cs using (bucket) group by bucket, construction"))
    def w_contrast(spark: SparkSession, d: str, edge: str = _edge) -> DataFrame:
        return influence.contrast(halo(entities(spark, d), edge=edge), influence.duration_bucket(F.col("span_us"), influence.SHORT_EDGES_H))

    @query(f"w_tiers_{_edge}", with_e(*OWNERS_SQL, lasting.halo_sql(_edge), influence.test_sql('"type"'), then="select bucket, case when max(case when test in ('T1', 'T3', 'T5') then 1 - p end) >= 0.9 then true else false end positive, case when max(case when test in ('T2', 'T4', 'T6') then 1 - p end) >= 0.9 then true else false end negative from t group by 1"))
    def w_sign(spark: SparkSession, d: str, edge: str = _edge) -> DataFrame:
        return influence.sign(influence.tests(halo(entities(spark, d), edge=edge), [F.col("type").alias("bucket")]))


@query("w_ttest_labels", influence.two_sample_sql("select quality g, n_chars::double v from documents join labels using (doc_id)"))
def w_ttest_labels(spark: SparkSession, d: str) -> DataFrame:
    rows = read(spark, d, "documents").select("doc_id", "n_chars").join(read(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    return influence.two_sample(rows, "n_chars", F.col("quality") == 1, F.col("quality") == 0)


for _impl in ("own", "ml"):
    @query(f"w_vector_kmeans_{_impl}")
    def w_vector_kmeans(spark: SparkSession, d: str, impl: str = _impl) -> DataFrame:
        vectors = read(spark, d, "embeddings").where("embedding is not null and not exists(embedding, x -> x is null or isnan(x))")
        run = cluster.vector_kmeans if impl == "own" else cluster.library_kmeans
        return run(vectors, "vec_id", "embedding", 10).groupBy("cluster").agg(F.count("*").alias("n"))
