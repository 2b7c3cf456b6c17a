"""Queries over the given tables, and the DuckDB SQL that each is held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.operators import cluster, describe, forest, influence, lasting, mine, relate
from geopat.plans.scratch import written
from geopat.sources.entities import ENTITY_SQL, read
from geopat.sources.entities import entities as adapted

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Time thresholds in minutes: (others, snow).
PAPER, DENSE, DENSER = (10, 40), (60, 240), (120, 480)


def entities(spark: SparkSession, d: str) -> DataFrame:
    """The entity table, written once a query: joins read it several times, and plan better from a table than from the adapter."""
    return written(adapted(spark, d))


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def with_e(*items: str, then: str) -> str:
    return f"with recursive {', '.join([ENTITY_SQL, *items])} {then}"


def nodes_of(df: DataFrame, minutes: tuple[int, int], rule: str = "arith") -> DataFrame:
    return forest.places(forest.build(forest.pick_parent(relate.links(df, *minutes), rule)), df)


@query("w_entities", with_e(then="select entity_id, type, kind, start_us, end_us, street, side, zip, city, state, road, round(lat, 6) lat, round(lon, 6) lon, station from e"))
def w_entities(spark: SparkSession, d: str) -> DataFrame:
    e = entities(spark, d).drop("provider_type", "code")
    return e.withColumns({"lat": F.round("lat", 6), "lon": F.round("lon", 6)})


for _kind in ("traffic", "weather"):
    @query(f"w_type_table_{_kind}", with_e(f"n as (select type, count(*) n from e where kind = '{_kind}' group by 1)", then="select type, n, round(100.0::double * n / sum(n) over (), 6) percent from n union all select 'total', sum(n)::bigint, 100.0 from n"))
    def w_type_table(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        return describe.type_table(entities(spark, d).where(F.col("kind") == kind))

for _unit, _part in (("month", "month(make_timestamp(start_us))"), ("weekday", "dayofweek(make_timestamp(start_us)) + 1"), ("hour", "hour(make_timestamp(start_us))")):
    @query(f"w_{_unit}", with_e(f"n as (select kind, ({_part})::bigint \"{_unit}\", count(*) n from e group by 1, 2)", then=f'select kind, "{_unit}", n, round(100.0::double * n / sum(n) over (partition by kind), 6) percent from n'))
    def w_calendar(spark: SparkSession, d: str, unit: str = _unit) -> DataFrame:
        return describe.calendar(entities(spark, d), unit)


def raw_reports(spark: SparkSession, d: str) -> DataFrame:
    e = entities(spark, d).select("entity_id", "type", "start_us", "lat", "lon")
    again = e.where("entity_id % 50 = 0")
    return e.union(again).union(again.withColumn("entity_id", F.col("entity_id") + 1_000_000_000))


_RAW = "w as (select entity_id, type, start_us, lat, lon from e union all select entity_id, type, start_us, lat, lon from e where entity_id % 50 = 0 union all select entity_id + 1000000000, type, start_us, lat, lon from e where entity_id % 50 = 0)"


@query("w_dedupe_id", with_e(_RAW, then="select distinct entity_id, type, start_us from w"))
def w_dedupe_id(spark: SparkSession, d: str) -> DataFrame:
    return describe.drop_same_id(raw_reports(spark, d), "entity_id", ["start_us"]).select("entity_id", "type", "start_us")


@query("w_dedupe_content", with_e(_RAW, then="select min(entity_id) entity_id, type, start_us from w group by type, start_us, lat, lon"))
def w_dedupe_content(spark: SparkSession, d: str) -> DataFrame:
    return describe.drop_same_content(raw_reports(spark, d).distinct(), ["type", "start_us", "lat", "lon"], "entity_id").select("entity_id", "type", "start_us")


@query("w_type_mismatch", with_e(then="select provider_type, count(*) n, count_if(type <> provider_type)::bigint changed, round(100.0::double * count_if(type <> provider_type) / count(*), 6) percent from e group by 1"))
def w_type_mismatch(spark: SparkSession, d: str) -> DataFrame:
    return describe.type_mismatch(entities(spark, d))


@query("w_station_of_city", with_e(then="select city, station from nr"))
def w_station_of_city(spark: SparkSession, d: str) -> DataFrame:
    return entities(spark, d).select("city", "station").distinct()


_OBS = "o as (select l_suppkey::bigint station, 1.3::double * l_quantity - 28 temperature, 700.0::double * l_discount wind, 150.0::double * l_tax precipitation, case split_part(p_type, ' ', 1) when 'STANDARD' then 'clear' when 'ECONOMY' then 'rain' when 'MEDIUM' then 'snow' when 'PROMO' then 'fog' when 'LARGE' then 'hail' when 'SMALL' then 'thunderstorm' end condition from lineitem join part on p_partkey = l_partkey)"


def observations(spark: SparkSession, d: str) -> DataFrame:
    """Weather records: station, temperature, wind, precipitation, condition."""
    first = F.split("p_type", " ")[0]
    names = {"STANDARD": "clear", "ECONOMY": "rain", "MEDIUM": "snow", "PROMO": "fog", "LARGE": "hail", "SMALL": "thunderstorm"}
    condition = F.create_map(*[F.lit(x) for kv in names.items() for x in kv])[first]
    rows = read(spark, d, "lineitem").join(read(spark, d, "part"), F.col("p_partkey") == F.col("l_partkey"))
    return rows.select(F.col("l_suppkey").cast("long").alias("station"), (1.3 * F.col("l_quantity") - 28).alias("temperature"), (700.0 * F.col("l_discount")).alias("wind"), (150.0 * F.col("l_tax")).alias("precipitation"), condition.alias("condition"))


for _name, _col, _k, _where in (("temp", "temperature", 5, "true"), ("wind", "wind", 3, "true"), ("rain", "precipitation", 3, "condition = 'rain'"), ("snow", "precipitation", 3, "condition = 'snow'")):
    @query(f"w_weather_thresholds_{_name}", f"with {_OBS}, v as (select {_col} x from o where {_where}), {cluster.lloyd_sql('v', 'x', _k)} select (row_number() over (order by c) - 1)::int i, round(c, 6) centre from c12")
    def w_thresholds(spark: SparkSession, d: str, col: str = _col, k: int = _k, where: str = _where) -> DataFrame:
        centres = cluster.lloyd_1d(observations(spark, d).where(where).select(col), col, k)
        return spark.createDataFrame([(i, float(c)) for i, c in enumerate(centres)], "i int, centre double").select("i", F.round("centre", 6).alias("centre"))


for _name, _t in (("paper", PAPER), ("dense", DENSE)):
    @query(f"w_links_{_name}", with_e(relate.link_sql(*_t), then="select * from l"))
    def w_links(spark: SparkSession, d: str, t: tuple = _t) -> DataFrame:
        return relate.links(entities(spark, d), *t)

    @query(f"w_link_coverage_{_name}", with_e(relate.weak_sql(*_t), "x as (select a id from wp union select b from wp)", then="select kind, count(*) n, count(id) n_linked, round(100.0::double * count(id) / count(*), 6) percent from e left join x on id = entity_id group by 1"))
    def w_coverage(spark: SparkSession, d: str, t: tuple = _t) -> DataFrame:
        e = entities(spark, d)
        return relate.coverage(e.select("entity_id", "kind"), relate.weak_pairs(e, *t))


@query("w_pick_parent", with_e(relate.link_sql(*DENSE), forest.FOREST_SQL, then="select node, parent from pp"))
def w_pick_parent(spark: SparkSession, d: str) -> DataFrame:
    return forest.pick_parent(relate.links(entities(spark, d), *DENSE), "arith")


@query("w_forest_nodes", with_e(relate.link_sql(*DENSE), forest.FOREST_SQL, then="select * from g"))
def w_forest_nodes(spark: SparkSession, d: str) -> DataFrame:
    return nodes_of(entities(spark, d), DENSE).drop("start_us")


@query("m_forest", with_e(relate.link_sql(*DENSE), forest.FOREST_SQL, then="select count(*) trees, sum(n)::bigint nodes, max(n) largest, max(d) deepest from (select tree, count(*) n, max(depth) d from f group by 1)"))
def m_forest(spark: SparkSession, d: str) -> DataFrame:
    return forest.stats(forest.build(forest.pick_parent(relate.links(entities(spark, d), *DENSE), "arith")))


_MINING = (("adaptive", DENSE, None), ("fixed02", DENSER, 0.02))
for _name, _t, _s in _MINING:
    @query(f"w_shapes2_city_{_name}", with_e(relate.link_sql(*_t), forest.FOREST_SQL, mine.shape_sql(_s is None), then="select state, city, shape, 2::bigint size, root_label, support_count, trees, support from s2"))
    def w_shapes2(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s, max_nodes=2).where("size = 2")

    @query(f"w_shapes_city_{_name}")
    def w_shapes(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s)

    @query(f"w_shapes_state_baseline_{_name}")
    def w_by_state(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.frequent(nodes_of(entities(spark, d), t), ["state"], s)

    @query(f"w_shape_catalogue2_{_name}", with_e(relate.link_sql(*_t), forest.FOREST_SQL, mine.shape_sql(_s is None), "q as (select distinct state, shape from s2)", then="select count(*) state_shapes, count(distinct shape) unique_shapes, case when count(*) > 0 then 2::bigint end fewest, case when count(*) > 0 then 2::bigint end most from q"))
    def w_catalogue(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return mine.catalogue(mine.state_core(w_shapes2(spark, d, t, s)))

    @query(f"w_initiators2_{_name}", with_e(relate.link_sql(*_t), forest.FOREST_SQL, mine.shape_sql(_s is None), then="select root_label, count(distinct shape) shapes from s2 group by 1"))
    def w_initiators(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        return w_shapes2(spark, d, t, s).groupBy("root_label").agg(F.countDistinct("shape").alias("shapes"))

    @query(f"w_shape_catalogue_all_{_name}")
    def w_catalogue_all(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_shapes) -> DataFrame:
        return mine.catalogue(mine.state_core(get(spark, d, t, s)))

    @query(f"w_initiators_all_{_name}")
    def w_initiators_all(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, get=w_shapes) -> DataFrame:
        return get(spark, d, t, s).groupBy("root_label").agg(F.countDistinct("shape").alias("shapes"))

    @query(f"w_state_groups_{_name}")
    def w_state_groups(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        e = entities(spark, d)
        return cluster.state_groups(cluster.state_vectors(mine.state_core(mine.frequent(nodes_of(e, t), ["state", "city"], s)), e.select("state").distinct()))

    for _variant, _options in (("induced", {"kind": "induced"}), ("ordered", {"ordered": True}), ("any_siblings", {"siblings": "any"})):
        @query(f"w_shapes_city_{_variant}_{_name}")
        def w_variant(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, options: dict = _options) -> DataFrame:
            return mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s, **options)


@query("w_duration_threshold", with_e(then="select quantile_cont(end_us - start_us, 0.99) threshold_us from e"))
def w_duration_threshold(spark: SparkSession, d: str) -> DataFrame:
    return lasting.threshold(entities(spark, d))


for _name, _p in (("p99", 0.99), ("p95", 0.95)):
    @query(f"w_lasting_{_name}", with_e(lasting.lasting_sql(_p), then="select entity_id, type, start_us, end_us from la"))
    def w_lasting(spark: SparkSession, d: str, p: float = _p) -> DataFrame:
        return lasting.extract(entities(spark, d), p).select("entity_id", "type", "start_us", "end_us")

    @query(f"w_lasting_conflicts_{_name}", with_e(lasting.lasting_sql(_p), then="select a, b from cf"))
    def w_conflicts(spark: SparkSession, d: str, p: float = _p) -> DataFrame:
        return lasting.conflicts(lasting.extract(entities(spark, d), p))

    @query(f"w_fused_components_{_name}", with_e(lasting.lasting_sql(_p), "rc as (select entity_id node, entity_id r from la union select case when rc.node = cf.a then cf.b else cf.a end, rc.r from rc join cf on rc.node in (cf.a, cf.b))", "cm as (select node, min(r) id from rc group by 1)", then="select id, min(start_us) start_us, max(end_us) end_us, array_to_string(list_sort(list(distinct type)), '_') \"type\", count(*) members from la join cm on node = entity_id group by id"))
    def w_fused(spark: SparkSession, d: str, p: float = _p) -> DataFrame:
        found = lasting.extract(entities(spark, d), p)
        return lasting.fuse_components(found, lasting.conflicts(found)).select("id", "start_us", "end_us", "type", "members")


#: Owners of halo windows: lasting entities (p95) with overlaps resolved by components.
OWNERS_SQL = (lasting.lasting_sql(0.95), lasting.FUSED_SQL)
_HOURS = "case " + " ".join(f"when span_us >= {h * 3_600_000_000} then {h}" for h in influence.SHORT_EDGES_H[:0:-1]) + " else 0 end"
BUCKETS = {"state": ("state", lambda: F.col("state")), "type": ('"type"', lambda: F.col("type")), "duration": (_HOURS, lambda: influence.duration_bucket(F.col("span_us"), influence.SHORT_EDGES_H))}
EDGES = ("keep", "complete", "one_sided")


def halo(e: DataFrame, rule: str = "components", **options: object) -> DataFrame:
    """Halo counts of lasting entities after fusion; what was fused is not counted."""
    found = written(lasting.extract(e, 0.95))
    owners = found if rule == "none" else written(lasting.fused_windows(found, rule=rule))
    return written(lasting.halo_counts(owners, e, excluded=found, **options))


for _edge in EDGES:
    @query(f"w_halo_counts_{_edge}", with_e(*OWNERS_SQL, lasting.halo_sql(_edge), then="select * from h"))
    def w_halo(spark: SparkSession, d: str, edge: str = _edge) -> DataFrame:
        return halo(entities(spark, d), edge=edge)

    for _by, (_sql, _column) in BUCKETS.items():
        for _flavour, _mark in (("pooled", ""), ("welch", "welch_")):
            @query(f"w_influence_{_mark}{_by}_{_edge}", with_e(*OWNERS_SQL, lasting.halo_sql(_edge), influence.test_sql(_sql, _flavour), then=f"select bucket, test, n, round(t, 6) + 0.0 t, round(df, 6) df, round(p, 6) p, {influence.TIER_SQL} tier from t"))
            def w_influence(spark: SparkSession, d: str, column=_column, edge: str = _edge, flavour: str = _flavour) -> DataFrame:
                return influence.tests(w_halo(spark, d, edge), [column().alias("bucket")], flavour)

        @query(f"w_tally_{_by}_{_edge}", with_e(*OWNERS_SQL, lasting.halo_sql(_edge), influence.test_sql(_sql), f"b as (select bucket, min(p) p from t where test in ('T1', 'T2') and p is not null group by 1)", then=f"select {influence.TIER_SQL} tier, count(*) buckets from b group by 1"))
        def w_tally(spark: SparkSession, d: str, column=_column, edge: str = _edge) -> DataFrame:
            return influence.tally(influence.tests(w_halo(spark, d, edge), [column().alias("bucket")]))

    @query(f"w_influence_fixpoint_{_edge}")
    def w_fixpoint(spark: SparkSession, d: str, edge: str = _edge) -> DataFrame:
        """State buckets of owners fused until no two conflict; no SQL."""
        return influence.tests(halo(entities(spark, d), "fixpoint", edge=edge), [F.col("state").alias("bucket")])


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Links, forest, and shapes by city at the densest thresholds."""
    return mine.frequent(nodes_of(entities(spark, d), DENSER), ["state", "city"], 0.02, max_nodes=3)
