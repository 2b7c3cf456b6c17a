"""Operators that users of the methods need around them, each one query with its SQL: scans, joins, aggregates, windows, sets, scalars, subqueries, sinks and streams."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geopat.plans.rangejoin import within_after
from geopat.plans.scratch import place
from geopat.sources.entities import read
from geopat.streaming import feeds
from geopat.workloads import entities, query, with_e

# ---- scans and sinks

_TABLES = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_name, n_regionkey", "customer": "c_custkey, c_nationkey, c_mktsegment", "supplier": "s_suppkey, s_nationkey", "part": "p_partkey, p_type, p_size", "orders": "o_orderkey, o_custkey, o_orderpriority",
    "lineitem": "l_orderkey, l_linenumber, l_quantity", "events": "event_id, user_id, event_type", "documents": "doc_id, lang, source", "embeddings": "vec_id, label", "pages": "page_id, url", "benchmark": "item_id", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role",
}
for _table, _cols in _TABLES.items():
    @query(f"op_scan_{_table}", f"select {_cols} from {_table}")
    def op_scan(spark: SparkSession, d: str, table: str = _table, cols: str = _cols) -> DataFrame:
        return read(spark, d, table).select(*cols.split(", "))

for _format in ("csv", "json", "orc"):
    @query(f"op_{_format}_roundtrip", "select n_nationkey, n_name, n_regionkey from nation")
    def op_roundtrip(spark: SparkSession, d: str, form: str = _format) -> DataFrame:
        df, path = read(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), place(spark)
        df.write.format(form).save(path)
        return spark.read.schema(df.schema).format(form).load(path)


@query("op_partitioned_scan", with_e(then="select entity_id, type, state from e where kind = 'weather' and state = 3"))
def op_partitioned_scan(spark: SparkSession, d: str) -> DataFrame:
    """Entities written by kind and state; the filter prunes folders."""
    path, e = place(spark), entities(spark, d)
    e.repartition("kind", "state").sortWithinPartitions("start_us").write.partitionBy("kind", "state").parquet(path)
    return spark.read.schema(e.schema).parquet(path).where("kind = 'weather' and state = 3").select("entity_id", "type", "state")


# ---- queries in SQL that both engines take as they are

_SQL = {
    "op_filter_conjunct": "select event_id from events where event_type = 'click' and value > 50",
    "op_filter_in": "select event_id from events where event_type in ('view', 'purchase')",
    "op_filter_like": "select p_partkey from part where p_type like 'ECONOMY%'",
    "op_filter_null": "select count(*) n from documents where text is null or lang is null",
    "op_filter_between_time": "select event_id from events where ts >= timestamp '2024-01-05 00:00:00' and ts < timestamp '2024-01-06 00:00:00'",
    "op_str_case": "select n_nationkey, upper(n_name) up, lower(n_name) low, length(n_name) len, substring(n_name, 1, 3) head, lpad(n_name, 20, '*') pad, trim(n_name) bare from nation",
    "op_str_replace": "select n_nationkey, replace(n_name, 'A', 'a') swapped, concat_ws('-', n_name, cast(n_regionkey as varchar(9))) joined, translate(n_name, 'EI', '31') mapped from nation",
    "op_str_distance": "select a.n_nationkey a, b.n_nationkey b, cast(levenshtein(a.n_name, b.n_name) as bigint) dist from nation a join nation b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey",
    "op_date_trunc": "select cast(date_trunc('month', o_orderdate) as date) month_start, count(*) n from orders group by 1",
    "op_date_extract": "select cast(year(o_orderdate) as bigint) y, cast(quarter(o_orderdate) as bigint) q, count(*) n from orders group by 1, 2",
    "op_math": "select event_id, cast(floor(value) as bigint) lower_part, cast(ceil(value) as bigint) upper_part, round(sqrt(abs(value)), 6) root, round(exp(-value / 100), 6) decay, greatest(value, 50.0) g, least(value, 50.0) l, cast(sign(value) as int) s from events",
    "op_null_safe": "select doc_id, coalesce(lang, 'none') lang, nullif(source, 'web') source from documents",
    "op_decimal_sum": "select l_returnflag, cast(sum(cast(l_quantity as decimal(18, 2))) as double) q from lineitem group by 1",
    "op_join_inner": "select o_orderkey, c_mktsegment from orders join customer on o_custkey = c_custkey",
    "op_join_left": "select n_name, count(s_suppkey) suppliers from nation left join supplier on s_nationkey = n_nationkey group by 1",
    "op_join_right": "select n_name, count(s_suppkey) suppliers from supplier right join nation on s_nationkey = n_nationkey group by 1",
    "op_join_full": "select coalesce(d.doc_id, l.doc_id) doc_id, l.quality from documents d full join labels l on d.doc_id = l.doc_id",
    "op_join_semi": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)",
    "op_join_anti": "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 300000)",
    "op_join_null_equal": "select count(*) n from (select distinct lang from documents) a join (select distinct lang from documents) b on a.lang is not distinct from b.lang",
    "op_join_star": "select r_name, c_mktsegment, count(*) n from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2",
    "op_agg_hash": "select event_type, count(*) n, min(value) low, max(value) high from events group by 1",
    "op_agg_distinct": "select event_type, count(distinct user_id) users from events group by 1",
    "op_agg_multi_distinct": "select count(distinct user_id) users, count(distinct event_type) types from events",
    "op_agg_filter": "select count(*) filter (where value > 100) big, count(*) n from events",
    "op_agg_having": "select user_id, count(*) n from events group by 1 having count(*) > 60",
    "op_agg_var": "select event_type, round(var_samp(value), 4) v, round(stddev_pop(value), 4) s from events group by 1",
    "op_agg_corr": "select round(corr(l_quantity, l_extendedprice), 6) r from lineitem",
    "op_agg_bool": "select event_type, bool_and(value >= 0) nonnegative, bool_or(value > 200) any_long from events group by 1",
    "op_agg_grouping_sets": "select event_type, cast(month(ts) as bigint) m, count(*) n from events group by grouping sets ((event_type), (month(ts)), ())",
    "op_agg_cube": "select o_orderpriority, o_orderstatus, count(*) n from orders group by cube (o_orderpriority, o_orderstatus)",
    "op_agg_rollup": "select o_orderpriority, o_orderstatus, count(*) n from orders group by rollup (o_orderpriority, o_orderstatus)",
    "op_win_rank": "select event_id, row_number() over w rn, rank() over w rk, dense_rank() over w dr from events window w as (partition by user_id order by ts, event_id)",
    "op_win_lag_lead": "select event_id, lag(event_id) over w before, lead(event_id) over w after from events window w as (partition by user_id order by ts, event_id)",
    "op_win_ntile": "select event_id, cast(ntile(4) over w as bigint) fourth, round(percent_rank() over w, 6) pr, round(cume_dist() over w, 6) cd from events window w as (partition by user_id order by ts, event_id)",
    "op_win_first_last": "select event_id, first_value(event_type) over w f, last_value(event_type) over w l from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)",
    "op_win_running": "select event_id, count(*) over w n, max(value) over w peak from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and current row)",
    "op_win_moving": "select event_id, max(value) over w peak from events window w as (partition by user_id order by ts, event_id rows between 3 preceding and current row)",
    "op_topk": "select event_id, value from events order by value desc, event_id limit 12",
    "op_topk_per_group": "select user_id, event_id from (select user_id, event_id, row_number() over (partition by user_id order by value desc, event_id) r from events) t where r <= 3",
    "op_limit_offset": "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10 offset 5",
    "op_union_all": "select event_type from events where value > 200 union all select event_type from events where value > 250",
    "op_union": "select n_regionkey k from nation union select r_regionkey k from region",
    "op_intersect": "select n_nationkey k from nation intersect select s_nationkey k from supplier",
    "op_intersect_all": "select s_nationkey k from supplier intersect all select c_nationkey k from customer",
    "op_except": "select c_custkey k from customer except select o_custkey k from orders",
    "op_except_all": "select c_nationkey k from customer except all select s_nationkey k from supplier",
    "op_subq_scalar": "select event_id from events where value > (select avg(value) * 3 from events)",
    "op_subq_in": "select c_custkey from customer where c_nationkey in (select n_nationkey from nation where n_regionkey = 1)",
    "op_subq_not_in": "select c_custkey from customer where c_nationkey not in (select n_nationkey from nation where n_regionkey = 1)",
    "op_subq_correlated": "select s_suppkey from supplier s where s_acctbal > (select avg(t.s_acctbal) from supplier t where t.s_nationkey = s.s_nationkey)",
    "op_cte": "with big as (select o_custkey, count(*) n from orders group by 1) select n, count(*) customers from big group by 1",
    "op_cte_recursive": "with recursive k as (select cast(l_linenumber as bigint) n, count(*) lines from lineitem group by 1), c(n, f, so_far) as (select n, n, lines from k where n = 1 union all select k.n, c.f * k.n, c.so_far + k.lines from c join k on k.n = c.n + 1) select n, f, so_far from c",
}


def in_sql(texts: dict[str, str]) -> None:
    """Register queries whose text both engines take; the tables they name become views."""
    for name, text in texts.items():
        @query(name, text)
        def op_sql(spark: SparkSession, d: str, text: str = text) -> DataFrame:
            for table in _TABLES:
                if re.search(rf"\b{table}\b", text):
                    read(spark, d, table).createOrReplaceTempView(table)
            return spark.sql(text)


in_sql(_SQL)


# ---- joins, aggregates and collections by the DataFrame API

for _hint in ("broadcast", "shuffle_hash", "merge"):
    @query(f"op_join_{_hint}", "select s_suppkey, n_name from supplier join nation on s_nationkey = n_nationkey")
    def op_join_hint(spark: SparkSession, d: str, hint: str = _hint) -> DataFrame:
        """The same answer by three physical joins; nation has 25 rows at any scale."""
        return read(spark, d, "supplier").join(read(spark, d, "nation").hint(hint), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")


@query("op_join_range", "select a.event_id first_id, b.event_id second_id from events a join events b on a.user_id = b.user_id and a.event_id <> b.event_id and epoch_us(b.ts) - epoch_us(a.ts) between 0 and 3600000000")
def op_join_range(spark: SparkSession, d: str) -> DataFrame:
    at = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(ts as timestamp_ntz))")
    a, b = (read(spark, d, "events").select(F.col("event_id").alias(f"{n}_id"), F.col("user_id").alias(f"{n}_user"), at.alias(f"{n}_us")) for n in ("first", "second"))
    return within_after(a, b, [("first_user", "second_user")], ("first_us", "second_us"), 3_600_000_000).where("first_id <> second_id").select("first_id", "second_id")


for _side in ("backward", "forward"):
    _sql = "select t.entity_id, arg_max(w.entity_id, [w.start_us, w.entity_id]) weather_id from e t left join e w on w.station = t.station and w.kind = 'weather' and w.start_us <= t.start_us where t.kind = 'traffic' group by 1"

    @query(f"op_join_asof_{_side}", with_e(then=_sql if _side == "backward" else _sql.replace("arg_max", "arg_min").replace("w.start_us <=", "w.start_us >=")))
    def op_join_asof(spark: SparkSession, d: str, side: str = _side) -> DataFrame:
        """Last weather of a station up to a traffic start, or first from it on: one sort per station, no pairs."""
        wet = F.col("kind") == "weather"
        back = side == "backward"
        order = [F.col("start_us") if back else F.desc("start_us"), F.when(wet, 0).otherwise(1), F.col("entity_id") if back else F.desc("entity_id")]
        w = Window.partitionBy("station").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
        rows = entities(spark, d).select("entity_id", "station", "start_us", "kind").withColumn("weather_id", F.last(F.when(wet, F.col("entity_id")), ignorenulls=True).over(w))
        return rows.where(~wet).select("entity_id", "weather_id")


@query("op_agg_percentile_exact", "select event_type, round(quantile_cont(value, 0.5), 6) med, round(quantile_cont(value, 0.99), 6) p99 from events group by 1")
def op_percentile(spark: SparkSession, d: str) -> DataFrame:
    q = lambda p: F.round(F.percentile("value", F.lit(p)), 6)
    return read(spark, d, "events").groupBy("event_type").agg(q(0.5).alias("med"), q(0.99).alias("p99"))


@query("op_agg_approx_distinct")
def op_approx(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("about"), F.countDistinct("user_id").alias("exact"))


@query("op_agg_minby", "select user_id, arg_min(event_type, [ts::varchar, event_id::varchar]) first_type from events group by 1")
def op_minby(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first_type"))


@query("op_agg_collect_sorted", "select user_id, array_to_string(list_sort(list(distinct event_type)), ',') types from events group by 1")
def op_collect(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types"))


@query("op_agg_pivot", with_e(then="select state, count_if(kind = 'traffic')::bigint traffic, count_if(kind = 'weather')::bigint weather from e group by 1"))
def op_pivot(spark: SparkSession, d: str) -> DataFrame:
    return entities(spark, d).groupBy("state").pivot("kind", ["traffic", "weather"]).count().fillna(0)


@query("op_agg_unpivot", "select doc_id, 'quality' k, quality v from labels union all select doc_id, 'toxic', toxic from labels")
def op_unpivot(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v")


@query("op_json_get", "select event_id, json_extract_string(props, '$.k')::bigint k from events")
def op_json(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("op_array_norm", "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 4) norm, len(embedding)::bigint dims from embeddings where embedding is not null and len(list_filter(embedding, lambda x: x is null or isnan(x))) = 0")
def op_array(spark: SparkSession, d: str) -> DataFrame:
    v = F.col("embedding")
    rows = read(spark, d, "embeddings").where(v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x)))
    total = F.aggregate(v, F.lit(0.0), lambda acc, x: acc + x.cast("double") * x.cast("double"))
    return rows.select("vec_id", F.round(F.sqrt(total), 4).alias("norm"), F.size(v).cast("long").alias("dims"))


@query("op_map_counts", with_e(then="select state, type, count(*) n from e group by 1, 2"))
def op_map(spark: SparkSession, d: str) -> DataFrame:
    """Type counts of a state as a map, and back to rows."""
    n = entities(spark, d).groupBy("state", "type").agg(F.count("*").alias("n"))
    return n.groupBy("state").agg(F.map_from_entries(F.collect_list(F.struct("type", "n"))).alias("m")).select("state", F.explode("m").alias("type", "n"))


@query("op_win_sessionize", "with g as (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) > 21600000000 then 1 else 0 end cut from events), s as (select *, sum(cut) over (partition by user_id order by ts, event_id rows unbounded preceding) sess from g) select user_id, sess::bigint sess, count(*) n from s group by 1, 2")
def op_sessionize(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.expr("timestampdiff(MICROSECOND, prev, ts)") > 21_600_000_000
    rows = read(spark, d, "events").withColumn("prev", F.lag("ts").over(w)).withColumn("cut", F.when(gap, 1).otherwise(0))
    return rows.withColumn("sess", F.sum("cut").over(w.rowsBetween(Window.unboundedPreceding, 0))).groupBy("user_id", "sess").agg(F.count("*").alias("n"))


# ---- streams, run to the end of the files

for _name, _step in (("tumbling", 3600), ("sliding", 1800)):
    _starts = "unnest([(epoch_us(ts) // 1800000000) * 1800000000, (epoch_us(ts) // 1800000000 - 1) * 1800000000])" if _name == "sliding" else "(epoch_us(ts) // 3600000000) * 3600000000"

    @query(f"st_{_name}", f"select start_us, event_type, count(*) n from (select {_starts} start_us, event_type from events) group by 1, 2")
    def st_windows(spark: SparkSession, d: str, slide: str | None = "30 minutes" if _name == "sliding" else None) -> DataFrame:
        counted = feeds.tumbling(feeds.feed(spark, d, "events"), "1 hour", slide).select(F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(start as timestamp_ntz))").alias("start_us"), "event_type", "n")
        return feeds.upsert(counted, ["start_us", "event_type"])


@query("st_complete_mode", "select event_type, count(*) n from events group by 1")
def st_complete(spark: SparkSession, d: str) -> DataFrame:
    return feeds.upsert(feeds.feed(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n")), ["event_type"], "complete")


@query("st_dedupe", "select distinct user_id, event_type from events")
def st_dedupe(spark: SparkSession, d: str) -> DataFrame:
    return feeds.drain(feeds.feed(spark, d, "events").select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


@query("st_static_join", "select event_id, c_mktsegment from events join customer on user_id = c_custkey")
def st_static_join(spark: SparkSession, d: str) -> DataFrame:
    stream = feeds.feed(spark, d, "events").select("event_id", "user_id")
    return feeds.drain(stream.join(read(spark, d, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("st_link_join", "select p.event_id parent_id, c.event_id child_id from events p join events c on p.user_id = c.user_id and epoch_us(c.ts) > epoch_us(p.ts) and epoch_us(c.ts) <= epoch_us(p.ts) + 3600000000")
def st_link_join(spark: SparkSession, d: str) -> DataFrame:
    side = lambda: feeds.feed(spark, d, "events").select(F.col("event_id").alias("entity_id"), F.col("ts").alias("at"), "user_id").withWatermark("at", "1 day")
    return feeds.drain(feeds.online_links(side(), side(), ["user_id"], 60))
