"""Studies that join the steps: state groups and their description length, the radius chain, shapes lost to coarse cells, initiators, measures of cost."""

from __future__ import annotations

from collections.abc import Iterator
from html.parser import HTMLParser
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.experiments import _HAV, _TP, traffic_points
from geopat.operators import cluster, density, describe, forest, influence, lasting, mine, relate
from geopat.plans.scratch import written
from geopat.plans.ship import ship
from geopat.sources.entities import FIRST_WEATHER, TAXONOMY, read, unified_type
from geopat.workloads import DENSE, DENSER, PAPER, entities, nodes_of, query, with_e

_MINING = (("adaptive", DENSE, None), ("fixed02", DENSER, 0.02))

# ---- states by their shapes, with SQL over two-node shapes

for _name, _t, _s in _MINING:
    _base = (relate.link_sql(*_t), forest.FOREST_SQL, mine.shape_sql(_s is None), cluster.groups_sql("s2"))

    def two_nodes(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        e = entities(spark, d)
        found = mine.frequent(nodes_of(e, t), ["state", "city"], s, max_nodes=2)
        return cluster.state_vectors(mine.state_core(found), e.select("state").distinct())

    @query(f"w_state_dl2_{_name}", with_e(*_base, then="select k::int k, round(length, 6) length, degenerate, best from dl"))
    def w_state_dl(spark: SparkSession, d: str, get=two_nodes) -> DataFrame:
        return cluster.state_groups(get(spark, d)).select("k", "length", "degenerate", "best").distinct()

    @query(f"w_state_kmeans2_{_name}", with_e(*_base, then='select k::int k, state, "cluster"::int "cluster" from kl'))
    def w_state_kmeans(spark: SparkSession, d: str, get=two_nodes) -> DataFrame:
        return cluster.state_groups(get(spark, d)).select("k", "state", "cluster")

    @query(f"w_state_distinctive2_{_name}", with_e(*_base, then='select b."cluster"::int "cluster", b.shape, b.states from (select shape, min("cluster") "cluster", count(distinct "cluster") clusters, count(*) states from v join kl using (state) join dl using (k) where best and x = 1 group by 1) b where clusters = 1'))
    def w_distinctive(spark: SparkSession, d: str, get=two_nodes) -> DataFrame:
        return cluster.distinctive(written(get(spark, d)))

    @query(f"w_state_volume2_{_name}", with_e(*_base, "iv as (select state, count(*) incidents from e where kind = 'traffic' group by 1)", then='select "cluster"::int "cluster", count(*) states, sum(coalesce(incidents, 0))::bigint incidents, round(avg(coalesce(incidents, 0)), 6) per_state from kl join dl using (k) left join iv using (state) where best group by 1'))
    def w_volume(spark: SparkSession, d: str, get=two_nodes) -> DataFrame:
        """Incident volume of the best groups."""
        e = entities(spark, d)
        n = e.where("kind = 'traffic'").groupBy("state").agg(F.count("*").alias("incidents"))
        best = cluster.state_groups(get(spark, d)).where("best").join(n, "state", "left").fillna(0, ["incidents"])
        return best.groupBy("cluster").agg(F.count("*").alias("states"), F.sum("incidents").alias("incidents"), F.round(F.avg("incidents"), 6).alias("per_state"))

    # ---- what coarse cells lose: five regions, each of the cities of five states

    _region = (relate.link_sql(*_t), forest.FOREST_SQL.replace("spot[1] state", "spot[1] % 5 state"), mine.shape_sql(_s is None), mine.three_sql(_s is None), mine.three_sql(_s is None, "state", "t3"))

    @query(f"w_shapes_lost_region_{_name}", with_e(*_region, then="select distinct state region, shape from s3 where (state, shape) not in (select (state, shape) from t3)"))
    def w_lost_region(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        n = written(nodes_of(entities(spark, d), t).withColumn("state", F.col("state") % 5))
        core = mine.state_core(mine.frequent(n, ["state", "city"], s, max_nodes=3))
        lost = core.join(mine.frequent(n, ["state"], s, max_nodes=3).select("state", "shape"), ["state", "shape"], "left_anti")
        return lost.select(F.col("state").alias("region"), "shape")

    # ---- who starts shapes

    _wet = ", ".join(f"'{name}'" for past, name in TAXONOMY if past > FIRST_WEATHER)
    _three = (*_base[:3], mine.three_sql(_s is None))

    @query(f"w_initiators_split3_{_name}", with_e(*_three, f"u as (select distinct shape, root_label, size from s3)", then=f"select case when root_label in ({_wet}) then 'weather' else 'traffic' end kind, root_label, size, count(*) shapes from u group by all"))
    def w_split(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s, most: int = 3) -> DataFrame:
        """Unique shapes by what starts them and by their size."""
        unique = mine.frequent(nodes_of(entities(spark, d), t), ["state", "city"], s, max_nodes=most).select("shape", "root_label", "size").distinct()
        wet = F.col("root_label").isin([name for past, name in TAXONOMY if past > FIRST_WEATHER])
        return unique.groupBy(F.when(wet, "weather").otherwise("traffic").alias("kind"), "root_label", "size").agg(F.count("*").alias("shapes"))

    @query(f"w_initiators_split_all_{_name}")
    def w_split_all(spark: SparkSession, d: str, get=w_split) -> DataFrame:
        return get(spark, d, most=7)

    @query(f"w_shapes_enumerated_{_name}")
    def w_enumerated(spark: SparkSession, d: str, t: tuple = _t, s: float | None = _s) -> DataFrame:
        """Shapes of up to four nodes by listing every node set of every tree, to hold the miner against."""
        return enumerated(nodes_of(entities(spark, d), t), ["state", "city"], s)


def enumerated(nodes: DataFrame, group: list[str], min_support: float | None, most: int = 4) -> DataFrame:
    """(group, shape, size, support_count) by exhaustion: every set of a tree's nodes that has one node above all others is a shape."""
    ship(nodes.sparkSession)
    packed = mine.pack(nodes, group)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in packed.select(*group).schema) + ", shape string, size long"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for record in batch.itertuples(index=False):
                up = {x["node"]: None if pd.isna(x["parent"]) else x["parent"] for x in record.nodes}
                label = {x["node"]: x["label"] for x in record.nodes}
                above = {}
                for node in up:
                    line, at = [], up[node]
                    while at is not None:
                        line.append(at)
                        at = up.get(at)
                    above[node] = line
                found = set()
                for size in range(2, most + 1):
                    for chosen in combinations(sorted(up), size):
                        near = {n: next((a for a in above[n] if a in chosen), None) for n in chosen}
                        if sum(a is None for a in near.values()) == 1:
                            found.add((_written(near, label), size))
                rows += [(*[getattr(record, g) for g in group], shape, size) for shape, size in found]
            yield pd.DataFrame(rows, columns=[*group, "shape", "size"])

    share = mine.adaptive_support(F.col("trees")) if min_support is None else F.lit(min_support)
    least = packed.groupBy(*group).agg(F.count("*").alias("trees")).withColumn("least", F.ceil(share * F.col("trees") - 1e-9))
    counted = packed.select(*group, "nodes").mapInPandas(run, schema).groupBy(*group, "shape", "size").agg(F.count("*").alias("support_count"))
    return counted.join(least, group).where("support_count >= least").select(*group, "shape", "size", "support_count")


def _written(near: dict, label: dict) -> str:
    """Text of a chosen node set, siblings alphabetical."""
    below: dict = {}
    for node, top in near.items():
        below.setdefault(top, []).append(node)

    def text(node: int) -> str:
        parts = sorted(text(x) for x in below.get(node, []))
        return label[node] + (f"({','.join(parts)})" if parts else "")

    return text(below[None][0])


# ---- the radius chain: samples -> eps, minPts -> clusters -> R


def sampled(points: DataFrame, n: int) -> DataFrame:
    """The n points that come first by an arithmetic hash of the id."""
    return points.orderBy((F.col("id") * 7919 + 104729) % 1_000_003, "id").limit(n)


_S2, _S1 = 2000, 6000
_PLACES = "pl{0} as materialized (select lat, lon, min(id) place, count(*) w from ({1}) group by 1, 2)"
_DRAWN = "select id, lat, lon from tp order by (id * 7919 + 104729) % 1000003, id limit {}"
_NEAREST = f"nn as (select p.place, p.w, case when p.w > 1 then 0 else (select min({_HAV}) from pl2 q where q.place <> p.place and abs(q.lat - p.lat) < 2) end dist from pl2 p)"


def _cluster_sql(places: str, eps: str, least: str, band: str) -> str:
    """WITH-list items up to `cl` (place, cluster, core) for DuckDB."""
    return f"""
nb as materialized (select p.place a, q.place b, q.w from {places} p join {places} q on abs(p.lat - q.lat) < {band} and {_HAV} <= {eps}),
co as materialized (select a place, sum(w) - 1 >= {least} core from nb group by 1),
ce as materialized (select a, b from nb where a in (select place from co where core) and b in (select place from co where core)),
lb as (select 0 r, place node, place l from co where core union all select r + 1, a, min(l) from lb join ce on ce.b = lb.node where r < 40 group by r, a),
hd as materialized (select node, min(l) l from lb where r = 40 group by 1),
cl as materialized (select co.place, coalesce(hd.l, (select min(h.l) from nb join hd h on h.node = nb.b where nb.a = co.place), -1) "cluster", core from co left join hd on hd.node = co.place)"""


def _radius_sql(places: str) -> str:
    return f"""
cp as (select t.id, t.lat, t.lon, cl."cluster" from ({{0}}) t join {places} using (lat, lon) join cl using (place) where cl."cluster" >= 0),
cc as (select "cluster", avg(lat) slat, avg(lon) slon from cp group by 1),
cr as (select max({_HAV.replace('q.lat', 'slat').replace('q.lon', 'slon').replace('p.', 'cp.')}) r from cp join cc using ("cluster") group by cp."cluster")"""


_ALL = "select id, lat, lon from tp"


@query("w_dbscan", with_e(_TP, _PLACES.format(1, _ALL), _cluster_sql("pl1", "150.5::double", "25", "0.002"), then='select tp.id, cl."cluster", cl.core from tp join pl1 using (lat, lon) join cl using (place)'))
def w_dbscan(spark: SparkSession, d: str) -> DataFrame:
    return density.dbscan(traffic_points(spark, d), 150.5, 25).select("id", "cluster", "core")


@query("w_halo_radius", with_e(_TP, _PLACES.format(1, _ALL), _cluster_sql("pl1", "150.5::double", "25", "0.002"), _radius_sql("pl1").format(_ALL), then="select count(*) clusters, round(avg(r), 3) radius_m from cr"))
def w_halo_radius(spark: SparkSession, d: str) -> DataFrame:
    return density.radius(density.dbscan(traffic_points(spark, d), 150.5, 25))


def radius_chain(points: DataFrame) -> tuple[float | None, float | None, DataFrame]:
    """(eps, minPts, one row of clusters and radius): parameters from one sample, clusters from another, as the study does."""
    row = density.parameters(sampled(points, _S2)).first()
    if row.eps_m is None:
        return None, None, points.sparkSession.createDataFrame([(0, None)], "clusters long, radius_m double")
    return row.eps_m, row.min_pts, density.radius(density.dbscan(written(sampled(points, _S1)), row.eps_m + 1e-6, int(-(-row.min_pts // 1))))


@query("w_radius_chain", with_e(
    _TP, _PLACES.format(2, _DRAWN.format(_S2)), _NEAREST, "n2 as (select dist from nn, range(0, w)), ep as materialized (select quantile_cont(dist, 0.99) eps from n2)",
    f"c2 as (select p.place, p.w, sum(q.w) - 1 n from pl2 p join pl2 q on abs(p.lat - q.lat) < 1 and {_HAV} <= (select eps from ep) + 1e-6 group by 1, 2), mp as materialized (select quantile_cont(n, 0.99) m from c2, range(0, w))",
    _PLACES.format(1, _DRAWN.format(_S1)), _cluster_sql("pl1", "(select eps + 1e-6 from ep)", "(select ceil(m) from mp)", "1"), _radius_sql("pl1").format(_DRAWN.format(_S1)),
    then="select round((select eps from ep), 4) eps_m, (select m from mp)::double min_pts, count(*) clusters, round(avg(r), 3) radius_m from cr"))
def w_radius_chain(spark: SparkSession, d: str) -> DataFrame:
    eps, least, found = radius_chain(written(traffic_points(spark, d)))
    return found.select(F.round(F.lit(eps).cast("double"), 4).alias("eps_m"), F.lit(least).cast("double").alias("min_pts"), "clusters", "radius_m")


@query("w_influence_chain")
def w_influence_chain(spark: SparkSession, d: str) -> DataFrame:
    """The whole second half in one: radius from the samples, fusion until no two conflict within it, halos of that radius, tests by state; no SQL."""
    e = entities(spark, d)
    radius = radius_chain(written(e.where("kind = 'traffic'").select(F.col("entity_id").alias("id"), "lat", "lon")))[2].first().radius_m or lasting.RADIUS
    found = written(lasting.extract(e, 0.95))
    owners = written(lasting.fused_windows(found, radius, "fixpoint"))
    return influence.tests(lasting.halo_counts(owners, e, radius, edge="complete", excluded=found), [F.col("state").alias("bucket")])


# ---- preparation, parents, measures


@query("w_dedupe_documents", "select min(doc_id) doc_id, count(*) copies from documents where text is not null group by text")
def w_dedupe_documents(spark: SparkSession, d: str) -> DataFrame:
    docs = read(spark, d, "documents").where("text is not null")
    return docs.groupBy(F.sha2("text", 256).alias("content")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("content")


@query("w_unify_types", with_e(then="select entity_id, code, type, kind from e"))
def w_unify_types(spark: SparkSession, d: str) -> DataFrame:
    """Types by a taxonomy table (code ranges), as an alternative to the built-in ladder."""
    lows = [0, *[past for past, _ in TAXONOMY[:-1]]]
    ranges = spark.createDataFrame([(code, name) for (past, name), low in zip(TAXONOMY, lows, strict=True) for code in range(low, past)], "code int, name string")
    rows = entities(spark, d).select("entity_id", "code", "kind")
    return rows.join(F.broadcast(ranges), "code", "left").select("entity_id", "code", F.coalesce("name", unified_type(F.col("code"))).alias("type"), "kind")


@query("w_month_lineitem", "with n as (select year(l_shipdate)::bigint y, month(l_shipdate)::bigint m, count(*) n from lineitem group by 1, 2) select y, m, n, round(100.0::double * n / sum(n) over (partition by y), 6) percent from n")
def w_month_lineitem(spark: SparkSession, d: str) -> DataFrame:
    """Monthly shares over several years."""
    from pyspark.sql import Window

    n = read(spark, d, "lineitem").groupBy(F.year("l_shipdate").cast("long").alias("y"), F.month("l_shipdate").cast("long").alias("m")).agg(F.count("*").alias("n"))
    return n.withColumn("percent", F.round(100.0 * F.col("n") / F.sum("n").over(Window.partitionBy("y")), 6))


@query("w_parents_all", with_e(relate.link_sql(*DENSE), then="select parents, count(*) children from (select child_id, count(*) parents from l group by 1) group by 1"))
def w_parents_all(spark: SparkSession, d: str) -> DataFrame:
    """How many parents children have before one is chosen."""
    return relate.links(entities(spark, d), *DENSE).groupBy("child_id").agg(F.count("*").alias("parents")).groupBy("parents").agg(F.count("*").alias("children"))


@query("w_pick_parent_nearest", with_e(relate.link_sql(*DENSE), then="select child_id node, arg_min(parent_id, [gap_us, parent_id]) parent from l group by 1"))
def w_pick_nearest(spark: SparkSession, d: str) -> DataFrame:
    return forest.pick_parent(relate.links(entities(spark, d), *DENSE), "nearest_time")


@query("w_forest_hash")
def w_forest_hash(spark: SparkSession, d: str) -> DataFrame:
    """Forest statistics under the default choice of parents, a seeded hash, for three seeds."""
    found = written(relate.links(entities(spark, d), *DENSE))
    parts = [forest.stats(forest.build(forest.pick_parent(found, "hash", seed))).withColumn("seed", F.lit(seed)) for seed in (0, 1, 2)]
    return parts[0].union(parts[1]).union(parts[2])


@query("w_duration_threshold_approx", with_e("q as (select quantile_cont(end_us - start_us, 0.98) lo, max(end_us - start_us) hi from e)", then="select true inside from q"))
def w_threshold_approx(spark: SparkSession, d: str) -> DataFrame:
    """Whether the approximate threshold lies between the exact 98th percentile and the longest duration."""
    e = entities(spark, d)
    about = lasting.threshold(e, 0.99, exact=False).first()[0]
    lo = lasting.quantile(e, lasting.span(), 0.98)
    return e.agg((F.lit(about).between(lo, F.max(lasting.span()))).alias("inside"))


@query("w_lasting_minutes", with_e("cut as (select floor(quantile_cont(end_us - start_us, 0.95) / 1800000000) * 1800000000 c from e)", then="select count(*) n, min(end_us - start_us) shortest from e, cut where end_us - start_us >= c"))
def w_lasting_minutes(spark: SparkSession, d: str) -> DataFrame:
    """Threshold rounded down to half hours, ties in."""
    found = lasting.extract(entities(spark, d), 0.95, inclusive=True, round_to_minutes=30)
    return found.agg(F.count("*").alias("n"), F.min(lasting.span()).alias("shortest"))


@query("m_reduction", with_e(relate.link_sql(*PAPER), "n as (select count(*) n from e), c as (select count(*) candidates from e p join e c on p.kind = 'traffic' and c.kind = 'traffic' and p.entity_id <> c.entity_id and c.start_us - p.start_us between 0 and 600000000 and p.state = c.state and p.city = c.city and p.zip = c.zip and p.street = c.street and p.side = c.side)", then="select n * (n - 1) all_pairs, candidates, (select count(*) from l where via = 'road') kept from n, c"))
def m_reduction(spark: SparkSession, d: str) -> DataFrame:
    """Ordered pairs in all, traffic pairs that the bucketed join compares by distance, and links kept."""
    e = entities(spark, d)
    n = e.count()
    seen = relate.candidates(e, *PAPER, metres=1e9).where("via = 'road'").count()
    kept = relate.links(e, *PAPER).where("via = 'road'").count()
    return spark.createDataFrame([(n * (n - 1), seen, kept)], "all_pairs long, candidates long, kept long")


class _Tags(HTMLParser):
    """(node, parent, tag) of a page, in document order; tags that never close have no children."""

    VOID = frozenset(("area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"))

    def __init__(self) -> None:
        super().__init__()
        self.rows: list[tuple[int, int | None, str]] = []
        self.open: list[tuple[int, str]] = []

    def handle_starttag(self, tag: str, attrs: list) -> None:
        self.rows.append((len(self.rows), self.open[-1][0] if self.open else None, tag))
        if tag not in self.VOID:
            self.open.append((len(self.rows) - 1, tag))

    def handle_endtag(self, tag: str) -> None:
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i][1] == tag:
                del self.open[i:]
                break


def markup(pages: DataFrame) -> DataFrame:
    """(tree, node, parent, label, start_us) of pages' tags; a tree is the first top tag with all below it."""
    ship(pages.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for page, html in zip(b["page_id"], b["html"], strict=True):
                p = _Tags()
                p.feed(html or "")
                rows += [(page, n, 0 if up is None and n else up, tag, n) for n, up, tag in p.rows]
            yield pd.DataFrame(rows, columns=["tree", "node", "parent", "label", "start_us"]).astype({"parent": "Int64"})

    return pages.select("page_id", "html").mapInPandas(run, "tree long, node long, parent long, label string, start_us long")


@query("w_forest_pages")
def w_forest_pages(spark: SparkSession, d: str) -> DataFrame:
    """Two-node shapes of markup trees in at least a fifth of all pages."""
    return mine.frequent(markup(read(spark, d, "pages")).withColumn("state", F.lit(0).cast("long")), ["state"], 0.2, max_nodes=2)


@query("w_vector_dl")
def w_vector_dl(spark: SparkSession, d: str) -> DataFrame:
    """Description length of vector clusters for several K."""
    vectors = written(read(spark, d, "embeddings").where("embedding is not null and not exists(embedding, x -> x is null or isnan(x))").select("vec_id", "embedding"))
    parts = [cluster.vector_length(vectors, "vec_id", "embedding", k) for k in (2, 4, 8)]
    return parts[0].union(parts[1]).union(parts[2])


@query("m_type_entropy", with_e("n as (select type, count(*)::double n from e group by 1)", then="select round(-sum(n / t * ln(n / t)), 6) nats from n, (select sum(n) t from n)"))
def m_entropy(spark: SparkSession, d: str) -> DataFrame:
    """Spread of types, as one number beside the frequency table."""
    n = describe.type_table(entities(spark, d)).where("type <> 'total'")
    share = F.col("percent") / 100
    return n.agg(F.round(-F.sum(share * F.log(share)), 6).alias("nats"))
