"""Queries of the operator families around the loader: filters, joins, aggregates, windows, sets, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.functions import udfs
from edgecsr.operators import csr as C
from edgecsr.operators import edges as E
from edgecsr.operators.csr_forms import to_blocks
from edgecsr.operators.degrees import combine_degrees, degrees, partial_degrees
from edgecsr.operators.readers import read_edges
from edgecsr.plans import measures, tune
from edgecsr.schema import Graph, GraphMeta
from edgecsr.sources import block_source
from edgecsr.sources import workloads as W
from edgecsr.sources.edgetext import write_csr_buckets
from edgecsr.streaming import edges as S

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(fn):
        key = name or fn.__name__
        QUERIES[key] = fn
        if sql:
            SQL[key] = sql
        return fn

    return add


def _on(name: str, g: str, sql: str, fn):
    """A query over one graph's edges with 64-bit weights; {e} in the SQL is that graph."""
    query(sql.replace("{e}", "(" + _G[g] + ")"), name)(lambda spark, sf_dir: fn(W.graph(spark, sf_dir, g).withColumn("weight", F.col("weight").cast("double"))))


_G = {
    "supp_part": "select l_suppkey as src, l_partkey as dst, l_quantity::float::double as weight from lineitem",
    "part_supp": "select l_partkey as src, l_suppkey as dst, l_quantity::float::double as weight from lineitem",
    "order_part": "select l_orderkey as src, l_partkey as dst, l_quantity::float::double as weight from lineitem",
    "cust_order": "select o_custkey as src, o_orderkey as dst, o_totalprice::float::double as weight from orders",
    "user_next": "select user_id as src, n as dst, 1.0::double as weight from (select user_id, lead(user_id) over (order by ts, event_id) as n from events) where n is not null",
}
_DEG = "(select src as vertex, count(*) as degree from {e} group by 1)"


def _deg(e: DataFrame) -> DataFrame:
    return degrees(e)


# --- projections and filters ------------------------------------------------

_on("proj_edges", "order_part", "select src, dst, weight * 2 as doubled from {e}", lambda e: e.select("src", "dst", (F.col("weight") * 2).alias("doubled")))
_on("edges_reversed", "order_part", "select dst as src, src as dst, weight from {e}", lambda e: E.reverse(e))
_on("filter_weight", "order_part", "select * from {e} where weight > 25", lambda e: e.where("weight > 25"))
_on("filter_range", "supp_part", "select * from {e} where src between 3 and 7", lambda e: E.vertex_range(e, 3, 7))
_on("filter_in", "supp_part", "select * from {e} where dst in (1, 5, 9)", lambda e: e.where(F.col("dst").isin(1, 5, 9)))
_on("no_self_loops", "user_next", "select * from {e} where src <> dst", lambda e: E.drop_self_loops(e))
_on("upper_triangle", "user_next", "select * from {e} where src < dst", lambda e: E.upper_triangle(e))
_on("lower_triangle", "user_next", "select * from {e} where src > dst", lambda e: E.lower_triangle(e))
_on("weight_class", "order_part", "select case when weight < 10 then 'low' when weight < 40 then 'mid' else 'high' end as class, count(*) as n from {e} group by 1", lambda e: e.groupBy(F.when(F.col("weight") < 10, "low").when(F.col("weight") < 40, "mid").otherwise("high").alias("class")).agg(F.count("*").alias("n")))
_on("sort_nulls", "order_part", "select src, dst, nullif(weight, 50) as w from {e} order by w desc nulls last, src, dst limit 25", lambda e: e.select("src", "dst", F.nullif("weight", F.lit(50.0)).alias("w")).orderBy(F.col("w").desc_nulls_last(), "src", "dst").limit(25))
_on("clean_weights", "order_part", "select src, dst, coalesce(nullif(weight, 50), 1.0)::double as weight from {e}", lambda e: E.clean_weights(e.withColumn("weight", F.nullif("weight", F.lit(50.0)).cast("float")), "fill").withColumn("weight", F.col("weight").cast("double")))


@query("select src_name, count(*) as n from (select unnest(string_split_regex(lower(text), '\\s+')) as src_name from documents) where src_name like 'th%' group by 1")
def filter_like(spark, sf_dir):
    return W.graph(spark, sf_dir, "word_doc").where(F.col("src_name").like("th%")).groupBy("src_name").agg(F.count("*").alias("n"))


@query("select l_partkey as src, l_suppkey as dst, l_quantity as weight from lineitem where l_partkey in (select p_partkey from part where p_size < 10) and l_suppkey in (select p_partkey from part where p_size < 10)")
def induced_subgraph(spark, sf_dir):
    v = W.table(spark, sf_dir, "part").where("p_size < 10").select(F.col("p_partkey").alias("vertex"))
    return E.induced_subgraph(W.graph(spark, sf_dir, "part_supp"), v).withColumn("weight", F.col("weight").cast("double"))


@query()
def sample_edges(spark, sf_dir):
    return E.sample_edges(W.graph(spark, sf_dir, "supp_part"), 0.1)


# --- joins ------------------------------------------------------------------


def _join_offsets(hint: str):
    def run(spark, sf_dir):
        e = W.graph(spark, sf_dir, "part_supp")
        v = C.build_csr(Graph(e, GraphMeta()), "staged").vertices.select(F.col("vertex").alias("src"), "offset")
        return e.join(v.hint(hint), "src").groupBy("src").agg(F.min("offset").alias("first_slot"), F.count("*").alias("n"))

    sql = f"select src, sum(count(*)) over (order by src rows between unbounded preceding and 1 preceding)::bigint as f, count(*) as n from ({_G['part_supp']}) group by 1"
    query(f"select src, coalesce(f, 0) as first_slot, n from ({sql})", "join_offsets" + ("" if hint == "merge" else "_hash"))(run)


_join_offsets("merge")
_join_offsets("shuffle_hash")


@query(f"select o_orderkey as vertex from orders where o_orderkey not in (select src from ({_G['order_part']}))")
def isolated_orders(spark, sf_dir):
    o = W.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vertex"))
    return o.join(W.graph(spark, sf_dir, "order_part").select(F.col("src").alias("vertex")), "vertex", "left_anti")


@query(f"select coalesce(a.vertex, b.vertex) as vertex, a.degree as out_degree, b.degree as in_degree from (select src as vertex, count(*) as degree from ({_G['user_next']}) group by 1) a full join (select dst as vertex, count(*) as degree from ({_G['user_next']}) group by 1) b using (vertex)")
def degree_diff(spark, sf_dir):
    e = W.graph(spark, sf_dir, "user_next")
    a = degrees(e).withColumnRenamed("degree", "out_degree")
    b = degrees(e, direction="in").withColumnRenamed("degree", "in_degree")
    return a.join(b, "vertex", "full").select("vertex", "out_degree", "in_degree")


@query(f"select row_number() over (order by src, dst, weight) - 1 as slot, src as owner from ({_G['part_supp']})")
def slot_owner(spark, sf_dir):
    """Range join of slots with vertex ranges through chunks of slots."""
    csr = C.build_csr(Graph(W.graph(spark, sf_dir, "part_supp"), GraphMeta()), "sorted")
    chunk = 256
    end = F.col("offset") + F.col("degree")
    ranges = csr.vertices.where("degree > 0").select(F.col("vertex").alias("owner"), "offset", end.alias("end"), F.explode(F.sequence(F.floor(F.col("offset") / chunk), F.floor((end - 1) / chunk))).alias("c"))
    slots = csr.slots.select("slot", F.floor(F.col("slot") / chunk).alias("c"))
    return slots.join(ranges, "c").where("slot >= offset and slot < end").select("slot", "owner")


@query("select n.n_nationkey, r.r_regionkey from nation n join region r on n.n_nationkey < r.r_regionkey * 5 + 2 and n.n_nationkey >= r.r_regionkey * 5")
def theta_small(spark, sf_dir):
    n, r = W.table(spark, sf_dir, "nation"), W.table(spark, sf_dir, "region")
    return n.join(F.broadcast(r), (F.col("n_nationkey") < F.col("r_regionkey") * 5 + 2) & (F.col("n_nationkey") >= F.col("r_regionkey") * 5)).select("n_nationkey", "r_regionkey")


@query("with a as (select * from events where event_type <> 'view'), b as (select * from events where event_type = 'view') select a.event_id, b.event_id as latest_view from a asof left join b on a.user_id = b.user_id and a.ts >= b.ts")
def asof_events(spark, sf_dir):
    """Each event with its user's latest earlier view: one window over the union, no range join."""
    e = W.table(spark, sf_dir, "events").select("event_id", "user_id", "ts", (F.col("event_type") == "view").alias("v"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("v").desc()).rowsBetween(Window.unboundedPreceding, 0)
    found = e.withColumn("latest_view", F.last(F.when(F.col("v"), F.col("event_id")), ignorenulls=True).over(w))
    return found.where("not v").select("event_id", "latest_view")


@query("select a.event_id as src, b.event_id as dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def interval_events(spark, sf_dir):
    """Pairs of a user's events within an hour, met in their hour or the next."""
    e = W.table(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600).alias("h"))
    a = e.select("user_id", F.col("event_id").alias("src"), F.col("ts").alias("ta"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = e.select("user_id", F.col("event_id").alias("dst"), F.col("ts").alias("tb"), "h")
    return a.join(b, ["user_id", "h"]).where("tb > ta and tb <= ta + interval 1 hour").select("src", "dst")


@query(f"select src, dst from (select src, dst, row_number() over (partition by src order by weight desc, dst) as r from (select distinct * from ({_G['supp_part']}))) where r <= 3")
def lateral_topn(spark, sf_dir):
    e = W.graph(spark, sf_dir, "supp_part").distinct()
    w = Window.partitionBy("src").orderBy(F.col("weight").desc(), "dst")
    return e.withColumn("r", F.row_number().over(w)).where("r <= 3").select("src", "dst")


@query(f"select src, dst from (select src, dst, row_number() over (partition by src order by weight desc, dst) as r from (select distinct * from ({_G['supp_part']}))) where r <= 3")
def lateral_join_topn(spark, sf_dir):
    """The same by a lateral subquery for each vertex."""
    e = W.graph(spark, sf_dir, "supp_part").distinct()
    each = e.select(F.col("src").alias("v")).distinct()
    best = e.where(F.col("src") == F.col("v").outer()).orderBy(F.col("weight").desc(), "dst").limit(3).select("dst")
    return each.lateralJoin(best).select(F.col("v").alias("src"), "dst")


@query(f"select vertex, count(*) as n, min(dst) as least from (select src as vertex, dst from ({_G['part_supp']})) group by 1")
def bucketed_join(spark, sf_dir):
    """Vertices and slots as tables bucketed by vertex: the join and the aggregate need no exchange."""
    name = f"csr_{abs(hash((sf_dir, spark.sparkContext.applicationId)))}"
    write_csr_buckets(C.build_csr(Graph(W.graph(spark, sf_dir, "part_supp"), GraphMeta()), "sorted"), name, 8)
    joined = spark.table(f"{name}_slots").join(spark.table(f"{name}_vertices").where("degree > 0").hint("merge"), "vertex")
    return joined.groupBy("vertex").agg(F.count("*").alias("n"), F.min("target").alias("least"))


@query("select quality, sum(n_chars)::bigint as n_chars, count(*) as n from labels join documents using (doc_id) group by 1")
def salted_join(spark, sf_dir):
    """A hot key joined with its dimension, dealt over salts: the small side is repeated, the large one split."""
    salts = 8
    e = W.table(spark, sf_dir, "labels").select("doc_id", F.col("quality")).withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int"))
    d = W.table(spark, sf_dir, "documents").select("doc_id", "n_chars")
    dim = e.select("quality").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return e.join(dim, ["quality", "salt"]).join(d, "doc_id").groupBy("quality", "salt").agg(F.sum("n_chars").alias("c"), F.count("*").alias("m")).groupBy("quality").agg(F.sum("c").alias("n_chars"), F.sum("m").alias("n"))


# --- aggregates -------------------------------------------------------------

_on("distinct_neighbors", "supp_part", "select src, count(distinct dst) as n from {e} group by 1", lambda e: e.groupBy("src").agg(F.countDistinct("dst").alias("n")))
_on("heaviest_edge", "order_part", "select src, max(dst) as dst, weight from {e} join (select src, max(weight) as weight from {e} group by 1) using (src, weight) group by src, weight", lambda e: e.groupBy("src").agg(F.max(F.struct("weight", "dst")).alias("m")).select("src", "m.dst", "m.weight"))
_on("neighbor_list_text", "order_part", "select src, string_agg(dst::varchar, ',' order by dst) as targets from {e} group by 1", lambda e: e.groupBy("src").agg(F.array_join(F.array_sort(F.collect_list("dst")), ",").alias("targets")))
_on("hubs_over_limit", "supp_part", "select src as vertex, count(*) as degree from {e} group by 1 having count(*) > 600", lambda e: _deg(e).where("degree > 600"))
_on("dedup_first", "part_supp", "select src, dst, min(weight) as weight from {e} group by all", lambda e: E.dedup(e).withColumn("weight", F.col("weight").cast("double")))
_on("dedup_sum", "part_supp", "select src, dst, sum(weight) as weight from {e} group by all", lambda e: E.dedup(e, "sum").withColumn("weight", F.col("weight").cast("double")))
_on("dedup_max", "part_supp", "select src, dst, max(weight) as weight from {e} group by all", lambda e: E.dedup(e, "max").withColumn("weight", F.col("weight").cast("double")))
_on("dedup_min", "part_supp", "select src, dst, min(weight) as weight from {e} group by all", lambda e: E.dedup(e, "min").withColumn("weight", F.col("weight").cast("double")))
_on("count_filtered", "order_part", "select src, count(*) filter (weight > 25) as heavy, bool_and(weight > 1) as all_over_one from {e} group by 1", lambda e: e.groupBy("src").agg(F.count_if(F.col("weight") > 25).alias("heavy"), F.bool_and(F.col("weight") > 1).alias("all_over_one")))
_on("degree_quantiles", "part_supp", "select quantile_cont(degree, 0.25)::double as q25, quantile_cont(degree, 0.75)::double as q75 from " + _DEG, lambda e: _deg(e).agg(F.percentile("degree", 0.25).alias("q25"), F.percentile("degree", 0.75).alias("q75")))


_on("degree_quantiles_approx", "part_supp", "select quantile_disc(degree, 0.25)::bigint as q25, quantile_disc(degree, 0.75)::bigint as q75 from " + _DEG, lambda e: _deg(e).agg(F.percentile_approx("degree", 0.25, 1_000_000).alias("q25"), F.percentile_approx("degree", 0.75, 1_000_000).alias("q75")))
_on("vertex_bitmaps", "supp_part", "select floor((src - 1) / 32768.0)::bigint + 1 as bucket, count(distinct src) as n from {e} group by 1", lambda e: e.select(F.bitmap_bucket_number("src").alias("bucket"), F.bitmap_bit_position("src").alias("bit")).groupBy("bucket").agg(F.bitmap_count(F.bitmap_construct_agg("bit")).alias("n")))


@query()
def degree_quantiles_sketch(spark, sf_dir):
    """Quantiles of degrees by a mergeable sketch; rows alone are checked, as its error is random."""
    sketch = _deg(W.graph(spark, sf_dir, "part_supp")).agg(F.expr("kll_sketch_agg_bigint(degree)").alias("s"))
    return sketch.select(F.expr("kll_sketch_get_quantile_bigint(s, 0.5)").alias("median"), F.expr("kll_sketch_get_n_bigint(s)").alias("n"))


def _grouping(name: str, sql: str, how):
    query(sql, name)(lambda spark, sf_dir: how(W.table(spark, sf_dir, "lineitem")).agg(F.count("*").alias("n_edges")))


_grouping("edges_rollup", "select l_returnflag, l_linestatus, count(*) as n_edges from lineitem group by rollup (l_returnflag, l_linestatus)", lambda t: t.rollup("l_returnflag", "l_linestatus"))
_grouping("edges_cube", "select l_returnflag, l_linestatus, count(*) as n_edges from lineitem group by cube (l_returnflag, l_linestatus)", lambda t: t.cube("l_returnflag", "l_linestatus"))
_grouping("edges_grouping_sets", "select l_returnflag, l_linestatus, count(*) as n_edges from lineitem group by grouping sets ((l_returnflag), (l_linestatus))", lambda t: t.groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus"))


@query("select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view from events group by 1")
def pivot_event_degree(spark, sf_dir):
    p = W.table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return p.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@query()
def approx_vertices(spark, sf_dir):
    e = W.graph(spark, sf_dir, "supp_part")
    return e.agg(F.approx_count_distinct("dst", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("hll"))


# --- windows ----------------------------------------------------------------

_on("rank_hubs", "part_supp", "select vertex, rank() over (order by degree desc) as r, dense_rank() over (order by degree desc) as d from " + _DEG, lambda e: _deg(e).select("vertex", F.rank().over(Window.orderBy(F.desc("degree"))).cast("long").alias("r"), F.dense_rank().over(Window.orderBy(F.desc("degree"))).cast("long").alias("d")))
_on("ntile_degree", "part_supp", "select vertex, ntile(4) over (order by degree, vertex) as q from " + _DEG, lambda e: _deg(e).select("vertex", F.ntile(4).over(Window.orderBy("degree", "vertex")).cast("long").alias("q")))
_on("edge_share", "order_part", "select src, dst, round(weight / sum(weight) over (partition by src), 6) as share from {e}", lambda e: e.select("src", "dst", F.round(F.col("weight") / F.sum("weight").over(Window.partitionBy("src")), 6).alias("share")))
_on("moving_avg", "cust_order", "select src, dst, round(avg(weight) over (partition by src order by dst rows between 2 preceding and current row), 3) as m from {e}", lambda e: e.select("src", "dst", F.round(F.avg("weight").over(Window.partitionBy("src").orderBy("dst").rowsBetween(-2, 0)), 3).alias("m")))
_on("top_neighbors", "part_supp", "select src, dst, weight from (select *, row_number() over (partition by src order by weight desc, dst) as r from {e}) where r <= 2", lambda e: e.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("weight"), "dst"))).where("r <= 2").drop("r"))
_on("lag_gap", "cust_order", "select src, dst, dst - lag(dst) over (partition by src order by dst) as gap from {e}", lambda e: e.select("src", "dst", (F.col("dst") - F.lag("dst").over(Window.partitionBy("src").orderBy("dst"))).alias("gap")))
_on("first_last", "cust_order", "select distinct src, first_value(dst) over w as f, last_value(dst) over w as l, nth_value(dst, 2) over w as s from {e} window w as (partition by src order by dst rows between unbounded preceding and unbounded following)", lambda e: e.select("src", *[f.over(Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for f, n in ((F.first("dst"), "f"), (F.last("dst"), "l"), (F.nth_value("dst", 2), "s"))]).distinct())


@query("select event_id, count(*) over (partition by user_id order by ts range between interval 1 hour preceding and current row) as n from events")
def range_frame_events(spark, sf_dir):
    e = W.table(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3_600_000_000, 0)).alias("n"))


# --- sets, limits -----------------------------------------------------------

_A, _B = f"select src, dst from ({_G['supp_part']}) where src % 2 = 0", f"select src, dst from ({_G['supp_part']}) where src % 3 = 0"


def _set(name: str, op: str, fn):
    def run(spark, sf_dir):
        e = W.graph(spark, sf_dir, "supp_part").select("src", "dst")
        return fn(e.where("src % 2 = 0"), e.where("src % 3 = 0"))

    query(f"({_A}) {op} ({_B})", name)(run)


_set("union_graphs", "union all", lambda a, b: a.unionByName(b))
_set("union_distinct_edges", "union", lambda a, b: a.union(b).distinct())
_set("intersect_edges", "intersect", lambda a, b: a.intersect(b))
_set("intersect_all_edges", "intersect all", lambda a, b: a.intersectAll(b))
_set("except_edges", "except", lambda a, b: a.subtract(b))
_set("except_all_edges", "except all", lambda a, b: a.exceptAll(b))
_on("distinct_edges", "supp_part", "select distinct src, dst from {e}", lambda e: e.select("src", "dst").distinct())
_on("limit_offset", "supp_part", "select * from {e} order by src, dst, weight limit 20 offset 10", lambda e: e.orderBy("src", "dst", "weight").offset(10).limit(20))

# --- scalar functions -------------------------------------------------------

_on("math_bins", "order_part", "select src, dst, (src % 4) as part, floor(sqrt(weight))::bigint as r, (dst // 16) as chunk, abs(src - dst) as gap, greatest(src, dst) as hi from {e}", lambda e: e.select("src", "dst", (F.col("src") % 4).alias("part"), F.floor(F.sqrt("weight")).alias("r"), F.shiftright("dst", 4).alias("chunk"), F.abs(F.col("src") - F.col("dst")).alias("gap"), F.greatest("src", "dst").alias("hi")))
_on("adjacency_map_exploded", "order_part", "select src, dst, max(weight) as weight from {e} group by all", lambda e: e.groupBy("src", "dst").agg(F.max("weight").alias("w")).groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", "w"))).alias("m")).select("src", F.explode("m").alias("dst", "weight")))
_on("array_functions", "order_part", "select src, list_sum(list(dst))::bigint as total, len(list_filter(list(dst), lambda x: x % 2 = 0)) as even, list_distinct(list(dst)).len() as kinds from {e} group by 1", lambda e: e.groupBy("src").agg(F.collect_list("dst").alias("l")).select("src", F.aggregate("l", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"), F.size(F.filter("l", lambda x: x % 2 == 0)).cast("long").alias("even"), F.size(F.array_distinct("l")).cast("long").alias("kinds")))


@query("select date_trunc('hour', ts) as hour, count(*) as n, round(sum(value), 4) as total from events group by 1")
def events_per_hour(spark, sf_dir):
    return W.table(spark, sf_dir, "events").groupBy(F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("select item_id, i::int as pos, substring(text, i::int + 1, 8) as kmer from (select item_id, text, unnest(range(0, length(text) - 7)) as i from benchmark)")
def udtf_kmers(spark, sf_dir):
    udfs.register(spark)
    W.table(spark, sf_dir, "benchmark").createOrReplaceTempView("_kmer_input")
    return spark.sql("select item_id, k.pos, k.kmer from _kmer_input, lateral kmers(text, 8) k")


@query(f"select src as vertex, dst as target from ({_G['part_supp']})")
def udtf_csr_neighbors(spark, sf_dir):
    udfs.register(spark)
    to_blocks(C.build_csr(Graph(W.graph(spark, sf_dir, "part_supp"), GraphMeta()), "staged"), 64).createOrReplaceTempView("_csr_blocks")
    return spark.sql("select n.vertex, n.target from _csr_blocks b, lateral csr_neighbors(b.base_vertex, b.base_offset, b.offsets, b.targets) n")


@query(f"select (src + 1)::varchar as a, (dst + 1)::varchar as b from ({_G['order_part']})")
def udtf_edge_tokens(spark, sf_dir):
    udfs.register(spark)
    spark.read.text(W.exported(spark, sf_dir, "order_part")).select("value", F.monotonically_increasing_id().alias("line")).createOrReplaceTempView("_token_lines")
    return spark.sql("select max(token) filter (where pos = 0) as a, max(token) filter (where pos = 1) as b from _token_lines, lateral edge_tokens(value) group by line")


@query(f"select src as vertex, max(dst) as greatest, count(*) as n from ({_G['part_supp']}) group by 1")
def sql_views(spark, sf_dir):
    """A graph and its CSR as SQL views."""
    e = W.graph(spark, sf_dir, "part_supp")
    udfs.register_views(e, C.build_csr(Graph(e, GraphMeta()), "sorted"))
    return spark.sql("select v.vertex, max(s.target) as greatest, count(*) as n from csr_vertices v join csr_slots s on v.vertex = s.vertex group by v.vertex")


@query(f"select src, dst, weight from ({_G['order_part']})")
def sql_functions(spark, sf_dir):
    udfs.register(spark)
    spark.read.text(W.exported(spark, sf_dir, "order_part")).createOrReplaceTempView("_edge_lines")
    return spark.sql("select edge_src(value) - 1 as src, edge_dst(value) - 1 as dst, edge_weight(value) as weight from _edge_lines")


@query(f"select src + 1 as src, dst + 1 as dst, weight from ({_G['order_part']})")
def udf_arrow_parse(spark, sf_dir):
    t = spark.read.text(W.exported(spark, sf_dir, "order_part")).select(udfs.parse_edge_arrow("value").alias("e"))
    return t.select("e.src", "e.dst", F.col("e.weight").cast("double").alias("weight"))


@query(f"select src + 1 as src, dst + 1 as dst, weight from ({_G['order_part']})")
def udf_row_parse(spark, sf_dir):
    t = spark.read.text(W.exported(spark, sf_dir, "order_part")).select(udfs.parse_edge_row("value").alias("e"))
    return t.select("e.src", "e.dst", F.col("e.weight").cast("double").alias("weight"))


@query(f"with d as (select degree, row_number() over (order by degree) as i, count(*) over () as n from (select count(*) as degree from ({_G['part_supp']}) group by l_partkey)) select round(sum((2 * i - n - 1) * degree) / (max(n) * sum(degree)), 6)::double as gini from d".replace("group by l_partkey", "group by src"))
def degree_gini(spark, sf_dir):
    return degrees(W.graph(spark, sf_dir, "part_supp")).agg(F.round(udfs.degree_gini("degree"), 6).alias("gini"))


# --- streams ----------------------------------------------------------------


@query(f"select src as vertex, count(*) as degree from ({_G['supp_part']}) group by 1")
def stream_degrees(spark, sf_dir):
    s = S.read_edges_stream(spark, W.exported(spark, sf_dir, "supp_part", files=5), files_per_trigger=2)
    return S.run_to_table(S.incremental_degrees(s), "complete")


@query(f"select src as vertex, count(*) as degree from ({_G['supp_part']}) group by 1")
def stream_block_source(spark, sf_dir):
    """The same from the byte-block source, a file an offset."""
    block_source.register(spark)
    s = spark.readStream.format("edgeblocks").option("path", W.exported(spark, sf_dir, "supp_part", files=5)).load()
    return S.run_to_table(S.incremental_degrees(s), "complete")


@query(f"select src as vertex, count(*) as degree from ({_G['supp_part']}) group by 1")
def stream_degree_state(spark, sf_dir):
    s = S.read_edges_stream(spark, W.exported(spark, sf_dir, "supp_part", files=5), files_per_trigger=2)
    out = S.run_to_table(S.degree_state(s), "update")
    return out.groupBy("vertex").agg(F.max("degree").alias("degree"))


@query("select time_bucket(interval 10 minutes, ts) as start, event_type, count(*) as n_edges, round(sum(value), 4) as total from events group by all")
def stream_tumbling(spark, sf_dir):
    return S.run_to_table(S.windowed_edges(S.read_events(spark, sf_dir), "10 minutes"), "complete")


@query("select w as start, event_type, count(*) as n_edges, round(sum(value), 4) as total from (select *, unnest([time_bucket(interval 10 minutes, ts), time_bucket(interval 10 minutes, ts) - interval 10 minutes]) as w from events) group by all")
def stream_sliding(spark, sf_dir):
    return S.run_to_table(S.windowed_edges(S.read_events(spark, sf_dir), "20 minutes", "10 minutes"), "complete")


@query("with a as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as b from events), s as (select *, sum(b) over (partition by user_id order by ts rows unbounded preceding) as k from a) select user_id, min(ts) as start, count(*) as n_edges from s group by user_id, k")
def stream_session(spark, sf_dir):
    return S.run_to_table(S.session_edges(S.read_events(spark, sf_dir), "30 minutes"), "complete")


@query("select event_id, user_id from events")
def stream_dedup(spark, sf_dir):
    return S.run_to_table(S.dedup_events(S.read_events(spark, sf_dir)).select("event_id", "user_id"))


@query("select event_id, c_nationkey from events join customer on c_custkey = user_id")
def stream_static_join(spark, sf_dir):
    dims = W.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return S.run_to_table(S.enrich(S.read_events(spark, sf_dir), dims, "user_id").select("event_id", "c_nationkey"))


@query("select a.event_id as src, b.event_id as dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def stream_stream_join(spark, sf_dir):
    return S.run_to_table(S.edge_pairs(S.read_events(spark, sf_dir), S.read_events(spark, sf_dir), "1 hour"))


@query(f"select row_number() over (order by src, dst, weight) - 1 as slot, src as vertex, dst as target, weight from ({_G['part_supp']})")
def stream_csr_upkeep(spark, sf_dir):
    e = W.graph(spark, sf_dir, "part_supp")
    csr = C.build_csr(Graph(e.where("dst % 5 <> 0"), GraphMeta()), "sorted")
    merged = S.merge_csr_delta(csr, e.where("dst % 5 = 0"))
    return merged.slots.withColumn("weight", F.col("weight").cast("double"))


# --- experiment workloads (times, so rows only) -----------------------------

for _name, _fn in (
    ("workload_readers", tune.sweep_readers),
    ("workload_variants", tune.sweep_variants),
    ("workload_parts", tune.sweep_parts),
    ("workload_csr_loaders", tune.compare_csr_loaders),
    ("workload_two_loaders", tune.compare_two_loaders),
    ("workload_header", tune.compare_header),
    ("workload_edge_loaders", tune.compare_edge_loaders),
    ("workload_split", tune.split_times),
    ("workload_weights", tune.sweep_weights),
    ("workload_lines", tune.sweep_lines),
    ("workload_shapes", tune.compare_degree_shapes),
    ("workload_in_memory", tune.convert_in_memory),
    ("workload_block_bytes", tune.sweep_block_bytes),
    ("workload_scaling", tune.sweep_tasks),
):
    query(None, _name)(lambda spark, sf_dir, fn=_fn: fn(spark, sf_dir))


_RUNS = [("w", g, m, p, c, r, sec, e, n, b, st) for g, m, p, c, r, sec, e, n, b, st in (
    ("web", "slow", "", 1, 0, 4.0, 100, 100, 1600, "ok"), ("web", "slow", "", 1, 1, 6.0, 100, 100, 1600, "ok"), ("web", "fast", "", 1, 0, 2.0, 100, 100, 1600, "ok"),
    ("web", "fast", "", 4, 0, 1.0, 100, 100, 1600, "ok"), ("road", "slow", "", 1, 0, 8.0, 50, 100, 900, "ok"), ("road", "fast", "", 1, 0, 1.0, 50, 100, 900, "ok"),
    ("road", "fast", "", 4, 0, 0.5, 50, 100, 900, "ok"), ("road", "broken", "", 1, 0, None, 50, 0, 900, "failed: X"),
)]
_RUNS_SQL = "select * from (values " + ", ".join(f"('{w}', '{g}', '{m}', '{p}', {c}, {r}, {'null' if sec is None else sec}::double, {e}::bigint, {n}::bigint, {b}::bigint, '{st}')" for w, g, m, p, c, r, sec, e, n, b, st in _RUNS) + ") t(workload, graph, method, params, cores, run, seconds, edges_in_file, edges_loaded, bytes, status)"
_MEANS = f"(select workload, graph, method, params, cores, avg(seconds) as seconds, max(edges_loaded) as edges_loaded, max(bytes) as bytes from ({_RUNS_SQL}) where status = 'ok' group by all)"


def _measure(name: str, sql: str, fn):
    query(sql.replace("{m}", _MEANS).replace("{r}", f"({_RUNS_SQL})"), f"measures_{name}")(lambda spark, sf_dir: fn(spark.createDataFrame(_RUNS, measures.RECORD)))


_measure("means", "select * from {m}", measures.means)
_measure("relative", "select m.workload, m.method, m.params, avg(m.seconds / b.s) as relative from {m} m join (select graph, seconds as s from {m} where method = 'slow') b using (graph) group by all", lambda f: measures.relative(f, "slow"))
_measure("speedup", "select workload, method, avg(s / seconds) as arithmetic, exp(avg(ln(s / seconds))) as geometric from {m} m join (select graph, seconds as s from {m} where method = 'slow') b using (graph) group by all", lambda f: measures.speedup(f, "slow"))
#: Runs as the events tell them: seconds are eighths, so that sums do not depend on their order.
_EVENT_RUNS = {
    "workload": "'w'", "graph": "event_type", "method": "case when user_id % 2 = 0 then 'slow' else 'fast' end", "params": "''", "cores": "cast(user_id % 4 + 1 as int)", "run": "cast(event_id % 5 as int)",
    "seconds": "case when event_id % 11 <> 0 then cast(event_id % 64 + 1 as double) / 8 end", "edges_in_file": "event_id + 1", "edges_loaded": "event_id + 1", "bytes": "(event_id + 1) * (user_id % 7 + 9)", "status": "case when event_id % 11 = 0 then 'failed: X' else 'ok' end",
}
_EVENT_MEANS = _MEANS.replace(_RUNS_SQL, "select " + ", ".join(f"{e} as {n}" for n, e in _EVENT_RUNS.items()) + " from events")


def _measure_events(name: str, sql: str, fn):
    query(sql.replace("{m}", _EVENT_MEANS), f"measures_{name}")(lambda spark, sf_dir: fn(W.table(spark, sf_dir, "events").select(*[F.expr(e).alias(n) for n, e in _EVENT_RUNS.items()])))


_measure_events("edge_rate", "select graph, method, cores, edges_loaded / seconds as edges_per_second from {m}", lambda f: measures.edge_rate(f).select("graph", "method", "cores", "edges_per_second"))
_measure_events("byte_rate", "select graph, method, cores, bytes / seconds as bytes_per_second, bytes / edges_loaded as bytes_per_edge from {m}", lambda f: measures.byte_rate(f).select("graph", "method", "cores", "bytes_per_second", "bytes_per_edge"))
_measure("scaling", "select m.graph, m.method, m.cores, b.s / m.seconds as speedup, case when m.cores > b.c then pow(b.s / m.seconds, 1 / log2(m.cores / b.c)) end as per_doubling from {m} m join (select graph, method, arg_min(seconds, cores) as s, min(cores) as c from {m} group by all) b using (graph, method)", lambda f: measures.scaling(f).select("graph", "method", "cores", "speedup", "per_doubling"))
_measure("phase_times", "select graph, avg(seconds) filter (method = 'fast') as edge_list, avg(seconds) filter (method = 'slow') as csr from {m} group by 1", lambda f: measures.phase_times(f.withColumn("method", F.when(F.col("method") == "fast", "edge_list").when(F.col("method") == "slow", "csr"))))
_measure("failures", "select graph, method, count(*) filter (status <> 'ok') as failed, count(*) as runs from {r} group by all", measures.failures)


@query("select count(*) as n_edges, (max(l_suppkey) + 1) as n_sources, sum(length((l_suppkey + 1)::varchar) + length((l_partkey + 1)::varchar) + length(l_quantity::float::varchar) + 3)::bigint as bytes from lineitem", "measures_graph_size")
def _graph_size(spark, sf_dir):
    """Edges, sources and bytes of the text export."""
    path = W.exported(spark, sf_dir, "supp_part")
    edges, size = measures.file_totals(spark, path)
    return W.graph(spark, sf_dir, "supp_part").agg(F.lit(edges).cast("long").alias("n_edges"), (F.max("src") + 1).alias("n_sources"), F.lit(size).cast("long").alias("bytes"))


@query(f"with d as (select (dst % 4)::int as part, src, count(*) as n from ({_G['part_supp']}) group by all), p as (select part, sum(n) as n from d group by 1) select (select count(*) from d) as part_rows, (select count(distinct src) from d) as rows, (select max(n) / avg(n) from p)::double as max_over_mean", "measures_space_and_skew")
def _space_and_skew(spark, sf_dir):
    """What private counters hold against combined ones, and the load of the fullest part."""
    e = E.with_part(W.graph(spark, sf_dir, "part_supp"), 4, "dst_mod")
    own = partial_degrees(e)
    return measures.space(own, combine_degrees(own)).crossJoin(measures.skew(E.edges_per_part(e))).select("part_rows", "rows", "max_over_mean")


@query("select count(*) as edges_loaded, 2 * count(*) as with_reverse from (" + "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b using (l_orderkey) where a.l_partkey < b.l_partkey" + ")")
def workload_symmetric(spark, sf_dir):
    """One triangle in a symmetric Matrix Market file: edges with the header ignored and honoured."""
    path = tune.symmetric_file(spark, sf_dir)
    counts = [read_edges(spark, path, header="mtx", honor_header=h).edges.agg(F.count("*").alias(n)) for h, n in ((False, "edges_loaded"), (True, "with_reverse"))]
    return counts[0].crossJoin(counts[1])
