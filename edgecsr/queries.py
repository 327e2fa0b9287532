"""All registered queries of the engine with the SQL each must equal."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgecsr import query_families
from edgecsr.functions.parse import parse_lines
from edgecsr.operators import baselines, csr_forms, graphops
from edgecsr.operators import csr as C
from edgecsr.operators import edges as E
from edgecsr.operators.degrees import combine_degrees, degree_histogram, degree_stats, degrees, log_bins, partial_degrees, top_hubs
from edgecsr.operators.readers import read_csr, read_edges, read_edges_csv
from edgecsr.operators.scan import exclusive_scan
from edgecsr.plans import invariants
from edgecsr.schema import Graph, GraphMeta
from edgecsr.session import shared_dir
from edgecsr.sources import edgetext, mtx
from edgecsr.sources import workloads as W

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


# --- the graphs in SQL ------------------------------------------------------

G = {
    "supp_part": "select l_suppkey as src, l_partkey as dst, l_quantity::float::double as weight from lineitem",
    "part_supp": "select l_partkey as src, l_suppkey as dst, l_quantity::float::double as weight from lineitem",
    "order_part": "select l_orderkey as src, l_partkey as dst, l_quantity::float::double as weight from lineitem",
    "cust_order": "select o_custkey as src, o_orderkey as dst, o_totalprice::float::double as weight from orders",
    "nation_region": "select n_nationkey::bigint as src, n_regionkey::bigint as dst, 1.0::double as weight from nation",
    "nation_cust": "select c_nationkey::bigint as src, c_custkey as dst, 1.0::double as weight from customer",
    "supp_nation": "select s_suppkey as src, s_nationkey::bigint as dst, 1.0::double as weight from supplier",
    "part_size": "select p_size::bigint as src, p_partkey as dst, p_retailprice::float::double as weight from part",
    "label_doc": "select quality::bigint as src, doc_id as dst, 1.0::double as weight from labels",
    "vec_label": "select label::bigint as src, vec_id as dst, 1.0::double as weight from embeddings",
    "user_k": "select user_id as src, (props->>'$.k')::bigint as dst, value::float::double as weight from events",
    "copurchase": "select distinct a.l_partkey as src, b.l_partkey as dst, 1.0::double as weight from lineitem a join lineitem b using (l_orderkey) where a.l_partkey < b.l_partkey",
    "order_chain": "select o_orderkey as src, n as dst, 1.0::double as weight from (select o_orderkey, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as n from orders) where n is not null",
    "user_next": "select user_id as src, n as dst, 1.0::double as weight from (select user_id, lead(user_id) over (order by ts, event_id) as n from events) where n is not null",
    "turns": "select conv_id * 1000 + turn as src, conv_id * 1000 + n as dst, 1.0::double as weight from (select conv_id, turn, lead(turn) over (partition by conv_id order by turn) as n from conversations) where n is not null",
}
G["copurchase_both"] = f"select * from ({G['copurchase']}) union all select dst, src, weight from ({G['copurchase']})"
NAMES = {
    "word_doc": "select unnest(string_split_regex(lower(text), '\\s+')) as src_name, doc_id::varchar as dst_name from documents",
    "kmer8": "select distinct substring(text, i::int, 8) as src_name, substring(text, i::int + 1, 8) as dst_name from (select text, unnest(range(1, length(text) - 8 + 1)) as i from benchmark where length(text) > 8)",
}


def edge_sql(g: str) -> str:
    return f"select src, dst, weight from ({G.get(g, g)})"


def offset_sql(g: str, n: str = "max(src) + 1") -> str:
    return f"""with e as ({G.get(g, g)}), d as (select src as vertex, count(*) as degree from e group by 1),
v as (select unnest(range(0, (select {n} from e) + 1)) as vertex)
select vertex, coalesce(degree, 0) as degree, coalesce(sum(coalesce(degree, 0)) over (order by vertex rows between unbounded preceding and 1 preceding), 0)::bigint as "offset" from v left join d using (vertex)"""


def slot_sql(g: str, order: str = "src, dst, weight") -> str:
    return f"select row_number() over (order by {order}) - 1 as slot, src as vertex, dst as target, weight from ({G.get(g, g)})"


def degree_sql(g: str, end: str = "src", agg: str = "count(*)") -> str:
    return f"select {end} as vertex, {agg} as degree from ({G.get(g, g)}) group by 1"


def out(edges: DataFrame) -> DataFrame:
    """Edges with 64-bit weights, as the SQL has them."""
    return edges.select("src", "dst", F.col("weight").cast("double").alias("weight"))


def slots_out(slots: DataFrame) -> DataFrame:
    return slots.select("slot", "vertex", "target", F.col("weight").cast("double").alias("weight"))


def graph_of(spark, sf_dir, g: str, **meta) -> Graph:
    return Graph(W.graph(spark, sf_dir, g), GraphMeta(**meta))


# --- readers ----------------------------------------------------------------


def _reader(name: str, g: str = "supp_part", text: dict | None = None, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return out(read_edges(spark, W.exported(spark, sf_dir, g, **(text or {})), **options).edges)

    query(edge_sql(g), name)(run)


_reader("edges_serial", method="serial")
_reader("edges_line_block", method="line_block")
_reader("edges_line_block_format", method="line_block", parser="format")
_reader("edges_buffered_format", method="line_block", line_source="buffered", parser="format")
_reader("edges_buffered_direct", method="line_block", line_source="buffered", parser="direct")
_reader("edges_block_direct", method="block")
_reader("edges_block_vector", method="block_vector")
_reader("edges_block_source", method="block_vector", source="blocks", block_bytes=65536)
_reader("edges_static_schedule", method="block", schedule="static")
_reader("edges_static_blocks", method="block_vector", source="blocks", schedule="static")
_reader("edges_header_auto", header="auto")
_reader("edges_digit_scan", method="block", parser="digit_scan")
_reader("edges_generic_parser", method="block", parser="generic")
_reader("edges_index_base0", text={"index_base": 0}, index_base=0)
_reader("edges_tabs", text={"sep": "\t"}, method="block")
_reader("edges_commas", text={"sep": ","}, method="block")
_reader("edges_gzip", text={"compression": "gzip"}, method="block")
_reader("edges_many_files", text={"files": 7})
_reader("edges_prices", g="cust_order", method="block")
_reader("edges_user_k", g="user_k", method="block")


@query(f"select src, dst, 1.0::double as weight from ({G['order_part']})")
def edges_unweighted(spark, sf_dir):
    return out(read_edges(spark, W.exported(spark, sf_dir, "order_part", weighted=False), "block", weighted=False).edges)


@query(edge_sql("nation_region"))
def edges_comments_blank_lines(spark, sf_dir):
    e = W.graph(spark, sf_dir, "nation_region")
    lines = e.select(F.explode(F.array(F.lit("% 9 9"), F.lit(""), F.lit("  # 1 1 1"), F.concat_ws("\t", F.lit(""), F.col("src") + 1, F.concat(F.col("dst") + 1, F.lit("  ")), "weight"))).alias("value"))
    return out(parse_lines(lines)[0])


_FLAWED_SQL = "select case l_orderkey % 8 when 0 then 'missing target' when 1 then 'bad id' when 2 then 'bad id' when 3 then 'below index base' else 'bad weight' end as reason, count(*) as n from lineitem where l_orderkey % 8 < 5 group by 1"


def _flawed_lines(spark, sf_dir):
    """Every lineitem as a line of text; what is wrong with it follows from its order's key, of which two in eight give good lines and one a comment."""
    a, b, w = (F.col(c).cast(t) for c, t in (("l_suppkey", "long"), ("l_partkey", "long"), ("l_quantity", "float")))
    line = lambda *tokens: F.concat_ws(" ", *[t.cast("string") if not isinstance(t, str) else F.lit(t) for t in tokens])
    kinds = [line(a + 1), line(a + 1, "x"), line("9223372036854775808", b + 1), line("0", b + 1), line(a + 1, b + 1, "z"), line("%", a), line(a + 1, b + 1, -w)]
    value = line(a + 1, b + 1, w)
    for i, kind in enumerate(kinds):
        value = F.when(F.col("l_orderkey") % 8 == i, kind).otherwise(value)
    return W.table(spark, sf_dir, "lineitem").select(value.alias("value"))


@query(_FLAWED_SQL)
def edges_bad_records(spark, sf_dir):
    return parse_lines(_flawed_lines(spark, sf_dir))[1].groupBy("reason").agg(F.count("*").alias("n"))


@query(_FLAWED_SQL)
def edges_bad_records_vector(spark, sf_dir):
    return parse_lines(_flawed_lines(spark, sf_dir), "vector")[1].groupBy("reason").agg(F.count("*").alias("n"))


@query("select * from (values (0::bigint, 1::bigint, 1.0::double), (2, 3, 1.0), (6, 7, -1500.0), (9, 1, 0.25)) t(src, dst, weight)")
def parse_numbers(spark, sf_dir):
    lines = spark.createDataFrame([("  1\t2 ",), ("3,4",), ("7 8 -1.5e3",), ("+10 02 .25\r",)], "value string")
    return out(parse_lines(lines)[0])


def _mtx(spark, sf_dir, g, field="real", symmetry="general", lower=False) -> str:
    path = f"{shared_dir(spark)}/mtx-{g}-{field}-{symmetry}-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    e = W.graph(spark, sf_dir, g)
    if lower:
        e = E.reverse(e)
    n = e.agg(F.max("src") + 1, F.max("dst") + 1).first()
    rows, cols = (max(n), max(n)) if symmetry != "general" else n
    mtx.write_mtx(e, path, rows, cols, field, symmetry)
    return path


@query(edge_sql("supp_part"))
def edges_mtx_general(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "supp_part"), "block", header="mtx").edges)


@query(edge_sql("copurchase_both"))
def edges_mtx_symmetric_once(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "copurchase", "pattern", "symmetric", True), "block", header="mtx").edges)


_UNEXT = G["user_next"]


@query(f"select * from ({_UNEXT}) union all select dst, src, weight from ({_UNEXT})")
def edges_mtx_symmetric_double(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "user_next", "pattern", "symmetric"), "block", header="mtx", self_loops="double").edges)


@query(f"select dst as src, src as dst, weight from ({G['copurchase']}) union all select src, dst, -weight from ({G['copurchase']})")
def edges_mtx_skew(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "copurchase", "real", "skew-symmetric", True), "block", header="mtx").edges)


@query("with e as (select l_suppkey as src, l_partkey as dst, l_quantity::float::double as weight from lineitem), n as (select max(src) as r, max(dst) as c, count(*) + 2 as n from e) select * from e union all select r, c, n::double from n union all select r, c, n::double from n")
def edges_mtx_entry_like_size(spark, sf_dir):
    """Two entries that read just like the size line stay."""
    e = W.graph(spark, sf_dir, "supp_part")
    top = e.agg(F.max("src").alias("src"), F.max("dst").alias("dst"), F.lit(0.0).cast("float").alias("weight"), (F.count("*") + 2).alias("n"))
    path = f"{shared_dir(spark)}/mtx-like-size-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    r, c, _, n = top.first()
    head = f"%%MatrixMarket matrix coordinate real general\n% entries like the size line\n{r + 1} {c + 1} {n}\n{r + 1} {c + 1} {n}\n{r + 1} {c + 1} {n}"
    spark.createDataFrame([(head,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/part=0")
    edgetext.write_edges(e, f"{path}/part=1")
    return out(read_edges(spark, path, header="mtx").edges)


@query(f"select src, dst, 1.0::double as weight from ({G['order_part']})")
def edges_mtx_pattern(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "order_part", "pattern"), "block", header="mtx").edges)


@query(edge_sql("order_part"))
def edges_mtx_integer(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "order_part", "integer"), "block", header="mtx").edges)


@query(f"select dst as src, src as dst, weight from ({G['copurchase']})")
def edges_header_ignored(spark, sf_dir):
    return out(read_edges(spark, _mtx(spark, sf_dir, "copurchase", "pattern", "symmetric", True), "block", header="mtx", honor_header=False).edges)


@query("select 'coordinate' as format, 'pattern' as field, 'symmetric' as symmetry, max(dst) + 1 as n_rows, max(dst) + 1 as n_cols, count(*) as entries from (" + G["copurchase"] + ")")
def mtx_header(spark, sf_dir):
    h = mtx.read_mtx_header(spark, _mtx(spark, sf_dir, "copurchase", "pattern", "symmetric", True))
    return spark.createDataFrame([(h.format, h.field, h.symmetry, h.rows, h.cols, h.entries)], "format string, field string, symmetry string, n_rows long, n_cols long, entries long")


@query(f"select src, dst, count(*) as n from ({G['supp_part']}) group by all")
def two_pass_edges(spark, sf_dir):
    return baselines.two_pass_edges(spark, W.exported(spark, sf_dir, "supp_part")).groupBy("src", "dst").agg(F.count("*").alias("n"))


@query("select 0::bigint as low, count(*) - 1 as high, count(*) as n from lineitem")
def two_pass_indices(spark, sf_dir):
    t = baselines.two_pass_edges(spark, W.exported(spark, sf_dir, "supp_part", files=5))
    return t.agg(F.min("edge_index").alias("low"), F.max("edge_index").alias("high"), F.countDistinct("edge_index").alias("n"))


@query(edge_sql("supp_part"))
def builtin_csv_edges(spark, sf_dir):
    return out(baselines.builtin_csv(spark, W.exported(spark, sf_dir, "supp_part")))


@query(
    """select case l_orderkey % 4 when 0 then 'not of the schema' when 1 then 'further columns' else 'good' end as kind,
concat_ws(' ', l_suppkey::varchar, case when l_orderkey % 4 = 0 then 'x' else l_partkey::varchar end, case l_orderkey % 4 when 0 then '1' when 1 then '8 9' else l_quantity::float::varchar end) as line from lineitem where l_orderkey % 4 <> 2"""
)
def csv_corrupt_records(spark, sf_dir):
    """Lines that do not fit the schema, beside those that do: each lineitem is one, of a kind that follows from its order's key; a quarter are comments."""
    path = f"{shared_dir(spark)}/csv-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    kind, a, b, w = F.col("l_orderkey") % 4, F.col("l_suppkey"), F.col("l_partkey"), F.col("l_quantity").cast("float").cast("string")
    line = F.when(kind == 0, F.concat_ws(" ", a, F.lit("x 1"))).when(kind == 1, F.concat_ws(" ", a, b, F.lit("8 9"))).when(kind == 2, F.lit("% note")).otherwise(F.concat_ws(" ", a + 1, b + 1, w))
    W.table(spark, sf_dir, "lineitem").select(line.alias("value")).write.mode("overwrite").text(path)
    g = read_edges_csv(spark, path)
    good = g.edges.select(F.lit("good").alias("kind"), F.concat_ws(" ", "src", "dst", "weight").alias("line"))
    return g.bad.select(F.col("reason").alias("kind"), "line").union(good)


@query("select count(*) as n_edges from lineitem")
def part_counts_total(spark, sf_dir):
    return E.edges_per_part(read_edges(spark, W.exported(spark, sf_dir, "supp_part", files=7)).edges).agg(F.sum("n_edges").alias("n_edges"))


@query("select count(*) as n_rows from lineitem")
def split_rows_total(spark, sf_dir):
    return edgetext.file_splits(spark, W.exported(spark, sf_dir, "supp_part")).agg(F.sum("rows").alias("n_rows"))


@query(f"select length((src + 1)::varchar) + length((dst + 1)::varchar) + 1 as n_bytes, count(*) as n from ({G['order_chain']}) group by 1")
def line_lengths(spark, sf_dir):
    lines = spark.read.text(W.exported(spark, sf_dir, "order_chain", weighted=False))
    return lines.groupBy(F.octet_length("value").cast("long").alias("n_bytes")).agg(F.count("*").alias("n"))


@query(f"select concat_ws(' ', (src + 1)::varchar, (dst + 1)::varchar) as line from ({G['order_chain']})")
def edge_lines(spark, sf_dir):
    return spark.read.text(W.exported(spark, sf_dir, "order_chain", weighted=False)).select(F.col("value").alias("line"))


@query(edge_sql("supp_part"))
def parquet_roundtrip(spark, sf_dir):
    path = f"{shared_dir(spark)}/edges-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    W.graph(spark, sf_dir, "supp_part").write.mode("overwrite").parquet(path)
    return out(spark.read.parquet(path))


# --- degrees and scans ------------------------------------------------------


def _degree(name: str, sql: str, g: str = "supp_part", weight: str | None = None, **options):
    query(sql, name)(lambda spark, sf_dir: degrees(W.graph(spark, sf_dir, g), weight=weight, **options))


_degree("degree_native", degree_sql("supp_part"))
_degree("degree_global", degree_sql("supp_part"), method="global")
_degree("degree_task", degree_sql("supp_part"), method="task")
_degree("degree_in", degree_sql("order_part", "dst"), "order_part", direction="in")
_degree("degree_total", f"select v as vertex, count(*) as degree from (select unnest([src, dst]) as v from ({G['user_next']})) group by 1", "user_next", direction="both")
_degree("degree_weighted", degree_sql("order_part", agg="sum(weight)"), "order_part", "weight")


@query(degree_sql("supp_part"))
def degree_parts4(spark, sf_dir):
    return combine_degrees(read_edges(spark, W.exported(spark, sf_dir, "supp_part"), with_degrees="parts").degrees)


@query(f"select (dst % 4)::int as part, src as vertex, count(*) as degree from ({G['supp_part']}) group by all")
def part_degrees(spark, sf_dir):
    return partial_degrees(E.with_part(W.graph(spark, sf_dir, "supp_part"), 4, "dst_mod"))


@query(degree_sql("part_supp"))
def part_degree_sum(spark, sf_dir):
    return combine_degrees(partial_degrees(E.with_part(W.graph(spark, sf_dir, "part_supp"), 8, "hash")))


_SCAN = f"with d as ({degree_sql('part_supp')}) select vertex, degree, coalesce(sum(degree) over (order by vertex rows between unbounded preceding and 1 preceding), 0)::bigint as \"offset\" from d"


@query(_SCAN)
def scan_single(spark, sf_dir):
    return exclusive_scan(degrees(W.graph(spark, sf_dir, "part_supp")), "vertex", "degree", "single")


@query(_SCAN)
def scan_two_level(spark, sf_dir):
    return exclusive_scan(degrees(W.graph(spark, sf_dir, "part_supp")), "vertex", "degree", chunk=128)


@query(f"with d as (select (dst % 4)::int as part, src as vertex, count(*) as degree from ({G['part_supp']}) group by all) select part, vertex, degree, coalesce(sum(degree) over (partition by part order by vertex rows between unbounded preceding and 1 preceding), 0)::bigint as \"offset\" from d")
def scan_by_part(spark, sf_dir):
    return exclusive_scan(partial_degrees(E.with_part(W.graph(spark, sf_dir, "part_supp"), 4, "dst_mod")), "vertex", "degree", chunk=128, by=["part"])


# --- CSR --------------------------------------------------------------------


def _csr(name: str, g: str, build: str, what: str, **options):
    def run(spark, sf_dir):
        csr = read_csr(spark, W.exported(spark, sf_dir, g), build, **options)
        return csr.vertices if what == "offsets" else slots_out(csr.slots)

    query(offset_sql(g) if what == "offsets" else slot_sql(g), name)(run)


for _m in ("single", "staged", "sorted", "auto"):
    _csr(f"csr_{_m}_offsets", "supp_part", _m, "offsets")
    _csr(f"csr_{_m}_slots", "supp_part", _m, "slots")
for _g in ("nation_region", "order_chain", "part_size", "label_doc", "vec_label", "supp_nation", "nation_cust", "turns"):
    _csr(f"csr_{_g}", _g, "auto", "offsets")
_csr("csr_user_next_selfloops", "user_next", "sorted", "slots")
_csr("csr_isolated_vertices", "order_part", "staged", "offsets")
_csr("csr_weighted_prices", "cust_order", "sorted", "slots")


def _csr_k(k: int):
    def run(spark, sf_dir):
        g = Graph(E.with_part(W.graph(spark, sf_dir, "supp_part"), k, "dst_mod"), GraphMeta())
        return slots_out(C.build_csr(g, "staged", k, order="part").slots)

    query(slot_sql("supp_part", f"src, dst % {k}, dst, weight"), f"csr_k{k}")(run)


for _k in (1, 2, 4, 8, 16, 32):
    _csr_k(_k)


@query(
    f"""with e as ({G['part_supp']}), v as (select unnest(range(0, (select max(src) + 1 from e) + 1)) as vertex), p as (select unnest(range(0, 4))::int as part),
d as (select (dst % 4)::int as part, src as vertex, count(*) as degree from e group by all)
select part, vertex, coalesce(degree, 0) as degree, coalesce(sum(coalesce(degree, 0)) over (partition by part order by vertex rows between unbounded preceding and 1 preceding), 0)::bigint as "offset" from v cross join p left join d using (part, vertex)"""
)
def part_csr_offsets(spark, sf_dir):
    return C.build_part_csr(Graph(E.with_part(W.graph(spark, sf_dir, "part_supp"), 4, "dst_mod"), GraphMeta()), 4).vertices


@query(slot_sql("part_supp", "src, dst % 4, dst, weight"))
def csr_merge_order(spark, sf_dir):
    g = Graph(E.with_part(W.graph(spark, sf_dir, "part_supp"), 4, "dst_mod"), GraphMeta())
    return slots_out(C.merge_part_csr(C.build_part_csr(g, 4)).slots)


@query(offset_sql("copurchase_both", "greatest(max(src), max(dst)) + 1"))
def csr_symmetric(spark, sf_dir):
    return read_csr(spark, _mtx(spark, sf_dir, "copurchase", "pattern", "symmetric", True), "sorted", header="mtx").vertices


@query(f"{offset_sql('select dst as src, src as dst, weight from (' + G['part_size'] + ')')}")
def csr_transpose_offsets(spark, sf_dir):
    return C.transpose(graph_of(spark, sf_dir, "part_size")).vertices


@query(edge_sql("order_part"))
def csr_roundtrip(spark, sf_dir):
    return out(C.csr_to_edges(C.build_csr(graph_of(spark, sf_dir, "order_part"), "sorted")))


@query(offset_sql("user_k"))
def edges_to_csr_in_memory(spark, sf_dir):
    e = W.table(spark, sf_dir, "events").select("user_id", F.get_json_object("props", "$.k").alias("k"), "value")
    return C.edges_to_csr(e, "user_id", "k", "value", method="staged").vertices


_POS = f"select src as vertex, row_number() over (partition by src order by dst, weight) - 1 as pos, dst as target from ({G['part_supp']})"


@query(_POS)
def csr_adjacency(spark, sf_dir):
    rows = csr_forms.to_adjacency(C.build_csr(graph_of(spark, sf_dir, "part_supp"), "staged"))
    return rows.select("vertex", F.posexplode("targets").alias("pos", "target")).select("vertex", F.col("pos").cast("long").alias("pos"), "target")


@query(_POS.replace(G["part_supp"], G["nation_cust"]))
def csr_segments(spark, sf_dir):
    rows = csr_forms.to_segments(C.build_csr(graph_of(spark, sf_dir, "nation_cust"), "staged"), 16)
    return rows.select("vertex", "segment", F.posexplode("targets").alias("pos", "target")).select("vertex", (F.col("segment") * 16 + F.col("pos")).cast("long").alias("pos"), "target")


@query(slot_sql("part_supp"))
def csr_blocks_exploded(spark, sf_dir):
    return slots_out(csr_forms.from_blocks(csr_forms.to_blocks(C.build_csr(graph_of(spark, sf_dir, "part_supp"), "sorted"), 100)))


@query(f"select row_number() over (order by src, dst) - 1 as slot, dst as target from ({G['nation_region']})")
def csr_packed_exploded(spark, sf_dir):
    p = csr_forms.to_packed(C.build_csr(graph_of(spark, sf_dir, "nation_region"), "single"))
    return p.select(F.posexplode("targets").alias("slot", "target")).select(F.col("slot").cast("long").alias("slot"), "target")


@query(f"select src as vertex, sum(weight) as value from ({G['part_supp']}) group by 1")
def csr_block_kernel(spark, sf_dir):
    blocks = csr_forms.to_blocks(C.build_csr(graph_of(spark, sf_dir, "part_supp"), "sorted"), 128)
    return csr_forms.map_blocks(blocks, csr_forms.row_sums, "vertex long, value double").where("value > 0")


@query(slot_sql("part_supp"))
def csr_from_adjacency(spark, sf_dir):
    return slots_out(csr_forms.from_adjacency(csr_forms.to_segments(C.build_csr(graph_of(spark, sf_dir, "part_supp"), "staged"), 8)))


@query(slot_sql("supp_part"))
def neighbors_of(spark, sf_dir):
    csr = C.build_csr(graph_of(spark, sf_dir, "supp_part"), "sorted")
    return slots_out(C.neighbors(csr, csr.vertices))


@query(f"select vertex, \"offset\" as first_slot, \"offset\" + degree as end_slot from ({offset_sql('part_supp')}) where vertex < (select max(l_partkey) + 1 from lineitem)")
def slot_range(spark, sf_dir):
    csr = C.build_csr(graph_of(spark, sf_dir, "part_supp"), "staged")
    return C.slot_range(csr, csr.vertices.where(f"vertex < {csr.meta.n_rows}"))


@query(degree_sql("part_supp"))
def degree_of(spark, sf_dir):
    csr = C.build_csr(graph_of(spark, sf_dir, "part_supp"), "staged")
    return C.degree_of(csr, csr.slots.select("vertex"))


@query(slot_sql("part_supp"))
def csr_files_roundtrip(spark, sf_dir):
    path = f"{shared_dir(spark)}/csr-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    edgetext.write_csr(C.build_csr(graph_of(spark, sf_dir, "part_supp"), "sorted"), path)
    return slots_out(edgetext.read_csr_files(spark, path).slots)


@query(f"select n_nationkey::bigint as vertex, r_regionkey::bigint as target, exists (select 1 from ({G['nation_region']}) e where e.src = n_nationkey and e.dst = r_regionkey) as found from nation, region")
def edge_exists(spark, sf_dir):
    pairs = W.table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("vertex"), F.explode(F.array([F.lit(i).cast("long") for i in range(5)])).alias("target"))
    return C.has_edge(C.build_csr(graph_of(spark, sf_dir, "nation_region"), "single"), pairs)


@query(f"select degree, count(*) as n_vertices from ({degree_sql('order_part')}) group by 1", "degree_histogram")
def _degree_histogram(spark, sf_dir):
    return degree_histogram(degrees(W.graph(spark, sf_dir, "order_part")))


@query(f"select floor(log2(degree))::bigint as log2_degree, count(*) as n_vertices from ({degree_sql('order_part')}) group by 1")
def degree_log_bins(spark, sf_dir):
    return log_bins(degrees(W.graph(spark, sf_dir, "order_part")))


@query(f"select count(*) as n_vertices, sum(degree)::bigint as n_edges, min(degree) as min_degree, avg(degree) as avg_degree, max(degree) as max_degree, quantile_cont(degree, 0.5)::double as median_degree, quantile_cont(degree, 0.99)::double as p99_degree, max(degree) / sum(degree)::double as top_share from ({degree_sql('supp_part')})", "degree_stats")
def _degree_stats(spark, sf_dir):
    return degree_stats(degrees(W.graph(spark, sf_dir, "supp_part")))


def _stats_sql(g):
    return f"select '{g}' as graph, count(distinct src) as n_sources, count(distinct dst) as n_targets, greatest(max(src), max(dst)) + 1 as n_vertices, count(*) as n_edges from ({G[g]})"


@query(" union all ".join(_stats_sql(g) for g in W.INTEGER), "graph_stats")
def _graph_stats(spark, sf_dir):
    frames = [E.graph_stats(W.graph(spark, sf_dir, g)).select(F.lit(g).alias("graph"), "*") for g in W.INTEGER]
    first = frames[0]
    for f in frames[1:]:
        first = first.union(f)
    return first


@query(f"select * from ({degree_sql('part_supp')}) order by degree desc, vertex limit 10", "top_hubs")
def _top_hubs(spark, sf_dir):
    return top_hubs(degrees(W.graph(spark, sf_dir, "part_supp")), 10)


@query(f"select src as vertex, unnest(list(dst order by dst, weight)) as target from ({G['part_supp']}) group by 1")
def collect_list_csr(spark, sf_dir):
    return baselines.collect_list_csr(W.graph(spark, sf_dir, "part_supp"), 1)[1].select("vertex", F.explode("targets").alias("target"))


def _baseline(name, make):
    query(offset_sql("supp_part"), name)(lambda spark, sf_dir: make(spark, W.exported(spark, sf_dir, "supp_part")).vertices)
    query(slot_sql("supp_part"), name.replace("_csr", "_slots"))(lambda spark, sf_dir: slots_out(make(spark, W.exported(spark, sf_dir, "supp_part")).slots))


_baseline("sequential_line_csr", lambda s, p: baselines.sequential_csr(s, p))
_baseline("sequential_coordinate_csr", lambda s, p: baselines.sequential_csr(s, p, "coordinate"))
_baseline("two_pass_csr", baselines.two_pass_csr)

_RULES = ["offsets do not decrease", "first offset is 0", "last offset is the number of edges", "offsets differ by degrees", "slots are 0 to n-1", "slots lie in their vertex's range", "edges are kept as a multiset", "degrees sum to the number of edges", "each vertex has one row"]


def _invariants(method: str):
    sql = " union all ".join("select '{}' as rule, 0::bigint as violations".format(r.replace("'", "''")) for r in _RULES)

    def run(spark, sf_dir):
        g = graph_of(spark, sf_dir, "order_part")
        return invariants.check(C.build_csr(g, method), g.edges)

    query(sql, f"invariants_{method}")(run)


for _m in ("single", "staged", "sorted"):
    _invariants(_m)


# --- named graphs -----------------------------------------------------------


def _encoded_sql(names: str) -> str:
    return f"""with e as (select * from ({names}) where src_name <> ''), n as (select name, row_number() over (order by encode(name)) - 1 as v from (select src_name as name from e union select dst_name from e))
select a.v as src, b.v as dst from e join n a on a.name = src_name join n b on b.name = dst_name"""


@query(f"select src, count(*) as n_edges, sum(dst)::bigint as dst_sum from ({_encoded_sql(NAMES['word_doc'])}) group by 1")
def encode_word_doc(spark, sf_dir):
    """Every edge of the encoded graph takes part; sums per source keep the SQL side small."""
    return E.encode_vertices(W.graph(spark, sf_dir, "word_doc"))[0].groupBy("src").agg(F.count("*").alias("n_edges"), F.sum("dst").alias("dst_sum"))


@query(f"select src_name, dst_name from ({NAMES['kmer8'].replace(' 8', ' 16').replace('> 8', '> 16').replace('- 8', '- 16')})")
def kmer16_edges(spark, sf_dir):
    return W.graph(spark, sf_dir, "kmer16").select("src_name", "dst_name")


@query("select dst_name as src_name, src_name as dst_name from (" + NAMES["word_doc"] + ") where src_name <> ''")
def doc_word_edges(spark, sf_dir):
    return W.graph(spark, sf_dir, "word_doc").select(F.col("dst_name").alias("src_name"), F.col("src_name").alias("dst_name"))


@query("select unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as src_name, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as dst_name from pages")
def link_host_edges(spark, sf_dir):
    return W.graph(spark, sf_dir, "host_link").select(F.col("dst_name").alias("src_name"), F.col("src_name").alias("dst_name"))


@query(offset_sql(_encoded_sql(NAMES["word_doc"]).replace("b.v as dst", "b.v as dst, 1.0 as weight")))
def csr_strings_word_doc(spark, sf_dir):
    e, _ = E.encode_vertices(W.graph(spark, sf_dir, "word_doc"))
    return C.build_csr(Graph(e.select("src", "dst", "weight"), GraphMeta()), "sorted").vertices


@query(offset_sql(_encoded_sql(NAMES["kmer8"]).replace("b.v as dst", "b.v as dst, 1.0 as weight")))
def csr_kmer(spark, sf_dir):
    e, _ = E.encode_vertices(W.graph(spark, sf_dir, "kmer8"))
    return C.build_csr(Graph(e.select("src", "dst", "weight"), GraphMeta()), "auto").vertices


@query(f"select src_name, dst_name from ({NAMES['kmer8']})")
def kmer_edges(spark, sf_dir):
    e, d = E.encode_vertices(W.graph(spark, sf_dir, "kmer8"))
    return E.decode_vertices(e, d).select("src_name", "dst_name")


@query("select regexp_extract(url, '^[a-z]+://([^/]+)', 1) as src_name, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as dst_name from pages")
def host_link_edges(spark, sf_dir):
    return W.graph(spark, sf_dir, "host_link").select("src_name", "dst_name")


for _g in ("user_k", "copurchase", "order_chain", "user_next", "turns"):
    query(edge_sql(_g), f"{_g}_edges")(lambda spark, sf_dir, g=_g: out(W.graph(spark, sf_dir, g)))


# --- graph operators --------------------------------------------------------


def _bfs(g):
    """Levels from the least vertex with an edge, over the whole graph."""
    sql = f"""with recursive e as (select distinct src, dst from ({G[g]})),
r(vertex, level) using key (vertex) as (select min(src), 0 from e union select e.dst, min(r.level) + 1 from r join e on e.src = r.vertex where e.dst not in (select vertex from recurring.r) group by 1)
select vertex, level::int as level from r"""

    def run(spark, sf_dir):
        e = W.graph(spark, sf_dir, g)
        return graphops.bfs_levels(e, e.agg(F.min("src")).first()[0])

    query(sql, f"bfs_levels_{g}")(run)


for _g in ("user_next", "order_chain"):
    _bfs(_g)


@query("select o_orderkey as vertex, min(o_orderkey) over (partition by o_custkey) as component from orders where o_custkey in (select o_custkey from orders group by 1 having count(*) > 1)")
def connected_components(spark, sf_dir):
    return graphops.connected_components(W.graph(spark, sf_dir, "order_chain"))


@query(f"select src as vertex, sum(weight * (dst % 7)) as value from ({G['order_part']}) group by 1", "spmv")
def _spmv(spark, sf_dir):
    e = W.graph(spark, sf_dir, "order_part")
    return graphops.spmv(e, e.select(F.col("dst").alias("vertex")).distinct().withColumn("value", (F.col("vertex") % 7).cast("double")))


@query(f"select a.src, b.dst, count(*) as n_paths from ({G['order_chain']}) a join ({G['order_chain']}) b on a.dst = b.src group by all", "two_hop")
def _two_hop(spark, sf_dir):
    return graphops.two_hop(W.graph(spark, sf_dir, "order_chain"))


@query(
    f"""with e as (select distinct src, dst from ({G['supp_part']})), p as (select s_suppkey as a, s_suppkey + 1 as b from supplier),
n as (select x.src as a, y.src as b, count(*) as n_common from e x join e y on x.dst = y.dst and y.src = x.src + 1 group by all)
select a, b, coalesce(n_common, 0) as n_common from p left join n using (a, b)""",
    "common_neighbors",
)
def _common_neighbors(spark, sf_dir):
    pairs = W.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("a"), (F.col("s_suppkey") + 1).alias("b"))
    return graphops.common_neighbors(W.graph(spark, sf_dir, "supp_part"), pairs)


@query(f"with e as (select distinct least(src, dst) as a, greatest(src, dst) as b from ({G['user_next']}) where src <> dst) select count(*) as n_triangles from e x join e y on x.b = y.a join e z on z.a = x.a and z.b = y.b", "triangle_count")
def _triangles(spark, sf_dir):
    return graphops.triangle_count(W.graph(spark, sf_dir, "user_next"))


@query(
    f"""with e as ({G['user_next']}), o as (select src, count(*) as d from e group by 1), n as (select (select greatest(max(src), max(dst)) + 1 from e) as n), v as (select unnest(range(0, (select n from n))) as vertex),
r1 as (select vertex, 0.15 / n + 0.85 * coalesce(s, 0) as rank from v cross join n left join (select dst as vertex, sum(1.0::double / n / d) as s from e join o using (src) cross join n group by 1) using (vertex)),
r2 as (select vertex, 0.15 / n + 0.85 * coalesce(s, 0) as rank from v cross join n left join (select dst as vertex, sum(rank / d) as s from e join o using (src) join r1 on r1.vertex = src group by 1) using (vertex))
select vertex, round(rank * 1000000, 3)::double as rank from r2"""
)
def pagerank_two_rounds(spark, sf_dir):
    e = W.graph(spark, sf_dir, "user_next")
    n = e.agg(F.greatest(F.max("src"), F.max("dst"))).first()[0] + 1
    return graphops.pagerank(e, n, 2).select("vertex", F.round(F.col("rank") * 1000000, 3).alias("rank"))


@query(
    f"""with e as ({G['user_next']}), d as (select v, row_number() over (order by count(*) desc, v) - 1 as n from (select unnest([src, dst]) as v from e) group by v)
select a.n as src, b.n as dst from e join d a on a.v = src join d b on b.v = dst"""
)
def relabel_by_degree(spark, sf_dir):
    return graphops.relabel_by_degree(W.graph(spark, sf_dir, "user_next")).select("src", "dst")


@query(f"select src, dst, weight, 'left' as side from (select * from ({G['supp_part']}) except all select * from ({G['supp_part']}) where src % 10 <> 0) union all select src, dst, weight, 'right' from ({G['supp_part']}) where false")
def diff_graphs(spark, sf_dir):
    e = W.graph(spark, sf_dir, "supp_part")
    return E.diff_graphs(e, e.where("src % 10 <> 0")).select("src", "dst", F.col("weight").cast("double").alias("weight"), "side")


@query(
    """with e as (select vec_id, embedding::double[] as v from embeddings where embedding is not null), n as (select vec_id, v, sqrt(list_dot_product(v, v)) as l from e),
p as (select a.vec_id as src, b.vec_id as dst, round(list_dot_product(a.v, b.v) / (a.l * b.l), 4) as weight from n a join n b on a.vec_id <> b.vec_id)
select src, dst, weight from (select *, row_number() over (partition by src order by weight desc, dst) as r from p) where r <= 5"""
)
def vec_knn(spark, sf_dir):
    return W.vec_knn(spark, sf_dir)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_csr(spark, W.exported(spark, sf_dir, "supp_part"), "staged").vertices


def queries():
    return {**QUERIES, **query_families.QUERIES}


def oracle_sql():
    return {**SQL, **query_families.SQL}
