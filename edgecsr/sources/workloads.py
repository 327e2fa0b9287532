"""The given tables as graphs, and their text exports."""

from __future__ import annotations

import os
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgecsr.operators.edges import project
from edgecsr.session import shared_dir
from edgecsr.sources.edgetext import write_edges

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {name: table(spark, sf_dir, name) for name in TABLES}


def _copurchase(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = li.withColumnRenamed("l_partkey", "a"), li.withColumnRenamed("l_partkey", "b")
    return project(a.join(b, "l_orderkey").where("a < b").select("a", "b").distinct(), "a", "b")


def _order_chain(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_orderkey")
    return project(o.withColumn("next", F.lead("o_orderkey").over(w)).where("next is not null"), "o_orderkey", "next")


def _user_next(spark, sf_dir):
    """A chain over all events: hours are ordered apart, and each hour's last user meets the next hour's first."""
    e = table(spark, sf_dir, "events").select("ts", "event_id", "user_id").withColumn("hour", F.date_trunc("hour", "ts"))
    w = Window.partitionBy("hour").orderBy("ts", "event_id")
    inside = e.withColumn("next", F.lead("user_id").over(w))
    first = e.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    after = first.select("hour", F.lead("first").over(Window.orderBy("hour")).alias("following"))  # one row per hour
    return project(inside.join(after, "hour").withColumn("next", F.coalesce("next", "following")).where("next is not null"), "user_id", "next")


def _turns(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn").withColumn("next", F.lead("turn").over(w)).where("next is not null")
    return project(c, F.col("conv_id") * 1000 + F.col("turn"), F.col("conv_id") * 1000 + F.col("next"))


def _simple(name, src, dst, weight=None):
    return lambda spark, sf_dir: project(table(spark, sf_dir, name), src, dst, weight)


INTEGER = {
    "supp_part": _simple("lineitem", "l_suppkey", "l_partkey", "l_quantity"),
    "part_supp": _simple("lineitem", "l_partkey", "l_suppkey", "l_quantity"),
    "order_part": _simple("lineitem", "l_orderkey", "l_partkey", "l_quantity"),
    "cust_order": _simple("orders", "o_custkey", "o_orderkey", "o_totalprice"),
    "nation_region": _simple("nation", "n_nationkey", "n_regionkey"),
    "nation_cust": _simple("customer", "c_nationkey", "c_custkey"),
    "supp_nation": _simple("supplier", "s_suppkey", "s_nationkey"),
    "part_size": _simple("part", "p_size", "p_partkey", "p_retailprice"),
    "label_doc": _simple("labels", "quality", "doc_id"),
    "vec_label": _simple("embeddings", "label", "vec_id"),
    "user_k": lambda spark, sf_dir: project(table(spark, sf_dir, "events"), "user_id", F.get_json_object("props", "$.k"), "value"),
    "copurchase": _copurchase,
    "order_chain": _order_chain,
    "user_next": _user_next,
    "turns": _turns,
}


def _word_doc_ids(spark, sf_dir):
    """Words and documents as numbers: a few words have very many edges."""
    from edgecsr.operators.edges import encode_vertices

    return encode_vertices(_word_doc(spark, sf_dir))[0].select("src", "dst", "weight")


def _word_doc(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), r"\s+")).alias("src_name"))
    return d.where("src_name <> ''").select("src_name", F.col("doc_id").cast("string").alias("dst_name"), F.lit(1.0).cast("float").alias("weight"))


def _host_link(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("src_name"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("dst_name"))
    return p.withColumn("weight", F.lit(1.0).cast("float"))


def kmer(spark, sf_dir, k: int) -> DataFrame:
    """Consecutive overlapping windows of k characters of each text, distinct pairs."""
    b = table(spark, sf_dir, "benchmark").where(F.length("text") > k)
    at = F.explode(F.sequence(F.lit(1), F.length("text") - k))
    pairs = b.select("text", at.alias("i")).select(F.expr(f"substring(text, i, {k})").alias("src_name"), F.expr(f"substring(text, i + 1, {k})").alias("dst_name"))
    return pairs.distinct().withColumn("weight", F.lit(1.0).cast("float"))


#: Integer graphs that are made from named ones.
ENCODED = {"word_doc_ids": _word_doc_ids}
NAMED = {"word_doc": _word_doc, "host_link": _host_link, "kmer8": lambda s, d: kmer(s, d, 8), "kmer16": lambda s, d: kmer(s, d, 16)}


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(src, dst, weight) of an integer graph, (src_name, dst_name, weight) of a named one."""
    return (INTEGER.get(name) or ENCODED.get(name) or NAMED[name])(spark, sf_dir)


def vec_knn(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 2048) -> DataFrame:
    """The k nearest vectors of each by cosine, exactly: blocks of vectors meet blocks in matrix products, and each pair of blocks sends k rows a vector."""
    e = table(spark, sf_dir, "embeddings").where(F.col("embedding").isNotNull()).select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    n = max(1, -(-e.count() // block))
    blocks = e.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(n)).alias("b")).agg(F.collect_list(F.struct("vec_id", "v")).alias("rows"))  # about ``block`` rows each
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    pairs = blocks.select(F.col("b").alias("i"), F.col("rows").alias("left"), every.alias("j")).join(blocks.select(F.col("b").alias("j"), F.col("rows").alias("right"), every.alias("i")), ["i", "j"])

    def arrays(scalar):
        ids = scalar.values.field("vec_id").to_numpy()
        m = scalar.values.field("v").flatten().to_numpy().reshape(len(ids), -1)
        return ids, m / np.sqrt((m * m).sum(1, keepdims=True))

    def run(batches):
        for batch in batches:
            for r in range(batch.num_rows):
                (a, ma), (b, mb) = (arrays(batch.column(c)[r]) for c in ("left", "right"))
                score = np.round(ma @ mb.T, 4)
                score[a[:, None] == b] = -np.inf
                top = min(k, len(b))
                order = np.lexsort((np.broadcast_to(b, score.shape), -score), axis=1)[:, :top]
                src, w = np.repeat(a, top), np.take_along_axis(score, order, 1).ravel()
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(b[order].ravel()), pa.array(w)], ["src", "dst", "weight"]).filter(pa.array(np.isfinite(w)))

    found = pairs.select("left", "right").mapInArrow(run, "src long, dst long, weight double")
    w = Window.partitionBy("src").orderBy(F.col("weight").desc(), "dst")
    return found.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).select("src", "dst", "weight")


_EXPORTED: dict[tuple, str] = {}


def exported(spark: SparkSession, sf_dir: str, name: str, sep: str = " ", index_base: int = 1, weighted: bool = True, files: int | None = None, **more) -> str:
    """Path of the graph's text export; written once for a session."""
    key = (spark.sparkContext.applicationId, os.getpid(), sf_dir, name, sep, index_base, weighted, files, *sorted(more.items()))
    if key not in _EXPORTED:
        path = f"{shared_dir(spark)}/text-{name}-{uuid.uuid4().hex}"
        edges = graph(spark, sf_dir, name)
        write_edges(edges.repartition(files) if files else edges, path, sep, index_base, weighted, **more)
        _EXPORTED[key] = path
    return _EXPORTED[key]
