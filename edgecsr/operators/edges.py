"""Edge-list operators: projections, direction, subgraphs, duplicates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgecsr.session import materialize


def project(df: DataFrame, src: str | Column, dst: str | Column, weight: str | Column | None = None) -> DataFrame:
    """Any DataFrame as an edge list; weight 1 where there is none."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    w = F.lit(1.0) if weight is None else col(weight)
    return df.select(col(src).cast("long").alias("src"), col(dst).cast("long").alias("dst"), w.cast("float").alias("weight"))


def rebase(edges: DataFrame, base: int = 1) -> DataFrame:
    return edges.withColumns({"src": F.col("src") - base, "dst": F.col("dst") - base})


def reverse(edges: DataFrame) -> DataFrame:
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest)


def symmetrize(edges: DataFrame, self_loops: str = "once", sign: int = 1) -> DataFrame:
    """Each edge and its reverse from one scan. Diagonal entries come once, or twice with ``self_loops='double'``.

    ``sign=-1`` negates the reverse (skew-symmetric).
    """
    rest = [c for c in edges.columns if c not in ("src", "dst", "weight")]
    one = F.struct(F.col("src"), F.col("dst"), F.col("weight"))
    two = F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), (F.col("weight") * F.lit(float(sign)).cast("float")).alias("weight"))
    both = F.array(one, two)
    if self_loops == "once":
        both = F.when(F.col("src") == F.col("dst"), F.array(one)).otherwise(both)
    elif self_loops != "double":
        raise ValueError("self_loops is 'once' or 'double'")
    return edges.select(*rest, F.inline(both)).select("src", "dst", "weight", *rest)


def with_part(edges: DataFrame, parts: int, key: str = "dst_range", n_cols: int | None = None) -> DataFrame:
    """Part of each edge by its own values: ranges of targets (keeps the canonical order), targets modulo k, or a hash."""
    if key == "dst_mod":
        part = F.pmod(F.col("dst"), F.lit(parts))
    elif key == "dst_range":
        width = n_cols if n_cols is not None else edges.agg(F.max("dst")).first()[0]
        part = F.least(F.lit(parts - 1), F.floor(F.col("dst") * F.lit(float(parts)) / F.lit(float((width or 0) + 1))))
    elif key == "hash":
        part = F.pmod(F.xxhash64("src", "dst", "weight"), F.lit(parts))
    else:
        raise ValueError("key is 'dst_range', 'dst_mod' or 'hash'")
    return edges.withColumn("part", part.cast("int"))


def edges_per_part(edges: DataFrame) -> DataFrame:
    return edges.groupBy("part").agg(F.count("*").alias("n_edges"))


def drop_self_loops(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst")


def upper_triangle(edges: DataFrame) -> DataFrame:
    return edges.where("src < dst")


def lower_triangle(edges: DataFrame) -> DataFrame:
    return edges.where("src > dst")


def vertex_range(edges: DataFrame, low: int, high: int) -> DataFrame:
    return edges.where(F.col("src").between(low, high))


def induced_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends in ``vertices`` (vertex)."""
    v = vertices.select(F.col("vertex").alias("src"))
    return edges.join(v, "src", "left_semi").join(v.withColumnRenamed("src", "dst"), "dst", "left_semi").select(edges.columns)


def clean_weights(edges: DataFrame, policy: str = "drop", value: float = 1.0) -> DataFrame:
    """Null and NaN weights: drop the edge, or set the weight."""
    w = F.nanvl("weight", F.lit(None).cast("float"))
    if policy == "drop":
        return edges.where(w.isNotNull())
    return edges.withColumn("weight", F.coalesce(w, F.lit(value).cast("float")))


def dedup(edges: DataFrame, how: str = "first") -> DataFrame:
    """Parallel edges as one; ``first`` is the least weight in canonical order."""
    agg = {"first": F.min, "min": F.min, "max": F.max, "sum": F.sum}[how]("weight")
    return edges.groupBy("src", "dst").agg(agg.cast("float").alias("weight"))


def sample_edges(edges: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """The same edges at every run, whatever the partitioning."""
    return edges.where(F.pmod(F.xxhash64("src", "dst", "weight", F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))


def encode_vertices(edges: DataFrame, src: str = "src_name", dst: str = "dst_name") -> tuple[DataFrame, DataFrame]:
    """(edges with numbers, dictionary vertex/name): names numbered in their order, without a single-task sort.

    The named edges are written first, so that what makes them (often a split of whole texts) runs once.
    """
    from edgecsr.operators.scan import number_rows

    edges = materialize(edges, "named")
    names = edges.select(F.explode(F.array(src, dst)).alias("name")).where("name is not null").distinct()
    dictionary = number_rows(names, ["name"], "vertex")
    a, b = dictionary.select(F.col("name").alias(src), F.col("vertex").alias("src")), dictionary.select(F.col("name").alias(dst), F.col("vertex").alias("dst"))
    return edges.join(a, src).join(b, dst).select("src", "dst", *[c for c in edges.columns if c not in (src, dst)]), dictionary


def decode_vertices(edges: DataFrame, dictionary: DataFrame) -> DataFrame:
    a, b = dictionary.select(F.col("vertex").alias("src"), F.col("name").alias("src_name")), dictionary.select(F.col("vertex").alias("dst"), F.col("name").alias("dst_name"))
    return edges.join(a, "src").join(b, "dst").select("src_name", "dst_name", "weight")


def checksum(edges: DataFrame) -> DataFrame:
    """Number of edges and an order-free sum of their hashes."""
    return edges.agg(F.count("*").alias("n_edges"), F.sum(F.xxhash64("src", "dst", "weight").cast("decimal(38,0)")).alias("checksum"))


def diff_graphs(a: DataFrame, b: DataFrame) -> DataFrame:
    """Edges of one multiset that the other lacks, with the side."""
    cols = ["src", "dst", "weight"]
    return a.select(cols).exceptAll(b.select(cols)).withColumn("side", F.lit("left")).union(b.select(cols).exceptAll(a.select(cols)).withColumn("side", F.lit("right")))


def graph_stats(edges: DataFrame) -> DataFrame:
    return edges.agg(F.countDistinct("src").alias("n_sources"), F.countDistinct("dst").alias("n_targets"), F.coalesce(F.greatest(F.max("src"), F.max("dst")) + 1, F.lit(0)).alias("n_vertices"), F.count("*").alias("n_edges"))
