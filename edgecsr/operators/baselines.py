"""The loaders that the staged loader is compared with, as Spark plans with the same bottlenecks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgecsr.functions.parse import parse_lines
from edgecsr.operators.csr import build_single, offsets
from edgecsr.operators.degrees import degrees
from edgecsr.operators.readers import read_edges, settled
from edgecsr.schema import Csr, Graph, GraphMeta
from edgecsr.session import materialize
from edgecsr.sources.block_source import scan_slices


def sequential_csr(spark: SparkSession, path: str, flavour: str = "line", **options) -> Csr:
    """One task for everything. ``coordinate`` writes the whole edge list before degrees, scan and fill start.

    Degrees are written once: the number of vertices is read off them, so the text is parsed for degrees and for the fill, not once more.
    """
    graph = read_edges(spark, path, method="serial", **options)
    if flavour == "coordinate":
        graph.edges = materialize(graph.edges, "coordinate")
    graph.edges = graph.edges.coalesce(1)
    counted = materialize(degrees(graph.edges), "degrees")
    if graph.meta.n_rows is None and not graph.meta.symmetric:
        graph.meta = graph.meta.having(n_rows=(counted.agg(F.coalesce(F.max("vertex"), F.lit(-1))).first()[0]) + 1)
    return build_single(graph, counted=counted)


def two_pass_edges(spark: SparkSession, path: str, weighted: bool = True, index_base: int = 1, slices: int | None = None) -> DataFrame:
    """Edges with their place in one global list: the text is read once to count and once to parse.

    Slices are equal and static. The second pass places each slice's edges
    after those of the slices before it.
    """
    lines = scan_slices(spark, path, slices or spark.sparkContext.defaultParallelism)
    counted = lines.groupBy("slice").agg(F.count("*").alias("n"))
    w = Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    bases = counted.select("slice", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("base"))  # one row per slice: their number is an argument
    parsed, _ = parse_lines(lines, "direct", weighted, index_base)
    return parsed.join(F.broadcast(bases), "slice").select((F.col("base") + F.col("at")).alias("edge_index"), "src", "dst", "weight")


def two_pass_csr(spark: SparkSession, path: str, **options) -> Csr:
    """Global degrees and a fill by whole vertices over the two-pass edge list, which is written once; symmetric input keeps its stored triangle."""
    return build_single(settled(Graph(two_pass_edges(spark, path, **options).select("src", "dst", "weight"), GraphMeta())), "global")


def builtin_csv(spark: SparkSession, path: str, weighted: bool = True, index_base: int = 1, sep: str = " ") -> DataFrame:
    """Spark's own delimited reader with a fixed schema."""
    schema = "src long, dst long" + (", weight float" if weighted else "")
    df = spark.read.schema(schema).option("sep", sep).option("comment", "%").csv(path)
    return df.select((F.col("src") - index_base).alias("src"), (F.col("dst") - index_base).alias("dst"), F.coalesce("weight", F.lit(1.0).cast("float")).alias("weight") if weighted else F.lit(1.0).cast("float").alias("weight"))


def collect_list_csr(edges: DataFrame, n_rows: int) -> tuple[DataFrame, DataFrame]:
    """(vertices, adjacency rows): each vertex gathers its list in one row."""
    rows = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "weight"))).alias("run"))
    lists = rows.select(F.col("src").alias("vertex"), F.col("run.dst").alias("targets"), F.col("run.weight").alias("weights"))
    return offsets(degrees(edges), n_rows), lists
