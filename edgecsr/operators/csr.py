"""Edge list to compressed sparse rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.operators.degrees import combine_degrees, degrees, densify, partial_degrees
from edgecsr.operators.edges import project, reverse, with_part
from edgecsr.operators.scan import exclusive_scan, number_rows
from edgecsr.schema import Csr, Graph, GraphMeta, PartCsr

METHODS = ("single", "staged", "sorted", "auto")


def n_vertices(graph: Graph) -> int:
    """Rows of the matrix: told by the header or the caller, else one more than the greatest source (both ends if symmetric)."""
    if graph.meta.n_rows is not None:
        return graph.meta.n_rows
    top = F.greatest(F.max("src"), F.max("dst")) if graph.meta.symmetric else F.max("src")
    found = graph.edges.agg(top).first()[0]
    return 0 if found is None else found + 1


def offsets(found: DataFrame, n: int, method: str = "two_level", sentinel: bool = True) -> DataFrame:
    """(vertex, degree, offset) with the closing row."""
    return exclusive_scan(densify(found, n, sentinel), "vertex", "degree", method, n_keys=n + 1, sparse=found)


def _before(*partition: str):
    return Window.partitionBy(*partition).orderBy("dst", "weight").rowsBetween(Window.unboundedPreceding, -1)


def _rank(*partition: str):
    """Position inside a group as a 64-bit running count."""
    return F.coalesce(F.sum(F.lit(1).cast("long")).over(_before(*partition)), F.lit(0))


def build_single(graph: Graph, degree_method: str = "global", counted: DataFrame | None = None) -> Csr:
    """Global degrees (``counted``, where they are known), global offsets, and each vertex fills its range in one task."""
    n = n_vertices(graph)
    vertices = offsets(degrees(graph.edges, degree_method) if counted is None else counted, n)
    slots = graph.edges.withColumn("_r", _rank("src")).join(vertices.select(F.col("vertex").alias("src"), "offset"), "src")
    return Csr(vertices, slots.select((F.col("offset") + F.col("_r")).alias("slot"), F.col("src").alias("vertex"), F.col("dst").alias("target"), "weight"), graph.meta.having(n_rows=n))


def build_part_csr(graph: Graph, parts: int) -> PartCsr:
    """One CSR for each part over all vertices; ``edges`` have a ``part``. A hot vertex is split over the parts."""
    n = n_vertices(graph)
    own = partial_degrees(graph.edges)
    every = graph.edges.sparkSession.range(n + 1).withColumnRenamed("id", "vertex").crossJoin(F.broadcast(graph.edges.sparkSession.range(parts).select(F.col("id").cast("int").alias("part"))))
    dense = every.join(own, ["part", "vertex"], "left").select("part", "vertex", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))
    vertices = exclusive_scan(dense, "vertex", "degree", by=["part"])
    slots = graph.edges.withColumn("_r", _rank("part", "src")).join(vertices.select("part", F.col("vertex").alias("src"), "offset"), ["part", "src"])
    return PartCsr(vertices, slots.select("part", (F.col("offset") + F.col("_r")).alias("slot"), F.col("src").alias("vertex"), F.col("dst").alias("target"), "weight"), parts, graph.meta.having(n_rows=n))


def merge_part_csr(part_csr: PartCsr) -> Csr:
    """Every vertex takes its run from part 0, then 1, ..., at its global offset."""
    n = part_csr.meta.n_rows
    vertices = offsets(combine_degrees(part_csr.vertices).where("degree > 0"), n)
    earlier = Window.partitionBy("vertex").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = part_csr.vertices.where("degree > 0").select("part", "vertex", F.col("offset").alias("_own"), F.coalesce(F.sum("degree").over(earlier), F.lit(0)).alias("_earlier"))
    base = base.join(vertices.select("vertex", F.col("offset").alias("_global")), "vertex")
    slots = part_csr.slots.join(base, ["part", "vertex"])
    return Csr(vertices, slots.select((F.col("_global") + F.col("_earlier") + F.col("slot") - F.col("_own")).alias("slot"), "vertex", "target", "weight"), part_csr.meta)


def build_staged(graph: Graph, parts: int = 4, part_key: str | None = "dst_range") -> Csr:
    """k part degrees and ranks, then one place for each edge: offset, smaller parts, rank in the part.

    Parts that are ranges of targets give the canonical order; ``part_key=None``
    takes the parts that the edges have, in their order.
    """
    n = n_vertices(graph)
    edges = graph.edges if part_key is None else with_part(graph.edges, parts, part_key, graph.meta.n_cols)
    own = partial_degrees(edges)
    vertices = offsets(combine_degrees(own), n)
    earlier = Window.partitionBy("vertex").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = own.select("part", F.col("vertex").alias("src"), F.coalesce(F.sum("degree").over(earlier), F.lit(0)).alias("_earlier"))
    base = base.join(vertices.select(F.col("vertex").alias("src"), "offset"), "src")
    slots = edges.withColumn("_r", _rank("part", "src")).join(base, ["part", "src"])
    return Csr(vertices, slots.select((F.col("offset") + F.col("_earlier") + F.col("_r")).alias("slot"), F.col("src").alias("vertex"), F.col("dst").alias("target"), "weight"), graph.meta.having(n_rows=n))


def build_sorted(graph: Graph, partitions: int | None = None) -> Csr:
    """The edge list sorted by (source, target, weight) is the CSR: one range exchange, hubs split by their targets."""
    n = n_vertices(graph)
    slots = number_rows(graph.edges.select("src", "dst", "weight"), ["src", "dst", "weight"], "slot", partitions)
    slots = slots.select("slot", F.col("src").alias("vertex"), F.col("dst").alias("target"), "weight")
    return Csr(offsets(degrees(slots.select(F.col("vertex").alias("src"))), n), slots, graph.meta.having(n_rows=n))


def build_csr(graph: Graph, method: str = "auto", parts: int = 4, order: str = "canonical", partitions: int | None = None, **thresholds) -> Csr:
    """CSR of a graph.

    single  the study's one-stage build (its choice for low degrees)
    staged  its k-part build (its choice for high degrees and hubs)
    sorted  range-sorted build, one exchange of the edges, for the largest inputs
    auto    by degree statistics, see ``plans.planner``
    ``order='part'`` keeps the parts' order inside a vertex (parts of the edges, or targets modulo k).
    """
    if method == "auto":
        from edgecsr.plans.planner import choose_method

        method = choose_method(graph, **thresholds)
    if order == "part":
        return build_staged(graph, parts, None if "part" in graph.edges.columns else "dst_mod")
    if method == "single":
        return build_single(graph)
    if method == "staged":
        return build_staged(graph, parts)
    if method == "sorted":
        return build_sorted(graph, partitions)
    raise ValueError(f"method must be one of {METHODS}")


def edges_to_csr(df: DataFrame, src, dst, weight=None, n_rows: int | None = None, method: str = "auto", **options) -> Csr:
    """CSR of any DataFrame, no file involved."""
    return build_csr(Graph(project(df, src, dst, weight), GraphMeta(n_rows=n_rows, weighted=weight is not None)), method, **options)


def csr_to_edges(csr: Csr) -> DataFrame:
    return csr.slots.select(F.col("vertex").alias("src"), F.col("target").alias("dst"), "weight")


def transpose(graph: Graph, method: str = "sorted") -> Csr:
    m = graph.meta
    return build_csr(Graph(reverse(graph.edges.select("src", "dst", "weight")), m.having(n_rows=m.n_cols, n_cols=m.n_rows)), method)


def neighbors(csr: Csr, vertices: DataFrame) -> DataFrame:
    """Slots of the given vertices (vertex)."""
    return csr.slots.join(vertices.select("vertex").distinct(), "vertex", "left_semi")


def degree_of(csr: Csr, vertices: DataFrame) -> DataFrame:
    """(vertex, degree) of the given vertices; what is no vertex of the graph has degree 0."""
    asked = vertices.select("vertex").distinct()
    return asked.join(csr.vertices.select("vertex", "degree"), "vertex", "left").select("vertex", F.coalesce("degree", F.lit(0)).alias("degree"))


def slot_range(csr: Csr, vertices: DataFrame) -> DataFrame:
    return csr.vertices.join(vertices.select("vertex").distinct(), "vertex").select("vertex", F.col("offset").alias("first_slot"), (F.col("offset") + F.col("degree")).alias("end_slot"))


def has_edge(csr: Csr, pairs: DataFrame) -> DataFrame:
    """(vertex, target, found) of asked pairs."""
    have = csr.slots.select("vertex", "target").distinct().withColumn("found", F.lit(True))
    return pairs.join(have, ["vertex", "target"], "left").select("vertex", "target", F.coalesce("found", F.lit(False)).alias("found"))
