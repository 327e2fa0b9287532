"""Degrees of vertices by the variants that the study compares."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

METHODS = ("native", "global", "task", "parts")


def _ends(edges: DataFrame, direction: str, weight: str | None) -> DataFrame:
    add = F.lit(1).cast("long") if weight is None else F.col(weight).cast("double")
    rest = [c for c in ("part",) if c in edges.columns]
    if direction == "both":
        return edges.select(F.explode(F.array("src", "dst")).alias("vertex"), add.alias("_one"), *rest)
    return edges.select(F.col("src" if direction == "out" else "dst").alias("vertex"), add.alias("_one"), *rest)


def partial_degrees(edges: DataFrame, direction: str = "out", weight: str | None = None) -> DataFrame:
    """(part, vertex, degree): counters private to a part; a hot vertex is counted in each part."""
    return _ends(edges, direction, weight).groupBy("part", "vertex").agg(F.sum("_one").alias("degree"))


def combine_degrees(partial: DataFrame) -> DataFrame:
    return partial.groupBy("vertex").agg(F.sum("degree").alias("degree"))


def degrees(edges: DataFrame, method: str = "native", direction: str = "out", weight: str | None = None, parts: int = 4) -> DataFrame:
    """(vertex, degree) of the vertices that have edges.

    native  map-side counts and one exchange of them
    global  every edge crosses the exchange to its vertex: what a shared counter costs
    task    counts per input task, then their sum
    parts   counts per part (k of them), then their sum
    """
    ends = _ends(edges, direction, weight)
    if method == "native":
        found = ends.groupBy("vertex").agg(F.sum("_one").alias("degree"))
    elif method == "global":
        found = ends.repartition("vertex").groupBy("vertex").agg(F.sum("_one").alias("degree"))
    elif method == "task":
        own = ends.withColumn("part", F.spark_partition_id())  # only a label of private counters; sums do not depend on it
        found = combine_degrees(own.groupBy("part", "vertex").agg(F.sum("_one").alias("degree")))
    elif method == "parts":
        dealt = ends if "part" in ends.columns else ends.withColumn("part", F.pmod(F.spark_partition_id(), F.lit(parts)))
        found = combine_degrees(dealt.groupBy("part", "vertex").agg(F.sum("_one").alias("degree")))
    else:
        raise ValueError(f"method must be one of {METHODS}")
    return found if isinstance(found.schema["degree"].dataType, LongType) or weight else found.withColumn("degree", F.col("degree").cast("long"))


def densify(found: DataFrame, n_vertices: int, sentinel: bool = True) -> DataFrame:
    """A row for every vertex, degree 0 where it has no edges, and the closing row that offsets need."""
    every = found.sparkSession.range(n_vertices + (1 if sentinel else 0)).withColumnRenamed("id", "vertex")
    return every.join(found, "vertex", "left").select("vertex", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def degree_stats(found: DataFrame) -> DataFrame:
    """Shape of a degree distribution and the share of the hottest vertex."""
    total = F.sum("degree")
    return found.agg(
        F.count("*").alias("n_vertices"),
        total.alias("n_edges"),
        F.min("degree").alias("min_degree"),
        F.avg("degree").alias("avg_degree"),
        F.max("degree").alias("max_degree"),
        F.percentile("degree", 0.5).alias("median_degree"),
        F.percentile("degree", 0.99).alias("p99_degree"),
        (F.max("degree") / total).alias("top_share"),
    )


def degree_histogram(found: DataFrame) -> DataFrame:
    return found.groupBy("degree").agg(F.count("*").alias("n_vertices"))


def log_bins(found: DataFrame) -> DataFrame:
    return found.groupBy(F.floor(F.log2(F.col("degree").cast("double"))).alias("log2_degree")).agg(F.count("*").alias("n_vertices"))


def top_hubs(found: DataFrame, k: int = 10) -> DataFrame:
    return found.orderBy(F.col("degree").desc(), "vertex").limit(k)
