"""What a CSR is used for: traversal, ranking, products, common neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.operators.scan import number_rows
from edgecsr.session import materialize


def bfs_levels(edges: DataFrame, source: int, max_depth: int | None = None) -> DataFrame:
    """(vertex, level) of everything that can be reached, or of what is at most ``max_depth`` edges away.

    Each round's vertices are written, and all that were found every 16 rounds, so lineage stays short.
    """
    spark = edges.sparkSession
    found = spark.createDataFrame([(source, 0)], "vertex long, level int")
    frontier, level = found, 0
    pairs = materialize(edges.select("src", "dst").distinct(), "pairs")
    while max_depth is None or level < max_depth:
        level += 1
        step = frontier.join(pairs, frontier.vertex == pairs.src).select(F.col("dst").alias("vertex")).distinct()
        frontier = materialize(step.join(found.select("vertex"), "vertex", "left_anti").withColumn("level", F.lit(level)), "frontier")
        if frontier.isEmpty():
            break
        found = found.union(frontier)
        if level % 16 == 0:
            found = materialize(found, "reached")
    return found


def connected_components(edges: DataFrame) -> DataFrame:
    """(vertex, component): the least vertex that is linked, directions ignored. Labels spread and jump until none changes."""
    both = materialize(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).union(edges.select("dst", "src")).where("a <> b").distinct(), "both")
    every = edges.select(F.explode(F.array("src", "dst")).alias("vertex")).distinct()
    labels = every.select("vertex", F.col("vertex").alias("component"))
    while True:
        labels = materialize(labels, "labels")
        near = both.join(labels.select(F.col("vertex").alias("b"), "component"), "b").groupBy("a").agg(F.min("component").alias("_m"))
        met = labels.join(near.withColumnRenamed("a", "vertex"), "vertex", "left").select("vertex", F.col("component").alias("_old"), F.least("component", F.coalesce("_m", "component")).alias("component"))
        up = met.select(F.col("vertex").alias("component"), F.col("component").alias("_up"))
        new = materialize(met.join(up, "component", "left").select("vertex", "_old", F.least(F.col("component"), F.coalesce("_up", "component")).alias("component")), "labels")
        if new.where("component <> _old").isEmpty():
            return new.select("vertex", "component")
        labels = new.select("vertex", "component")


def pagerank(edges: DataFrame, n: int, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(vertex, rank) after a fixed number of rounds; a vertex without out-edges passes nothing on."""
    out = edges.groupBy("src").agg(F.count("*").alias("_d"))
    links = edges.join(out, "src").select("src", "dst", (1.0 / F.col("_d")).alias("_p"))
    every = edges.sparkSession.range(n).withColumnRenamed("id", "vertex")
    rank = every.withColumn("rank", F.lit(1.0 / n))
    for i in range(rounds):
        sent = links.join(rank.withColumnRenamed("vertex", "src"), "src").groupBy("dst").agg(F.sum(F.col("rank") * F.col("_p")).alias("_s"))
        rank = every.join(sent.withColumnRenamed("dst", "vertex"), "vertex", "left").select("vertex", (F.lit((1 - damping) / n) + damping * F.coalesce("_s", F.lit(0.0))).alias("rank"))
        if i % 4 == 3:
            rank = materialize(rank, "rank")
    return rank


def spmv(edges: DataFrame, x: DataFrame) -> DataFrame:
    """(vertex, value) of matrix times vector (vertex, value)."""
    return edges.join(x.select(F.col("vertex").alias("dst"), "value"), "dst").groupBy(F.col("src").alias("vertex")).agg(F.sum(F.col("weight").cast("double") * F.col("value")).alias("value"))


def two_hop(edges: DataFrame) -> DataFrame:
    """(src, dst, n_paths) over exactly two edges."""
    a, b = edges.select("src", F.col("dst").alias("_m")), edges.select(F.col("src").alias("_m"), "dst")
    return a.join(b, "_m").groupBy("src", "dst").agg(F.count("*").alias("n_paths"))


def common_neighbors(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, n_common) of asked pairs."""
    e = edges.select("src", "dst").distinct()
    left = pairs.join(e.withColumnRenamed("src", "a"), "a")
    hit = left.join(e.withColumnRenamed("src", "b"), ["b", "dst"]).groupBy("a", "b").agg(F.count("*").alias("n_common"))
    return pairs.join(hit, ["a", "b"], "left").select("a", "b", F.coalesce("n_common", F.lit(0)).alias("n_common"))


def triangle_count(edges: DataFrame) -> DataFrame:
    """Triangles of an undirected graph: edges point from the vertex of smaller degree, so hubs spread few."""
    e = edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    deg = e.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
    e = e.join(deg.select(F.col("v").alias("a"), F.col("d").alias("da")), "a").join(deg.select(F.col("v").alias("b"), F.col("d").alias("db")), "b")
    swap = (F.col("da") > F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") > F.col("b")))
    e = e.select(F.when(swap, F.col("b")).otherwise(F.col("a")).alias("u"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("v"))
    two = e.alias("x").join(e.alias("y"), F.col("x.u") == F.col("y.u")).where("x.v < y.v").select(F.col("x.v").alias("p"), F.col("y.v").alias("q"))
    closing = e.select(F.least("u", "v").alias("p"), F.greatest("u", "v").alias("q"))
    return two.join(closing, ["p", "q"]).agg(F.count("*").alias("n_triangles"))


def relabel_by_degree(edges: DataFrame) -> DataFrame:
    """Vertices renumbered from the greatest degree down (ties by number)."""
    deg = edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg((-F.count("*")).alias("_d"))
    new = number_rows(deg, ["_d", "v"], "n")
    return edges.join(new.select(F.col("v").alias("src"), F.col("n").alias("_s")), "src").join(new.select(F.col("v").alias("dst"), F.col("n").alias("_t")), "dst").select(F.col("_s").alias("src"), F.col("_t").alias("dst"), "weight")
