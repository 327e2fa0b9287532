"""Times, rates, speedups and scaling, as the study reports them."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

RECORD = "workload string, graph string, method string, params string, cores int, run int, seconds double, edges_in_file long, edges_loaded long, bytes long, status string"


def consume(df: DataFrame) -> int:
    """Computes every row and keeps none; how many edges the rows hold (their number, or the sum of degrees) is seen on the way."""
    seen = Observation()
    held = F.coalesce(F.sum("degree"), F.lit(0)) if "degree" in df.columns else F.count(F.lit(1))
    df.observe(seen, held.alias("edges")).write.format("noop").mode("overwrite").save()
    return seen.get["edges"]


def time_runs(fn: Callable[[], DataFrame], runs: int = 5) -> tuple[list[tuple[float, str]], int]:
    """(seconds, status) of every run, of which a failed one has no number; and the edges that a run loads, so that no further run counts them."""
    out, loaded = [], 0
    for _ in range(runs):
        began = time.perf_counter()
        try:
            loaded = consume(fn())
            out.append((time.perf_counter() - began, "ok"))
        except Exception as e:  # a measure of failures, so any of them
            out.append((float("nan"), f"failed: {type(e).__name__}"))
    return out, loaded


def file_totals(spark: SparkSession, path: str) -> tuple[int, int]:
    """(edges, bytes) of a text edge list's files."""
    lines = spark.read.option("recursiveFileLookup", "true").text(path).where(r"trim(value) <> '' and not value rlike '^\\s*[%#]'")
    size = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).agg(F.coalesce(F.sum("length"), F.lit(0)))
    return lines.count(), size.first()[0]


def records(spark: SparkSession, workload: str, graph: str, method: str, runs: list[tuple[float, str]], params: str = "", edges_in_file: int = 0, edges_loaded: int = 0, size: int = 0, cores: int | None = None) -> DataFrame:
    """One row for each run; ``cores`` is what the session has unless the runs used fewer tasks."""
    cores = cores or spark.sparkContext.defaultParallelism
    rows = [(workload, graph, method, params, cores, i, s, edges_in_file, edges_loaded, size, status) for i, (s, status) in enumerate(runs)]
    return spark.createDataFrame(rows, RECORD)


def means(found: DataFrame) -> DataFrame:
    ok = found.where("status = 'ok'")
    return ok.groupBy("workload", "graph", "method", "params", "cores").agg(F.avg("seconds").alias("seconds"), F.max("edges_loaded").alias("edges_loaded"), F.max("bytes").alias("bytes"))


def relative(found: DataFrame, reference: str) -> DataFrame:
    """Time over that of a reference method, per graph and averaged over graphs."""
    m = means(found)
    base = m.where(F.col("method") == reference).select("workload", "graph", F.col("seconds").alias("_base"))
    per = m.join(base, ["workload", "graph"]).withColumn("relative", F.col("seconds") / F.col("_base"))
    return per.groupBy("workload", "method", "params").agg(F.avg("relative").alias("relative"))


def speedup(found: DataFrame, base: str) -> DataFrame:
    """How many times faster than ``base``: arithmetic and geometric mean over graphs."""
    m = means(found)
    b = m.where(F.col("method") == base).select("workload", "graph", F.col("seconds").alias("_base"))
    per = m.join(b, ["workload", "graph"]).withColumn("x", F.col("_base") / F.col("seconds"))
    return per.groupBy("workload", "method").agg(F.avg("x").alias("arithmetic"), F.exp(F.avg(F.log("x"))).alias("geometric"))


def edge_rate(found: DataFrame) -> DataFrame:
    return means(found).withColumn("edges_per_second", F.col("edges_loaded") / F.col("seconds"))


def byte_rate(found: DataFrame) -> DataFrame:
    return means(found).withColumns({"bytes_per_second": F.col("bytes") / F.col("seconds"), "bytes_per_edge": F.col("bytes") / F.col("edges_loaded")})


def scaling(found: DataFrame) -> DataFrame:
    """Speedup over the fewest cores, and what each doubling of cores brings."""
    m = means(found)
    least = m.groupBy("workload", "graph", "method").agg(F.min_by("seconds", "cores").alias("_base"), F.min("cores").alias("_cores"))
    times = F.col("cores") / F.col("_cores")
    s = m.join(least, ["workload", "graph", "method"]).withColumn("speedup", F.col("_base") / F.col("seconds"))
    return s.withColumn("per_doubling", F.when(times > 1, F.pow("speedup", 1 / F.log2(times)))).drop("_base", "_cores")


def failures(found: DataFrame) -> DataFrame:
    """Runs that have no number, of all runs."""
    return found.groupBy("graph", "method").agg(F.count_if(F.col("status") != "ok").alias("failed"), F.count("*").alias("runs"))


def per_doubling(speedup_value: float, doublings: float) -> float:
    return speedup_value ** (1.0 / doublings)


def phase_times(found: DataFrame) -> DataFrame:
    """Edge-list and CSR time side by side."""
    return means(found).groupBy("graph").pivot("method", ["edge_list", "csr"]).agg(F.avg("seconds"))


def skew(rows_per_partition: DataFrame, count: str = "n_edges") -> DataFrame:
    """Greatest over mean and over median load: what contention becomes in a shuffle."""
    return rows_per_partition.agg((F.max(count) / F.avg(count)).alias("max_over_mean"), (F.max(count) / F.percentile(count, 0.5)).alias("max_over_median"))


def space(part_degrees: DataFrame, whole: DataFrame) -> DataFrame:
    """Rows that private counters hold against rows of the combined degrees."""
    return part_degrees.agg(F.count("*").alias("part_rows")).crossJoin(whole.agg(F.count("*").alias("rows"))).withColumn("ratio", F.col("part_rows") / F.col("rows"))
