"""Edges that arrive as a stream, and CSR upkeep."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgecsr.functions.parse import parse_lines
from edgecsr.operators.csr import build_csr
from edgecsr.schema import Csr, Graph, GraphMeta
from edgecsr.session import materialize, shared_dir


def read_edges_stream(spark: SparkSession, path: str, weighted: bool = True, index_base: int = 1, files_per_trigger: int = 16) -> DataFrame:
    lines = spark.readStream.option("maxFilesPerTrigger", files_per_trigger).text(path)
    return parse_lines(lines, "direct", weighted, index_base)[0]


def read_events(spark: SparkSession, sf_dir: str, delay: str = "10 minutes") -> DataFrame:
    """The events table as a stream with a watermark."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    events = spark.readStream.schema(schema).parquet(path + "*")
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def incremental_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("vertex")).agg(F.count("*").alias("degree"))


def windowed_edges(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n_edges"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n_edges", "total")


def session_edges(events: DataFrame, gap: str) -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n_edges")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n_edges")


def dedup_events(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def enrich(events: DataFrame, dims: DataFrame, on: str) -> DataFrame:
    return events.join(dims, on)


def edge_pairs(events: DataFrame, other: DataFrame, within: str) -> DataFrame:
    """Pairs of a user's events of two streams at most ``within`` apart."""
    a = events.select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("event_id").alias("src"))
    b = other.select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("dst"))
    return a.join(b, F.expr(f"a_user = b_user and b_ts > a_ts and b_ts <= a_ts + interval {within}")).select("src", "dst")


def degree_state(edges: DataFrame) -> DataFrame:
    """Running out-degree kept by own state, one row out per vertex and trigger."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key, frames, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"vertex": [key[0]], "degree": [n]})

    return edges.groupBy("src").applyInPandasWithState(update, "vertex long, degree long", "degree long", "update", GroupStateTimeout.NoTimeout)


def run_to_table(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now and returns its result; state and offsets go to the shared folder."""
    spark = df.sparkSession
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        df.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")
    last: list[DataFrame] = []

    def keep(batch: DataFrame, n: int) -> None:
        last[:] = [materialize(batch, "batch")] if mode == "complete" else [*last, materialize(batch.withColumn("_batch", F.lit(n)), "batch")]

    df.writeStream.foreachBatch(keep).option("checkpointLocation", f"{at}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    out = last[0]
    for more in last[1:]:
        out = out.union(more)
    return out


def merge_csr_delta(csr: Csr, batch: DataFrame) -> Csr:
    """CSR after more edges: vertices that the batch touches are rebuilt, all others only move.

    Slots of untouched vertices shift by the edges that come before them; a
    broadcast-free join by vertex brings the shift.
    """
    batch = batch.select("src", "dst", "weight")
    n = max(csr.meta.n_rows or 0, (batch.agg(F.max("src")).first()[0] or -1) + 1)
    touched = batch.select(F.col("src").alias("vertex")).distinct()
    old = csr.slots.join(touched, "vertex", "left_semi").select(F.col("vertex").alias("src"), F.col("target").alias("dst"), "weight")
    new_part = build_csr(Graph(old.union(batch), GraphMeta(n_rows=n)), "staged")
    whole = csr.vertices.where(F.col("vertex") < F.lit(csr.meta.n_rows)).select("vertex", "degree").join(touched, "vertex", "left_anti").union(new_part.vertices.join(touched, "vertex", "left_semi").select("vertex", "degree"))
    from edgecsr.operators.csr import offsets

    vertices = materialize(offsets(whole, n), "vertices")
    moved = csr.slots.join(touched, "vertex", "left_anti").join(csr.vertices.select("vertex", F.col("offset").alias("_was")), "vertex")
    fresh = new_part.slots.join(new_part.vertices.select("vertex", F.col("offset").alias("_was")), "vertex")
    cols = ["vertex", "target", "weight", "slot", "_was"]
    slots = moved.select(cols).union(fresh.select(cols)).join(vertices.select("vertex", "offset"), "vertex")
    return Csr(vertices, slots.select((F.col("offset") + F.col("slot") - F.col("_was")).alias("slot"), "vertex", "target", "weight"), csr.meta.having(n_rows=n))
