"""Physical forms of a CSR."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.schema import Csr


def to_segments(csr: Csr, max_segment: int = 65536) -> DataFrame:
    """(vertex, segment, offset, degree, targets, weights): at most ``max_segment`` targets a row, so hubs fit."""
    based = csr.slots.join(csr.vertices.select("vertex", "offset"), "vertex").withColumn("segment", F.floor((F.col("slot") - F.col("offset")) / F.lit(max_segment)).cast("int"))
    run = F.array_sort(F.collect_list(F.struct("slot", "target", "weight")))
    rows = based.groupBy("vertex", "segment").agg(F.min("slot").alias("offset"), F.count("*").alias("degree"), run.alias("_run"))
    return rows.select("vertex", "segment", "offset", "degree", F.col("_run.target").alias("targets"), F.col("_run.weight").alias("weights"))


def to_adjacency(csr: Csr) -> DataFrame:
    """(vertex, offset, degree, targets, weights); one row per vertex with edges, for degrees that fit a row."""
    run = F.array_sort(F.collect_list(F.struct("slot", "target", "weight")))
    rows = csr.slots.groupBy("vertex").agg(F.min("slot").alias("offset"), F.count("*").alias("degree"), run.alias("_run"))
    return rows.select("vertex", "offset", "degree", F.col("_run.target").alias("targets"), F.col("_run.weight").alias("weights"))


BLOCK = "block_id long, base_vertex long, base_offset long, offsets array<long>, targets array<long>, weights array<float>"


def to_blocks(csr: Csr, vertices_per_block: int = 4096) -> DataFrame:
    """The three arrays for each range of vertices, for vectorised kernels. ``offsets`` start at ``base_offset``."""
    size = vertices_per_block
    v = csr.vertices.where(F.col("vertex") < csr.meta.n_rows).select(F.floor(F.col("vertex") / size).alias("block_id"), "vertex", "degree", F.lit(None).cast("long").alias("slot"), F.lit(None).cast("long").alias("target"), F.lit(None).cast("float").alias("weight"))
    s = csr.slots.select(F.floor(F.col("vertex") / size).alias("block_id"), "vertex", F.lit(None).cast("long").alias("degree"), "slot", "target", "weight")

    def pack(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        own, edges = t.filter(pc.is_null(t.column("slot"))), t.filter(pc.is_valid(t.column("slot")))
        vertex = own.column("vertex").to_numpy()
        degree = own.column("degree").to_numpy()[np.argsort(vertex, kind="stable")]
        slot = edges.column("slot").to_numpy()
        by_slot = pa.array(np.argsort(slot, kind="stable"))
        base = int(slot.min()) if len(slot) else 0
        offsets = base + np.concatenate([[0], np.cumsum(degree)]).astype(np.int64)
        lists = [pa.array(offsets), *(edges.column(c).take(by_slot).combine_chunks() for c in ("target", "weight"))]
        cols = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x) for x in lists]
        return pa.table([pa.array([key[0].as_py()], pa.int64()), pa.array([int(vertex.min())], pa.int64()), pa.array([base], pa.int64()), *cols], ["block_id", "base_vertex", "base_offset", "offsets", "targets", "weights"])

    return v.union(s).groupBy("block_id").applyInArrow(pack, BLOCK)


def to_packed(csr: Csr, max_edges: int = 10_000_000) -> DataFrame:
    """One row with the three arrays; refuses more than ``max_edges``."""
    n = csr.slots.count()
    if n > max_edges:
        raise ValueError(f"{n} edges are more than max_edges; use to_blocks")
    arrays = csr.slots.agg(F.array_sort(F.collect_list(F.struct("slot", "target", "weight"))).alias("_s"))
    heads = csr.vertices.agg(F.array_sort(F.collect_list(F.struct("vertex", "offset"))).alias("_v"))
    return heads.join(F.broadcast(arrays)).select(F.col("_v.offset").alias("offsets"), F.col("_s.target").alias("targets"), F.col("_s.weight").alias("weights"))


def from_adjacency(rows: DataFrame) -> DataFrame:
    """Slots of adjacency or segment rows."""
    return rows.select("vertex", "offset", F.posexplode(F.arrays_zip("targets", "weights")).alias("pos", "e")).select((F.col("offset") + F.col("pos")).alias("slot"), "vertex", F.col("e.targets").alias("target"), F.col("e.weights").alias("weight"))


def from_blocks(blocks: DataFrame) -> DataFrame:
    """Slots of block rows: each vertex takes its run of ``targets`` between its offset and the next."""
    run = F.arrays_zip("targets", "weights")
    rows = blocks.select("base_vertex", "base_offset", "offsets", run.alias("_run"), F.posexplode(F.expr("slice(offsets, 1, size(offsets) - 1)")).alias("_v", "_from"))
    n = F.get("offsets", F.col("_v") + 1) - F.col("_from")
    own = rows.where(n > 0).select((F.col("base_vertex") + F.col("_v")).alias("vertex"), "_from", F.slice("_run", (F.col("_from") - F.col("base_offset") + 1).cast("int"), n.cast("int")).alias("_run"))
    return own.select("vertex", "_from", F.posexplode("_run").alias("_i", "_e")).select((F.col("_from") + F.col("_i")).alias("slot"), "vertex", F.col("_e.targets").alias("target"), F.col("_e.weights").alias("weight"))


def map_blocks(blocks: DataFrame, kernel, schema: str) -> DataFrame:
    """``kernel(base_vertex, offsets, targets, weights)`` on the numpy arrays of every block; it returns the columns of ``schema``."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches):
        for batch in batches:
            for r in range(batch.num_rows):
                row = {c: batch.column(i)[r] for i, c in enumerate(batch.schema.names)}
                base = row["base_offset"].as_py()
                arrays = (np.asarray(row[c].as_py(), t) for c, t in (("offsets", np.int64), ("targets", np.int64), ("weights", np.float32)))
                offsets, targets, weights = arrays
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in kernel(row["base_vertex"].as_py(), offsets - base, targets, weights)], names)

    return blocks.mapInArrow(run, schema)


def row_sums(base_vertex, offsets, targets, weights):
    """Kernel: the weights of each vertex of a block, added up."""
    sums = np.concatenate([[0.0], np.cumsum(weights.astype(np.float64))])
    return base_vertex + np.arange(len(offsets) - 1), sums[offsets[1:]] - sums[offsets[:-1]]
