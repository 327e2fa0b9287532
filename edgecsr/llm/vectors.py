"""Vectors in shards, and stated queries against all of them in blocks."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and vector of the rows that take part: no null id or vector, no null or non-finite component."""
    slim = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("vector"))
    fine = F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return slim.where(F.col("vec_id").isNotNull() & F.col("vector").isNotNull()).where(F.coalesce(fine, F.lit(False)))


def pack(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Ids and matrix of a batch; shorter vectors end in zeros."""
    ids, lists = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), batch.column(1)
    lengths = np.diff(lists.offsets.to_numpy())
    width = int(lengths.max(initial=0))
    flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if (lengths == width).all():
        return ids, flat.reshape(len(ids), width)
    m = np.zeros((len(ids), width))
    m[np.arange(width) < lengths[:, None]] = flat
    return ids, m


PACKED = "part int, n long, width int, ids binary, matrix binary"


def packed(vectors: DataFrame, parts: int, rows_per_part: int) -> DataFrame:
    """Whole vectors as ``parts`` packed rows, dealt by the hash of row and id: a part holds about ``rows_per_part``.

    Copies of one vector are spread over the parts, and so are rows that repeat
    an id: the place of a row in its file takes part, which a repeated task finds again.
    """
    dealt = vectors.withColumn("part", F.pmod(F.xxhash64("vec_id", "vector", F.monotonically_increasing_id()), F.lit(parts)).cast("int"))

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        batch = table.select(["vec_id", "vector"]).to_batches()[0]
        ids, m = pack(batch)
        order = np.argsort(ids, kind="stable")
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "n": pa.array([len(ids)], pa.int64()), "width": pa.array([m.shape[1]], pa.int32()), "ids": [ids[order].tobytes()], "matrix": [np.ascontiguousarray(m[order]).tobytes()]})

    return dealt.groupBy("part").applyInArrow(run, PACKED)


def unpack(ids: bytes, matrix: bytes, width: int) -> tuple[np.ndarray, np.ndarray]:
    ids = np.frombuffer(ids, np.int64)
    return ids, np.frombuffer(matrix, np.float64).reshape(len(ids), width)


def widened(m: np.ndarray, width: int) -> np.ndarray:
    return m if m.shape[1] >= width else np.hstack([m, np.zeros((len(m), width - m.shape[1]))])


#: Tasks that a search over few parts is spread over; with more parts, each is one task's.
LEAST_TASKS = 8


def met(parts: DataFrame, n_parts: int, blocks: DataFrame, n_blocks: int, load: Callable[[dict], object], answer: Callable[[object, dict], pa.RecordBatch], schema: str) -> DataFrame:
    """``answer(load(part), block)`` for every part with every block of queries.

    Parts have the column ``part``, blocks the column ``block``; a row of either is bounded. The blocks go to all parts,
    as the asked are the fewer. Each task loads a part once and then takes the
    blocks one by one, so neither side has to fit in memory as a whole.
    """
    splits = max(1, min(n_blocks, -(-LEAST_TASKS // max(n_parts, 1))))
    held = parts.select("*", F.explode(F.sequence(F.lit(0), F.lit(splits - 1))).alias("_split"), F.lit(-1).alias("block"))
    asked = blocks.select("*", F.explode(F.sequence(F.lit(0), F.lit(max(n_parts, 1) - 1))).alias("part"), F.pmod("block", F.lit(splits)).alias("_split"))
    both = held.unionByName(asked, allowMissingColumns=True).withColumn("_task", (F.col("part") * splits + F.col("_split")).cast("int"))
    dealt = both.repartitionById(max(n_parts, 1) * splits, F.col("_task")).sortWithinPartitions("_task", "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        loaded = None, None
        for batch in batches:
            for r in range(batch.num_rows):
                row = {n: batch.column(i)[r].as_py() for i, n in enumerate(batch.schema.names)}
                if row["block"] < 0:
                    loaded = row["part"], load(row)
                elif row["part"] == loaded[0]:  # no rows, no part
                    yield answer(loaded[1], row)

    return dealt.mapInArrow(run, schema)


def best(found: DataFrame, k: int) -> DataFrame:
    """The k highest of each query over all parts, ties to the smaller id; a part has sent k at most."""
    w = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def queries_of(vectors: DataFrame, every: int) -> DataFrame:
    """Rows whose id is divisible by ``every``; of repeated ids the least vector asks."""
    return vectors.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("vector").alias("vector"))


def distinct_rows(ids: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct vectors with the ids of each, ascending."""
    if not len(m):
        return m, []
    if m.dtype == object:  # numbers beyond 64 bits
        by: dict[tuple, list[int]] = {}
        for i, row in zip(ids.tolist(), m.tolist()):
            by.setdefault(tuple(row), []).append(i)
        rows = sorted(by)
        return np.array(rows, dtype=object).reshape(len(rows), -1), [np.array(sorted(by[r])) for r in rows]
    uniq, inverse = np.unique(m, axis=0, return_inverse=True)
    inverse = inverse.ravel()
    order = np.lexsort((ids, inverse))
    cuts = np.flatnonzero(np.diff(inverse[order])) + 1
    return uniq, np.split(ids[order], cuts)
