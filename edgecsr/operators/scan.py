"""Exclusive prefix sums and row numbers without a single-task pass over the data."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.session import materialize

#: Chunk totals that may be broadcast: 16 bytes each.
MOST_BROADCAST = 1_000_000


def exclusive_scan(df: DataFrame, key: str, value: str, method: str = "two_level", chunk: int = 1 << 20, by: list[str] | None = None, n_keys: int | None = None, out: str = "offset", sparse: DataFrame | None = None) -> DataFrame:
    """Adds ``out``: the sum of ``value`` over smaller keys (per ``by``).

    two_level  sums per chunk of keys, a running sum over the few chunks, and
               a running sum inside every chunk; ``sparse`` has the rows of ``df``
               whose value is not 0, for the sums per chunk, where ``n_keys`` is known
    single     one window over everything; for tests and tiny inputs
    """
    by = by or []
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    if method == "single":
        w = before(Window.partitionBy(*by).orderBy(key) if by else Window.orderBy(key))
        return df.withColumn(out, F.coalesce(F.sum(value).over(w), F.lit(0)).cast("long"))
    if method != "two_level":
        raise ValueError("method is 'two_level' or 'single'")
    cut = df.withColumn("_chunk", F.floor(F.col(key) / F.lit(chunk)))
    if sparse is None or n_keys is None or by:
        totals = cut.groupBy(*by, "_chunk").agg(F.sum(value).alias("_total"))
    else:
        own = sparse.groupBy(F.floor(F.col(key) / F.lit(chunk)).alias("_chunk")).agg(F.sum(value).alias("_total"))
        every = df.sparkSession.range(n_keys // chunk + 1).withColumnRenamed("id", "_chunk")
        totals = every.join(own, "_chunk", "left").select("_chunk", F.coalesce("_total", F.lit(0)).alias("_total"))
    w = before(Window.partitionBy(*by).orderBy("_chunk") if by else Window.orderBy("_chunk"))
    bases = totals.withColumn("_base", F.coalesce(F.sum("_total").over(w), F.lit(0))).drop("_total")
    if n_keys is not None and not by and n_keys // chunk + 1 <= MOST_BROADCAST:
        bases = F.broadcast(bases)
    inner = before(Window.partitionBy(*by, "_chunk").orderBy(key))
    local = cut.withColumn("_local", F.coalesce(F.sum(value).over(inner), F.lit(0)))
    return local.join(bases, [*by, "_chunk"]).withColumn(out, (F.col("_base") + F.col("_local")).cast("long")).drop("_chunk", "_base", "_local")


def number_rows(df: DataFrame, order: list[str], out: str, partitions: int | None = None) -> DataFrame:
    """Numbers rows 0.. in a total order: range exchange, local sort, local index, and a base per partition.

    The sorted rows are written once, so that numbers do not change if a task
    is repeated. Positions are 64-bit; range bounds fall inside runs of a hot
    first key where ``order`` goes on.
    """
    cols = df.columns
    ranged = df.repartitionByRange(partitions, *order) if partitions else df.repartitionByRange(*order)
    local = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    sorted_rows = materialize(ranged.sortWithinPartitions(*order).select(*cols, F.spark_partition_id().alias("_p"), local.alias("_i")), "ranged")
    sizes = sorted_rows.groupBy("_p").agg(F.count("*").alias("_n"))
    w = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.select("_p", F.coalesce(F.sum("_n").over(w), F.lit(0)).alias("_base"))  # one row per partition
    return sorted_rows.join(F.broadcast(bases), "_p").select(*cols, (F.col("_base") + F.col("_i")).cast("long").alias(out))
