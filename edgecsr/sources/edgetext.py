"""Text and binary files of edges: scan and write."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def part_id(parts: int) -> Column:
    """A part for each split of a text scan; it follows from file and place alone, so a repeated task gives the same."""
    return F.pmod(F.xxhash64("_metadata.file_path", "_metadata.file_block_start"), F.lit(parts)).cast("int").alias("part")


def scan_lines(spark: SparkSession, path: str, parts: int = 4) -> DataFrame:
    """value and part of the lines of all files under ``path``."""
    return spark.read.option("recursiveFileLookup", "true").text(path).select("value", part_id(parts))


def estimate_edges(spark: SparkSession, path: str, sample: int = 1 << 20) -> int:
    """About how many edges a text holds, from its bytes and the lines in the first ``sample`` bytes of its first file.

    A hint for partition counts; nothing is reserved by it.
    """
    from edgecsr.sources.block_source import listed, opened

    files = [x for x in listed(path) if x[1]]
    if not files or any(p.endswith((".gz", ".bz2", ".zst", ".lz4", ".snappy")) for p, _ in files):
        return 0
    system, at = opened(files[0][0])
    with system.open_input_file(at) as f:
        head = f.read(sample)
    return round(sum(size for _, size in files) * max(1, head.count(b"\n")) / len(head))


def file_splits(spark: SparkSession, path: str) -> DataFrame:
    """file, start, length and rows of each split of a text scan."""
    m = "_metadata."
    return spark.read.text(path).groupBy(F.col(m + "file_name").alias("file"), F.col(m + "file_block_start").alias("start"), F.col(m + "file_block_length").alias("length")).agg(F.count("*").alias("rows"))


def write_edges(edges: DataFrame, path: str, sep: str = " ", index_base: int = 1, weighted: bool = True, compression: str | None = None) -> None:
    columns = [(F.col(c) + index_base).cast("string") for c in ("src", "dst")] + ([F.col("weight").cast("string")] if weighted else [])
    writer = edges.select(F.concat_ws(sep, *columns).alias("value")).write.mode("overwrite")
    (writer.option("compression", compression) if compression else writer).text(path)


def write_csr(csr, path: str) -> None:
    """Slots ordered by slot and vertices by vertex: row groups then have narrow ranges that prune lookups. Sizes go along."""
    spark = csr.slots.sparkSession
    csr.slots.repartitionByRange("slot").sortWithinPartitions("slot").write.mode("overwrite").parquet(f"{path}/slots")
    csr.vertices.repartitionByRange("vertex").sortWithinPartitions("vertex").write.mode("overwrite").parquet(f"{path}/vertices")
    m = csr.meta
    spark.createDataFrame([(m.n_rows, m.n_cols, m.symmetric, m.weighted)], META).coalesce(1).write.mode("overwrite").json(f"{path}/meta")


META = "n_rows long, n_cols long, symmetric boolean, weighted boolean"


def read_csr_files(spark: SparkSession, path: str):
    from edgecsr.schema import CSR_SLOTS, CSR_VERTICES, Csr, GraphMeta

    meta = spark.read.schema(META).json(f"{path}/meta").first()
    return Csr(spark.read.schema(CSR_VERTICES).parquet(f"{path}/vertices"), spark.read.schema(CSR_SLOTS).parquet(f"{path}/slots"), GraphMeta(*meta))


def write_csr_buckets(csr, name: str, buckets: int = 64) -> None:
    """Slots and vertices as tables ``name_slots`` and ``name_vertices``, bucketed and sorted by vertex: joins on it need no exchange."""
    for df, what, order in ((csr.slots, "slots", ["vertex", "slot"]), (csr.vertices, "vertices", ["vertex"])):
        df.write.mode("overwrite").format("parquet").bucketBy(buckets, "vertex").sortBy(*order).saveAsTable(f"{name}_{what}")
