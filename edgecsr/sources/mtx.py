"""Matrix Market headers and files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgecsr.schema import MtxHeader
from edgecsr.sources.edgetext import part_id


def _size_line(head: list[str]) -> str | None:
    return next((x for x in head[1:] if x.strip() and not x.startswith("%")), None)


def read_mtx_header(spark: SparkSession, path: str) -> MtxHeader:
    """Banner and size line. Reads the first lines of single files, in name order, until one begins with a banner, and of that one as many as its comments take."""
    for file in sorted(spark.read.option("recursiveFileLookup", "true").text(path).inputFiles()):
        first = spark.read.text(file).select("value", "_metadata.file_path").first()
        if first and first[0].startswith("%%MatrixMarket"):
            break
    else:
        raise ValueError(f"no Matrix Market banner in {path}")
    n, head, size = 100, [], None
    while size is None:
        head = [r[0] for r in spark.read.text(file).limit(n).collect()]
        size = _size_line(head)
        if size is None and len(head) < n:
            raise ValueError(f"no size line in {path}")
        n *= 10
    _, obj, fmt, field, symmetry = head[0].split()[:5]
    rows, cols, *entries = map(int, size.split())
    return MtxHeader(obj.lower(), fmt.lower(), field.lower(), symmetry.lower(), rows, cols, entries[0] if entries else rows * cols, size, file, first[1])


def has_banner(spark: SparkSession, path: str) -> bool:
    try:
        read_mtx_header(spark, path)
    except ValueError:
        return False
    return True


def write_mtx(edges: DataFrame, path: str, rows: int, cols: int, field: str = "real", symmetry: str = "general") -> None:
    """Header as the first part file, entries (1-based) after it."""
    spark, n = edges.sparkSession, edges.count()
    head = [f"%%MatrixMarket matrix coordinate {field} {symmetry}", "% written by edgecsr", f"{rows} {cols} {n}"]
    spark.createDataFrame([("\n".join(head),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/part=0")
    columns = [(F.col("src") + 1).cast("string"), (F.col("dst") + 1).cast("string")]
    if field == "integer":
        columns.append(F.col("weight").cast("long").cast("string"))
    elif field != "pattern":
        columns.append(F.col("weight").cast("string"))
    edges.select(F.concat_ws(" ", *columns).alias("value")).write.mode("overwrite").text(f"{path}/part=1")


def mtx_body(spark: SparkSession, path: str, header: MtxHeader, parts: int = 4) -> DataFrame:
    """Entry lines and their parts.

    The size line is one line of the first split of the file with the banner. An
    entry there may read just like it; lines that read alike are the same edge, so all
    of them go and all but one come back. That takes a second look at this one file,
    and only where entries have three numbers, as the size line has.
    """
    at_start = (F.col("_metadata.file_path") == header.place) & (F.col("_metadata.file_block_start") == 0) & (F.col("value") == header.size_line)
    lines = spark.read.option("recursiveFileLookup", "true").text(path)
    rest = lines.where(~at_start).select("value", part_id(parts))
    if header.field == "pattern" or len(header.size_line.split()) != 3:
        return rest
    alike = spark.read.text(header.file).where(at_start).select("value", part_id(parts)).groupBy("value", "part").agg(F.count("*").alias("n"))
    back = alike.where("n > 1").select(F.explode(F.sequence(F.lit(2), F.col("n"))), "value", "part").select("value", "part")
    return rest.union(back)
