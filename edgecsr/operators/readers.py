"""Text to edge list: the reader variants that the study compares."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from edgecsr.functions.parse import parse_lines
from edgecsr.operators.csr import build_csr
from edgecsr.operators.degrees import combine_degrees, degrees, partial_degrees
from edgecsr.operators.edges import symmetrize
from edgecsr.schema import Csr, Graph, GraphMeta
from edgecsr.session import materialize
from edgecsr.sources import block_source
from edgecsr.sources.block_source import scan_chunks, scan_slices
from edgecsr.sources.edgetext import scan_lines
from edgecsr.sources.mtx import has_banner, mtx_body, read_mtx_header

METHODS = ("serial", "line_block", "block", "block_vector")


def _one_task_lines(spark: SparkSession, path: str) -> DataFrame:
    """Lines in order by one task, numbered."""
    lines = spark.read.option("recursiveFileLookup", "true").text(path).coalesce(1)
    return lines.select("value", F.monotonically_increasing_id().alias("_line"))


def _dealt(numbered: DataFrame, lines_per_block: int) -> DataFrame:
    return numbered.withColumn("_block", F.floor(F.col("_line") / lines_per_block)).repartition("_block")


def read_edges(
    spark: SparkSession,
    path: str,
    method: str = "block_vector",
    header: str = "none",
    weighted: bool | None = None,
    symmetric: bool | None = None,
    index_base: int = 1,
    block_bytes: int = 262144,
    parts: int = 4,
    mode: str = "PERMISSIVE",
    self_loops: str = "once",
    parser: str | None = None,
    lines_per_block: int = 131072,
    parse_chunk: int = 1024,
    source: str = "text",
    line_source: str = "text",
    honor_header: bool = True,
    with_degrees: str = "none",
    schedule: str = "dynamic",
) -> Graph:
    """Edges (src, dst, weight, part), 0-based, of a text edge list or Matrix Market file.

    serial        one task reads and parses (pattern by pattern)
    line_block    one task reads; blocks of lines are dealt to all tasks and parsed there
                  (parser 'direct', or 'format' for a format-driven parse); with ``line_source='buffered'``
                  that task takes ``parse_chunk`` lines at a time out of a file buffer and deals
                  them as one text, which is cut into lines where it is parsed
    block         file splits are read where they are, parsed by expressions
    block_vector  file splits are read where they are, parsed in bulk per Arrow batch;
                  ``source='blocks'`` reads byte blocks through the Python source
    ``schedule='static'`` gives each slot one slice of the same number of bytes; 'dynamic' deals out as many splits as there are.
    Flags are settled here, so each setting is a plan of its own. ``header='auto'`` looks for a Matrix Market banner.
    With degrees, the edges are written once, and degrees come from what was written: the text is read and parsed once.
    """
    slices = spark.sparkContext.defaultParallelism if schedule == "static" else None
    if header == "auto":
        header = "mtx" if has_banner(spark, path) else "none"
    meta = GraphMeta(weighted=weighted is not False)
    skew = False
    if header == "mtx":
        h = read_mtx_header(spark, path)
        weighted = h.weighted if weighted is None else weighted
        symmetric = h.symmetric if symmetric is None and honor_header else symmetric
        skew = h.symmetry == "skew-symmetric" and honor_header
        n = max(h.rows, h.cols) if symmetric else h.rows
        meta = GraphMeta(n, max(h.rows, h.cols) if symmetric else h.cols, bool(symmetric), weighted)
    weighted = weighted is not False
    if header == "mtx":
        lines = mtx_body(spark, path, h, parts)
    elif slices:
        lines = scan_slices(spark, path, slices).select("value", F.pmod("slice", F.lit(parts)).cast("int").alias("part"))
    else:
        lines = scan_lines(spark, path, parts)
    if method == "serial":
        edges, bad = parse_lines(lines.coalesce(1), parser or "generic", weighted, index_base, mode)
    elif method == "line_block":
        if line_source == "buffered" and header != "mtx":
            dealt = scan_chunks(spark, path, parse_chunk, lines_per_block).repartition("block").select(F.explode(F.split("value", "\n")).alias("value"), F.col("block").alias("_block"))
        elif header != "mtx":
            dealt = _dealt(_one_task_lines(spark, path), lines_per_block)
        else:
            dealt = _dealt(lines.coalesce(1).select("value", F.monotonically_increasing_id().alias("_line")), lines_per_block)
        dealt = dealt.select("value", F.pmod("_block", F.lit(parts)).cast("int").alias("part"))
        edges, bad = parse_lines(dealt, parser or "direct", weighted, index_base, mode)
    elif method == "block":
        edges, bad = parse_lines(lines, parser or "direct", weighted, index_base, mode)
    elif method == "block_vector" and source == "blocks":
        block_source.register(spark)
        read = spark.read.format("edgeblocks").options(path=path, block_bytes=block_bytes, weighted=str(weighted).lower(), index_base=index_base, **({"slices": slices} if slices else {})).load()
        edges, bad = read.select("src", "dst", "weight", F.pmod("block", F.lit(parts)).cast("int").alias("part")), parse_lines(scan_lines(spark, path, parts), "vector", weighted, index_base)[1]
    elif method == "block_vector":
        edges, bad = parse_lines(lines, parser or "vector", weighted, index_base, mode)
    else:
        raise ValueError(f"method must be one of {METHODS}")
    if symmetric:
        edges = symmetrize(edges, self_loops, -1 if skew else 1)
        meta = meta.having(symmetric=True)
    graph = Graph(edges, meta, bad)
    if with_degrees != "none":
        graph = settled(graph)
        graph.degrees = partial_degrees(graph.edges) if with_degrees == "parts" else degrees(graph.edges, with_degrees)
    return graph


def settled(graph: Graph) -> Graph:
    """The graph with its edges written once; the greatest source and target are seen on the way, so sizes need no pass of their own."""
    seen = Observation()
    edges = materialize(graph.edges.observe(seen, F.max("src").alias("src"), F.max("dst").alias("dst")), "edges")
    found = seen.get
    rows, cols = ((found.get(c) if found.get(c) is not None else -1) + 1 for c in ("src", "dst"))
    if graph.meta.symmetric:
        rows = cols = max(rows, cols)
    meta = graph.meta.having(n_rows=rows if graph.meta.n_rows is None else graph.meta.n_rows, n_cols=cols if graph.meta.n_cols is None else graph.meta.n_cols)
    return Graph(edges, meta, graph.bad, graph.degrees)


def read_edges_csv(spark: SparkSession, path: str, schema: str = "src long, dst long, weight float", sep: str = " ", comment: str = "%", mode: str = "PERMISSIVE", index_base: int = 1) -> Graph:
    """Edges by Spark's delimited reader with a fixed schema; ``bad`` has the lines that it could not read whole, in PERMISSIVE mode."""
    rows = spark.read.schema(f"{schema}, _line string").options(sep=sep, comment=comment, mode=mode, columnNameOfCorruptRecord="_line", columnPruning=False).csv(path)  # a line is judged by all its columns
    weight = F.col("weight") if "weight" in rows.columns else F.lit(1.0).cast("float")
    fine = rows.where(F.col("_line").isNull()).select((F.col("src") - index_base).alias("src"), (F.col("dst") - index_base).alias("dst"), weight.alias("weight"))
    whole = F.concat(*[F.col(c).cast("string") for c in rows.columns if c != "_line"]).isNotNull()
    bad = rows.where(F.col("_line").isNotNull()).select(F.col("_line").alias("line"), F.when(whole, "further columns").otherwise("not of the schema").alias("reason"))
    return Graph(fine, GraphMeta(weighted="weight" in rows.columns), bad)


def read_csr(spark: SparkSession, path: str, csr_method: str = "auto", order: str = "canonical", csr_parts: int = 4, **read_options) -> Csr:
    """Reading and conversion: the operation that the study times. The text is read and parsed once."""
    return build_csr(settled(read_edges(spark, path, **read_options)), csr_method, parts=csr_parts, order=order)


def degrees_while_reading(graph: Graph) -> DataFrame:
    """Whole degrees of a graph that was read with part degrees."""
    return combine_degrees(graph.degrees)
