"""Python functions for SQL and DataFrames. Each has an expression twin that is faster."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, LongType, StringType, StructField, StructType

from edgecsr.functions.parse import parse_line
from edgecsr.schema import EDGE

# types as objects: strings would need a session when this module is imported
KMER = StructType([StructField("pos", IntegerType()), StructField("kmer", StringType())])


@udf(returnType=EDGE)
def parse_edge_row(line):
    """One line at a time: the slow way, for comparison."""
    return next((found for x in (line or "").encode().split(b"\n") if (found := parse_line(x, True, 0)[0])), None)


def _parse_edges(lines: pd.Series) -> pd.DataFrame:
    t = lines.fillna("").str.strip().str.split(r"[\s,;]+", n=2, expand=True).reindex(columns=[0, 1, 2])
    return pd.DataFrame({"src": pd.to_numeric(t[0], errors="coerce").astype("Int64"), "dst": pd.to_numeric(t[1], errors="coerce").astype("Int64"), "weight": pd.to_numeric(t[2], errors="coerce").fillna(1.0).astype("float32")})


parse_edge_arrow = pandas_udf(_parse_edges, EDGE, F.PandasUDFType.SCALAR)


def _gini(degree: pd.Series) -> float:
    d = np.sort(degree.to_numpy(float))
    n, total = len(d), d.sum()
    return float((2 * np.arange(1, n + 1) - n - 1) @ d / (n * total)) if total else 0.0


degree_gini = pandas_udf(_gini, DoubleType(), F.PandasUDFType.GROUPED_AGG)


@udtf(returnType=KMER)
class Kmers:
    """All windows of k characters."""

    def eval(self, text: str, k: int):
        for i in range(len(text or "") - k + 1):
            yield i, text[i : i + k]


@udtf(returnType=StructType([StructField("pos", IntegerType()), StructField("token", StringType())]))
class EdgeTokens:
    """The tokens of an edge line in order."""

    def eval(self, line: str):
        yield from enumerate((line or "").translate(str.maketrans("\t,;\r", "    ")).split())


@udtf(returnType=StructType([StructField("vertex", LongType()), StructField("target", LongType())]))
class CsrNeighbors:
    """Every (vertex, target) of a CSR block."""

    def eval(self, base_vertex: int, base_offset: int, offsets: list, targets: list):
        for i, (a, b) in enumerate(zip(offsets, offsets[1:])):
            for t in targets[a - base_offset : b - base_offset]:
                yield base_vertex + i, t


def register_views(graph_edges, csr) -> None:
    """SQL views ``edges``, ``csr_vertices`` and ``csr_slots`` over a graph and its CSR."""
    for name, df in (("edges", graph_edges), ("csr_vertices", csr.vertices), ("csr_slots", csr.slots)):
        df.createOrReplaceTempView(name)


def register(spark) -> None:
    """SQL names: parse_edge(line), degree_gini(degree), kmers(text, k), edge_tokens(line), csr_neighbors(base_vertex, base_offset, offsets, targets), and the expression twins edge_src, edge_dst, edge_weight."""
    spark.udf.register("parse_edge", parse_edge_row)
    spark.udf.register("degree_gini", degree_gini)
    for table_name, made in (("kmers", Kmers), ("edge_tokens", EdgeTokens), ("csr_neighbors", CsrNeighbors)):
        spark.udtf.register(table_name, made)
    for name, i, kind in (("edge_src", 0, "bigint"), ("edge_dst", 1, "bigint"), ("edge_weight", 2, "double")):
        spark.sql(f"create or replace temporary function {name}(line string) returns {kind} return try_cast(get(split(trim(translate(line, '\\t,;', '   ')), ' +'), {i}) as {kind})")
