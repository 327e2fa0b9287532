"""Rules that every CSR must obey; each yields its number of violations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.schema import Csr


def _one(df: DataFrame, rule: str, violations) -> DataFrame:
    return df.agg(F.coalesce(violations, F.lit(0)).cast("long").alias("violations")).select(F.lit(rule).alias("rule"), "violations")


def check(csr: Csr, edges: DataFrame) -> DataFrame:
    """(rule, violations) of all rules."""
    v, s = csr.vertices, csr.slots
    n = csr.meta.n_rows
    step = v.join(v.select((F.col("vertex") - 1).alias("vertex"), F.col("offset").alias("_next")), "vertex", "left")
    ends = v.agg(F.max("offset").alias("last"), F.min("offset").alias("first"), F.sum("degree").alias("total"))
    size = s.agg(F.count("*").alias("n"), F.min("slot").alias("low"), F.max("slot").alias("high"), F.countDistinct("slot").alias("distinct"))
    owned = s.join(v, "vertex", "left")
    cols = ["src", "dst", "weight"]
    back = s.select(F.col("vertex").alias("src"), F.col("target").alias("dst"), "weight")
    lost = edges.select(cols).exceptAll(back).union(back.exceptAll(edges.select(cols)))
    found = [
        _one(step, "offsets do not decrease", F.count_if(F.col("_next") < F.col("offset"))),
        _one(ends, "first offset is 0", F.sum(F.when(F.col("first") != 0, 1).otherwise(0))),
        _one(ends.crossJoin(F.broadcast(size)), "last offset is the number of edges", F.sum(F.when(F.coalesce("last", F.lit(0)) != F.col("n"), 1).otherwise(0))),
        _one(step, "offsets differ by degrees", F.count_if((F.col("_next") - F.col("offset")) != F.col("degree"))),
        _one(size, "slots are 0 to n-1", F.sum(F.when((F.col("n") > 0) & ((F.col("low") != 0) | (F.col("high") != F.col("n") - 1) | (F.col("distinct") != F.col("n"))), 1).otherwise(0))),
        _one(owned, "slots lie in their vertex's range", F.count_if(F.col("offset").isNull() | (F.col("slot") < F.col("offset")) | (F.col("slot") >= F.col("offset") + F.col("degree")))),
        _one(lost, "edges are kept as a multiset", F.count("*")),
        _one(ends.crossJoin(F.broadcast(size)), "degrees sum to the number of edges", F.sum(F.when(F.coalesce("total", F.lit(0)) != F.col("n"), 1).otherwise(0))),
        _one(v, "each vertex has one row", F.abs(F.count("*") - F.lit(n + 1))),
    ]
    out = found[0]
    for f in found[1:]:
        out = out.union(f)
    return out


def vertices_without_edges(csr: Csr) -> DataFrame:
    w = Window.partitionBy("offset")
    return csr.vertices.where("degree = 0").withColumn("shared", F.count("*").over(w))
