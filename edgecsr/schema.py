"""Schemas and the small records that travel with graphs."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql.types import FloatType, IntegerType, LongType, StringType, StructField, StructType

EDGE = StructType([StructField("src", LongType()), StructField("dst", LongType()), StructField("weight", FloatType())])
CSR_VERTICES = StructType([StructField("vertex", LongType()), StructField("degree", LongType()), StructField("offset", LongType())])
CSR_SLOTS = StructType([StructField("slot", LongType()), StructField("vertex", LongType()), StructField("target", LongType()), StructField("weight", FloatType())])
PART_DEGREE = StructType([StructField("part", IntegerType()), StructField("vertex", LongType()), StructField("degree", LongType())])
BAD_RECORD = StructType([StructField("line", StringType()), StructField("reason", StringType())])


@dataclass(frozen=True)
class GraphMeta:
    """Sizes where they are known; ``n_rows`` bounds sources, ``n_cols`` targets."""

    n_rows: int | None = None
    n_cols: int | None = None
    symmetric: bool = False
    weighted: bool = True

    def having(self, **changes) -> GraphMeta:
        return replace(self, **changes)


@dataclass
class Graph:
    edges: DataFrame
    meta: GraphMeta
    bad: DataFrame | None = None
    degrees: DataFrame | None = None


@dataclass
class Csr:
    vertices: DataFrame
    slots: DataFrame
    meta: GraphMeta


@dataclass
class PartCsr:
    vertices: DataFrame
    slots: DataFrame
    parts: int
    meta: GraphMeta


@dataclass(frozen=True)
class MtxHeader:
    object: str
    format: str
    field: str
    symmetry: str
    rows: int
    cols: int
    entries: int
    size_line: str
    file: str = ""  # as it can be read, and as the scan names it
    place: str = ""

    @property
    def weighted(self) -> bool:
        return self.field != "pattern"

    @property
    def symmetric(self) -> bool:
        return self.symmetry in ("symmetric", "skew-symmetric", "hermitian")
