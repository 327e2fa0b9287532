"""One grammar in all parsers, headers by place, wide numbers, and settings that come back."""

import pytest
from pyspark.sql import functions as F

from edgecsr.functions.parse import parse_lines
from edgecsr.operators import csr as C
from edgecsr.operators.csr_forms import from_blocks, to_blocks
from edgecsr.operators.readers import read_csr, read_edges, settled
from edgecsr.schema import Graph, GraphMeta
from edgecsr.sources.block_source import equal_slices
from edgecsr.sources.edgetext import estimate_edges, read_csr_files, scan_lines, write_csr, write_csr_buckets

ODD = [
    "1 2 3", "1_0 2 3", "0x10 2 3", "+1 2", "1.0 2", "1e2 3", "1 2 nan", "1 2 inf", "1 2 1d", "1 2 1f", "1 2 1_0", "1 2 .5", "1 2 5.", "1 2 .", "1 2 1e", "1 2 +1E+2",
    "\"1\" 2", "'1' 2", "1", "", " ", ",,", ",% 1 2", "# 1 2", "  % 1 2", "1 2 3 4 x", "1;2;3", "1,2\t3\r", "-1 2", "0 5", "9223372036854775807 1", "9223372036854775808 1",
    "-9223372036854775809 1", "1 2 1e400", "1 2 NULL", "NA 2", "1\x0b2", "1 2\x01", "1  2   7", "x", "1 x", "1 2 --3", "1 +-2", "١ 2",
]


@pytest.mark.parametrize("weighted", [True, False])
def test_all_parsers_agree_on_odd_lines(spark, weighted):
    lines = spark.createDataFrame([(x,) for x in ODD], "value string").coalesce(1)
    found = {}
    for parser in ("direct", "generic", "format", "vector"):
        edges, bad = parse_lines(lines, parser, weighted)
        found[parser] = sorted(map(tuple, edges.select("src", "dst", "weight").collect())), sorted(map(tuple, bad.collect()))
    assert found["direct"] == found["generic"] == found["format"] == found["vector"]
    edges, bad = found["direct"]
    assert (9, 1, 3.0) not in edges and (15, 1, 3.0) not in edges and len(bad) > 10 and len(edges) > 5


def test_a_line_reads_alike_in_any_block(spark):
    """Regular lines alone, and among odd ones that send the block another way."""
    regular = [f"{i} {i + 1} {i}.25" for i in range(1, 50)]
    alone, among = (parse_lines(spark.createDataFrame([(x,) for x in rows], "value string").coalesce(1), "vector")[0] for rows in (regular, regular + ODD))
    assert set(map(tuple, alone.collect())) <= set(map(tuple, among.collect()))


@pytest.mark.parametrize("method", ["block", "block_vector"])
def test_bad_records_and_modes(spark, tmp_path, method):
    (tmp_path / "e.txt").write_text("1 2 3\n4 x 5\n6\n")
    path = str(tmp_path / "e.txt")
    g = read_edges(spark, path, method)
    assert g.edges.count() == 1 and {r.reason for r in g.bad.collect()} == {"bad id", "missing target"}
    with pytest.raises(Exception, match="bad edge line"):
        read_edges(spark, path, method, mode="FAILFAST").edges.collect()
    assert read_edges(spark, path, "block_vector", source="blocks").bad.count() == 2


def test_size_line_goes_by_its_place(spark, tmp_path):
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate real general\n" + "% note\n" * 150 + "3 3 4\n1 1 1\n3 3 4\n2 2 2\n3 3 4\n")
    path = str(tmp_path / "m.mtx")
    for method in ("serial", "line_block", "block", "block_vector"):
        got = sorted(map(tuple, read_edges(spark, path, method, header="auto").edges.select("src", "dst", "weight").collect()))
        assert got == [(0, 0, 1.0), (1, 1, 2.0), (2, 2, 4.0), (2, 2, 4.0)], method


def test_blocks_keep_all_64_bits(spark):
    rows = [(0, 2**53 + 1, 1.0), (0, 2**62 + 3, 2.0), (2, 5, 0.5)]
    csr = C.build_csr(Graph(spark.createDataFrame(rows, "src long, dst long, weight float"), GraphMeta(n_rows=4)), "sorted")
    back = from_blocks(to_blocks(csr, 2))
    assert back.exceptAll(csr.slots).isEmpty() and back.count() == 3 and 2**53 + 1 in {r.target for r in back.collect()}


def test_parts_of_one_large_file_differ(spark, tmp_path):
    (tmp_path / "e.txt").write_text("".join(f"{i} {i}\n" for i in range(1, 40000)))
    before = spark.conf.get("spark.sql.files.maxPartitionBytes"), spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.files.maxPartitionBytes", "16384")
    try:
        parts = scan_lines(spark, str(tmp_path / "e.txt"), 4).groupBy("part").count().collect()
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before[0])
    assert {r.part for r in parts} == {0, 1, 2, 3} and sum(r["count"] for r in parts) == 39999
    read_edges(spark, str(tmp_path / "e.txt"), "line_block", weighted=False, parser="vector", parse_chunk=7).edges.count()
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before[1]


def test_static_slices_are_equal_and_hold_every_line_once(spark, tmp_path):
    for name, n in (("a.txt", 1000), ("b.txt", 3), ("c.txt", 500)):
        (tmp_path / name).write_text("".join(f"{i} {i * 3}\n" for i in range(1, n + 1)))
    sizes = [(str(p), p.stat().st_size) for p in sorted(tmp_path.iterdir())]
    slices = [sum(s.length for s in x) for x in equal_slices(sizes, 7)]
    assert sum(slices) == sum(n for _, n in sizes) and max(slices) - min(slices) <= 1
    want = sorted(map(tuple, read_edges(spark, str(tmp_path), weighted=False).edges.select("src", "dst").collect()))
    for options in ({"method": "block", "schedule": "static"}, {"source": "blocks", "schedule": "static"}, {"method": "line_block", "line_source": "buffered"}):
        got = read_edges(spark, str(tmp_path), weighted=False, **options).edges.select("src", "dst")
        assert sorted(map(tuple, got.collect())) == want and len(want) == 1503
    assert abs(estimate_edges(spark, str(tmp_path)) - 1503) < 300


def test_csr_reads_the_text_once(spark, tmp_path):
    (tmp_path / "e.txt").write_text("1 2 3\n4 2 5\n4 9 1\n")
    g = settled(read_edges(spark, str(tmp_path / "e.txt")))
    assert (g.meta.n_rows, g.meta.n_cols) == (4, 9)
    for method in ("single", "staged", "sorted"):
        csr = read_csr(spark, str(tmp_path / "e.txt"), method)
        for df in (csr.vertices, csr.slots):
            plan = df._jdf.queryExecution().toString()
            assert "FileScan text" not in plan and "FileScan parquet" in plan or "Range" in plan
        assert [r.offset for r in csr.vertices.orderBy("vertex").collect()] == [0, 1, 1, 1, 3]
    with_degrees = read_edges(spark, str(tmp_path / "e.txt"), with_degrees="parts")
    assert "FileScan text" not in with_degrees.degrees._jdf.queryExecution().toString()


def test_files_keep_sizes_and_buckets_need_no_exchange(spark, tmp_path):
    e = spark.createDataFrame([(0, 3, 1.0), (2, 1, 1.0), (2, 2, 1.0)], "src long, dst long, weight float")
    csr = C.build_csr(Graph(e, GraphMeta(n_rows=5, n_cols=4)), "staged")
    write_csr(csr, str(tmp_path / "csr"))
    back = read_csr_files(spark, str(tmp_path / "csr"))
    assert back.meta == csr.meta and back.slots.exceptAll(csr.slots).isEmpty() and back.vertices.count() == 6
    assert {r.vertex: r.degree for r in C.degree_of(back, spark.range(8).withColumnRenamed("id", "vertex")).collect()} == {0: 1, 1: 0, 2: 2, 3: 0, 4: 0, 5: 0, 6: 0, 7: 0}
    write_csr_buckets(csr, "bucketed_csr", 4)
    joined = spark.table("bucketed_csr_slots").join(spark.table("bucketed_csr_vertices").hint("merge"), "vertex")
    assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString() and joined.count() == 3


def test_distribution_hints(spark):
    e = spark.range(100).select(F.col("id").alias("src"), (F.col("id") % 3).cast("int").alias("p"))
    assert "REBALANCE" in e.hint("rebalance", "src")._jdf.queryExecution().toString().upper()
    placed = e.repartitionById(3, F.col("p")).select("p", F.spark_partition_id().alias("at")).distinct().collect()
    assert {(r.p, r.at) for r in placed} == {(0, 0), (1, 1), (2, 2)}
