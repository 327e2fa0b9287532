"""Worked examples, block and parser properties, and equality of all methods."""

import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from edgecsr.functions.parse import parse_buffer, parse_lines
from edgecsr.operators import csr as C
from edgecsr.operators import edges as E
from edgecsr.operators.csr_forms import from_blocks, to_blocks, to_packed
from edgecsr.operators.readers import read_edges
from edgecsr.plans import invariants, measures
from edgecsr.plans.planner import choose_method
from edgecsr.schema import Graph, GraphMeta
from edgecsr.sources.blocks import align_block, plan_blocks
from edgecsr.sources.mtx import read_mtx_header, write_mtx
from edgecsr.streaming.edges import merge_csr_delta

FILE = b"1 2\n1 3 \n2 3\n10 11\n3 1\n"


@pytest.mark.parametrize("size,cuts", [(4, [(0, 4), (4, 9), (9, 13), (13, 19), (19, 23), (23, 23)]), (8, [(0, 9), (9, 19), (19, 23)]), (64, [(0, 23)])])
def test_block_cuts(size, cuts):
    assert [align_block(FILE, at, size) for at in range(0, len(FILE), size)] == cuts


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text(alphabet="0123 ", max_size=12)), st.integers(1, 40), st.booleans())
def test_blocks_tile_any_file(lines, size, ended):
    data = "\n".join(lines).encode() + (b"\n" if ended else b"")
    cuts = [align_block(data, at, size) for at in range(0, len(data), size)]
    assert b"".join(data[a:b] for a, b in cuts) == data
    for a, _ in cuts:
        assert a in (0, len(data)) or data[a - 1] == 0x0A


def test_plan_blocks():
    assert [(b.start, b.length) for b in plan_blocks([("a", 10), ("b", 0)], 4)] == [(0, 4), (4, 4), (8, 2)]


def test_parser_table(spark):
    rows = ["  1\t2 ", "3,4", "5", "6 x", "7 8 -1.5e3", "% 9 9", "", "9223372036854775808 1", "0 1", "1 2 3\r"]
    lines = spark.createDataFrame([(r,) for r in rows], "value string")
    want = {(0, 1, 1.0), (2, 3, 1.0), (6, 7, -1500.0), (0, 1, 3.0)}
    for parser in ("direct", "generic", "format", "vector"):
        edges, bad = parse_lines(lines, parser)
        assert {tuple(r) for r in edges.select("src", "dst", "weight").collect()} == want, parser
        if parser != "vector":
            assert bad.count() == 4
    with pytest.raises(Exception, match="bad edge line"):
        parse_lines(lines, "direct", mode="FAILFAST")[0].collect()
    assert parse_buffer(b"1 2\n3 4")[0].tolist() == [0, 2]


F2 = [(1, 0, 0.5), (2, 0, 1.5), (2, 1, 2.5), (4, 2, -3.0), (3, 3, 7.0)]


@pytest.mark.parametrize("loops,degrees,offsets", [("double", [2, 2, 3, 2, 1], [0, 2, 4, 7, 9, 10]), ("once", [2, 2, 3, 1, 1], [0, 2, 4, 7, 8, 9])])
def test_symmetric_with_diagonal(spark, loops, degrees, offsets):
    e = E.symmetrize(spark.createDataFrame(F2, "src long, dst long, weight float"), loops)
    for method in ("single", "staged", "sorted"):
        csr = C.build_csr(Graph(e, GraphMeta(n_rows=5)), method)
        rows = csr.vertices.orderBy("vertex").collect()
        assert [r.degree for r in rows][:5] == degrees and [r.offset for r in rows] == offsets
        got = [(r.target, r.weight) for r in csr.slots.orderBy("slot").collect()]
        assert got[:4] == [(1, 0.5), (2, 1.5), (0, 0.5), (2, 2.5)] and got[-1] == (2, -3.0)


def test_two_parts(spark):
    rows = [(0, 1), (0, 2), (1, 2), (0, 3), (2, 0), (0, 1)]
    e = spark.createDataFrame([(s, d, float(i), i % 2) for i, (s, d) in enumerate(rows)], "src long, dst long, weight float, part int")
    part = C.build_part_csr(Graph(e, GraphMeta(n_rows=4)), 2)
    v = {(r.part, r.vertex): (r.degree, r.offset) for r in part.vertices.collect()}
    assert [v[0, i] for i in range(4)] == [(1, 0), (1, 1), (1, 2), (0, 3)]
    assert [v[1, i] for i in range(4)] == [(3, 0), (0, 3), (0, 3), (0, 3)]
    merged = C.merge_part_csr(part)
    direct = C.build_staged(Graph(e, GraphMeta(n_rows=4)), 2, None)
    for csr in (merged, direct):
        assert [r.offset for r in csr.vertices.orderBy("vertex").collect()] == [0, 4, 5, 6, 6]
        assert [r.target for r in csr.slots.orderBy("slot").collect()][:1] == [1]
        assert [r.target for r in csr.slots.orderBy("slot").collect()][4:] == [2, 0]
    assert merged.slots.exceptAll(direct.slots).isEmpty()


def test_methods_agree_and_obey_the_rules(spark):
    rng = random.Random(3)
    rows = [(rng.choice([0, 0, 0, 1, 2, 5, 9]), rng.randrange(12), float(rng.randrange(3))) for _ in range(400)]
    e = spark.createDataFrame(rows, "src long, dst long, weight float")
    first = None
    for method, n in (("single", None), ("staged", None), ("sorted", 1), ("sorted", 7), ("auto", None)):
        csr = C.build_csr(Graph(e, GraphMeta()), method, partitions=n)
        assert invariants.check(csr, e).where("violations > 0").isEmpty(), method
        first = first or csr
        assert csr.slots.exceptAll(first.slots).isEmpty() and csr.vertices.exceptAll(first.vertices).isEmpty()
    assert from_blocks(to_blocks(first, 3)).exceptAll(first.slots).isEmpty()
    packed = to_packed(first).first()
    assert packed.offsets[-1] == 400 and len(packed.targets) == 400
    with pytest.raises(ValueError):
        to_packed(first, 10)


def test_empty_graph(spark):
    e = spark.createDataFrame([], "src long, dst long, weight float")
    for method in ("single", "staged", "sorted"):
        csr = C.build_csr(Graph(e, GraphMeta()), method)
        assert [tuple(r) for r in csr.vertices.collect()] == [(0, 0, 0)] and csr.slots.isEmpty()


def test_delta_equals_rebuild(spark):
    rng = random.Random(5)
    rows = [(rng.randrange(9), rng.randrange(9), 1.0) for _ in range(200)]
    e = spark.createDataFrame(rows, "src long, dst long, weight float")
    csr = C.build_csr(Graph(e.where("dst < 6 and src < 7"), GraphMeta()), "sorted")
    merged, whole = merge_csr_delta(csr, e.where("not (dst < 6 and src < 7)")), C.build_csr(Graph(e, GraphMeta()), "sorted")
    assert merged.slots.exceptAll(whole.slots).isEmpty() and merged.vertices.exceptAll(whole.vertices).isEmpty()


def test_matrix_market(spark, tmp_path):
    path = str(tmp_path / "m")
    e = spark.createDataFrame(F2, "src long, dst long, weight float")
    write_mtx(e, path, 5, 5, "real", "symmetric")
    h = read_mtx_header(spark, path)
    assert (h.rows, h.cols, h.entries, h.symmetric, h.weighted) == (5, 5, 5, True, True)
    g = read_edges(spark, path, "block", header="mtx")
    assert g.edges.count() == 9 and g.meta.n_rows == 5
    assert read_edges(spark, path, "block", header="mtx", honor_header=False).edges.count() == 5


@pytest.mark.parametrize("block", [3, 7, 64, 4096])
def test_block_source_reads_every_line_once(spark, tmp_path, block):
    path = tmp_path / "edges.txt"
    path.write_text("".join(f"{i + 1} {i * 7 % 50 + 1} {i}.5\n" for i in range(500))[:-1])
    g = read_edges(spark, str(path), source="blocks", block_bytes=block).edges
    assert sorted(r.src for r in g.select("src").collect()) == list(range(500))
    from edgecsr.sources.block_source import Split, lines_of

    size = path.stat().st_size
    whole = b"".join(lines_of(Split(str(path), at, min(block, size - at), size)) for at in range(0, size, block))
    assert whole == path.read_bytes()


def test_planner(spark):
    chain = spark.range(1000).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).cast("float").alias("weight"))
    hub = spark.range(1000).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"), F.lit(1.0).cast("float").alias("weight"))
    assert choose_method(Graph(chain, GraphMeta())) == "single"
    assert choose_method(Graph(hub, GraphMeta())) == "staged"
    assert choose_method(Graph(hub, GraphMeta()), large=10) == "sorted"


def test_sorted_build_has_no_single_partition_exchange_of_edges(spark):
    e = spark.range(1000).select((F.col("id") % 7).alias("src"), F.col("id").alias("dst"), F.lit(1.0).cast("float").alias("weight"))
    plan = e.repartitionByRange("src", "dst", "weight").sortWithinPartitions("src", "dst", "weight")._jdf.queryExecution().toString()
    assert "rangepartitioning" in plan and "SinglePartition" not in plan


def test_measures(spark):
    a = measures.records(spark, "w", "g", "slow", [(4.0, "ok"), (6.0, "ok")], edges_loaded=100, size=1000)
    b = measures.records(spark, "w", "g", "fast", [(2.0, "ok"), (3.0, "ok"), (float("nan"), "failed: X")], edges_loaded=100, size=1000)
    both = a.union(b)
    assert {r.method: r.relative for r in measures.relative(both, "slow").collect()} == {"slow": 1.0, "fast": 0.5}
    assert {r.method: r.arithmetic for r in measures.speedup(both, "slow").collect()}["fast"] == 2.0
    assert {r.method: r.edges_per_second for r in measures.edge_rate(both).collect()}["fast"] == 40.0
    assert round(measures.per_doubling(25.0, 5), 2) == 1.90 and round(measures.per_doubling(13.9, 5), 2) == 1.69
