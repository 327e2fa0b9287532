"""Work is done once: tokens of a line, passes over a text, runs of an experiment."""

import pytest

from edgecsr.functions.parse import parse_buffer, parse_line, parse_lines
from edgecsr.functions.udfs import parse_edge_row
from edgecsr.operators.baselines import sequential_csr
from edgecsr.plans import tune

LINES = ["1 2 3.5", "", "% c", "5", "6 x", "9223372036854775808 1", "0 1", "1 2 z", "+7,08;-1.5e3 more", "\t3\t4\r", "9223372036854775807 1 1e400"]


@pytest.mark.parametrize(("parser", "call", "most"), [("generic", "regexp_extract(", 3), ("direct", "split(", 1), ("format", "from_csv(", 1), ("digit_scan", "regexp_extract_all(", 1)])
def test_tokens_are_computed_once(spark, parser, call, most):
    lines = spark.createDataFrame([(x,) for x in LINES], "value string")
    edges, bad = parse_lines(lines, parser)
    for df in (edges, bad):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert plan.lower().replace("csvtostructs(", "from_csv(").count(call) <= most


def test_one_line_is_parsed_as_in_a_block():
    for line in LINES:
        bad = []
        a, b, w = parse_buffer(f"{line}\n% {line} é\n".encode(), True, 1, bad)
        found, reason = parse_line(line.encode())
        assert (found is not None) == (len(a) == 1) and reason == (bad[0][1] if bad else None)
        if found:
            assert found[:2] == (a[0], b[0]) and (found[2] == pytest.approx(w[0]))
    assert parse_edge_row.func("4 5 6.5") == (4, 5, 6.5) and parse_edge_row.func(None) is None and parse_edge_row.func("x y") is None


def test_sequential_offsets_come_from_written_degrees(spark, tmp_path):
    (tmp_path / "g").mkdir()
    (tmp_path / "g/a.txt").write_text("1 2 3\n4 1 1\n1 1 1\n")
    csr = sequential_csr(spark, str(tmp_path / "g"))
    assert not [x for x in csr.vertices.inputFiles() if x.endswith("a.txt")]
    assert [tuple(r) for r in csr.vertices.orderBy("vertex").collect()] == [(0, 2, 0), (1, 0, 2), (2, 0, 2), (3, 1, 2), (4, 0, 3)]
    (tmp_path / "none").mkdir()
    (tmp_path / "none/a.txt").write_text("% nothing\n")
    assert [tuple(r) for r in sequential_csr(spark, str(tmp_path / "none")).vertices.collect()] == [(0, 0, 0)]


def test_an_experiment_runs_as_often_as_asked(spark):
    calls = []

    def fn():
        calls.append(1)
        return spark.range(7)

    rows = tune._all(spark, "w", "g", {"m": fn}, 2).collect()
    assert len(calls) == 2 and [(r.edges_loaded, r.status) for r in rows] == [(7, "ok")] * 2
    degrees = lambda: spark.range(3).selectExpr("id as vertex", "id as degree")
    assert tune._all(spark, "w", "g", {"m": degrees}, 1).first().edges_loaded == 3
