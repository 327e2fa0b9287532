"""The two-pass edge list is written once."""

from edgecsr.operators.baselines import two_pass_csr


def test_two_pass_slots_come_from_a_written_edge_list(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1 2 3\n4 1 1\n1 1 1\n")
    csr = two_pass_csr(spark, str(tmp_path))
    assert csr.slots.inputFiles() and "edgelines" not in csr.slots._jdf.queryExecution().optimizedPlan().toString()
    assert [tuple(r) for r in csr.slots.orderBy("slot").collect()] == [(0, 0, 0, 1.0), (1, 0, 1, 3.0), (2, 3, 0, 1.0)]
    assert [tuple(r) for r in csr.vertices.orderBy("vertex").collect()] == [(0, 2, 0), (1, 0, 2), (2, 0, 2), (3, 1, 2), (4, 0, 3)]
    (tmp_path / "none").mkdir()
    (tmp_path / "none/a.txt").write_text("% nothing\n")
    assert [tuple(r) for r in two_pass_csr(spark, str(tmp_path / "none")).vertices.collect()] == [(0, 0, 0)]
