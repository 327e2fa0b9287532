"""Workload rows carry what the rates and the scaling are computed from."""

from edgecsr.plans import measures, tune


def test_rows_have_edges_bytes_and_rates(spark, sf):
    found = tune.sweep_weights(spark, sf, "nation_region", runs=1).union(tune.compare_degree_shapes(spark, sf, ("nation_region",), runs=1))
    for r in found.collect():
        in_memory = r.workload == "shapes"
        assert r.edges_loaded == 25 and r.edges_in_file == (0 if in_memory else 25) and (r.bytes == 0) == in_memory
    assert all(r.edges_per_second > 0 for r in measures.edge_rate(found).collect())
    assert all(r.bytes_per_second > 0 for r in measures.byte_rate(found.where("workload = 'weights'")).collect())


def test_scaling_over_real_task_counts(spark, sf):
    rows = measures.scaling(tune.sweep_tasks(spark, sf, "nation_region", (1, 2), 1)).collect()
    assert {(r.method, r.cores) for r in rows} == {(m, c) for m in ("edge_list", "csr") for c in (1, 2)}
    assert all((r.per_doubling is not None) == (r.cores == 2) for r in rows)


def test_readers_are_different_plans():
    assert len({tuple(sorted(o.items())) for o in tune.READERS.values()}) == len(tune.READERS)
    assert {"R1", "R2", "R3", "R4", "R5", "R6"} == set(tune.READERS)


def test_scaling_over_sessions_of_their_own(spark, sf):
    rows = tune.scale_cores(spark, sf, "nation_region", (1, 2), 1).collect()
    assert {(r.method, r.cores, r.status) for r in rows} == {(m, c, "ok") for m in ("edge_list", "csr") for c in (1, 2)}
