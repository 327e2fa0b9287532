"""Graph operators on whole graphs: what a filter or a bound on rounds would lose."""

from itertools import combinations

from edgecsr.operators import graphops
from edgecsr.queries import queries
from edgecsr.sources import workloads as W


def test_bfs_goes_on_to_the_end_of_a_long_chain(spark):
    edges = spark.range(1, 54, numPartitions=1).selectExpr("id - 1 as src", "id as dst")
    assert {(r.vertex, r.level) for r in graphops.bfs_levels(edges, 0).collect()} == {(i, i) for i in range(54)}
    assert graphops.bfs_levels(edges, 0, 3).count() == 4


def test_triangles_of_the_whole_graph(spark, sf):
    pairs = {frozenset((r.src, r.dst)) for r in W.graph(spark, sf, "user_next").collect() if r.src != r.dst}
    near = {}
    for a, b in map(tuple, pairs):
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    want = sum(frozenset((a, b)) in pairs for of in near.values() for a, b in combinations(of, 2)) // 3
    assert queries()["triangle_count"](spark, sf).first()[0] == want


def test_lookups_ask_every_vertex(spark, sf):
    suppliers = W.table(spark, sf, "supplier").count()
    assert queries()["common_neighbors"](spark, sf).count() == suppliers
    assert queries()["neighbors_of"](spark, sf).count() == W.graph(spark, sf, "supp_part").count()
    top = W.graph(spark, sf, "part_supp").agg({"src": "max"}).first()[0]
    assert queries()["slot_range"](spark, sf).count() == top + 1
