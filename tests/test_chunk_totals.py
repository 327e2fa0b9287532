"""Chunk totals of offsets come from the degrees that there are."""

from edgecsr.operators.csr import offsets
from edgecsr.operators.scan import exclusive_scan


def test_offsets_over_chunks_without_a_vertex(spark):
    found = spark.createDataFrame([(3, 2), (4, 1), (25, 4), (39, 1)], "vertex long, degree long")
    dense = [(v, {3: 2, 4: 1, 25: 4, 39: 1}.get(v, 0)) for v in range(41)]
    df = spark.createDataFrame(dense, "vertex long, degree long")
    expected = [(v, d, sum(x for _, x in dense[:v])) for v, d in dense]
    for more in ({}, {"n_keys": 41}, {"n_keys": 41, "sparse": found}):
        assert [tuple(r) for r in exclusive_scan(df, "vertex", "degree", chunk=5, **more).orderBy("vertex").collect()] == expected
    assert [tuple(r) for r in offsets(found, 40).orderBy("vertex").collect()] == expected
