"""Queries that once made their data up take every row of a given table."""

import pytest

from edgecsr.queries import queries
from edgecsr.sources import workloads as W


@pytest.mark.parametrize("name", ["edges_bad_records", "edges_bad_records_vector"])
def test_bad_records_of_the_whole_table(spark, sf, name):
    flawed = W.table(spark, sf, "lineitem").where("l_orderkey % 8 < 5").count()
    assert sum(r.n for r in queries()[name](spark, sf).collect()) == flawed > 1000


def test_corrupt_records_of_the_whole_table(spark, sf):
    assert len(queries()["csv_corrupt_records"](spark, sf).collect()) == W.table(spark, sf, "lineitem").where("l_orderkey % 4 <> 2").count() > 1000


@pytest.mark.parametrize("name", ["measures_byte_rate", "measures_edge_rate"])
def test_rates_of_runs_in_events(spark, sf, name):
    found = queries()[name](spark, sf)
    assert any(x.endswith("events.parquet") for x in found.inputFiles())
    events = W.table(spark, sf, "events").where("event_id % 11 <> 0")
    assert found.count() == events.selectExpr("event_type", "user_id % 4").distinct().count()
