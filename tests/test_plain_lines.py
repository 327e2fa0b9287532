"""Plain lines are parsed as all others, with less work."""

import numpy as np
import pytest

from edgecsr.functions.parse import parse_line, parse_lines

ODD = ["1 2", "1 2 3", "1 2 3.", "1 2 .5", "1  2 3", " 1 2 3", "1 2 3 ", "1 2 3 4", "1 2 -3", "1 2 3e2", "1 2\r", "1,2,3", "1 2 3\r", "999999999999999999 1", "9223372036854775807 1", "9223372036854775808 1", "0 1", "1 0 x", "1", "1 ", "a b", "1 2 x", "1 2 3.4.5", "1 2 \x01", "1\x01 2", "٣ 2", "1 2 1234567890123456", "", "%", " # 1 2", "1 2 NaN", "1 2 3f", "1 2 1d"]


@pytest.mark.parametrize("parser", ["direct", "generic", "format"])
def test_plain_lines_are_parsed_as_all_others(spark, parser):
    lines = spark.createDataFrame([(x,) for x in ODD], "value string")
    edges, bad = parse_lines(lines, parser)
    told = [parse_line(x.encode()) for x in ODD]
    assert sorted((r.src, r.dst, r.weight) for r in edges.collect()) == sorted((a, b, float(np.float32(w))) for (found, _) in told if found for a, b, w in [found])
    assert sorted((r.line, r.reason) for r in bad.collect()) == sorted((x, reason) for x, (_, reason) in zip(ODD, told) if reason)
    assert edges._jdf.queryExecution().optimizedPlan().toString().count("translate(") <= 1  # characters are looked up one by one in lines that need it only
