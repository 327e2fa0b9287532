"""Streams: late rows, and a restart that goes on where it stopped."""

import json

from pyspark.sql import functions as F

from edgecsr.sources import block_source
from edgecsr.streaming import edges as S


def _run(df, at, mode="append"):
    q = df.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_rows_behind_the_watermark_are_dropped_and_counted(spark, tmp_path):
    at = tmp_path / "in"
    at.mkdir()
    (at / "1.json").write_text("\n".join(json.dumps({"ts": f"2024-01-01 {h:02}:00:00", "event_type": "a", "value": 1.0}) for h in (1, 2, 9)))
    events = spark.readStream.schema("ts timestamp, event_type string, value double").json(str(at)).withWatermark("ts", "1 hour")
    counted = S.windowed_edges(events, "1 hour")
    _run(counted, tmp_path)
    (at / "2.json").write_text("\n".join(json.dumps({"ts": f"2024-01-01 {h:02}:30:00", "event_type": "a", "value": 1.0}) for h in (1, 12)))
    q = _run(counted, tmp_path)
    dropped = sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])
    assert dropped == 1  # the row of 01:30, seven hours behind
    rows = {str(r.start): r.n_edges for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert rows["2024-01-01 01:00:00"] == 1 and rows["2024-01-01 09:00:00"] == 1


def test_a_restarted_stream_reads_each_file_once(spark, tmp_path):
    at = tmp_path / "in"
    at.mkdir()
    block_source.register(spark)
    stream = lambda: spark.readStream.format("edgeblocks").option("path", str(at)).load().select("src", "dst")
    (at / "a.txt").write_text("1 2 1\n3 4 1\n")
    _run(stream(), tmp_path)
    (at / "b.txt").write_text("5 6 1\n")
    _run(stream(), tmp_path)
    _run(stream(), tmp_path)
    assert sorted(r.src for r in spark.read.parquet(f"{tmp_path}/out").collect()) == [0, 2, 4]
    total = S.run_to_table(S.incremental_degrees(stream()), "complete")
    assert total.agg(F.sum("degree")).first()[0] == 3
