"""The pool of pseudo-labels: whole, without a shuffle of features, and documents alike counted once."""

import numpy as np

from edgecsr.llm import quality
from edgecsr.llm.linear import LinearModel


def test_pool_is_ranked_by_distinct_keys_and_not_dealt(spark, monkeypatch):
    texts = [f"word{i % 9} and some more text" for i in range(60)] + ["labelled text"]
    docs = spark.createDataFrame([(i, t, "en", "web", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    labels = spark.createDataFrame([(60, 1), (60, 1), (None, 0)], "doc_id long, quality int")
    pool = quality.unlabelled(docs, labels)
    plan = pool._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning" not in plan.split("BroadcastExchange")[0]
    monkeypatch.setattr(quality, "BROADCAST_IDS", 0)
    rows = pool.collect()
    assert len(rows) == 60 and sorted(map(tuple, rows)) == sorted(map(tuple, quality.unlabelled(docs, labels).collect()))
    monkeypatch.setattr(quality, "PER_ROUND", 4)
    weights = {int(f): (j % 7) / 10 for j, f in enumerate(sorted({f for r in rows for f in np.frombuffer(r.content, np.uint32).tolist()}))}
    models, scales = [LinearModel(weights, 4.0), LinearModel({}, -4.0)], [(1.0, 0.0)] * 2
    by_key = {r.key: float(quality.Weights(models[0]).margins([np.frombuffer(r.content, np.uint32)])[0]) for r in rows}
    assert len(by_key) == 9
    used = {max(by_key.items(), key=lambda x: (x[1], x[0]))[0]}
    content, metadata = quality._surest_of(pool)(models, scales, used)
    want = sorted(((z, key) for key, z in by_key.items() if key not in used), reverse=True)[:4]
    assert [(key, label) for key, _, _, label in content] == [(key, 1) for _, key in want]
    assert [(key, label) for key, _, _, label in metadata] == [(key, 0) for key in sorted(by_key.keys() - used, reverse=True)[:4]]
