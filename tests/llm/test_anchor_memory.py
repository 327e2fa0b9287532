"""What a task that finds anchors holds at once."""

import tracemalloc

import numpy as np
import pyarrow as pa

from edgecsr.llm import suffix_array as S


class Direct:
    def mapInArrow(self, run, schema):
        return run


def test_anchors_of_a_task_take_little_memory():
    rng = np.random.default_rng(1)
    words = ["".join(w) for w in rng.choice(list("abcdefghijklmnop"), (4000, 6))]
    texts = [" ".join(rng.choice(words, 900)) for _ in range(1200)]  # 7.5 MB
    batch = pa.RecordBatch.from_arrays([pa.array(range(1200), pa.int64()), pa.array(texts), pa.array(range(1200), pa.int64())], ["doc_id", "text", "text_hash"])
    run = S._anchored(Direct(), np.zeros(0, np.uint64), 64, 64, S.LENGTH)
    tracemalloc.start()
    try:
        blobs = [(k, b) for out in run(iter([batch])) for k, b in zip(out.column(1).to_pylist(), out.column(2).to_pylist())]
        peak = tracemalloc.get_traced_memory()[1] / 1e6
    finally:
        tracemalloc.stop()
    doc, _, start, count, *_ = S.joined([b for k, b in blobs if k == S._OPEN], S.REGION_KINDS)
    assert int(count.sum()) + sum(int(S.unwrap_rows(b, S.COVERED)[3].sum()) for k, b in blobs if k == S._SETTLED) == sum(len(t) - S.LENGTH + 1 for t in texts)
    print("peak MB", peak)
    assert peak < 120
