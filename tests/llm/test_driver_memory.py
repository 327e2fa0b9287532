"""What stays on the driver after fits and rounds."""

import gc
import re
from pathlib import Path

import numpy as np

from edgecsr.llm import dart_minhash, toxicity


class Sample:
    def __init__(self, rows):
        self.rows = rows

    def select(self, *columns):
        return self

    def toLocalIterator(self):
        return iter(self.rows)


def resident() -> float:
    return sum(map(int, re.findall(r"\nPss_Anon:\s+(\d+)", Path("/proc/self/smaps_rollup").read_text()))) / 1024


def test_a_fit_gives_its_memory_back(spark, monkeypatch):
    def rows():
        rng = np.random.default_rng(1)
        words = np.array(["".join(w) for w in rng.choice(list("abcdefghijklmnop"), (60_000, 9))])
        return Sample([(i, " ".join(rng.choice(words, 200)), i % 2, i % 3 % 2) for i in range(4000)])

    monkeypatch.setattr(toxicity, "labelled_sample", lambda *a: rows())
    docs = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    gc.collect()
    before = resident()
    toxicity.train(docs, docs)
    print("MB kept", resident() - before)
    assert resident() - before < 16


def test_every_round_releases_what_it_used(spark, monkeypatch):
    rounds = []
    monkeypatch.setattr(dart_minhash, "release", rounds.append)
    text = " ".join(f"word{i}" for i in range(60))
    docs = spark.createDataFrame([(1, text), (2, text + " more"), (3, "other text of few words")], "doc_id long, text string")
    assert {r.doc_id: r.class_id for r in dart_minhash.classes(docs).collect()} == {1: 1, 2: 1, 3: 3}
    assert rounds
