"""Pairs that a crowd of unlike texts makes, and the bound that leaves them out."""

import random

import numpy as np
from pyspark.sql import functions as F

from edgecsr.llm import dart_minhash as M
from edgecsr.llm.shingles import similarity, weighted


def test_parities_leave_no_similar_pair_out(spark):
    rng = np.random.default_rng(3)
    rows = []
    for n in (0, 1, 3, 40, 300, 5000):
        for off in (0, 1, 2, n // 20, n // 9, n // 3):
            one = rng.integers(0, 1 << 62, n, dtype=np.uint64)
            two = np.concatenate([one[off:], rng.integers(0, 1 << 62, rng.integers(0, off + 1), dtype=np.uint64)])
            a, b = ((x := np.unique(s), rng.integers(1, 3, len(x)).astype(float) if n % 2 else np.ones(len(x))) for s in (one, two))
            rows.append((similarity(a, b), float(a[1].sum()), float(b[1].sum()), *M._parities(a[0]).tolist(), *M._parities(b[0]).tolist()))
    names = ["found", "size", "_size", *M.PARITIES, *[f"_{p}" for p in M.PARITIES]]
    told = spark.createDataFrame(rows, names).select("found", F.expr(M._may_be_similar(0.8)).alias("may")).collect()
    assert all(r.may for r in told if r.found >= 0.8)
    assert any(r.found >= 0.8 for r in told) and any(not r.may for r in told)


def test_a_crowd_of_unlike_texts_makes_few_pairs(spark, monkeypatch):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(9000)]
    base = rng.sample(words, 150)
    rows = []
    for i in range(120):  # each half like the base, and like hardly another
        t = list(base)
        for at in rng.sample(range(150), 10):
            t[at] = rng.choice(words)
        rows.append((i, " ".join(t)))
    rows += [(200 + i, rows[7 * i][1] + " more of it") for i in range(10)]
    made = []
    estimated = M._estimated

    def counted(pairs, signatures):
        made.append(pairs.count())
        return estimated(pairs, signatures)

    monkeypatch.setattr(M, "_estimated", counted)
    sets = {i: weighted(t) for i, t in rows}
    want = {i: next(j for j in sets if similarity(sets[i], sets[j]) >= 0.8) for i in sets}
    got = {r.doc_id: r.class_id for r in M.classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want and len(set(want.values())) == 120
    assert sum(made[M.COARSE + 1 :]) < 2 * len(rows)
