"""Near duplicates, repeated strings and vector search against brute force and on odd inputs; the pipeline's stages."""

import hashlib
import math
import random
from collections import defaultdict

import numpy as np
import pytest

from edgecsr.llm import dart_minhash, exact_topk, hnsw
from edgecsr.llm.shingles import shingles, similarity, weighted
from edgecsr.llm.suffix_array import equal_windows, remove_repeats, suffix_array
from edgecsr.llm.vectors import queries_of, usable

SCHEMA = "doc_id long, text string, id long, label string, bucket int"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, 1, "x", 2) for i, t in rows], SCHEMA)


# --- near duplicates --------------------------------------------------------


def _components(sets: dict, threshold: float) -> dict:
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[:n]:
            if similarity(sets[a], sets[b]) >= threshold:
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_classes_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = _components({r.doc_id: weighted(r.text) for r in docs.collect()}, 0.8)
    assert {r.doc_id: r.class_id for r in dart_minhash.classes(docs).collect()} == want


@pytest.mark.parametrize("counts", [False, True])
def test_a_crowd_of_near_copies_and_chains(spark, counts):
    rng = random.Random(4)
    words = [f"w{i}" for i in range(5000)]
    base = rng.sample(words, 150)
    rows = []
    for i in range(60):  # many near copies of one text, some too far from each other
        t = list(base)
        for _ in range(rng.randrange(5)):
            t[rng.randrange(150)] = rng.choice(words)
        rows.append((i, " ".join(t)))
    chain = rng.sample(words, 200)
    for i in range(100, 112):  # each like the next, the ends unlike
        rows.append((i, " ".join(chain)))
        at = (i - 100) * 15
        chain[at : at + 10] = rng.sample(words, 10)
    rows += [(200 + i, " ".join(rng.sample(words, 80))) for i in range(20)]
    want = _components({i: weighted(t, counts=counts) for i, t in rows}, 0.8)
    got = {r.doc_id: r.class_id for r in dart_minhash.classes(frame(spark, rows), counts=counts).collect()}
    assert got == want and len(set(want.values())) > 3


def test_classes_of_odd_rows(spark):
    rows = [(5, None), (6, ""), (7, "  \n"), (8, "one two"), (9, "One  two"), (9, "One  two"), (None, "one two"), (10, "a b c d e f g " * 30000)]
    got = {r.doc_id: r.class_id for r in dart_minhash.classes(frame(spark, rows)).collect()}
    assert got == {5: 5, 6: 5, 7: 5, 8: 8, 9: 8, 10: 10}
    assert dart_minhash.classes(frame(spark, [])).collect() == []


def test_repeated_ids_keep_the_links_of_each_text(spark):
    rng = random.Random(8)
    w, v = (" ".join(rng.choice("abcdefghijklm") + str(rng.randrange(900)) for _ in range(120)) for _ in range(2))
    got = {tuple(r) for r in dart_minhash.classes(frame(spark, [(1, w), (5, v), (5, w + " x"), (9, v + " y")])).collect()}
    assert got == {(1, 1, 1, 1), (5, 5, 1, 1), (5, 5, 5, 1), (9, 9, 5, 1)}


def test_signatures_estimate_weighted_similarity():
    rng = np.random.default_rng(0)
    el = rng.integers(0, 2**63, 300).astype(np.uint64)
    a, b = rng.integers(1, 5, 300) + rng.random(300), rng.integers(1, 5, 300) + rng.random(300)
    want = np.minimum(a, b).sum() / np.maximum(a, b).sum()
    assert abs((dart_minhash.signature(el, a, 3000) == dart_minhash.signature(el, b, 3000)).mean() - want) < 0.04
    alone, together = dart_minhash.signature(el, a, 64), dart_minhash.signatures([(el[:5], b[:5]), (el, a)], 64)[1]
    assert (alone == together).all()


def test_shingles():
    assert len(shingles("a b c d e f")) == 2 and len(shingles("a b")) == 1 and len(shingles("  ")) == 0
    assert (shingles("A b c D e") == shingles("a  B\nc d E")).all()


# --- repeated strings -------------------------------------------------------


def brute(rows, length):
    seen, out = {}, {}
    for doc, text in rows:
        data = (text or "").encode()
        for j in range(len(data) - length + 1):
            w = data[j : j + length]
            seen[w] = min(seen.get(w, doc), doc)
    for doc, text in rows:
        data = (text or "").encode()
        covered = np.zeros(len(data), bool)
        for j in range(len(data) - length + 1):
            if seen[data[j : j + length]] < doc:
                covered[j : j + length] = True
        kept = bytes(np.frombuffer(data, np.uint8)[~covered])
        out[doc] = (len(data), int(covered.sum()), int((np.diff(np.concatenate([[0], covered.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest())
    return out


def removed(docs):
    return {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in remove_repeats(docs).collect()}


def test_suffix_array_equals_sorting():
    rng = np.random.default_rng(1)
    for _ in range(200):
        s = rng.integers(0, rng.integers(1, 5), rng.integers(0, 60))
        assert suffix_array(s).tolist() == sorted(range(len(s)), key=lambda i: s[i:].tolist())
    text = np.frombuffer(b"abcabcabcx", np.uint8).astype(np.int64)
    place, kind = equal_windows(text, np.arange(10) < 8, 3)
    same = defaultdict(set)
    for p, k in zip(place.tolist(), kind.tolist()):
        same[k].add(p)
    assert {0, 3, 6} in same.values() and {1, 4} in same.values()


def test_given_documents_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert removed(docs) == brute([(r.doc_id, r.text) for r in docs.collect()], 50)


def test_random_overlaps_equal_brute_force(spark):
    rng = random.Random(7)
    shared = ["".join(rng.choice("abcd é\n") for _ in range(rng.randrange(30, 160))) for _ in range(6)]
    rows = []
    for i in range(120):
        parts = [rng.choice(shared)[rng.randrange(20) :] if rng.random() < 0.6 else "".join(rng.choice("abcdefgh ") for _ in range(rng.randrange(90))) for _ in range(rng.randrange(5))]
        rows.append((rng.randrange(10**9), "".join(parts)))
    rows += [(10**9 + i, "a" * 70 + "b" * i) for i in range(5)]
    assert removed(frame(spark, rows)) == brute(rows, 50)


def test_repeats_of_odd_rows(spark):
    long = "".join(chr(97 + (i * i) % 26) for i in range(3000)) * 900  # longer than a batch
    rows = [(3, None), (4, ""), (5, "short"), (6, long), (7, "x" + long[100:400]), (8, "é" * 60), (9, "y" + "é" * 60)]
    got = removed(frame(spark, [*rows, (None, long)]))
    data = long.encode()
    assert got.pop(None) == (len(data), 0, 0, hashlib.sha256(data).hexdigest())
    assert got == brute(rows, 50)
    twice = removed(frame(spark, [(1, "q" * 80), (1, "q" * 80), (2, "q" * 80)]))
    assert twice[1][1] == 0 and twice[2][1] == 80
    assert removed(frame(spark, [])) == {}


def test_rows_of_a_repeated_id_are_judged_by_their_own_texts(spark):
    one, two = "q" * 64 + "rst", "Z" * 40 + "".join(map(chr, range(33, 100)))
    got = sorted((r.doc_id, r.n_bytes, r.n_removed) for r in remove_repeats(frame(spark, [(1, one), (2, one), (2, two), (2, two), (3, two[5:])])).collect())
    assert got == [(1, 67, 0), (2, 67, 67), (2, 107, 0), (2, 107, 0), (3, 102, 102)]


def test_a_phrase_in_very_many_surroundings(spark, monkeypatch):
    """Hot anchors: regions around them become windows of their own, with the same result."""
    import edgecsr.llm.suffix_array as S

    rng = random.Random(9)
    phrase = "a phrase of less than fifty bytes that all share"
    rows = [(i, "".join(rng.choice("abcdefgh ") for _ in range(60)) + phrase + rng.choice("xyz") * rng.randrange(4) + "".join(rng.choice("abcdefgh ") for _ in range(60))) for i in range(150)]
    want = brute(rows, 50)
    monkeypatch.setattr(S, "HOT_REGIONS", 100)
    total, hot = S._measured(S.keyed(frame(spark, rows)), 50, 1)
    assert len(hot) and total == sum(len(t) for _, t in rows)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in S.remove_repeats(frame(spark, rows), sample=1).collect()}
    assert got == want and sum(w[1] for w in want.values()) > 0


# --- search -----------------------------------------------------------------


def vectors(spark, rows):
    return spark.createDataFrame([(i, v, 7, 0) for i, v in rows], "vec_id long, embedding array<float>, part int, score int")


ODD = [(0, None), (100, [1.0, None]), (200, [float("nan"), 1.0]), (300, [float("inf"), 0.0]), (None, [1.0, 1.0]), (400, [0.0, 0.0])]


def _top(rows, every, k, score):
    out = set()
    for i, q in rows:
        if i % every == 0:
            ranked = sorted(((-score(q, v), j) for j, v in rows if j != i))[:k]
            out |= {(i, n + 1, j, -s) for n, (s, j) in enumerate(ranked)}
    return out


def test_exact_topk_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(0, 1, 8)]) for i in range(900)]
    rows += [(1000 + i, rows[3][1]) for i in range(40)]  # ties
    floor = lambda v: np.floor(1024 * np.array(v)).astype(np.int64)
    want = _top([(i, floor(v)) for i, v in rows], 100, 10, lambda a, b: int(a @ b))
    got = {tuple(r) for r in exact_topk.search(vectors(spark, rows + ODD[:5]), part_rows=200, block_rows=4).collect()}
    assert got == want


def test_exact_topk_of_few_and_none(spark):
    got = exact_topk.search(vectors(spark, [(0, [1.0]), (1, [2.0, 1.0]), (2, [-3.0])])).collect()
    assert [tuple(r) for r in sorted(got)] == [(0, 1, 1, 2 * 1024 * 1024), (0, 2, 2, -3 * 1024 * 1024)]
    assert exact_topk.search(vectors(spark, ODD[:5])).collect() == []
    assert exact_topk.search(vectors(spark, [])).collect() == []


def test_search_with_components_of_any_size(spark):
    big = [(0, [1e8, 1.0]), (1, [1e8, -1e8]), (2, [-1e300, 2.0]), (3, [1.7e308, 1.0]), (4, [1e-300, 0.0]), (5, [3.0, 4.0]), (5, [3.0, 4.0])]
    wide = spark.createDataFrame(big, "vec_id long, embedding array<double>")
    clip = lambda x: min(max(x, -(2**63)), 2**63 - 1)
    exact = lambda v: [math.floor(1024 * x) if abs(x) < 1e300 else 1024 * int(x) for x in v]
    q = exact(big[0][1])
    want = sorted(((clip(sum(a * b for a, b in zip(q, exact(v)))), i) for i, v in big[1:]), key=lambda x: (-x[0], x[1]))
    assert [(r.score, r.vec_id) for r in exact_topk.search(wide).orderBy("rank").collect()] == want
    got = {r.vec_id: r.score for r in hnsw.nearest(wide).collect()}
    assert abs(got[3] - 1) < 1e-12 and abs(got[5] - (3 + 4e-8) / 5) < 1e-9 and abs(got[4] - 1) < 1e-12
    assert abs(hnsw.cosine(np.array([[1e200, 1e200], [1e-200, 0.0]]), np.array([1e-200, 1e-200])) - [1, 0.5**0.5]).max() < 1e-12


def test_graph_search_recall_and_scores(spark):
    rng = np.random.default_rng(3)
    centres = rng.normal(0, 1, (12, 24))
    m = (centres[rng.integers(0, 12, 1500)] + rng.normal(0, 0.6, (1500, 24))).astype(np.float32).astype(float)
    m[700:900] = m[700]  # a crowd of copies
    rows = [(i, list(map(float, v))) for i, v in enumerate(m)]
    frame_ = vectors(spark, rows + ODD)
    index, n = hnsw.build_index(frame_, 400)
    found = hnsw.search(index.cache(), n, queries_of(hnsw.nonzero(usable(frame_)), 50)).collect()
    unit = m / np.linalg.norm(m, axis=1)[:, None]
    got = defaultdict(list)
    for r in found:
        got[r.query_id].append((r.rank, r.vec_id, r.score))
        assert abs(r.score - float(unit[r.query_id] @ unit[r.vec_id])) < 1e-9 and r.vec_id != r.query_id
    hit = 0
    for q in range(0, 1500, 50):
        s = unit @ unit[q]
        best = [j for j in np.lexsort((np.arange(1500), -np.round(s, 12))) if j != q][:5]
        hit += len({v for _, v, _ in got[q]} & set(best))
        assert [r for r, _, _ in sorted(got[q])] == [1, 2, 3, 4, 5]
    assert hit / 150 >= 0.9 and [v for _, v, _ in sorted(got[700])] == [701, 702, 703, 704, 705]


def test_graph_search_of_few_and_none(spark):
    assert [(r.query_id, r.vec_id) for r in hnsw.nearest(vectors(spark, [(0, [1.0, 0.0]), (1, [1.0, 1.0])])).collect()] == [(0, 1)]
    assert hnsw.nearest(vectors(spark, ODD)).collect() == []
    assert hnsw.nearest(vectors(spark, [])).collect() == []


# --- pipeline ---------------------------------------------------------------


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as p

    from edgecsr.llm.common import materialize

    assert [n for n, _ in p.STAGES] == ["toxicity", "quality", "near_dedup", "suffix_dedup", "packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in p.STAGES:
        before = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
        after = materialize(stage(spark, docs, sf), name)
        if name == "packing":
            assert {r.doc_id for r in after.select("doc_id").collect()} == set(before)
            break
        assert after.columns == docs.columns
        rows = {r.doc_id: r.text for r in after.select("doc_id", "text").collect()}
        assert set(rows) <= set(before) and len(rows) > 0.5 * len(before)
        if name == "near_dedup":
            want = _components({i: weighted(t) for i, t in before.items()}, 0.8)
            assert set(rows) == set(want.values())
        elif name == "suffix_dedup":
            want = brute(sorted(before.items()), 50)
            for i, t in rows.items():
                if want[i][1] == 0:
                    assert t == before[i]
                else:
                    assert want[i][0] - want[i][1] - len(t.encode()) in range(8)
        else:
            assert all(before[i] == t for i, t in rows.items())
        docs = after


def test_registered_queries():
    from edgecsr.llm.queries import oracle_sql, queries

    assert sorted({n.split("_")[0] for n in queries()}) == sorted([*(f"op{i}" for i in range(1, 11)), "pipeline"])
    assert set(oracle_sql()) <= set(queries())
