"""Encoding, extraction, packing, classifiers and language model against brute force and on odd inputs."""

import hashlib
import math
import random
import struct
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from tokenizers import Tokenizer

from edgecsr.llm import log_bilinear, quality, toxicity
from edgecsr.llm.bpe_transducer import Encoder, Transducer, Utf8Machine, decode_stream, encode_documents, load_ranks
from edgecsr.llm.html_extract import extract, extract_pages
from edgecsr.llm.linear import platt
from edgecsr.llm.packing import added_tokens, fill_exactly, pack, plan_of

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n long, token string, score double, label int"
TEXTS = [None, "", " ", "one", "a b c d e", "Straße – naïve 漢字 😀 <|endoftext|>", "x" * 5000, "line\n\n\nline  end ", "the the the the the the", "the the the the the the"]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in any column, empty and long texts, ties, a repeated row, and columns that clash with those made inside."""
    rows = [(i, t, None, None, None, 1, "t", 0.5, 1) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame([*rows, rows[4], (None, "no id here", "en", "src0", 3, None, None, None, None)], SCHEMA)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


RANKS, PATTERN = public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN


def test_transducer_equals_library():
    ranks = load_ranks(RANKS)
    own, library = Encoder(ranks, PATTERN), tiktoken.Encoding("t", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(2)
    parts = ["a", "b", "é", "漢", "  ", "\n", " ", "'", "1", "!", "😀", "ll", "the", "\0", "z" * 50, " " * 70, "\t", "=" * 33]
    for _ in range(1500):
        s = "".join(rng.choice(parts) for _ in range(rng.randrange(40)))
        assert own.encode(s) == library.encode_ordinary(s), s
    for _ in range(3000):  # spaces beside every kind of white space, and words that no table has
        s = "".join(rng.choice(["x", " ", " ", "\x1c", "\xa0", "\u3000", "\x85", "\r", "\n", ",", "é"]) for _ in range(rng.randrange(12)))
        s += "".join(chr(rng.choice([rng.randrange(97, 103), rng.randrange(32, 127), rng.randrange(0x600)])) for _ in range(rng.randrange(30)))
        assert own.encode(s) == library.encode_ordinary(s), s


def test_transducer_with_tiny_tables_and_long_texts():
    ranks = load_ranks(RANKS)
    small, usual = Transducer(ranks, max_states=50), Transducer(ranks)
    for word in ("internationalisation", "aaaaaaaaaaaaaaaaaaaaab", "Überraschungsgäste"):
        assert small.encode(word.encode()) == usual.encode(word.encode())
    own = Encoder(ranks, PATTERN)
    text = ("some words, and  more\n" * 60000)[:1_200_000]
    library = tiktoken.Encoding("t", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    assert own.encode(text) == library.encode_ordinary(text)


def test_streaming_decode_never_cuts_a_character():
    ranks = load_ranks(RANKS)
    bytes_of = {i: t for t, i in ranks.items()}
    text = "añ漢😀" * 50
    ids = [ranks[bytes([b])] for b in text.encode()]
    for chunk in (1, 2, 3, 7):
        assert "".join(decode_stream(ids, bytes_of, chunk)) == text
    m = Utf8Machine("replace")
    assert m.feed(b"\xf0\x9f") == "" and m.finish() == "�"
    for data in (b"\xed\xa0\x80", b"\xe0\x80", b"\xf4\x90", b"\x80\x80", b"a\xc3", b"\xf5x", "né😀".encode()):
        m = Utf8Machine("replace")
        assert "".join(m.feed(bytes((b,))) for b in data) + m.finish() == data.decode("utf-8", "replace")


def test_encode_documents(spark, odd, nothing):
    library = tiktoken.Encoding("t", pat_str=PATTERN, mergeable_ranks=load_ranks(RANKS), special_tokens={})
    rows = encode_documents(odd, RANKS, PATTERN).collect()
    assert len(rows) == len(TEXTS) + 2
    for r in rows:
        text = "no id here" if r.doc_id is None else TEXTS[r.doc_id] or ""
        ids = library.encode_ordinary(text)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256(text.encode()).hexdigest())
    assert encode_documents(nothing, RANKS, PATTERN).collect() == []


@pytest.mark.parametrize(
    "html,text",
    [
        (None, ""),
        ("", ""),
        ("plain words", "plain words"),
        ("<html><body><nav>menu</nav><article><h1>T</h1><p>a&amp;b   c<b>d</b></p><p>two, more</p></article><footer>f</footer>", "T a&b cd two, more"),
        ("<body><div class='sidebar'>x</div><div id=main><p>First, long enough<p>second<ul><li>one<li>two</ul></div><div class=comments><p>bad, bad, bad</p></div><form>q</form>", "First, long enough second one two"),
        ("<body><script>var t='<p>no</p>';</script><article><p>yes<br>and", "yes and"),
        ("<p>", ""),
    ],
)
def test_extract(html, text):
    assert extract(html) == text


def test_extract_given_pages(spark, sf):
    import html as h
    import re

    pages = spark.read.parquet(f"{sf}/pages.parquet")
    got = {r.page_id: r for r in extract_pages(pages).collect()}
    for r in pages.collect():
        inside = re.search(r"<article>(.*?)(</article>|$)", r.html, re.S)[1]
        want = " ".join(h.unescape(re.sub(r"<[^>]*>?", " ", inside)).split())
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want)


def test_extract_odd_pages(spark):
    rows = [(1, None, None, 1), (None, "u", "<p>x", 2), (1, None, None, 1), (2, "u", "<div>" * 3000 + "deep", 3)]
    got = extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string, text int")).collect()
    assert sorted((r.page_id or 0, r.text) for r in got) == [(0, "x"), (1, ""), (1, ""), (2, "deep")]
    assert extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []


PACK_RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
ADDED = added_tokens(public_tokenizers.path("byte_bpe_50k.json"))


def _check_packed(rows, texts, capacity):
    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    by = Counter()
    place = {}
    for r in rows:
        ids = [*t.encode(texts[r.doc_id] or "", add_special_tokens=False).ids, 2]
        part = ids[r.start : r.start + r.length]
        assert len(part) == r.length and zlib.crc32(np.array(part, np.uint32).tobytes()) == r.ids_crc32
        assert r.length == capacity or r.piece == 0
        by[r.doc_id] += r.length
        place.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for of in place.values():
        at = 0
        for offset, length in sorted(of):
            assert offset == at
            at += length
        assert at <= capacity
    return by, len(place)


def test_pack_odd_documents(spark, odd, nothing):
    texts = {**dict(enumerate(TEXTS)), None: "no id here"}
    for capacity in (8, 1024):
        rows = pack(odd, PACK_RANKS, capacity, added=ADDED).collect()
        by, n = _check_packed(rows, texts, capacity)
        assert n >= math.ceil(sum(by.values()) / capacity)
    assert pack(nothing, PACK_RANKS).collect() == []


def test_pack_given_documents_nearly_fills(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    by, n = _check_packed(pack(docs, PACK_RANKS, added=ADDED).collect(), texts, 1024)
    assert n <= 1.06 * math.ceil(sum(by.values()) / 1024)


def test_exact_fills_respect_counts():
    rng = np.random.default_rng(0)
    for _ in range(40):
        counts = np.concatenate([[0], rng.integers(0, 4, 32)])
        counts[32] = 0
        start = counts.copy()
        plan = fill_exactly(counts, 32)
        used = np.zeros_like(counts)
        for items, times in plan:
            assert sum(items) == 32 and len(items) <= 4
            for i in items:
                used[i] += times
        assert (counts >= 0).all() and (used + counts == start).all()
    plan = plan_of({5: 3, 1024: 2, 1019: 3})
    assert sorted((sum(i), n) for i, n in plan) == [(1024, 2), (1024, 3)]


def _labelled(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")


def test_chain_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = _labelled(spark, sf)
    train, test = labels.where("doc_id % 4 <> 0"), labels.where("doc_id % 4 = 0")
    chain = toxicity.train(docs, train)
    assert chain.categories == ("low_quality", "toxic") and len(chain.models[1].extra) == 1
    scored = toxicity.score(docs, chain).withColumnRenamed("toxic", "said").join(test, "doc_id").toPandas()
    assert scored[scored.toxic == 1].said.mean() > 0.8 and scored[scored.toxic == 0].said.mean() < 0.01


def test_co_training_on_held_out_rows(spark):
    docs, labels = _labelled(spark, "/root/testdata/sf0.1")
    model = quality.train(docs, labels.where("doc_id % 4 <> 0"))
    scored = quality.score(docs, model).join(labels.where("doc_id % 4 = 0"), "doc_id").toPandas()
    assert scored[scored.quality == 1].keep.mean() > 0.98 and scored[scored.quality == 0].keep.mean() < 0.1
    assert ((scored.p_quality >= 0) & (scored.p_quality <= 1)).all()


def test_classifiers_on_odd_rows(spark, sf, odd, nothing):
    docs, labels = _labelled(spark, sf)
    chain, model = toxicity.train(docs, labels), quality.train(docs, labels)
    for frame, n in ((odd, len(TEXTS) + 2), (nothing, 0)):
        assert toxicity.score(frame, chain).count() == n and quality.score(frame, model).count() == n
        assert toxicity.score(frame, chain, frame.columns).columns[: len(frame.columns)] == frame.columns
    none = labels.limit(0)
    assert toxicity.score(odd, toxicity.train(docs, none)).count() == len(TEXTS) + 2
    assert quality.score(odd, quality.train(nothing, none)).count() == len(TEXTS) + 2


def test_platt_calibrates():
    rng = np.random.default_rng(1)
    m = rng.normal(0, 3, 4000)
    y = rng.random(4000) < 1 / (1 + np.exp(-(0.5 * m - 1)))
    a, b = platt(m, y)
    assert abs(a - 0.5) < 0.1 and abs(b + 1) < 0.2


def _language_model(spark, docs):
    rows = log_bilinear.score(docs).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 10 == 0
    c = Counter(w for r in docs.collect() if not held(r.doc_id) for w in log_bilinear.tokens(r.text))
    n, v = sum(c.values()), len(c)
    for r in rows:
        words = log_bilinear.tokens(texts[r.doc_id])
        base = sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in words)
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held(r.doc_id), len(words), sum(c[w] > 0 for w in words), n)
        assert abs(r.base_score - base) < 1e-6 * max(1, abs(base))
    return rows


def test_language_model(spark, sf, odd, nothing):
    rows = _language_model(spark, spark.read.parquet(f"{sf}/documents.parquet"))
    held = [r for r in rows if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
    assert len(_language_model(spark, odd)) == len(TEXTS) + 2
    assert log_bilinear.score(nothing).collect() == []


def test_language_model_is_normalised():
    k = log_bilinear.CLASSES
    rng = np.random.default_rng(0)
    table = log_bilinear.train_vectors(np.array([5, 77, k * k + 3]), np.array([9.0, 3.0, 1.0]), rng.random(k) + 0.1, steps=20)
    assert np.allclose((10.0 ** table.astype(float)).sum(1), 1, atol=1e-4)
