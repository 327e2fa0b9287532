"""What an operator must not leave out: cases that a partial job would get wrong."""

import math
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from edgecsr.llm import log_bilinear, quality, toxicity
from edgecsr.llm.common import materialize
from edgecsr.llm.html_extract import extract
from edgecsr.llm.queries import op8_complement_packing

MARKED = ["a <|endoftext|> b", "<|endoftext|>", "<|endoftext|><|endoftext|>x", "two  \n <|endoftext|>\n\n  lines", "<|endoftext", "no mark", "é<|endoftext|>漢 <|ENDOFTEXT|>", "w <|endoftext|> " * 700]


def test_packing_gives_added_tokens_their_ids(spark, tmp_path):
    """The query and the pipeline's stage against the tokenizer in its default setting."""
    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    assert t.encode(MARKED[0], add_special_tokens=False).ids == [64, 220, 50256, 275]
    docs = spark.createDataFrame(list(enumerate(MARKED)), "doc_id long, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    for packed in (op8_complement_packing(spark, str(tmp_path)), corpus_pipeline.pack_sequences(spark, docs, str(tmp_path))):
        seen = dict.fromkeys(range(len(MARKED)), 0)
        for r in packed.collect():
            ids = [*t.encode(MARKED[r.doc_id], add_special_tokens=False).ids, 2]
            assert zlib.crc32(np.array(ids[r.start : r.start + r.length], np.uint32).tobytes()) == r.ids_crc32
            seen[r.doc_id] += r.length
        assert seen == {i: len(t.encode(x, add_special_tokens=False).ids) + 1 for i, x in enumerate(MARKED)}


def test_language_model_learns_from_every_counted_triple():
    """No draws: neither the order of the cells nor counts in two parts change the model."""
    k = log_bilinear.CLASSES
    rng = np.random.default_rng(3)
    cells = rng.choice(k**3, 5000, replace=False)
    n, mass = rng.integers(2, 50, 5000).astype(float), rng.random(k) + 0.1
    want = log_bilinear.train_vectors(cells, n, mass, steps=10)
    turned = rng.permutation(5000)
    for c, m in ((cells[turned], n[turned]), (np.concatenate([cells, cells]), np.concatenate([n - 1, np.ones(5000)]))):
        assert np.allclose(log_bilinear.train_vectors(c, m, mass, steps=10), want, atol=1e-3)


def test_nothing_is_toxic_without_training_rows(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    for none in (labels.limit(0), labels.withColumn("doc_id", -1 - labels.doc_id)):
        rows = toxicity.score(docs, toxicity.train(docs, none)).collect()
        assert len(rows) == docs.count() and not any(r.toxic for r in rows)


def test_article_keeps_its_lists_of_links():
    """Short and long reference lists stay, navigation by element, role or class goes."""
    for n in (2, 200):
        links = "".join(f"<li><a href='/{i}'>Reference number {i}</a></li>" for i in range(n))
        page = f"<body><article><p>First, long enough, with commas.</p>{{}}<nav><ul>{links}</ul></nav><div class=related>{links}</div><div role=navigation>{links}</div></article></body>"
        want = " ".join(["First, long enough, with commas.", *[f"Reference number {i}" for i in range(n)]])
        for block in (f"<ol>{links}</ol>", f"<section><ul>{links}</ul></section>"):
            assert extract(page.format(block)) == want


LONG = "<p>" + "A sentence of an article, with some commas, goes on for a while and ends. " * 6 + "</p>"


def test_words_of_layout_do_not_cost_the_article():
    want = " ".join(LONG[3:-4].split())
    side = "<div class='sidebar'><p>Something, beside, the text.</p></div><div class='comments'><p>A reader, says, this.</p></div>"
    for open_, close in (("<div class='content has-sidebar'>", "</div>"), ("<article class='post share-enabled'>", "</article>"), ("<main id='main-with-ads'>", "</main>"), ("<form id=page action='/'><div>", "</div></form>"), ("<form><article>", "</article></form>")):
        assert extract(f"<body><nav>menu</nav>{side}{open_}{LONG}{close}<footer>f</footer>") == want, open_
    assert extract(f"<body><nav>menu</nav><div class='widget'>{LONG}</div>") == want
    assert extract(f"<body><article>{LONG}<p class='legal'>Some legal remark.</p></article>") == want + " Some legal remark."
    assert extract(f"<body><div><div>Short lead of the text.</div><div>{LONG}{LONG}</div></div>") == f"Short lead of the text. {want} {want}"
    assert extract(f"<body><div class=main>{LONG}</div>{side}<form><p>Write to us</p><input></form>") == want
    assert extract("<body><nav>menu</nav><div class='cookie-notice'>We use cookies.</div><form>q</form>") == ""


def _plain_sigmoid(z):
    return 1 / (1 + math.exp(-max(-35.0, min(35.0, z))))


def test_chain_scores_equal_a_plain_chain(spark, sf):
    """Each link by hand: its weights over the text's features and over the links before it."""
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    chain = toxicity.train(docs, labels)
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in toxicity.score(docs, chain).collect():
        found, earlier = toxicity.features_of(texts[r.doc_id] or ""), []
        for m in chain.models:
            z = m.bias
            for f, w in m.weights.items():
                z += w if f in found else 0.0
            for w, p in zip(m.extra, earlier):
                z += w * p
            earlier.append(_plain_sigmoid(z))
        assert abs(earlier[0] - r.p_low_quality) < 1e-9 and abs(earlier[1] - r.p_toxic) < 1e-9 and r.toxic == (earlier[1] >= 0.5)


def test_chain_trains_on_out_of_fold_probabilities(monkeypatch):
    """The second link's dense input of a row comes from a model that has not seen the row."""
    seen = []
    fit = toxicity.fit
    monkeypatch.setattr(toxicity, "fit", lambda rows, y, extra=None, **more: seen.append((len(rows), np.array(extra))) or fit(rows, y, extra, **more))
    rng = np.random.default_rng(4)
    texts = [("bad " if i % 3 == 0 else "fine ") + " ".join(f"w{j}" for j in rng.integers(0, 40, 12)) for i in range(90)]
    y = [int(i % 3 == 0) for i in range(90)]
    toxicity.fit_chain(texts, {"a": y, "b": y[::-1]})
    fold = np.array([toxicity.hash_fold(t, toxicity.FOLDS) for t in texts])
    rows = toxicity.compact(toxicity.features_of(t) for t in texts)
    want = np.zeros(90)
    for k in range(toxicity.FOLDS):
        m = fit([rows[i] for i in np.flatnonzero(fold != k)], np.array(y)[fold != k], np.zeros((int((fold != k).sum()), 0)))
        want[fold == k] = [m.probability(rows[i]) for i in np.flatnonzero(fold == k)]
    assert np.allclose(seen[-1][1][:, 0], want) and seen[-1][0] == 90


def test_quality_scores_and_pool_equal_plain_ones(spark, sf):
    """All unlabelled documents are asked, the surest are those of a plain sort, and scores are plain sums."""
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    told = {r.doc_id for r in labels.collect()}
    slim = quality._with_metadata(docs)
    pool = quality.unlabelled(slim, labels)
    views = {i: (quality.content_view(r.text), quality.metadata_view(r.lang, r.source, r.n_chars)) for i, r in rows.items()}
    assert {(r.content, r.metadata) for r in pool.collect()} == {(a.tobytes(), b.tobytes()) for i, (a, b) in views.items() if i not in told}
    model = quality.train(docs, labels)

    def margin(m, view):
        return m.bias + sum(m.weights.get(f, 0.0) for f in view.tolist())

    for r in quality.score(docs, model).collect():
        a, b = (s[0] * margin(m, v) + s[1] for m, s, v in zip((model.content, model.metadata), (model.content_scale, model.metadata_scale), views[r.doc_id]))
        assert abs(r.p_content - _plain_sigmoid(a)) < 1e-9 and abs(r.p_metadata - _plain_sigmoid(b)) < 1e-9
        assert abs(r.p_quality - _plain_sigmoid(a + b - model.base)) < 1e-9 and r.keep == (r.p_quality >= 0.5)
    scales = [model.content_scale, model.metadata_scale]
    kept = pool.cache()
    found = quality._surest_of(kept)([model.content, model.metadata], scales, set())
    bar = math.log(quality.SURE / (1 - quality.SURE))
    for k, m in enumerate((model.content, model.metadata)):
        for label in (0, 1):
            z = sorted((((1 if label else -1) * (scales[k][0] * margin(m, np.frombuffer(r[k + 1], np.uint32)) + scales[k][1]), r.key) for r in kept.collect()), reverse=True)
            assert {key for key, _, _, own in found[k] if own == label} == {key for v, key in z[: quality.PER_ROUND] if v >= bar}
    shared = set(np.concatenate([a for a, _ in views.values()]).tolist()) & set(np.concatenate([b for _, b in views.values()]).tolist())
    assert not shared  # the views have no feature in common


def test_pipeline_with_clashing_columns(spark, sf):
    """Columns that have the names of what the stages make inside pass through all of them."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = ["toxic", "keep", "_text", "kept_text", "row", "text_hash", "p_toxic", "id", "class", "in0"]
    more = docs.select("*", *[F.concat(F.lit(f"{n} "), F.col("doc_id").cast("string")).alias(n) for n in names]).unionByName(docs.limit(1).select(F.lit(None).cast("long").alias("doc_id"), *docs.columns[1:]), allowMissingColumns=True)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        more, before = materialize(stage(spark, more, sf), name), more.columns
        assert more.columns == before
        assert more.where(F.col("doc_id").isNotNull() & ~F.expr(" AND ".join(f"`{n}` = concat('{n} ', doc_id)" for n in names))).isEmpty()
    assert more.where("doc_id is null").count() == 1 and more.count() > 100
    assert corpus_pipeline.pack_sequences(spark, more, sf).where("doc_id is null").count() >= 1


def test_language_model_score_equals_a_plain_sum(spark, sf):
    """Every token by hand: its class after the two classes before it, times its share of the class; shares of a class add up to 1."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    train = [log_bilinear.tokens(t) for i, t in texts.items() if zlib.crc32(str(i).encode()) % 10]
    c = Counter(w for words in train for w in words)
    lexicon, _, _, mass = log_bilinear.lexicon_of(spark.createDataFrame([(bytearray(w), n) for w, n in c.items()], "token binary, n long"))
    cells = Counter()
    for words in train:
        k = [0, 0, *map(lexicon.class_of, words)]
        cells.update((k[i] * log_bilinear.CLASSES + k[i + 1]) * log_bilinear.CLASSES + k[i + 2] for i in range(len(words)))
    at = np.array(sorted(cells))
    table = log_bilinear.train_vectors(at, np.array([cells[i] for i in at.tolist()], float), mass)
    for r in log_bilinear.score(docs).collect():
        words = log_bilinear.tokens(texts[r.doc_id])
        k = [0, 0, *map(lexicon.class_of, words)]
        want = sum(float(table[k[i] * log_bilinear.CLASSES + k[i + 1], k[i + 2]]) + math.log10((c[w] + 0.1) / mass[k[i + 2]]) for i, w in enumerate(words))
        assert abs(r.score - want) < 2e-3 * max(1, abs(want) / 100)
    shares = np.zeros(log_bilinear.CLASSES)
    for w, n in c.items():
        shares[lexicon.class_of(w)] += (n + 0.1) / mass[lexicon.class_of(w)]
    assert (shares <= 1 + 1e-9).all() and shares[np.array([lexicon.class_of(w) for w in c])].min() > 0.5
