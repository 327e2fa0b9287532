"""Document quality by co-training of two views.

One classifier reads what a text says and how it is written; the other reads
the page's metadata alone: source, language and stated length. Over some rounds each passes the unlabelled
documents that it is surest of, out of all there are, to the other as labelled; in the end both are
calibrated on held-out folds, and as the views share nothing, their log odds over the base rate add up.
"""

from __future__ import annotations

import heapq
import math
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, StructField, StructType

from edgecsr.llm.common import fresh, materialize, release
from edgecsr.llm.linear import LinearModel, content_features, fit, layout_features, platt
from edgecsr.llm.toxicity import hash_fold, labelled_sample

#: Labelled rows that are fitted at most, by the least hash of their id; unlabelled ones all take part.
TRAIN_ROWS = 4000
ROUNDS = 3
#: Pseudo-labels a view passes on per round and class at most, and how sure it must be.
PER_ROUND, SURE = 400, 0.95


def _hashed(features: set[bytes]) -> np.ndarray:
    """Features as ascending 32-bit numbers."""
    return np.unique(np.fromiter(map(zlib.crc32, features), np.uint32, len(features)))


def content_view(text: str) -> np.ndarray:
    return _hashed(content_features(text) | layout_features(text))


def metadata_view(lang, source, n_chars) -> np.ndarray:
    """Nothing of the text; missing values are features too."""
    size = b"-" if n_chars is None else b"%d" % int(2 * math.log2(max(1, n_chars)))
    lang, source = (b"-" if x is None else b"=" + x.encode() for x in (lang, source))
    pairs = {b"lang source": lang + b" " + source, b"source size": source + b" " + size, b"lang size": lang + b" " + size}
    return _hashed({b"lang:" + lang, b"source:" + source, b"size:" + size, *(k + b":" + v for k, v in pairs.items())})


class Weights:
    """A linear model over hashed features as arrays, for many rows at once."""

    def __init__(self, model: LinearModel):
        ids = np.array(sorted(model.weights), np.uint32)
        self.ids, self.values, self.bias = np.append(ids, np.uint32(0)), np.array([*(model.weights[i] for i in ids.tolist()), 0.0]), model.bias

    def margins(self, rows: list[np.ndarray]) -> np.ndarray:
        flat = np.concatenate(rows) if rows else np.zeros(0, np.uint32)
        at = np.searchsorted(self.ids[:-1], flat)
        hit = np.where(self.ids[at] == flat, self.values[at], 0.0)
        return self.bias + np.bincount(np.repeat(np.arange(len(rows)), [len(r) for r in rows]), hit, len(rows))


@dataclass
class CoTrained:
    content: LinearModel
    metadata: LinearModel
    content_scale: tuple[float, float]
    metadata_scale: tuple[float, float]
    base: float

    def odds(self, content: list[np.ndarray], metadata: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Log odds of good quality by content, by metadata and by both; ``base`` are those of a document of which nothing is known."""
        a, b = (s[0] * Weights(m).margins(rows) + s[1] for m, s, rows in ((self.content, self.content_scale, content), (self.metadata, self.metadata_scale, metadata)))
        return a, b, a + b - self.base


def _rows(features: np.ndarray) -> tuple[int, ...]:
    return tuple(features.tolist())


def co_train(views: tuple[list, list], y: list[int], surest, texts: list[str], rounds: int = ROUNDS, folds: int = 3) -> CoTrained:
    """``views``: hashed features of the labelled rows in the content and the metadata view.

    ``surest(models, scales, used)`` gives for each view the (key, content, metadata, label) rows outside ``used``
    that its model is surest of, by calibrated odds: a view that knows little is seldom sure.
    """
    own = [([_rows(r) for r in v], list(y)) for v in views]
    fold, used = np.array([hash_fold(t, folds) for t in texts], int), set()

    def calibrated(k: int) -> tuple[float, float]:
        """Slope and offset by labelled rows that the fitted model has not seen; pseudo-labelled rows are in no fold."""
        held = np.zeros(len(y))
        extra = list(range(len(y), len(own[k][1])))
        for f in range(folds):
            inside, outside = [*np.flatnonzero(fold != f), *extra], np.flatnonzero(fold == f)
            m = fit([own[k][0][i] for i in inside], [own[k][1][i] for i in inside])
            held[outside] = Weights(m).margins([views[k][i] for i in outside])
        return platt(held, y)

    models, scales = [fit(*own[k]) for k in range(2)], [calibrated(k) for k in range(2)]
    for _ in range(rounds):
        found = surest(models, scales, used)
        if not any(found):
            break
        for k in range(2):
            for key, content, metadata, label in found[k]:
                if key not in used:  # passed on once, by the view that is asked first
                    used.add(key)
                    own[1 - k][0].append(_rows((content, metadata)[1 - k]))
                    own[1 - k][1].append(label)
        models, scales = [fit(*own[k]) for k in range(2)], [calibrated(k) for k in range(2)]
    rate = (sum(y) + 1) / (len(y) + 2)
    return CoTrained(models[0], models[1], scales[0], scales[1], math.log(rate / (1 - rate)))


#: Ids of labelled documents that are broadcast at most, 8 bytes each; beyond that both sides of the join are dealt.
BROADCAST_IDS = 4_000_000


def unlabelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Hashed features of every unlabelled document, and a key that is the same for documents alike in both views.

    Such documents are told apart from each other nowhere, so the ranking counts them once; features are not dealt out to find them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            content = [content_view(t.as_py()).tobytes() for t in batch.column(0)]
            metadata = [metadata_view(*m).tobytes() for m in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)))]
            yield pa.RecordBatch.from_arrays([pa.array(content, pa.binary()), pa.array(metadata, pa.binary())], ["content", "metadata"])

    told = labels.select(F.col("doc_id").cast("long").alias("doc_id")).distinct()
    if told.count() <= BROADCAST_IDS:  # then whole texts need not travel to be left out
        told = F.broadcast(told)
    others = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).join(told, "doc_id", "left_anti")
    found = others.select("text", "lang", "source", "n_chars").mapInArrow(run, "content binary, metadata binary")
    return found.select(F.xxhash64("content", "metadata").alias("key"), "content", "metadata")


def _surest_of(pool: DataFrame):
    """Top-k of the whole pool: each task sends the ``PER_ROUND`` keys of each view and class that it is surest of, and those are ranked, each key once."""
    bar = math.log(SURE / (1 - SURE))

    def surest(models, scales, used):
        weights, taken = [Weights(m) for m in models], frozenset(used)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tops: list[list] = [[] for _ in range(4)]
            held: list[set] = [set() for _ in range(4)]
            for batch in batches:
                keys = batch.column(0).to_pylist()
                rows = [[np.frombuffer(x, np.uint32) for x in batch.column(i).to_pylist()] for i in (1, 2)]
                for k in range(2):
                    margins = scales[k][0] * weights[k].margins(rows[k]) + scales[k][1]
                    for label, z in enumerate((-margins, margins)):
                        top, have = tops[2 * k + label], held[2 * k + label]
                        for i in np.flatnonzero(z >= bar).tolist():
                            if keys[i] in taken or keys[i] in have or len(top) == PER_ROUND and (z[i], keys[i]) < top[0][:2]:
                                continue
                            have.add(keys[i])
                            item = (float(z[i]), keys[i], rows[0][i].tobytes(), rows[1][i].tobytes())
                            if len(top) < PER_ROUND:
                                heapq.heappush(top, item)
                            else:
                                have.discard(heapq.heappushpop(top, item)[1])
            out = [(n, *item) for n, top in enumerate(tops) for item in top]
            cols = list(zip(*out)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.float64(), pa.int64(), pa.binary(), pa.binary()))], ["list", "z", "key", "content", "metadata"])

        found = materialize(pool.mapInArrow(run, "list int, z double, key long, content binary, metadata binary"), "surest")
        views: list[list] = [[], []]
        for n in range(4):
            best = [r[0] for r in found.where(F.col("list") == n).select("key", "z").groupBy("key").agg(F.max("z").alias("z")).orderBy(F.col("z").desc(), F.col("key").desc()).limit(PER_ROUND).collect()]
            rows = {r["key"]: r for r in found.where((F.col("list") == n) & F.col("key").isin(best)).dropDuplicates(["key"]).collect()} if best else {}
            for r in map(rows.__getitem__, best):
                views[n // 2].append((r["key"], np.frombuffer(r["content"], np.uint32), np.frombuffer(r["metadata"], np.uint32), n % 2))
        return views

    return surest


def _with_metadata(docs: DataFrame) -> DataFrame:
    have = set(docs.columns)
    of = lambda name, kind: (F.col(name) if name in have else F.lit(None)).cast(kind).alias(name)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), of("lang", "string"), of("source", "string"), of("n_chars", "long"))


def train(docs: DataFrame, labels: DataFrame, rounds: int = ROUNDS) -> CoTrained:
    slim = _with_metadata(docs)
    told = sorted(labelled_sample(slim, labels, {"quality": F.col("quality")}, TRAIN_ROWS).select("doc_id", "text", "lang", "source", "n_chars", "quality").toLocalIterator(), key=lambda r: r[0])
    views = [content_view(r[1]) for r in told], [metadata_view(*r[2:5]) for r in told]
    surest = _surest_of(materialize(unlabelled(slim, labels), "unlabelled")) if told else lambda models, scales, used: ([], [])
    model = co_train(views, [r[5] for r in told], surest, [r[1] for r in told], rounds)
    del told, views, surest
    release(docs.sparkSession)
    return model


def score(docs: DataFrame, model: CoTrained, columns: list[str] | None = None, threshold: float = 0.5) -> DataFrame:
    """``columns`` of docs with p_content, p_metadata, p_quality and keep (p_quality at or over the threshold).

    A null text counts as empty, missing metadata as its own value; every row
    is scored, repeated rows too. No shuffle: rows are independent. Columns of docs that have the name of an added one give way to it.
    """
    added = ["p_content", "p_metadata", "p_quality"]
    kept = [c for c in columns or ["doc_id"] if c not in (*added, "keep")]
    out = StructType([*[docs.schema[c] for c in kept], *[StructField(n, DoubleType()) for n in added], StructField("keep", BooleanType())])
    have = set(docs.columns)
    inputs = [(F.col(c) if c in have else F.lit(None)).cast("long" if c == "n_chars" else "string").alias(n) for c, n in zip(("text", "lang", "source", "n_chars"), fresh(kept, 4))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = len(kept)
            content = [content_view(t.as_py() or "") for t in batch.column(n)]
            metadata = [metadata_view(*m) for m in zip(*(batch.column(n + i).to_pylist() for i in (1, 2, 3)))]
            p = [1 / (1 + np.exp(-np.clip(z, -35, 35))) for z in model.odds(content, metadata)]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(n)), *map(pa.array, p), pa.array(p[2] >= threshold)], [*kept, *added, "keep"])

    return docs.select(*[F.col(f"`{c}`") for c in kept], *inputs).mapInArrow(run, out)
