"""Toxicity by a chain of linear classifiers.

Categories are predicted one after another; each later model sees the
probabilities of the earlier ones besides the text. In training these come out of fold,
so that a later model learns from predictions as good as it will meet.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, StructField, StructType

from edgecsr.llm.common import fresh, release
from edgecsr.llm.linear import LinearModel, compact, fit, layout_features, text_features

FOLDS = 3
#: Labelled rows that are fitted at most: those with the least hash of their id.
TRAIN_ROWS = 6000


@dataclass
class Chain:
    categories: tuple[str, ...]
    models: tuple[LinearModel, ...]

    def probabilities(self, features: set[bytes]) -> list[float]:
        found: list[float] = []
        for model in self.models:
            found.append(model.probability(features, tuple(found)))
        return found


def features_of(text: str) -> set[bytes]:
    return text_features(text) | layout_features(text)


def fit_chain(texts: list[str], labels: dict[str, list[int]], folds: int = FOLDS) -> Chain:
    """``labels``: category to 0/1 per row, in chain order. Equal texts share a fold.

    Without rows nothing is known of any category: each link is constant at
    0.01, so that nothing is called toxic.
    """
    if not texts:
        return Chain(tuple(labels), tuple(LinearModel({}, math.log(0.01 / 0.99), (0.0,) * i) for i in range(len(labels))))
    rows = compact(features_of(t) for t in texts)
    fold = np.array([hash_fold(t, folds) for t in texts], int)
    earlier = np.zeros((len(rows), 0))
    models = []
    for y in labels.values():
        y = np.asarray(y, int)
        out = np.zeros(len(rows))
        for k in range(folds):
            inside, outside = np.flatnonzero(fold != k), np.flatnonzero(fold == k)
            if len(outside):
                m = fit([rows[i] for i in inside], y[inside], earlier[inside])
                out[outside] = [m.probability(rows[i], tuple(earlier[i])) for i in outside]
        models.append(fit(rows, y, earlier))
        earlier = np.column_stack([earlier, out])
    return Chain(tuple(labels), tuple(models))


def hash_fold(text: str, folds: int) -> int:
    return zlib.crc32(text.encode()) % folds


def labelled_sample(docs: DataFrame, labels: DataFrame, wanted: dict[str, Column], most: int = TRAIN_ROWS) -> DataFrame:
    """At most ``most`` labelled documents with text, by the hash of their id: a top-k, bounded on the driver.

    Of rows that repeat a doc_id with other labels or another text the least counts.
    """
    told = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.struct(*[c.cast("int").alias(n) for n, c in wanted.items()]).alias("told"))
    told = told.where(F.col("doc_id").isNotNull() & ~reduce(or_, [F.col(f"told.{n}").isNull() for n in wanted]))
    told = told.groupBy("doc_id").agg(F.min("told").alias("told")).select("doc_id", "told.*")
    known = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    least = known.join(told, "doc_id").select("doc_id", F.xxhash64("doc_id").alias("_h")).distinct().orderBy("_h", "doc_id").limit(most)
    found = known.join(F.broadcast(least.select("doc_id")), "doc_id")
    rest = [c for c in found.columns if c not in ("doc_id", "text")]
    one = found.groupBy("doc_id").agg(F.min(F.struct("text", *rest)).alias("_one")).select("doc_id", "_one.*")
    return one.join(told, "doc_id")


def default_chain() -> dict[str, Column]:
    return {"low_quality": 1 - F.col("quality"), "toxic": F.col("toxic")}


def train(docs: DataFrame, labels: DataFrame, categories: dict[str, Column] | None = None, most: int = TRAIN_ROWS) -> Chain:
    wanted = categories or default_chain()
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sample = sorted(labelled_sample(slim, labels, wanted, most).select("doc_id", "text", *wanted).toLocalIterator(), key=lambda r: r[0])
    chain = fit_chain([r[1] for r in sample], {n: [r[i + 2] for r in sample] for i, n in enumerate(wanted)})
    del sample
    release(docs.sparkSession)
    return chain


def score(docs: DataFrame, chain: Chain, columns: list[str] | None = None, threshold: float = 0.5) -> DataFrame:
    """``columns`` of docs with ``p_<category>`` for each link and ``toxic`` (last link at or over the threshold).

    A null text counts as empty; every row is scored, repeated rows too. No
    shuffle: rows are independent. Columns of docs that have the name of an added one give way to it.
    """
    names = [f"p_{c}" for c in chain.categories]
    kept = [c for c in columns or ["doc_id"] if c not in (*names, "toxic")]
    schema = [docs.schema[c] for c in kept]
    out = StructType([*schema, *[StructField(n, DoubleType()) for n in names], StructField("toxic", BooleanType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = [chain.probabilities(features_of(t.as_py() or "")) for t in batch.column(batch.num_columns - 1)]
            cols = [pa.array([r[i] for r in p], pa.float64()) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays([batch.column(i) for i in range(len(kept))] + cols + [pa.array([r[-1] >= threshold for r in p], pa.bool_())], kept + names + ["toxic"])

    return docs.select(*[F.col(f"`{c}`") for c in kept], F.col("text").cast("string").alias(fresh(kept, 1)[0])).mapInArrow(run, out)
