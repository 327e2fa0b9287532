"""Log10 probabilities of whole texts under a class-factored log-bilinear model.

A word's probability is that of its class after the two classes before it,
times its share of the class. Classes are the most frequent words, one each,
and groups of all others by their endings, so that any word's class follows
from its spelling. The classes of the context each have a vector per place; the
sum of the two, by inner products with the vectors of all classes, gives the
normalised distribution of the next class. Vectors are learned by
noise-contrastive estimation, in numpy, in passes over the counts of all class
triples of the whole training corpus; shares come from the word counts of the whole training
corpus. Only the most frequent words' counts travel to every task, in a number
that does not grow; all other words meet their counts in a join.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import count as counter

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.llm.common import documents_only, materialize

#: Classes of single words, of endings, and the rest by kind of last byte; the end of a text is a word of its own, "".
SINGLES, ENDINGS, KINDS = 64, 88, 8
CLASSES = SINGLES + ENDINGS + KINDS
#: Words whose counts every task holds.
HEAD = 120_000
#: Vector length, noise words for each true one, and passes over all counted cells.
WIDTH, NOISE, STEPS = 40, 10, 200
END = b""


def tokens(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lowered, and the end."""
    found = (text or "").encode().lower().split()
    found.append(END)
    return found


def ending(word: bytes) -> bytes:
    """Last three bytes before any closing mark, and that mark."""
    bare = word.rstrip(b".,;:!?")
    return bare[-3:] + b" " + word[len(bare) : len(bare) + 1]


@dataclass
class Lexicon:
    """The classes of words; a few hundred entries."""

    singles: dict[bytes, int]
    endings: dict[bytes, int]

    def class_of(self, word: bytes) -> int:
        k = self.singles.get(word)
        if k is None:
            k = self.endings.get(ending(word))
            if k is None:
                last = word[-1]
                k = SINGLES + ENDINGS + (0 if last >= 192 else 1 if last >= 128 else 2 if 97 <= last < 110 else 3 if 110 <= last < 123 else 4 if 48 <= last < 58 else 5 if last in b".,;:!?" else 6 if len(word) == 1 else 7)
        return k


class Classer(dict):
    """Word to class; remembers a bounded number of words."""

    def __init__(self, lexicon: Lexicon):
        super().__init__()
        self.of = lexicon.class_of

    def __missing__(self, word: bytes) -> int:
        if len(self) > 300_000:
            self.clear()
        k = self[word] = self.of(word)
        return k


def _identified(docs: DataFrame) -> DataFrame:
    slim = documents_only(docs)
    return slim.withColumn("held_out", F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(10)) == 0)


def word_counts(train: DataFrame) -> DataFrame:
    """token binary, n long over all training texts; each task adds up its own first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def out():
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], ["token", "n"])

        for batch in batches:
            for text in batch.column(0):
                held.update(tokens(text.as_py()))
                if len(held) > 400_000:
                    yield out()
                    held.clear()
        yield out()

    return train.select("text").mapInArrow(run, "token binary, n long").groupBy("token").agg(F.sum("n").alias("n"))


def lexicon_of(counts: DataFrame) -> tuple[Lexicon, dict[bytes, int], np.ndarray, np.ndarray]:
    """The classes, the head words with log10(c + 0.1) of each, and the mass of each class.

    Only the head and per-class sums reach the driver; both are bounded.
    """
    top = counts.orderBy(F.col("n").desc(), "token").limit(HEAD).toArrow()
    head = list(zip(top.column("token").to_pylist(), top.column("n").to_pylist()))
    first = [w for w, _ in head[: SINGLES - 1]]
    singles = {w: i for i, w in enumerate([END, *[w for w in first if w != END]][:SINGLES])}
    sums: Counter = Counter()
    for w, n in head:
        if w not in singles:
            sums[ending(w)] += n
    endings = {e: SINGLES + i for i, (e, _) in enumerate(sorted(sums.items(), key=lambda x: (-x[1], x[0]))[:ENDINGS])}
    lexicon = Lexicon(singles, endings)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mass = np.zeros(CLASSES)
        for batch in batches:
            if batch.num_rows:
                k = np.fromiter(map(lexicon.class_of, batch.column(0).to_pylist()), np.int64, batch.num_rows)
                mass += np.bincount(k, batch.column(1).to_numpy() + 0.1, CLASSES)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CLASSES), pa.int32()), pa.array(mass)], ["k", "mass"])

    mass = np.zeros(CLASSES)
    for r in counts.select("token", "n").where(F.length("token") >= 0).mapInArrow(run, "k int, mass double").groupBy("k").agg(F.sum("mass").alias("mass")).collect():
        mass[r[0]] = r[1]
    mass[SINGLES:] += 0.1  # one unknown word for each class of several
    mass[:SINGLES] = np.maximum(mass[:SINGLES], 0.1)
    return lexicon, {w: i for i, (w, _) in enumerate(head)}, np.log10(np.array([n for _, n in head], float) + 0.1), mass


def context_ids(k: np.ndarray) -> np.ndarray:
    """Each place's two classes before it as one number; a text starts as if after two ends."""
    before = np.concatenate([[0, 0], k[:-1]]) if len(k) else k
    return before[: len(k)] * CLASSES + before[1 : len(k) + 1]


def triple_counts(train: DataFrame, lexicon: Lexicon) -> DataFrame:
    """cell int, n long: how often each class follows each two classes, over all training texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classer, cells = Classer(lexicon), np.zeros(CLASSES**3, np.int64)
        for batch in batches:
            for text in batch.column(0):
                found = tokens(text.as_py())
                k = np.fromiter(map(classer.__getitem__, found), np.int64, len(found))
                part, n = np.unique(context_ids(k) * CLASSES + k, return_counts=True)
                cells[part] += n
        at = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(cells[at])], ["cell", "n"])

    return train.select("text").mapInArrow(run, "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n"))


def train_vectors(cells: np.ndarray, n: np.ndarray, mass: np.ndarray, steps: int = STEPS, seed: int = 5) -> np.ndarray:
    """Noise-contrastive estimation from weighted class triples; returns log10 P(class | two before), a row per context.

    Nothing is drawn: each step goes over all counted cells, weighted by their
    counts, and takes the noise by its expectation over all classes.
    """
    rng = np.random.default_rng(seed)
    noise = mass / mass.sum()
    a, b, r = (rng.normal(0, 0.1, (CLASSES, WIDTH)) for _ in range(3))
    bias = np.log(noise)
    if len(cells):
        contexts, row = np.unique(cells // CLASSES, return_inverse=True)
        c1, c2 = contexts // CLASSES, contexts % CLASSES
        true = np.zeros((len(contexts), CLASSES), np.float32)
        np.add.at(true, (row, cells % CLASSES), n / n.sum())
        log_noise = np.log(NOISE * noise)
        # weight of a class in a context as true word or as noise
        either = true + true.sum(1, keepdims=True) * (NOISE * noise).astype(np.float32)
        # contexts in order of either class, for sums over equal ones
        by_first, by_second = np.argsort(c1, kind="stable"), np.argsort(c2, kind="stable")
        first_at, second_at = np.unique(c1[by_first], return_index=True), np.unique(c2[by_second], return_index=True)
        values = [a, b, r, bias]
        first, second = [np.zeros_like(v) for v in values], [np.zeros_like(v) for v in values]
        for step in range(1, steps + 1):
            h = (a[c1] + b[c2]).astype(np.float32)
            g = h @ r.T.astype(np.float32)
            g += (bias - log_noise).astype(np.float32)
            np.clip(g, -30, 30, out=g)
            np.negative(g, out=g)
            np.exp(g, out=g)
            g += 1
            np.divide(either, g, out=g)
            g -= true
            gh = g @ r.astype(np.float32)
            grads = [np.zeros_like(a), np.zeros_like(b), (g.T @ h).astype(float), g.sum(0, dtype=np.float64)]
            grads[0][first_at[0]] = np.add.reduceat(gh[by_first], first_at[1], axis=0)
            grads[1][second_at[0]] = np.add.reduceat(gh[by_second], second_at[1], axis=0)
            rate = 0.05 * (1 - step / (steps + 1))
            for v, d, f, s in zip(values, grads, first, second):
                f += 0.1 * (d - f)
                s += 0.01 * (d * d - s)
                v -= rate * (f / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-8)
    h = (a[:, None, :] + b[None, :, :]).reshape(-1, WIDTH)
    z = h @ r.T + bias
    z -= z.max(1, keepdims=True)
    return ((z - np.log(np.exp(z).sum(1, keepdims=True))) / math.log(10)).astype(np.float32)


SCORED = "row long, doc_id long, held_out boolean, n_tokens long, head_known long, head_sum double, class_sum double, tail array<binary>"


def score(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every document.

    A null text counts as empty: one token, the end. A null doc_id counts as
    the empty text where documents are held out and stays null. Repeated rows
    are counted and scored each. Without training documents all words are
    unknown, and the base score is 0 for each.
    """
    rows = _identified(docs)
    train = rows.where(~F.col("held_out"))
    counts = materialize(word_counts(train), "word_counts")
    n_all, v_all = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    lexicon, head, head_log, mass = lexicon_of(counts)
    found = triple_counts(train, lexicon).toArrow()  # CLASSES**3 rows at most
    table = train_vectors(found.column("cell").to_numpy().astype(np.int64), found.column("n").to_numpy().astype(float), mass)
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast((table, np.log10(mass)))  # CLASSES**3 numbers, whatever the input
    known_words = spark.sparkContext.broadcast((head, head_log))  # HEAD words at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (log_class, log_mass), (places, logs) = shared.value, known_words.value
        classer, get, number = Classer(lexicon), places.get, counter(TaskContext.get().partitionId() << 33)
        for batch in batches:
            cols = [[] for _ in range(6)]
            for text in batch.column(2):
                words = tokens(text.as_py())
                at = [get(w, -1) for w in words]
                place = np.array(at)
                k = np.fromiter(map(classer.__getitem__, words), np.int64, len(words))
                inside = place[place >= 0]
                values = (next(number), len(words), len(inside), float(logs[inside].sum()), float((log_class[context_ids(k), k] - log_mass[k]).sum(dtype=np.float64)), [w for w, i in zip(words, at) if i < 0])
                for c, v in zip(cols, values):
                    c.append(v)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.binary())]
            c = [pa.array(v, t) for v, t in zip(cols, kinds)]
            yield pa.RecordBatch.from_arrays([c[0], batch.column(0), batch.column(1), *c[1:]], [x.split()[0] for x in SCORED.split(", ")])

    scored = materialize(rows.select("doc_id", "held_out", "text").mapInArrow(run, SCORED), "scored")
    rare = scored.select("row", F.explode("tail").alias("token"))
    lost = F.log10(F.coalesce(F.col("n"), F.lit(0)) + F.lit(0.1))
    tail = rare.join(counts, "token", "left").groupBy("row").agg(F.sum(lost).alias("tail_sum"), F.count("n").alias("tail_known"))
    total = F.col("head_sum") + F.coalesce("tail_sum", F.lit(0.0))
    return scored.drop("tail").join(tail, "row", "left").select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("head_known") + F.coalesce("tail_known", F.lit(0))).alias("n_known"),
        F.lit(int(n_all)).cast("long").alias("train_tokens"),
        (total - F.col("n_tokens") * math.log10(n_all + 0.1 * (v_all + 1))).alias("base_score"),
        (total + F.col("class_sum")).alias("score"),
    )
