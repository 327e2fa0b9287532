"""Sparse features of texts and linear models on them, in numpy."""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np

#: ASCII that is no letter or digit parts words; bytes of other characters stay.
_SPACED = bytes(i if i >= 128 or chr(i).isalnum() else 32 for i in range(256))


def words_of(text: str) -> list[bytes]:
    return text.lower().encode().translate(_SPACED).split()


def _bin(value: float, cuts: tuple[float, ...]) -> int:
    return sum(value >= c for c in cuts)


def layout_features(text: str) -> set[bytes]:
    """The form of a text, not its words: shares of kinds of characters and lengths, each as one of a few bins."""
    n = max(1, len(text))
    tokens = text.split()
    shares = (0.001, 0.005, 0.01, 0.02, 0.05, 0.1, 0.2)
    found = {
        b"#bar:%d" % _bin(text.count("|") / n, shares),
        b"#bang:%d" % _bin(text.count("!") / n, shares),
        b"#marks:%d" % _bin(sum(map(text.count, "#$%&*@^~=<>{}[]\\")) / n, shares),
        b"#stops:%d" % _bin(sum(map(text.count, ".,;:?")) / n, shares),
        b"#digits:%d" % _bin(sum(map(text.count, "0123456789")) / n, shares),
        b"#lines:%d" % _bin(text.count("\n") / n, (0.0005, 0.002, 0.005, 0.01, 0.02, 0.05)),
        b"#word:%d" % _bin((n - text.count(" ")) / max(1, len(tokens)), (3, 4, 5, 6, 7, 9, 12)),
        b"#kinds:%d" % _bin(len(set(tokens)) / max(1, len(tokens)) * math.log1p(len(tokens)), (0.5, 1, 2, 3, 4, 5)),
    }
    upper = sum(map(str.isupper, tokens)) / max(1, len(tokens))
    found.add(b"#upper:%d" % _bin(upper, (0.02, 0.05, 0.1, 0.3, 0.6)))
    return found


def text_features(text: str, prefixes: tuple[int, ...] = (6, 7)) -> set[bytes]:
    """Words and beginnings of longer words; each counts once however often it occurs."""
    words = set(words_of(text))
    found = set(words)
    for n in prefixes:
        found.update([b"%d:" % n + w[:n] for w in words if len(w) > n])
    return found


_MARKS = re.compile(r"[^\w\s]+")


def content_features(text: str) -> set[bytes]:
    """Words, runs of marks, capitals and repetition: what is written, wherever it came from."""
    found = text_features(text)
    found.update([b"~" + m[:4].encode() for m in set(_MARKS.findall(text))])
    tokens = text.split()
    n = max(1, len(tokens) - 1)
    found.add(b"~again:%d" % _bin(sum(map(str.__eq__, tokens, tokens[1:])) / n, (0.01, 0.05, 0.1, 0.3, 0.6)))
    found.add(b"~upper:%d" % _bin(sum(map(str.isupper, tokens)) / (n + 1), (0.02, 0.05, 0.1, 0.3, 0.6)))
    found.add(b"~marks:%d" % _bin(sum(not t[-1].isalnum() for t in tokens) / (n + 1), (0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.7)))
    return found


def compact(rows: Iterable[set[bytes]]) -> list[tuple[bytes, ...]]:
    """The same features with every distinct one held once: rows of a sample share most of theirs."""
    held: dict[bytes, bytes] = {}
    return [tuple([held.setdefault(f, f) for f in r]) for r in rows]


def sigmoid(z):
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


@dataclass
class LinearModel:
    """Logistic regression over a chosen vocabulary; ``extra`` are weights of dense inputs (earlier links of a chain)."""

    weights: dict[bytes, float]
    bias: float
    extra: tuple[float, ...] = ()

    def margin(self, features: Iterable[bytes], extra: tuple[float, ...] = ()) -> float:
        w = self.weights
        return self.bias + sum([w[f] for f in w.keys() & features]) + sum(a * b for a, b in zip(self.extra, extra))

    def probability(self, features: Iterable[bytes], extra: tuple[float, ...] = ()) -> float:
        return float(sigmoid(self.margin(features, extra)))


def select(rows: list[tuple[bytes, ...]], y: np.ndarray, most: int, least_z: float, least_rows: int) -> list[bytes]:
    """Features whose share of rows differs most between the classes, by the two-sample z value."""
    n1, n0 = float(y.sum()), float(len(y) - y.sum())
    if not n1 or not n0:
        return []
    one, all_rows = Counter(), Counter()
    for r, v in zip(rows, y):
        all_rows.update(r)
        if v:
            one.update(r)
    scored = []
    for f, n in all_rows.items():
        if least_rows <= n < len(rows):
            a, p = one[f], n / len(rows)
            z = abs(a / n1 - (n - a) / n0) / math.sqrt(p * (1 - p) * (1 / n1 + 1 / n0))
            if z >= least_z:
                scored.append((-z, f))
    return [f for _, f in sorted(scored)[:most]]


def fit(rows: list[tuple[bytes, ...]], y, extra=None, weight=None, most: int = 3000, least_z: float = 3.5, least_rows: int = 4, l2: float = 0.3, steps: int = 120) -> LinearModel:
    """Feature choice, then regularised logistic regression.

    With one class alone, or no rows, the model is constant.
    """
    y = np.asarray(y, float)
    width = 0 if extra is None or not len(extra) else np.asarray(extra).shape[1]
    if not len(y) or y.min() == y.max():
        p = 0.5 if not len(y) else 0.01 + 0.98 * y[0]
        return LinearModel({}, math.log(p / (1 - p)), (0.0,) * width)
    vocabulary = select(rows, y, most, least_z, least_rows)
    index = {f: i for i, f in enumerate(vocabulary)}
    at = [[index[f] for f in r if f in index] for r in rows]
    lengths = np.array([len(a) for a in at])
    cols = np.array([c for a in at for c in a], int)
    row_of = np.repeat(np.arange(len(rows)), lengths)
    n, d = len(rows), len(vocabulary)
    dense = np.zeros((n, 0)) if not width else np.asarray(extra, float)
    weight = np.ones(n) if weight is None else np.asarray(weight, float)
    x = np.zeros(d + width + 1)  # feature weights, weights of dense inputs, bias
    x[-1] = math.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))
    first, second = np.zeros_like(x), np.zeros_like(x)
    for step in range(1, steps + 1):  # moment-scaled gradient steps over the whole sample, ever smaller
        z = x[-1] + np.bincount(row_of, x[cols], n) + dense @ x[d : d + width]
        g = (sigmoid(z) - y) * weight
        grad = np.concatenate([np.bincount(cols, g[row_of], d) if d else np.zeros(0), dense.T @ g, [g.sum()]])
        grad[:-1] += l2 * x[:-1]
        first = 0.9 * first + 0.1 * grad
        second = 0.99 * second + 0.01 * grad**2
        x -= 0.2 * (1 - step / (steps + 1)) * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-8)
    w, v, b = x[:d], x[d : d + width], x[-1]
    return LinearModel({f: float(w[i]) for f, i in index.items() if abs(w[i]) > 1e-6}, float(b), tuple(map(float, v)))


def platt(margins, y) -> tuple[float, float]:
    """Slope and offset that turn margins into calibrated log odds (Newton steps, smoothed targets)."""
    m, y = np.asarray(margins, float), np.asarray(y, float)
    if not len(y) or y.min() == y.max():
        return 1.0, 0.0
    t = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    x = np.stack([m, np.ones_like(m)], 1)
    c = np.array([1.0, 0.0])
    for _ in range(30):
        p = sigmoid(x @ c)
        h = x.T @ (x * (p * (1 - p))[:, None]) + 1e-3 * np.eye(2)
        c = c - np.clip(np.linalg.solve(h, x.T @ (p - t) + 1e-3 * (c - [1.0, 0.0])), -1, 1)
    return float(c[0]), float(c[1])
