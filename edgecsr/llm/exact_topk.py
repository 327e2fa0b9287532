"""Exact top-k by inner product, reading sorted lists only (no random access).

Each part keeps one list per component, sorted by value. A query walks all
lists from the end that helps it most, in steps; what is read adds to a
vector's lower bound, and a vector's upper bound takes, for each component not
read yet, the value at which that list stands. Reading stops when no vector
outside can reach the k-th lower bound; the scores of those left are then
resolved in full. Parts of bounded size work alone and send k rows a query.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from edgecsr.llm.vectors import best, distinct_rows, met, packed, queries_of, unpack, usable, widened

PART_ROWS, BLOCK_ROWS = 8192, 512


class SortedLists:
    """The distinct integer vectors of one part with a sorted list for every component."""

    def __init__(self, ids: np.ndarray, m: np.ndarray):
        self.m, self.ids = distinct_rows(ids, m)
        low_first = np.argsort(self.m, axis=0, kind="stable")
        self.order = np.ascontiguousarray(low_first.T)
        self.values = np.ascontiguousarray(_in_doubles(np.take_along_axis(self.m, low_first, 0)).T)

    def _read(self, lists: np.ndarray, up: bool, depth: int, take: int) -> tuple[np.ndarray, np.ndarray]:
        """The next ``take`` entries of some lists, from their low (``up``) or their high end."""
        n = len(self.m)
        part = slice(depth, depth + take) if up else slice(n - depth - take, n - depth)
        rows, values = self.order[lists, part], self.values[lists, part]
        return (rows, values) if up else (rows[:, ::-1], values[:, ::-1])

    def top(self, q: np.ndarray, k: int, own: int) -> list[tuple[int, int]]:
        """(score, id) of the k best but ``own``, best first, ties to the smaller id."""
        n = len(self.m)
        if not n:
            return []
        want = k + 1  # the query's own vector may be among them
        ends = [np.flatnonzero(q < 0), np.flatnonzero(q > 0)]  # read upwards, downwards
        lists = np.concatenate(ends)
        weight = _in_doubles(q[lists])
        worst = np.where(weight < 0, self.values[lists, -1], self.values[lists, 0]) * weight
        known, unread = np.zeros(n), np.ones((n, len(lists)), np.float32)
        columns = np.arange(len(lists))[:, None]
        # sums of integers are exact below 2**53; the single-precision bounds get a margin
        margin = 1.0 + 1e-5 * float((np.abs(weight) * np.abs(self.values[lists]).max(1, initial=0)).sum())
        depth, step, left = 0, max(64, n // 16), np.arange(n)
        while depth < n and len(lists) and n > want:
            take = min(step, n - depth)
            read = [self._read(of, up, depth, take) for of, up in zip(ends, (True, False))]
            rows, values = (np.concatenate([r[i] for r in read]) for i in range(2))
            values = values * weight[:, None]
            known += np.bincount(rows.ravel(), values.ravel(), n)
            unread[rows, columns] = 0
            depth, step = depth + take, max(64, n // 8)
            bounds = unread @ np.stack([worst, values[:, -1]], 1).astype(np.float32)
            lower = known + bounds[:, 0] - margin
            bar = np.partition(lower, n - want)[n - want]
            left = np.flatnonzero(known + bounds[:, 1] + margin >= bar)
            if len(left) <= 4 * want:
                break
        scores = self.m[left] @ q
        found: list[tuple[int, int]] = []
        for i in np.argsort(-scores, kind="stable"):
            if len(found) >= k and scores[i] < found[k - 1][0]:
                break
            found += [(int(scores[i]), int(v)) for v in self.ids[left[i]][: k + 1] if v != own]
            found.sort(key=lambda x: (-x[0], x[1]))
        return found[:k]


def _in_doubles(m: np.ndarray) -> np.ndarray:
    """Numbers as doubles; what passes 64 bits is shifted down, all of an array alike. Bounds alone are made of them."""
    if m.dtype != object:
        return m.astype(float)
    bits = max((abs(x) for x in m.ravel().tolist()), default=0).bit_length()
    return (m >> max(0, bits - 500)).astype(float)


def floored(m: np.ndarray) -> np.ndarray:
    """floor(1024 x) of each component: 64-bit numbers if sums of products fit them, else whole numbers of any size."""
    if not m.size or np.abs(m).max() <= 2**14:
        return np.floor(1024.0 * m).astype(np.int64)
    out = np.empty(m.shape, object)
    for i, row in enumerate(m.tolist()):
        out[i] = [math.floor(1024.0 * x) if abs(x) < 1e300 else 1024 * int(x) for x in row]
    return out


def search(vectors: DataFrame, every: int = 100, k: int = 10, part_rows: int = PART_ROWS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score for each row whose id is divisible by ``every``.

    Vectors that are null or hold null or non-finite components, and null ids,
    take no part. Rows with the query's id are not its candidates; repeated
    rows are candidates each. Fewer candidates than k give fewer rows. Vectors
    are ranked by their whole scores, however large; the column ``score`` ends at the bounds of 64 bits,
    and where it does so ties of the column go to the smaller vec_id.
    """
    rows = usable(vectors)
    asked = queries_of(rows, every)
    n_parts, n_blocks = (max(1, math.ceil(d.count() / size)) for d, size in ((rows, part_rows), (asked, block_rows)))
    blocks = packed(asked, n_blocks, block_rows).drop("n").withColumnRenamed("part", "block")

    def load(row: dict) -> tuple:
        ids, m = unpack(row["ids"], row["matrix"], row["width"])
        return ids, m, {}

    def answer(part: tuple, row: dict) -> pa.RecordBatch:
        ids, m, lists = part
        asked_ids, q = unpack(row["ids"], row["matrix"], row["width"])
        width = max(m.shape[1], q.shape[1])
        if width not in lists:  # once for a part, but where a block holds longer vectors
            lists[width] = SortedLists(ids, floored(widened(m, width)))
        least, most = -(2**63), 2**63 - 1
        out = [(int(i), v, min(max(s, least), most)) for i, x in zip(asked_ids, floored(widened(q, width))) for s, v in lists[width].top(x, k, int(i))]
        return pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], pa.int64()) for c in range(3)], ["query_id", "vec_id", "score"])

    found = met(packed(rows, n_parts, part_rows).drop("n"), n_parts, blocks, n_blocks, load, answer, "query_id long, vec_id long, score long")
    return best(found, k)
