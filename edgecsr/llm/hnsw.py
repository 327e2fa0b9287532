"""Approximate nearest neighbours: one navigable small-world graph per shard, in flat arrays."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.llm.common import materialize
from edgecsr.llm.vectors import best, distinct_rows, met, packed, queries_of, unpack, usable, widened

SHARD_ROWS, BLOCK_ROWS = 8192, 512
#: Neighbours kept per layer (twice as many on the lowest), and the beam widths of building and of search.
M, EF_BUILD, EF_SEARCH = 12, 56, 160


class Graph:
    """Layers of neighbours as arrays: ``links[layer][node]`` holds node numbers, -1 behind the last."""

    def __init__(self, unit: np.ndarray, m: int = M):
        self.unit, self.m = unit, m
        n = len(unit)
        draws = np.random.default_rng(7).random(n)
        self.level = np.minimum((-np.log(np.maximum(draws, 1e-12)) / math.log(m)).astype(np.int32), 12)
        self.links = [np.full((n, 2 * m if layer == 0 else m), -1, np.int32) for layer in range(int(self.level.max(initial=0)) + 1)]
        self.entry = -1

    def _beam(self, q: np.ndarray, starts: list[tuple[float, int]], ef: int, layer: int) -> list[tuple[float, int]]:
        """The ``ef`` nearest that a best-first walk finds, as (similarity, node), unsorted."""
        links, unit = self.links[layer], self.unit
        seen = np.zeros(len(unit), bool)
        seen[[i for _, i in starts]] = True
        todo = [(-s, i) for s, i in starts]
        heapq.heapify(todo)
        kept = list(starts)
        heapq.heapify(kept)
        while todo:
            s, i = heapq.heappop(todo)
            if len(kept) >= ef and -s < kept[0][0]:
                break
            near = links[i]
            near = near[near >= 0]
            near = near[~seen[near]]
            if not len(near):
                continue
            seen[near] = True
            for t, j in zip((unit[near] @ q).tolist(), near.tolist()):
                if len(kept) < ef:
                    heapq.heappush(kept, (t, j))
                    heapq.heappush(todo, (-t, j))
                elif t > kept[0][0]:
                    heapq.heapreplace(kept, (t, j))
                    heapq.heappush(todo, (-t, j))
        return kept

    def _choose(self, found: list[tuple[float, int]], most: int) -> list[int]:
        """Neighbours in different directions: one nearer to a chosen one than to the node waits; gaps are filled at the end."""
        ranked = sorted(found, reverse=True)
        if len(ranked) <= most:
            return [i for _, i in ranked]
        nodes = np.array([i for _, i in ranked])
        between = self.unit[nodes] @ self.unit[nodes].T
        chosen, waiting = [], []
        for a, (s, _) in enumerate(ranked):
            if len(chosen) < most and (not chosen or between[a, chosen].max() <= s):
                chosen.append(a)
            else:
                waiting.append(a)
        return [int(nodes[a]) for a in (chosen + waiting)[:most]]

    def add(self, i: int) -> None:
        q, top = self.unit[i], int(self.level[i])
        if self.entry < 0:
            self.entry = i
            return
        at = [(float(self.unit[self.entry] @ q), self.entry)]
        for layer in range(int(self.level[self.entry]), -1, -1):
            if layer > top:
                at = [max(self._beam(q, at, 1, layer))]
                continue
            at = self._beam(q, at, EF_BUILD, layer)
            links = self.links[layer]
            for j in self._choose(at, self.m):
                own = links[i]
                own[np.argmax(own < 0)] = j
                theirs = links[j]
                free = np.flatnonzero(theirs < 0)
                if len(free):
                    theirs[free[0]] = i
                else:
                    around = np.append(theirs, i)
                    theirs[:] = self._choose(list(zip((self.unit[around] @ self.unit[j]).tolist(), around.tolist())), len(theirs))
        if top > self.level[self.entry]:
            self.entry = i

    def build(self) -> Graph:
        for i in range(len(self.unit)):
            self.add(i)
        return self

    def search(self, q: np.ndarray, ef: int) -> list[int]:
        if self.entry < 0:
            return []
        at = [(float(self.unit[self.entry] @ q), self.entry)]
        for layer in range(int(self.level[self.entry]), 0, -1):
            at = [max(self._beam(q, at, 1, layer))]
        return [i for _, i in self._beam(q, at, ef, 0)]

    def flat(self) -> tuple[bytes, bytes, int]:
        return self.level.tobytes(), b"".join(x.tobytes() for x in self.links), self.entry

    @classmethod
    def from_flat(cls, unit: np.ndarray, level: bytes, links: bytes, entry: int, m: int = M) -> Graph:
        g = cls.__new__(cls)
        g.unit, g.m, g.level, g.entry, g.links = unit, m, np.frombuffer(level, np.int32), entry, []
        flat, at, n = np.frombuffer(links, np.int32), 0, len(unit)
        for layer in range(int(g.level.max(initial=0)) + 1):
            width = 2 * m if layer == 0 else m
            g.links.append(flat[at : at + n * width].reshape(n, width))
            at += n * width
        return g


def normalised(m: np.ndarray) -> np.ndarray:
    scale = np.abs(m).max(axis=1, keepdims=True, initial=0)
    m = m / np.where(scale > 0, scale, 1)
    return (m / np.maximum(np.sqrt((m * m).sum(1, keepdims=True)), 1e-300)).astype(np.float32)


def cosine(m: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Row by row alike, so equal vectors get equal scores wherever they lie.

    Rows are first brought near 1 by powers of two, which changes no digit and keeps squares in range.
    """
    m, q = (np.ldexp(x, -np.frexp(np.abs(x).max(axis=-1, keepdims=True, initial=0))[1]) for x in (m, q))
    return (m * q).sum(1) / (np.sqrt((m * m).sum(1)) * math.sqrt(float((q * q).sum())))


INDEX = "part int, width int, n_distinct long, matrix binary, members binary, member_cuts binary, level binary, links binary, entry int"


def nonzero(vectors: DataFrame) -> DataFrame:
    return vectors.where(F.exists("vector", lambda x: x != 0))


def build_index(vectors: DataFrame, shard_rows: int = SHARD_ROWS) -> tuple[DataFrame, int]:
    """One row per shard: its distinct vectors, their ids and the graph over them; and the number of shards.

    Equal vectors are one node of a shard's graph, so a crowd of copies cannot fill
    neighbour lists. Every usable row is in the index.
    """
    rows = nonzero(usable(vectors))
    n = max(1, math.ceil(rows.count() / shard_rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                row = {c: batch.column(i)[r].as_py() for i, c in enumerate(batch.schema.names)}
                m, members = distinct_rows(*unpack(row["ids"], row["matrix"], row["width"]))
                mix = np.random.default_rng(3).permutation(len(m))  # distinct_rows sorts; a graph wants no such order
                m, members = np.ascontiguousarray(m[mix]), [members[i] for i in mix]
                level, links, entry = Graph(normalised(m)).build().flat()
                cuts = np.cumsum([0, *map(len, members)]).astype(np.int64)
                values = [row["part"], row["width"], len(m), m.tobytes(), np.concatenate(members).tobytes(), cuts.tobytes(), level, links, entry]
                kinds = [pa.int32(), pa.int32(), pa.int64(), *[pa.binary()] * 5, pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds)], [c.split()[0] for c in INDEX.split(", ")])

    return packed(rows, n, shard_rows).drop("n").mapInArrow(run, INDEX), n


def search(index: DataFrame, n_shards: int, asked: DataFrame, k: int = 5, ef: int = EF_SEARCH, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of every row of ``asked`` (vec_id, vector) but its own."""
    n_blocks = max(1, math.ceil(asked.count() / block_rows))
    blocks = packed(asked, n_blocks, block_rows).drop("n").withColumnRenamed("part", "block")

    def load(row: dict) -> tuple:
        m = np.frombuffer(row["matrix"], np.float64).reshape(row["n_distinct"], row["width"])
        members, cuts = np.frombuffer(row["members"], np.int64), np.frombuffer(row["member_cuts"], np.int64)
        return m, members, cuts, Graph.from_flat(normalised(m), row["level"], row["links"], row["entry"])

    def answer(shard: tuple, row: dict) -> pa.RecordBatch:
        m, members, cuts, graph = shard
        asked_ids, q = unpack(row["ids"], row["matrix"], row["width"])
        width = max(m.shape[1], q.shape[1])
        m, q = widened(m, width), widened(q, width)
        out = []
        for i, x, u in zip(asked_ids.tolist(), q, normalised(q)):
            near = np.array(graph.search(u[: graph.unit.shape[1]], max(ef, k + 1)), int)
            found = [(-s, v, i) for s, j in zip(cosine(m[near], x).tolist(), near) for v in members[cuts[j] : cuts[j + 1]][: k + 1].tolist() if v != i]
            out += heapq.nsmallest(k, found)
        return pa.RecordBatch.from_arrays([pa.array([o[2] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int64()), pa.array([-o[0] for o in out], pa.float64())], ["query_id", "vec_id", "score"])

    return best(met(index, n_shards, blocks, n_blocks, load, answer, "query_id long, vec_id long, score double"), k)


def nearest(vectors: DataFrame, every: int = 50, k: int = 5) -> DataFrame:
    """Index every usable row, then search with the rows whose id is divisible by ``every``.

    Vectors that are null, zero or hold null or non-finite components, and
    null ids, take no part; rows with the query's id are not its candidates;
    repeated rows are candidates each; fewer candidates than k give fewer rows.
    """
    index, n = build_index(vectors)
    return search(materialize(index, "hnsw"), n, queries_of(nonzero(usable(vectors)), every), k)
