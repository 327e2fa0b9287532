"""Best-fit packing of token sequences by exact complements.

Items of one length are alike, so the plan is made on the histogram of lengths,
which has no more entries than a sequence has tokens: sums of one, two and
three available lengths that fill a gap exactly are consumed as often as their
counts allow, and what is left goes best-fit. Every item then finds its place
from its rank among the items of its length.
"""

from __future__ import annotations

import base64
import json
import zlib
from array import array
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.llm.common import documents_only, materialize, per_worker

CAPACITY, END_ID = 1024, 2
#: Items that share one ordered group when ranks are taken.
RANK_GROUP = 50_000
#: The rank files' pattern in the form that never backtracks over letters; it splits alike.
FAST_PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s"""


def fill_exactly(counts: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Takes from ``counts`` (items by length) all combinations of up to four items that fill a sequence; longest first."""
    plan = []
    for a in range(capacity - 1, 0, -1):
        while counts[a] > 0:
            gap, rest = capacity - a, None
            counts[a] -= 1  # the item itself is not its own filler
            if gap <= a and counts[gap] > 0:
                rest = (gap,)
            if rest is None:
                high = np.arange(min(a, gap - 1), (gap - 1) // 2, -1)  # pair sums: the longer part from the longest down
                fine = (counts[high] > 0) & (counts[gap - high] > np.where(high * 2 == gap, 1, 0))
                if fine.any():
                    b = int(high[fine.argmax()])
                    rest = (b, gap - b)
            if rest is None and gap > 2:
                for b in range(min(a, gap - 2), (gap - 1) // 3, -1):  # triple sums
                    if counts[b] > 0:
                        counts[b] -= 1
                        left = gap - b
                        high = np.arange(min(b, left - 1), (left - 1) // 2, -1)
                        fine = (counts[high] > 0) & (counts[left - high] > np.where(high * 2 == left, 1, 0))
                        counts[b] += 1
                        if fine.any():
                            c = int(high[fine.argmax()])
                            rest = (b, c, left - c)
                            break
            counts[a] += 1
            if rest is None:
                break
            lengths, need = np.unique([a, *rest], return_counts=True)
            times = int((counts[lengths] // need).min())
            counts[lengths] -= need * times
            plan.append(((a, *rest), times))
    return plan


def fill_best(counts: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit of what is left, longest first; alike sequences are handled together."""
    groups: dict[int, list[list]] = {}  # gap to [[items], how many]
    for a in range(capacity, 0, -1):
        left = int(counts[a]) if a < len(counts) else 0
        while left:
            gap = min((g for g in groups if g >= a), default=None)
            if gap is None:
                each = capacity // a  # new sequences, each as full of this length as it gets
                n, odd = divmod(left, each)
                if n:
                    groups.setdefault(capacity - each * a, []).append([(a,) * each, n])
                if odd:
                    groups.setdefault(capacity - odd * a, []).append([(a,) * odd, 1])
                break
            items, n = groups[gap].pop()
            if not groups[gap]:
                del groups[gap]
            used = min(n, left)
            if n > used:
                groups.setdefault(gap, []).append([items, n - used])
            groups.setdefault(gap - a, []).append([(*items, a), used])
            left -= used
        counts[a] = 0 if a < len(counts) else 0
    return [(items, n) for of_gap in groups.values() for items, n in of_gap]


def plan_of(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a sequence, how many such sequences); full items make sequences of their own."""
    counts = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        counts[length] += n
    plan = [((capacity,), int(counts[capacity]))] if counts[capacity] else []
    counts[capacity] = 0
    return plan + fill_exactly(counts, capacity) + fill_best(counts, capacity)


def places(plan: list[tuple[tuple[int, ...], int]]) -> dict[int, np.ndarray]:
    """Length to rows (first rank, first sequence, items per sequence, offset): where the items of each rank go."""
    found: dict[int, list] = {}
    ranks: dict[int, int] = {}
    sequence = 0
    for items, times in plan:
        offset, i = 0, 0
        while i < len(items):
            same = 1
            while i + same < len(items) and items[i + same] == items[i]:
                same += 1
            first = ranks.get(items[i], 0)
            found.setdefault(items[i], []).append((first, sequence, same, offset))
            ranks[items[i]] = first + same * times
            offset += items[i] * same
            i += same
        sequence += times
    return {k: np.array(v, np.int64) for k, v in found.items()}


def added_tokens(json_path: str) -> dict[str, int]:
    """The added tokens of a ``tokenizers`` file, which are matched inside texts before anything else, with their ids."""
    with open(json_path, encoding="utf-8") as f:
        found = json.load(f)["added_tokens"]
    for t in found:
        if t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"]:
            raise ValueError(f"added token {t['content']!r}: only tokens that match as they stand are supported")
    return {t["content"]: t["id"] for t in found}


def load_encoding(ranks_path: str, added: dict[str, int] | None = None) -> tiktoken.Encoding:
    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("packing", pat_str=FAST_PATTERN, mergeable_ranks=ranks, special_tokens=added or {})


PIECES = "row long, doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces_of(docs: DataFrame, ranks_path: str, capacity: int = CAPACITY, end_id: int = END_ID, added: dict[str, int] | None = None) -> DataFrame:
    """Each text's ids and the end id, cut into pieces of ``capacity`` of which the first may be shorter."""
    added = added or {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = per_worker(("encoding", ranks_path, *sorted(added.items())), lambda: load_encoding(ranks_path, added))
        number = count(TaskContext.get().partitionId() << 33)
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = array("I", encoding.encode(text.as_py() or "", allowed_special="all"))
                ids.append(end_id)
                packed, n = memoryview(ids.tobytes()), len(ids)
                start, end = 0, n % capacity or capacity
                for piece in range((n + capacity - 1) // capacity):
                    out.append((next(number), doc, piece, start, end - start, zlib.crc32(packed[4 * start : 4 * end])))
                    start, end = end, end + capacity
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            cols = list(zip(*out)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], [c.split()[0] for c in PIECES.split(", ")])

    return documents_only(docs).mapInArrow(run, PIECES)


def pack(docs: DataFrame, ranks_path: str, capacity: int = CAPACITY, end_id: int = END_ID, added: dict[str, int] | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece.

    ``added`` has the vocabulary's added tokens, which a rank file lacks; where
    a text holds one literally it gets that id. Without them such text is split
    into ordinary ids. A null text counts as empty and yields the end id alone. Repeated rows are
    packed each. A null doc_id stays null. No document gives no rows.
    """
    pieces = materialize(pieces_of(docs, ranks_path, capacity, end_id, added), "pieces")
    histogram = {r[0]: r[1] for r in pieces.groupBy("length").count().collect()}  # at most ``capacity`` rows
    place = places(plan_of(histogram, capacity))
    groups = max(1, sum(histogram.values()) // RANK_GROUP)
    grouped = pieces.withColumn("_group", F.pmod(F.xxhash64("row"), F.lit(groups)).cast("int"))
    sizes = grouped.groupBy("length", "_group").agg(F.count("*").alias("_n"))
    before = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(Window.partitionBy("length").orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    within = F.row_number().over(Window.partitionBy("length", "_group").orderBy("row")) - 1
    ranked = grouped.withColumn("_within", within).join(before, ["length", "_group"]).withColumn("_rank", F.col("_before") + F.col("_within"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lengths, ranks = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            sequence, offset = np.zeros(len(ranks), np.int64), np.zeros(len(ranks), np.int64)
            for length in np.unique(lengths):
                at, of = np.flatnonzero(lengths == length), place[int(length)]
                hit = of[np.searchsorted(of[:, 0], ranks[at], "right") - 1]
                sequence[at] = hit[:, 1] + (ranks[at] - hit[:, 0]) // hit[:, 2]
                offset[at] = hit[:, 3] + (ranks[at] - hit[:, 0]) % hit[:, 2] * length
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    slim = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "_rank")
    return slim.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
