"""Removal of repeated byte strings across documents by difference-cover suffix sorting.

A string of ``length`` bytes is repeated if it also starts in a document of
smaller id. Sorting every suffix of a corpus at once would move each byte many
times over the network, so the suffixes are dealt to shards first, by content
alone, such that equal strings meet in one shard:

* Each window of ``length`` bytes has an anchor, the least of its substrings of
  ``ANCHOR`` bytes under a hash. Neighbouring windows mostly share one, so a
  document falls into short regions of windows with the same anchor. Regions
  with one anchor meet; those that are equal throughout settle all their
  windows at once, and only the copy with the least id goes on.
* Regions that share an anchor and are not equal (the ends of a repeated
  passage, the surroundings of an edit) are cut into runs of ``RUN`` windows at
  fixed places before the anchor. Runs meet by the bytes that all windows of
  the run have in common, and equal runs are folded in every task before they
  travel, so no shard grows with the number of copies.
* In each shard that holds runs of several documents the suffixes of its
  distinct runs are sorted by the difference-cover algorithm: the suffixes at
  places not divisible by three by their first three bytes, names for these,
  recursion on the names while they are not unique, the rest by their first
  byte and the order of what follows, and one merge. Neighbours in that order
  with a common prefix of ``length`` bytes are equal strings.

Everything moves in packed arrays.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.llm.common import documents_only, materialize
from edgecsr.llm.shingles import mix, powers

LENGTH, ANCHOR, RUN = 50, 20, 18
#: Bytes of text in a group of documents, and in a batch of anchors, which takes some 80 times as much memory; beyond so many groups they grow, as blobs would hold too little.
GROUP_BYTES, BATCH_BYTES, MOST_GROUPS = 8 << 20, 1 << 19, 1 << 18
#: Regions that a task deals out together.
FLUSH_REGIONS = 1_000_000
#: An anchor with this many distinct regions, or this share of all, is hot; one text in ``SAMPLE`` is counted for that.
HOT_REGIONS, HOT_ANCHORS, SAMPLE = 500_000, 100_000, 64
_BASE = np.uint64(0xD1342543DE82EF95)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_OTHER = np.uint64(0x9E6C63D0676A9A99)
_OTHER_INVERSE = np.uint64(pow(int(_OTHER), -1, 1 << 64))


# --- suffix sorting ---------------------------------------------------------


def _ranks(keys: np.ndarray) -> tuple[np.ndarray, int]:
    """Dense ranks of numbers, from 1."""
    uniq, inverse = np.unique(keys, return_inverse=True)
    return inverse.ravel().astype(np.int64) + 1, len(uniq)


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Order of the suffixes of a sequence of numbers (from 0; a shorter suffix is the smaller on ties)."""
    n = len(s)
    if n < 4:
        return np.array(sorted(range(n), key=lambda i: s[i:].tolist()), np.int64)
    t = np.concatenate([s.astype(np.int64) + 1, np.zeros(3, np.int64)])
    pairs, _ = _ranks((t[:-1] << 31) + t[1:]) if t.max() < 1 << 31 else _ranks(t[:-1] * 0 + t[:-1])
    pairs = np.append(pairs, 0)  # rank of the first two, for every place
    sample = np.concatenate([np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)])
    names, kinds = _ranks((pairs[sample] << 31) + t[sample + 2])
    if kinds < len(sample):
        order = sample[suffix_array(names)]
    else:
        order = np.empty(len(sample), np.int64)
        order[names - 1] = sample
    rank = np.zeros(n + 4, np.int64)
    rank[order] = np.arange(1, len(order) + 1)
    order = order[order < n]
    rest = np.arange(0, n, 3)
    key = (t[rest] << 31) + rank[rest + 1]
    by_key = np.argsort(key, kind="stable")
    rest, key = rest[by_key], key[by_key]
    one, two = order[order % 3 == 1], order[order % 3 == 2]
    # a place of the rest against one third of the sample each, by what both can be compared with
    before = np.searchsorted((t[one] << 31) + rank[one + 1], key)
    before += np.searchsorted((pairs[two] << 31) + rank[two + 2], (pairs[rest] << 31) + rank[rest + 2])
    out = np.full(n, -1, np.int64)
    out[np.arange(len(rest)) + before] = rest
    out[out < 0] = order
    return out


def equal_windows(text: np.ndarray, valid: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Places where ``valid`` windows begin, in suffix order, and a class number for each: equal windows share one."""
    order = suffix_array(text)
    order = order[valid[order]]
    if not len(order):
        return order, order
    view = np.lib.stride_tricks.sliding_window_view(text, length)
    same = np.ones(len(order) - 1, bool)
    for at in range(0, len(same), 1 << 18):
        part = slice(at, min(at + (1 << 18), len(same)))
        same[part] = (view[order[:-1][part]] == view[order[1:][part]]).all(1)
    return order, np.concatenate([[0], np.cumsum(~same)])


# --- packed arrays ----------------------------------------------------------

_CODEC = "zstd"


def _planes(a: np.ndarray) -> bytes:
    """Bytes of an array; numbers byte place by byte place, so that small ones compress."""
    a = np.ascontiguousarray(a)
    return a.view(np.uint8).reshape(len(a), -1).T.tobytes() if a.dtype.kind != "S" and a.itemsize > 1 and len(a) else a.tobytes()


def _unplaned(data: bytes, kind: np.dtype, n: int, at: int) -> np.ndarray:
    if kind.kind == "S" or kind.itemsize == 1 or not n:
        return np.frombuffer(data, kind, n, at)
    return np.ascontiguousarray(np.frombuffer(data, np.uint8, n * kind.itemsize, at).reshape(kind.itemsize, n).T).view(kind).ravel()


def wrap(*arrays: np.ndarray) -> bytes:
    """Arrays of the same length as one compressed blob, column by column."""
    data = b"".join(map(_planes, arrays))
    return len(arrays[0]).to_bytes(8, "little") + len(data).to_bytes(8, "little") + pa.compress(data, _CODEC, asbytes=True)


def unwrap(blob: bytes, kinds: list) -> list[np.ndarray]:
    n, size = int.from_bytes(blob[:8], "little"), int.from_bytes(blob[8:16], "little")
    data, at, out = pa.decompress(blob[16:], size, _CODEC, asbytes=True), 0, []
    for k in map(np.dtype, kinds):
        out.append(_unplaned(data, k, n, at))
        at += n * k.itemsize
    return out


#: A document's key: its id and a hash of its text, as rows may repeat an id with another text.
KEY = ["i8", "i8"]


def wrap_rows(doc: np.ndarray, text: np.ndarray, start: np.ndarray, *more: np.ndarray) -> bytes:
    """Rows of documents as a blob: each key once with its number of rows, and starts as steps from the row before."""
    order = np.lexsort((start, text, doc))
    doc, text, start = doc[order], text[order], start[order].astype(np.int64)
    new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (text[1:] != text[:-1])])
    heads = np.flatnonzero(new)
    step = np.diff(start, prepend=0)
    step[heads] = start[heads]
    keys = wrap(doc[heads], text[heads], np.diff(np.append(heads, len(doc))).astype("i4"))
    return len(keys).to_bytes(8, "little") + keys + wrap(step.astype("i4"), *(m[order] for m in more))


def unwrap_rows(blob: bytes, kinds: list) -> list[np.ndarray]:
    cut = 8 + int.from_bytes(blob[:8], "little")
    doc, text, n = unwrap(blob[8:cut], [*KEY, "i4"])
    step, *more = unwrap(blob[cut:], ["i4", *kinds])
    start = np.cumsum(step, dtype=np.int64)
    heads = np.cumsum(n) - n
    start -= np.repeat(np.where(heads > 0, start[heads - 1], 0), n)
    return [np.repeat(doc, n), np.repeat(text, n), start.astype("i4"), *more]


def joined(blobs: list[bytes], kinds: list) -> list[np.ndarray]:
    """doc, text, start and the columns of ``kinds`` of all blobs."""
    parts = [unwrap_rows(b, kinds) for b in blobs]
    return [np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, k) for i, k in enumerate([*KEY, "i4", *kinds])]


def dealt(to: np.ndarray, *arrays: np.ndarray, of: np.ndarray | None = None) -> Iterator[tuple[int, bytes]]:
    """A blob of rows (doc, text, start and more) for every number in ``to``, which has one for each row, or for each of the rows ``of``."""
    order = np.argsort(to, kind="stable")
    cuts = np.flatnonzero(np.diff(to[order])) + 1
    for rows in np.split(order, cuts) if len(order) else []:
        at = int(to[rows[0]])
        rows = rows if of is None else of[rows]
        yield at, wrap_rows(*[a[rows] for a in arrays])


def part_of(doc: np.ndarray, text: np.ndarray, parts: int) -> np.ndarray:
    """By the whole key, so that rows of one repeated id are dealt like others."""
    return (mix(doc.astype(np.int64).view(np.uint64) + mix(text.astype(np.int64).view(np.uint64))) % np.uint64(parts)).astype(np.int64)


COVERED = ["i4"]  # windows, from a start on
MOVED = "to int, kind int, blob binary"
_TEXTS, _SETTLED, _OPEN = 0, 1, 2


def moved(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    cols = list(zip(*rows)) or [[], [], []]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int32(), pa.int32(), pa.binary()))], ["to", "kind", "blob"])


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and a hash of it, of rows with an id."""
    return documents_only(docs).where(F.col("doc_id").isNotNull()).select("doc_id", "text", F.xxhash64("text").alias("text_hash"))


# --- anchors ----------------------------------------------------------------


class Hashes:
    """Hashes of any substrings of some bytes."""

    def __init__(self, data: np.ndarray, base: np.uint64 = _BASE, inverse: np.uint64 = _INVERSE):
        n = len(data)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(n, base), out=self.sums[1:])
        self.down = powers(n + 1, inverse)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64))


def regions(data: np.ndarray, cuts: np.ndarray, length: int, k: int) -> tuple[np.ndarray, ...]:
    """Regions of the texts that end at ``cuts``: first window, number of windows, anchor's place, its hash, hash of all bytes."""
    n, span = len(data), length - k + 1
    starts = np.concatenate([[0], cuts[:-1]])
    none = np.zeros(0, np.int64)
    if n < length:
        return none, none, none, none.view(np.uint64), none.view(np.uint64)
    hashes = Hashes(data)
    places = np.arange(n - k + 1)
    own = hashes.of(places, places + k)
    least = (own & ~np.uint64(0xFFFFFF)) | places.astype(np.uint64)  # a batch is shorter than 2**24
    width = 1
    while 2 * width <= span:  # least over 1, 2, 4, ... places
        least = np.minimum(least[: len(least) - width], least[width:])
        width *= 2
    if width < span:
        least = np.minimum(least[: len(least) - (span - width)], least[span - width :])
    anchor = (least & np.uint64(0xFFFFFF)).astype(np.int64)
    fits = np.zeros(n + 1, np.int64)  # windows inside one text
    last = cuts - length
    ok = last >= starts
    np.add.at(fits, starts[ok], 1)
    np.add.at(fits, last[ok] + 1, -1)
    windows = np.flatnonzero(np.cumsum(fits)[: len(anchor)] > 0)
    if not len(windows):
        return none, none, none, none.view(np.uint64), none.view(np.uint64)
    a = anchor[windows]
    new = np.flatnonzero(np.concatenate([[True], (np.diff(a) != 0) | (np.diff(windows) != 1)]))
    first, count = windows[new], np.diff(np.append(new, len(windows)))
    return first, count, a[new], own[a[new]], hashes.of(first, first + count + length - 1)


def _single_windows(data: np.ndarray, found: tuple[np.ndarray, ...], hot: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """``found`` with the regions at hot anchors as windows of their own, that are their own anchors.

    So what stands around a common phrase is dealt by what it is, and equal windows still meet.
    """
    first, count, place, anchor, whole = found
    split = np.isin(anchor, hot)
    if not split.any():
        return found
    n = count[split]
    window = np.repeat(first[split] - (np.cumsum(n) - n), n) + np.arange(n.sum())
    own, other = (h.of(window, window + length) for h in (Hashes(data), Hashes(data, _OTHER, _OTHER_INVERSE)))
    more = (window, np.ones(len(window), np.int64), window, own, other)
    return tuple(np.concatenate([a[~split], b]) for a, b in zip(found, more))


def _settle(doc, text, start, count, place, anchor, whole):
    """Rows of equal regions: which are settled by a copy in a smaller document, and which go on."""
    order = np.lexsort((start, text, doc, whole, anchor))
    a, w, d = anchor[order], whole[order], doc[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (w[1:] != w[:-1])]) if len(a) else np.zeros(0, bool)
    least = d[np.flatnonzero(new)][np.cumsum(new) - 1] if len(a) else d
    return order[d > least], order[d == least]


# --- the five steps ---------------------------------------------------------


def _batches_of(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[list[tuple]]:
    """(doc, text's hash, first byte, bytes) of texts, long ones in overlapping sections, in lists of bounded size."""
    held, size = [], 0
    for batch in batches:
        for doc, text, key in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
            data = (text.as_py() or "").encode()
            if len(data) < length:
                continue
            for at in range(0, len(data) - length + 1, BATCH_BYTES):
                held.append((doc, key, at, data[at : at + BATCH_BYTES + length - 1]))
                size += len(held[-1][3])
                if size >= BATCH_BYTES:
                    yield held
                    held, size = [], 0
    if held:
        yield held


def _measured(docs: DataFrame, length: int, sample: int) -> tuple[int, np.ndarray]:
    """Bytes of all texts, and the hot anchors: those of so many distinct regions that no task should take them all.

    Their counts come from every ``sample``-th text by its hash. They only say
    where rows travel, so a wrong estimate costs time, not rows. At most
    ``HOT_ANCHORS`` anchors, 8 bytes each.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counted: dict[int, int] = {}
        regions_seen = 0
        for held in _batches_of(batches, length):
            data = np.frombuffer(b"".join(h[3] for h in held), np.uint8)
            _, _, _, anchor, whole = regions(data, np.cumsum([len(h[3]) for h in held]), length, ANCHOR)
            distinct = np.unique(np.stack([anchor, whole]), axis=1)[0]
            regions_seen += len(distinct)
            found, n = np.unique(distinct, return_counts=True)
            for i in np.flatnonzero(n > 1):
                counted[int(found[i])] = counted.get(int(found[i]), 0) + int(n[i])
            if len(counted) > 4 * HOT_ANCHORS:
                counted = dict(sorted(counted.items(), key=lambda x: -x[1])[:HOT_ANCHORS])
        top = np.array(sorted(counted.items(), key=lambda x: -x[1])[:HOT_ANCHORS], np.uint64).reshape(-1, 2)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(top[:, 0], np.uint64(0)).view(np.int64)), pa.array(np.append(top[:, 1].astype(np.int64), 0)), pa.array(np.append(np.zeros(len(top), np.int64), regions_seen))], ["anchor", "n", "regions"])

    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if total < HOT_REGIONS:  # fewer bytes than that many regions need
        return total, np.zeros(0, np.uint64)
    seen = materialize(docs.where(F.pmod("text_hash", F.lit(sample)) == 0).mapInArrow(run, "anchor long, n long, regions long"), "anchors")
    everything = seen.agg(F.sum("regions")).first()[0] or 0
    least = max(HOT_REGIONS, sample * everything // HOT_ANCHORS) / sample
    hot = seen.where("n > 0").groupBy("anchor").agg(F.sum("n").alias("n")).where(F.col("n") >= least).orderBy(F.col("n").desc()).limit(HOT_ANCHORS).select("anchor").toArrow()
    return total, np.sort(hot.column(0).to_numpy().view(np.uint64))


def _anchored(docs: DataFrame, hot: np.ndarray, buckets: int, parts: int, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[list[np.ndarray]] = [[] for _ in range(7)]

        def column(i: int) -> np.ndarray:
            whole = np.concatenate(waiting[i])
            waiting[i].clear()
            return whole

        def flush():  # rows are taken blob by blob, as this is the most that a task holds
            doc, text, start, count, place, anchor, whole = map(column, range(7))
            settled, on = _settle(doc, text, start, count, place, anchor, whole)
            rows = [(int(t % buckets), _SETTLED, b) for t, b in dealt(part_of(doc[settled], text[settled], parts), doc, text, start, count, of=settled)]
            to = (anchor[on] % np.uint64(buckets)).astype("i4")
            rows += [(t, _OPEN, b) for t, b in dealt(to, doc, text, start, count, place, (anchor >> np.uint64(32)).astype(np.uint32), whole, of=on)]
            return moved(rows)

        n = 0
        for held in _batches_of(batches, length):
            data = np.frombuffer(b"".join(h[3] for h in held), np.uint8)
            cuts = np.cumsum([len(h[3]) for h in held])
            first, count, place, anchor, whole = _single_windows(data, regions(data, cuts, length, ANCHOR), hot, length)
            of = np.searchsorted(cuts, first, "right")
            shift = np.array([h[2] for h in held]) - np.concatenate([[0], cuts[:-1]])
            doc, text = (np.array([h[i] for h in held], np.int64)[of] for i in (0, 1))
            for held_column, more in zip(waiting, (doc, text, (first + shift[of]).astype("i4"), count.astype("i4"), (place - first).astype("i4"), anchor, whole)):
                held_column.append(more)
            n += len(first)
            if n > FLUSH_REGIONS:
                yield flush()
                n = 0
        if n:
            yield flush()

    return docs.mapInArrow(run, MOVED)


REGION_KINDS = ["i4", "i4", "u4", "u8"]  # windows, anchor's place after the start, half of its hash (the rest chose the bucket), hash of all bytes


def _met(rows: DataFrame, parts: int) -> DataFrame:
    """Regions by anchor: equal ones are settled, unequal ones of several documents stay open."""

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        kinds, blobs = table.column("kind").to_pylist(), table.column("blob").to_pylist()
        out = _passed_on(kinds, blobs, parts)
        cols = joined([b for b, k in zip(blobs, kinds) if k == _OPEN], REGION_KINDS)
        settled, on = _settle(*cols)
        doc, text, start, count = (c[settled] for c in cols[:4])
        out += [(t, _SETTLED, b) for t, b in dealt(part_of(doc, text, parts), doc, text, start, count)]
        doc, anchor, whole = (cols[i][on] for i in (0, 5, 6))  # sorted by anchor
        if len(on):
            new = np.concatenate([[True], anchor[1:] != anchor[:-1]])
            group, heads = np.cumsum(new) - 1, np.flatnonzero(new)
            many = (np.minimum.reduceat(doc, heads) < np.maximum.reduceat(doc, heads)) & (np.minimum.reduceat(whole, heads) < np.maximum.reduceat(whole, heads))
            open_ = [c[on[many[group]]] for c in cols[:5]]
            out += [(t, _OPEN, b) for t, b in dealt(part_of(open_[0], open_[1], parts), *open_)]
        return pa.Table.from_batches([moved(out)])

    return rows.groupBy("to").applyInArrow(run, MOVED)


def _passed_on(kinds: list[int], blobs: list[bytes], parts: int) -> list[tuple[int, int, bytes]]:
    """Settled rows that came along, on their way to their documents."""
    rows = joined([b for b, k in zip(blobs, kinds) if k == _SETTLED], COVERED)
    return [(t, _SETTLED, b) for t, b in dealt(part_of(rows[0], rows[1], parts), *rows)]


def _texts(docs: DataFrame, parts: int) -> DataFrame:
    """Documents packed by part: keys, how many rows each has, lengths and bytes. Equal rows of a task travel once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}

        def flush():
            keys = list(held)
            part = part_of(np.array([k[0] for k in keys], np.int64), np.array([k[1] for k in keys], np.int64), parts)
            order = np.argsort(part, kind="stable")
            rows = []
            for group in np.split(order, np.flatnonzero(np.diff(part[order])) + 1):
                of = [held[keys[i]] for i in group]
                data = b"".join(x[0] for x in of)
                head = np.array([(*keys[i], x[1], len(x[0])) for i, x in zip(group, of)], np.int64).tobytes()
                rows.append((int(part[group[0]]), _TEXTS, len(group).to_bytes(8, "little") + len(data).to_bytes(8, "little") + head + pa.compress(data, _CODEC, asbytes=True)))
            return moved(rows)

        size = 0
        for batch in batches:
            for doc, text, key in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
                if (doc, key) in held:
                    held[doc, key][1] += 1
                    continue
                held[doc, key] = [(text.as_py() or "").encode(), 1]
                size += len(held[doc, key][0]) + 64
                if size > 32 << 20:
                    yield flush()
                    held, size = {}, 0
        if held:
            yield flush()

    return docs.mapInArrow(run, MOVED)


def _unpacked(blob: bytes) -> Iterator[tuple[int, int, int, bytes]]:
    n, size = int.from_bytes(blob[:8], "little"), int.from_bytes(blob[8:16], "little")
    head = np.frombuffer(blob, np.int64, 4 * n, 16).reshape(n, 4)
    data, at = pa.decompress(blob[16 + 32 * n :], size, _CODEC, asbytes=True), 0
    for doc, text, times, length in head.tolist():
        yield doc, text, times, data[at : at + length]
        at += length


def _by_document(table: pa.Table, kind: int, kinds: list) -> tuple[dict[tuple[int, int], tuple[int, int]], list[np.ndarray]]:
    """Rows of one kind, sorted by document, and each document's slice."""
    blobs = [b for b, k in zip(table.column("blob").to_pylist(), table.column("kind").to_pylist()) if k == kind]
    cols = joined(blobs, kinds)
    order = np.lexsort((cols[2], cols[1], cols[0]))
    cols = [c[order] for c in cols]
    heads = np.flatnonzero(np.concatenate([[True], (cols[0][1:] != cols[0][:-1]) | (cols[1][1:] != cols[1][:-1])])) if len(order) else np.zeros(0, int)
    ends = np.append(heads[1:], len(order))
    return {(int(cols[0][h]), int(cols[1][h])): (int(h), int(e)) for h, e in zip(heads, ends)}, cols


def _runs(texts_and_open: DataFrame, buckets: int, length: int) -> DataFrame:
    """Open regions as runs of windows at fixed places before their anchor, dealt by what a run's windows share."""
    wide = length + RUN - 1

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        at, cols = _by_document(table, _OPEN, ["i4", "i4"])
        found: list[tuple] = []
        for blob in [b for b, k in zip(table.column("blob").to_pylist(), table.column("kind").to_pylist()) if k == _TEXTS]:
            for doc, text, _, data in _unpacked(blob):
                if (doc, text) not in at:
                    continue
                h, e = at.pop((doc, text))  # equal rows of other tasks have the same runs
                start, count, place = (c[h:e].astype(np.int64) for c in cols[2:])
                # window by window: its distance before the anchor, and the run that the distance is in
                n = int(count.sum())
                window = np.repeat(start - (np.cumsum(count) - count), count) + np.arange(n)
                ahead = np.repeat(start + place, count) - window
                turn = np.concatenate([[True], (np.diff(ahead // RUN) != 0) | (np.diff(window) != 1) | (np.diff(np.repeat(np.arange(len(start)), count)) != 0)]) if n else np.zeros(0, bool)
                heads = np.flatnonzero(turn)
                size = np.diff(np.append(heads, n))
                first, anchor = window[heads], window[heads] + ahead[heads]
                core = anchor - (ahead[heads] // RUN) * RUN  # the latest place at which a window of this run may begin
                padded = np.concatenate([np.frombuffer(data, np.uint8), np.zeros(wide, np.uint8)])
                shared = length - (RUN - 1)  # bytes that all windows of a run have in common
                keys = np.empty(len(heads), np.uint64)
                for i in range(0, len(heads), 50_000):
                    keys[i : i + 50_000] = (padded[core[i : i + 50_000, None] + np.arange(shared)].astype(np.uint64) + np.uint64(1)) @ powers(shared, _BASE)
                keys = mix(keys + (ahead[heads] // RUN).astype(np.uint64))
                body = padded[first[:, None] + np.arange(wide)]
                body[np.arange(wide) >= (size + length - 1)[:, None]] = 0
                found.append((keys, np.full(len(first), doc), np.full(len(first), text), first.astype("i4"), size.astype("i4"), np.hstack([body, np.ones((len(body), 1), np.uint8)]).view(f"S{wide + 1}").ravel()))
        out = []
        if found:
            keys, doc, text, first, size, body = (np.concatenate([f[i] for f in found]) for i in range(6))
            # equal runs inside this group of documents: only those of the least document travel
            order = np.lexsort((doc, size, body, keys))
            b, s, d, k = body[order], size[order], doc[order], keys[order]
            new = np.concatenate([[True], (b[1:] != b[:-1]) | (s[1:] != s[:-1]) | (k[1:] != k[:-1])])
            least = d[np.flatnonzero(new)][np.cumsum(new) - 1]
            settled, on = order[d > least], order[d == least]
            out = [(int(key[0].as_py() % buckets), _SETTLED, wrap_rows(doc[settled], text[settled], first[settled], size[settled]))] if len(settled) else []
            to = (keys[on] % np.uint64(buckets)).astype(np.int64)
            out += [(t, _OPEN, x) for t, x in dealt(to, doc[on], text[on], first[on], size[on], keys[on], body[on])]
        return pa.Table.from_batches([moved(out)])

    return texts_and_open.groupBy("to").applyInArrow(run, MOVED)


def _sorted_shards(rows: DataFrame, parts: int, length: int) -> DataFrame:
    """Shards of runs: suffix order, then equal windows; all but those of the least document are covered."""
    wide = length + RUN - 1

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        kinds, blobs = table.column("kind").to_pylist(), table.column("blob").to_pylist()
        out = _passed_on(kinds, blobs, parts)
        doc, text_of, first, size, keys, body = joined([b for b, k in zip(blobs, kinds) if k == _OPEN], ["i4", "u8", f"S{wide + 1}"])
        order = np.argsort(keys, kind="stable")
        if len(order):
            heads = np.flatnonzero(np.concatenate([[True], keys[order][1:] != keys[order][:-1]]))
            group = np.cumsum(np.concatenate([[1], keys[order][1:] != keys[order][:-1]])) - 1
            d = doc[order]
            several = np.minimum.reduceat(d, heads) < np.maximum.reduceat(d, heads)
            order = order[several[group]]
        group = 0
        while group < len(order):
            part = order[group : group + 20_000]  # whole shards of the same key stay together
            end = group + len(part)
            while end < len(order) and keys[order[end]] == keys[order[end - 1]]:
                end += 1
            part, group = order[group:end], end
            # distinct runs once; rows refer to them
            uniq, of = np.unique(body[part], return_inverse=True)
            of = of.ravel()
            width = np.zeros(len(uniq), np.int64)
            width[of] = size[part]
            text = uniq.view(np.uint8).reshape(len(uniq), wide + 1).astype(np.int64) + 2
            text[np.arange(wide + 1) >= (width + length - 1)[:, None]] = 0  # between runs
            valid = np.arange(wide + 1) < width[:, None]
            place, kind = equal_windows(text.ravel(), valid.ravel(), length)
            # the least document of each run, then of each class of equal windows
            low = np.full(len(uniq), np.iinfo(np.int64).max)
            np.minimum.at(low, of, doc[part])
            best = np.full(int(kind.max(initial=-1)) + 1, np.iinfo(np.int64).max)
            run_of, offset = place // (wide + 1), place % (wide + 1)
            np.minimum.at(best, kind, low[run_of])
            least = np.full((len(uniq), RUN), np.iinfo(np.int64).max)
            least[run_of, offset] = best[kind]
            hit, off = np.nonzero(least[of] < doc[part][:, None])
            rows = doc[part][hit], text_of[part][hit], (first[part][hit] + off).astype("i4"), np.ones(len(hit), "i4")
            out += [(t, _SETTLED, b) for t, b in dealt(part_of(rows[0], rows[1], parts), *rows)]
        return pa.Table.from_batches([moved(out)])

    return rows.groupBy("to").applyInArrow(run, MOVED)


def _kept(texts_and_covered: DataFrame, length: int, with_text: bool) -> DataFrame:
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, text_hash long" + (", kept_text string" if with_text else "")

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        at, cols = _by_document(table, _SETTLED, COVERED)
        rows = []
        for blob in [b for b, k in zip(table.column("blob").to_pylist(), table.column("kind").to_pylist()) if k == _TEXTS]:
            for doc, text, times, data in _unpacked(blob):
                removed = spans = 0
                if (doc, text) in at:
                    h, e = at[doc, text]
                    start, end = cols[2][h:e].astype(np.int64), cols[2][h:e].astype(np.int64) + cols[3][h:e] + length - 1
                    reach = np.maximum.accumulate(end)
                    new = np.concatenate([[True], start[1:] > reach[:-1]])
                    begins, ends = start[new], reach[np.append(np.flatnonzero(new)[1:] - 1, len(reach) - 1)]
                    removed, spans = int((ends - begins).sum()), len(begins)
                    kept = b"".join(data[a:b] for a, b in zip([0, *ends.tolist()], [*begins.tolist(), len(data)]))
                else:
                    kept = data
                rows += [(doc, len(data), removed, spans, hashlib.sha256(kept).hexdigest(), text, *([kept.decode("utf-8", "ignore")] if with_text else []))] * times
        kinds = [pa.int64()] * 4 + [pa.string(), pa.int64(), pa.string()]
        names = [c.split()[0] for c in schema.split(", ")]
        cols = list(zip(*rows)) or [[]] * len(names)
        return pa.table({n: pa.array(c, k) for n, c, k in zip(names, cols, kinds)})

    return texts_and_covered.groupBy("to").applyInArrow(run, schema)


def remove_repeats(docs: DataFrame, length: int = LENGTH, with_text: bool = False, sample: int = SAMPLE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, text_hash (and kept_text) of every row.

    A null text counts as empty. Rows of a repeated doc_id do not remove each
    other's bytes, and each is judged by its own text. Rows without doc_id are
    neither before nor after any document: they stay whole and remove nothing.
    Texts shorter than ``length`` bytes stay whole. A cut inside a
    character leaves its other bytes in the digest; ``kept_text`` drops them.
    """
    slim = keyed(docs)
    total, hot = _measured(slim, length, sample)
    groups = min(max(64, int(total // GROUP_BYTES)), MOST_GROUPS)
    settled_or_open = materialize(_met(_anchored(slim, hot, groups, groups, length), groups), "regions")
    texts = _texts(slim, groups)
    covered = materialize(_sorted_shards(_runs(texts.union(settled_or_open.where(F.col("kind") == _OPEN)), groups, length), groups, length), "runs")
    kept = _kept(texts.union(settled_or_open.where(F.col("kind") == _SETTLED)).union(covered), length, with_text)
    text = F.coalesce("text", F.lit(""))
    none = F.lit(0).cast("long")
    nameless = documents_only(docs).where(F.col("doc_id").isNull())
    whole = nameless.select("doc_id", F.octet_length(text).cast("long").alias("n_bytes"), none.alias("n_removed"), none.alias("n_spans"), F.sha2(text.cast("binary"), 256).alias("kept_sha256"), F.xxhash64("text").alias("text_hash"), *([text.alias("kept_text")] if with_text else []))
    return kept.union(whole)
