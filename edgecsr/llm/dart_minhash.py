"""Near duplicates by dart-throwing signatures of weighted shingle sets, banded and verified.

Every element owns the same random darts in all sets: points over its weight
axis and a rank axis. A set holds the darts that lie under its weights; each
dart belongs to one of k coordinates, and a coordinate's value is its dart of
least rank. Two sets agree in a coordinate with the probability of their
weighted Jaccard similarity. Only darts below a rank at which about k (log k +
4) are expected need be thrown, so long sets cost little more than reading them.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgecsr.llm.common import Scratch, documents_only, materialize, release
from edgecsr.llm.shingles import mix, similarity, weighted

WORDS, THRESHOLD = 5, 0.8
#: 32 bands of 5: two sets of similarity 0.8 miss each other with probability 3e-6.
BANDS, ROWS = 32, 5
#: Estimated similarity below which a pair is not looked at: 5 deviations under the threshold.
LEAST_ESTIMATE = 0.64
#: Members of a bucket that are compared with all others of it in each of the first rounds; four times as many in each later one.
LEADERS = 1
#: Rounds over the buckets of bands, after the one in which each member meets one leader, before those that are not done are dealt into finer ones.
COARSE = 1
#: Ids that are broadcast at most, some 50 bytes each; beyond that both sides of the join are dealt.
BROADCAST_IDS = 1_000_000
#: Keys of finer buckets that are written as one batch.
KEYS = 500_000
#: Columns of 64 bits that tell unlike sets apart: a bit is the parity of the shingles that fall on it.
PARITIES = [f"parity{i}" for i in range(4)]
_LOW = 6  # ranks below 2**-_LOW are one cell, then cells double up to rank 1, then each has length 1


def _poisson_cuts(area: float) -> np.ndarray:
    """Cumulated Poisson probabilities as 64-bit numbers."""
    p, total, cuts = math.exp(-area), 0.0, []
    for i in range(1, 40):
        total += p
        cuts.append(total)
        p *= area / i
    return (np.minimum(np.array(cuts), 1 - 2**-53) * 2**64).astype(np.uint64)


_CELLS = [(0.0, 2.0**-_LOW), *[(2.0 ** -(i + 1), 2.0 ** -(i + 1)) for i in range(_LOW - 1, -1, -1)]]  # (from, length), up to rank 1
_CUTS = {length: _poisson_cuts(length) for length in {c[1] for c in _CELLS} | {1.0}}


def _unit(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(11)).astype(np.float64) * 2.0**-53


def _expanded(elements: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit cells of the weight axis, and how far the weight reaches into each."""
    if not len(elements) or weights.max() == weights.min() == 1:
        return elements, np.ones(len(elements))
    cells = np.ceil(weights).astype(int)
    floor = np.arange(int(cells.sum())) - np.repeat(np.cumsum(cells) - cells, cells)
    return mix(np.repeat(elements, cells) + floor.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), np.minimum(1.0, np.repeat(weights, cells) - floor)


def signatures(sets: list[tuple[np.ndarray, np.ndarray]], k: int) -> np.ndarray:
    """A row of k 32-bit values for each set of (elements, weights); an empty set has zeros."""
    n = len(sets)
    best, out = np.full(n * k, np.inf), np.zeros(n * k, np.uint32)
    grown = [_expanded(*x) for x in sets]
    elements = np.concatenate([g[0] for g in grown]) if n else np.zeros(0, np.uint64)
    limits = np.concatenate([g[1] for g in grown]) if n else np.zeros(0)
    owner = np.repeat(np.arange(n), [len(g[0]) for g in grown])
    total = np.bincount(owner, limits, n)
    below = np.where(total > 0, k * (math.log(k) + 4) / np.maximum(total, 1e-9), 0)
    cell, upto = 0, 0.0
    while len(elements):
        low, length = _CELLS[cell] if cell < len(_CELLS) else (float(cell - len(_CELLS) + 1), 1.0)
        key = np.uint64((cell * 0xA24BAED4963EE407 + 0x9FB21C651E98DF25) % 2**64)
        cuts = _CUTS[length]
        for at in range(0, len(elements), 1 << 18):
            h = mix(elements[at : at + (1 << 18)] ^ key)
            hit = np.flatnonzero(h >= cuts[0])
            if not len(hit):
                continue
            times = np.searchsorted(cuts, h[hit], "right")
            own = np.repeat(hit, times)
            nth = np.arange(len(own)) - np.repeat(np.cumsum(times) - times, times)
            dart = mix(h[own] + (nth + 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            inside = _unit(mix(dart + np.uint64(1))) < limits[at + own]
            dart, own = dart[inside], own[inside]
            rank = low + length * _unit(mix(dart + np.uint64(2)))
            where = owner[at + own] * k + (mix(dart + np.uint64(3)) % np.uint64(k)).astype(np.int64)
            better = rank < best[where]
            where, rank, dart = where[better], rank[better], dart[better]
            order = np.argsort(-rank, kind="stable")  # the least rank is written last
            best[where[order]] = rank[order]
            out[where[order]] = (dart[order] >> np.uint64(32)).astype(np.uint32)
        cell += 1
        upto = low + length
        done = upto >= below
        if done.any():
            done &= ~np.isinf(best).reshape(n, k).any(1) | (total == 0)  # else darts of higher ranks are needed
            going = ~done[owner]
            elements, limits, owner = elements[going], limits[going], owner[going]
    return out.reshape(n, k)


def signature(elements: np.ndarray, weights: np.ndarray, k: int) -> np.ndarray:
    return signatures([(elements, weights)], k)[0]


def band_hashes(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    total = np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0xE7037ED1A0B428DB)
    for j in range(rows):
        total = mix(total + sig[: bands * rows].reshape(bands, rows)[:, j].astype(np.uint64) + np.uint64(1))
    return total.view(np.int64)


#: A text of a document: rows that repeat a doc_id with another text are texts of their own.
ID = "struct<doc_id:bigint,text_hash:bigint>"
SIGNED = f"id {ID}, digest binary, signature binary, bands array<long>"
PAIR = f"leader {ID}, id {ID}"


def identified(docs: DataFrame) -> DataFrame:
    """id (doc_id and a hash of the text) and text of the rows that have a doc_id."""
    slim = documents_only(docs).where(F.col("doc_id").isNotNull())
    return slim.select(F.struct("doc_id", F.xxhash64("text").alias("text_hash")).alias("id"), "text")


def signed(docs: DataFrame, words: int = WORDS, counts: bool = False, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Digest of the weighted shingle set, signature and band hashes of every document with an id.

    Bands are made of whole values; the signature that is kept has half of each, as unlike values agree in it once in 65,536 times.
    """

    k = bands * rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, held, size, done = batch.column(0), [], 0, 0
            for i, text in enumerate(batch.column(1), 1):
                held.append(weighted(text.as_py() or "", words, counts))
                size += len(held[-1][0])
                if size >= 200_000 or i == batch.num_rows:  # sets that are signed together
                    sigs = signatures(held, k)
                    digests = [hashlib.blake2b(e.tobytes() + (w.tobytes() if counts else b""), digest_size=16).digest() for e, w in held]
                    flat = pa.array(np.concatenate([band_hashes(x, bands, rows) for x in sigs]))
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(held) + 1) * bands, pa.int32()), flat)
                    yield pa.RecordBatch.from_arrays([ids.slice(done, len(held)), pa.array(digests, pa.binary()), pa.array([x.tobytes() for x in sigs.astype(np.uint16)], pa.binary()), lists], ["id", "digest", "signature", "bands"])
                    held, size, done = [], 0, i

    return identified(docs).mapInArrow(run, SIGNED)


def _estimated(pairs: DataFrame, signatures: DataFrame) -> DataFrame:
    """Pairs whose signatures agree often enough to be looked at."""
    own = signatures.select(F.col("id"), F.col("signature").alias("_a"))
    other = signatures.select(F.col("id").alias("leader"), F.col("signature").alias("_b"))
    joined = pairs.join(own, "id").join(other, "leader").select("leader", "id", "_a", "_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a, b = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint16).reshape(batch.num_rows, -1) for i in (2, 3))
                near = pa.array((a == b).mean(1) >= LEAST_ESTIMATE)
                yield pa.RecordBatch.from_arrays(batch.columns[:2], ["leader", "id"]).filter(near)

    return joined.mapInArrow(run, PAIR)


def _verified(pairs: DataFrame, texts: DataFrame, words: int, counts: bool, threshold: float) -> DataFrame:
    """Pairs whose similarity, computed from the whole texts, is ``threshold`` or more."""
    own = texts.select(F.col("id"), F.col("text").alias("_a"))
    other = texts.select(F.col("id").alias("leader"), F.col("text").alias("_b"))
    joined = pairs.join(own, "id").join(other, "leader").select("leader", "id", "_a", "_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = (None, None)
        for batch in batches:
            near = []
            for leader, a, b in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3)):
                if last[0] != leader:  # pairs of a leader mostly come together
                    last = (leader, weighted(b.as_py() or "", words, counts))
                near.append(similarity(weighted(a.as_py() or "", words, counts), last[1]) >= threshold)
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["leader", "id"]).filter(pa.array(near, pa.bool_()))

    return joined.mapInArrow(run, PAIR)


def _refined(pairs: DataFrame, texts: DataFrame, words: int, counts: bool, threshold: float) -> DataFrame:
    """Finer buckets (bucket, id, label, size, most, parities) for members of buckets that have ``pivot`` as their first leader.

    Shingles are put in one order for all that share a pivot: those that the
    pivot lacks, then its own. A member gets a bucket for each shingle of its
    head, with its whole weight ``size`` and the ``most`` that a partner may
    weigh if this is their first common shingle: all they share is in the rest
    from there on, and must be threshold / (1 + threshold) of both weights.
    The head ends where no partner is light enough to be similar. Two similar
    sets thus meet in the bucket of their first common shingle, each within
    the other's ``most``. In a crowd around a pivot heads are mostly made of
    what sets a member apart.
    """
    own = texts.select(F.col("id"), F.col("text").alias("_a"))
    other = texts.select(F.col("id").alias("pivot"), F.col("text").alias("_b"))
    joined = pairs.join(own, "id").join(other, "pivot").select("pivot", "id", "label", "_a", "_b")
    names = ["bucket", "id", "label", "size", "most", *PARITIES]
    id_type = pa.struct([("doc_id", pa.int64()), ("text_hash", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size, last = 0, (None, None, None)

        def flush():
            times = [len(h[0]) for h in held]
            of = np.repeat(np.arange(len(held)), times)
            ids = [pa.array([h[i] for h in held], id_type).take(pa.array(of)) for i in (1, 2)]
            numbers = [np.concatenate([h[0] for h in held]).view(np.int64), np.array([h[3] for h in held])[of], np.concatenate([h[4] for h in held])]
            parities = np.array([h[5] for h in held])[of]
            return pa.RecordBatch.from_arrays([pa.array(numbers[0]), *ids, pa.array(numbers[1]), pa.array(numbers[2]), *[pa.array(parities[:, i]) for i in range(len(PARITIES))]], names)

        for batch in batches:
            for pivot, doc, label, a, b in zip(*(batch.column(i).to_pylist() for i in range(3)), batch.column(3), batch.column(4)):
                if last[0] != pivot:
                    last = (pivot, weighted(b.as_py() or "", words, counts)[0], mix(np.array([pivot["doc_id"]], np.int64).view(np.uint64)) + np.array([pivot["text_hash"]], np.int64).view(np.uint64))
                found, weights = weighted(a.as_py() or "", words, counts)
                order = np.lexsort((found, np.isin(found, last[1], assume_unique=True)))
                rest = np.cumsum(weights[order][::-1])[::-1]
                size_of = float(weights.sum())
                most = rest * (1 + threshold) / threshold - size_of + 1e-6
                head = found[order][most >= threshold * size_of]
                held.append((mix(head ^ mix(last[2])), doc, label, size_of, most[: len(head)], _parities(found)))
                size += len(head)
                if size >= KEYS:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    return joined.mapInArrow(run, f"bucket long, id {ID}, label {ID}, size double, most double, {' long, '.join(PARITIES)} long")


def _parities(elements: np.ndarray) -> np.ndarray:
    """The parities of a set, as signed 64-bit numbers.

    Where two sets have unlike parities, one of them holds a shingle that the
    other lacks; so they differ by as many shingles as parities at least.
    """
    n = 64 * len(PARITIES)
    odd = np.bincount((mix(elements) % np.uint64(n)).astype(np.int64), minlength=n) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def _may_be_similar(threshold: float) -> str:
    """Whether the parities leave a pair similar: with weights of s together that differ by d, its similarity is (s - d) / (s + d)."""
    unlike = " + ".join(f"bit_count({p} ^ _{p})" for p in PARITIES)
    return f"({unlike}) * {1 + threshold}D <= (size + _size) * {1 - threshold}D + 1e-6D"


def components(links: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """id, label of every end of ``links`` (leader, id): the least id that it is linked with, over any number of links.

    Least labels spread to neighbours and then jump to their label's label, so
    rounds grow with the logarithm of a chain's length. Each round is written.
    """
    keep = scratch.keep if scratch else materialize
    both = keep(links.selectExpr("leader as a", "id as b").union(links.selectExpr("id as a", "leader as b")).distinct(), "links")
    labels = both.groupBy("a").agg(F.min("b").alias("_m")).select(F.col("a").alias("id"), F.least("a", "_m").alias("label"))
    labels = keep(labels, "labels")
    while True:
        near = both.join(labels.withColumnRenamed("id", "b"), "b").groupBy("a").agg(F.min("label").alias("_m"))
        met = labels.join(near.withColumnRenamed("a", "id"), "id").select("id", F.col("label").alias("_old"), F.least("label", "_m").alias("label"))
        jumped = met.join(met.select(F.col("id").alias("label"), F.col("label").alias("_up")), "label", "left").select("id", "_old", F.least(F.col("label"), F.coalesce("_up", "label")).alias("label"))
        jumped = keep(jumped, "labels")
        if jumped.where(F.col("label") != F.col("_old")).isEmpty():
            return jumped.select("id", "label")
        labels = jumped.select("id", "label")


def classes(docs: DataFrame, words: int = WORDS, threshold: float = THRESHOLD, counts: bool = False) -> DataFrame:
    """doc_id, same_set_id, class_id, n_links of every document.

    ``same_set_id``: the least doc_id with the same shingle set. ``class_id``: the least doc_id that it
    is linked with by similarity ``threshold`` or more, over any number of links; ``n_links``: verified
    links of its shingle set. Null and empty texts have the empty set and so are alike;
    rows without doc_id take no part; rows of a repeated doc_id count once if their sets are equal, else
    each set is classed by its own text and has a row.
    """
    told = classed(docs, words, threshold, counts)
    return told.select(F.col("id.doc_id").alias("doc_id"), F.col("same_set.doc_id").alias("same_set_id"), F.col("class.doc_id").alias("class_id"), "n_links").distinct()


def classed(docs: DataFrame, words: int = WORDS, threshold: float = THRESHOLD, counts: bool = False) -> DataFrame:
    """id, same_set, class, n_links of every distinct (doc_id, text): ids of the least member each; see ``classes``.

    Copies are folded to one representative before anything is paired. In
    the first round each member meets one leader, which links most of a crowd. In
    every later round each bucket compares some of its members (first the one that
    meets most others, then more) with those of other classes in it; they are
    then done with there, and a bucket is done when its members are all of one
    class. After the first rounds the members of buckets that are not done are
    dealt into finer ones, which keep every two that can be similar together.
    So every two representatives of a band's bucket have been compared, cannot
    be similar or are linked already.
    """
    scratch = Scratch(docs.sparkSession)
    rows = scratch.keep(signed(docs, words, counts), "signed")
    folded = rows.groupBy("digest").agg(F.min("id").alias("id"))
    reps = rows.join(folded, ["digest", "id"], "left_semi").dropDuplicates(["id"])
    reps = scratch.keep(reps.select("id", "signature", "bands"), "representatives")
    members = scratch.keep(rows.select("id", "digest").distinct().join(folded.withColumnRenamed("id", "same_set"), "digest").select("id", "same_set"), "members")
    scratch.forget("signed")
    in_bands = reps.select("id", F.explode("bands").alias("bucket"))
    shared = in_bands.groupBy("bucket").agg(F.count("*").alias("_n")).where("_n > 1")  # representatives differ, and a band is part of its hash
    company = F.sum("_n").over(Window.partitionBy("id")).alias("company")  # how many others a member meets: most at the middle of a crowd
    buckets = scratch.keep(in_bands.join(shared, "bucket").select("bucket", "id", company), "buckets")
    candidates = scratch.keep(buckets.select("id").distinct(), "candidates")
    signatures = scratch.keep(reps.select("id", "signature").join(candidates, "id"), "signatures")
    scratch.forget("representatives")
    few = candidates.count() <= BROADCAST_IDS  # then whole texts need not travel to be left out
    texts = scratch.keep(identified(docs).join(F.broadcast(candidates) if few else candidates, "id").dropDuplicates(["id"]), "texts")
    links = label = firsts = None
    buckets, turn = buckets.withColumns({"label": F.col("id"), "size": F.lit(0.0), "most": F.lit(0.0)}), 0
    while not buckets.isEmpty():
        coarse = turn <= COARSE  # buckets of bands, not yet finer ones
        order = [F.col("company").desc(), F.col("id")] if coarse else [F.col("most").desc(), F.col("id")]
        ranked = buckets.withColumn("_r", F.row_number().over(Window.partitionBy("bucket").orderBy(*order)))
        each = LEADERS * 4 ** max(0, turn - COARSE)
        more = ["company"] if coarse else PARITIES
        leaders = scratch.keep(ranked.where(F.col("_r") <= each).select("bucket", F.col("id").alias("leader"), *[F.col(c).alias(f"_{c}") for c in ("size", "most", *more)], F.col("label").alias("_with"), "_r"), "leaders")
        if not turn:
            firsts = scratch.keep(leaders.where("_r = 1").select("bucket", F.col("leader").alias("pivot")), "firsts")
        met = buckets.join(leaders, "bucket").where("label <> _with AND size <= _most AND _size <= most")
        if not coarse:
            met = met.where(_may_be_similar(threshold))
        if not turn:  # each member with one leader, the one of all its buckets that meets most others
            met = met.groupBy("id").agg(F.max(F.struct("_company", "leader")).alias("_best")).select("id", "_best.leader")
        pairs = met.select(F.greatest("id", "leader").alias("id"), F.least("id", "leader").alias("leader")).distinct()
        found = scratch.keep(_verified(_estimated(pairs, signatures), texts, words, counts, threshold), "found")
        left = buckets.join(leaders.select("bucket", F.col("leader").alias("id")), ["bucket", "id"], "left_anti") if turn else buckets
        if not found.isEmpty():
            links = found if links is None else links.union(found)
            label = components(links, scratch)
            left = left.drop("label").join(label, "id", "left").withColumn("label", F.coalesce("label", "id"))
        buckets = scratch.keep(_mixed(scratch.keep(left.select("bucket", "id", "label", "size", "most", *more), "left")), f"buckets{turn}")
        if turn == COARSE:
            crowd = buckets.join(firsts, "bucket").select("pivot", "id", "label").distinct()
            buckets = scratch.keep(_mixed(scratch.keep(_refined(crowd, texts, words, counts, threshold), "finer")), "refined")
            scratch.forget("finer", "buckets", f"buckets{turn}", "firsts")
        scratch.forget("left", "leaders", f"buckets{turn - 1}")
        turn += 1
        release(docs.sparkSession)
    if links is None:
        told = members.select("id", "same_set", F.col("same_set").alias("class"), F.lit(0).cast("long").alias("n_links"))
    else:
        ends = links.select(F.explode(F.array("leader", "id")).alias("id")).groupBy("id").agg(F.count("*").alias("n_links"))
        linked = label.join(ends, "id").withColumnRenamed("id", "same_set")
        told = members.join(linked, "same_set", "left").select("id", "same_set", F.coalesce("label", "same_set").alias("class"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
    told = materialize(told, "classes")
    scratch.drop()
    return told


def _mixed(members: DataFrame) -> DataFrame:
    """Members that may be similar to one of another class in their bucket, by what they weigh and what their partners may weigh."""
    ends = [f(f"label.{c}").alias(f"_{n}_{c}") for c in ("doc_id", "text_hash") for f, n in ((F.min, "l"), (F.max, "h"))]
    several = "_l_doc_id < _h_doc_id OR _l_text_hash < _h_text_hash"
    reach = members.groupBy("bucket").agg(F.min("size").alias("_least"), F.max("most").alias("_widest"), *ends).where(several)
    able = members.join(reach, "bucket").where("most >= _least AND size <= _widest").select(members.columns)
    return able.join(able.groupBy("bucket").agg(*ends).where(several).select("bucket"), "bucket")
