"""Byte-level BPE encoding by a lazily determinised transducer, and streaming decode.

A merge table admits one segmentation of any byte string, and a segmentation
is that one exactly if every two neighbouring tokens, merged on their own,
stay apart. So the last token of each prefix follows from the last tokens of
shorter prefixes. A transducer state stands for the set of places at which a
token may have begun; the longest end of the bytes read that some token begins
with tells that set, so there are no more states than beginnings of tokens,
whatever the texts. A state carries the tokens that end in it. Just one of them
stays apart from the last token of the bytes in front of it, which a table of
pairs tells, and the ids are read off from the end of the string. States, arcs
and pairs are made when first needed and kept; outputs of whole stretches of
text are kept too. All these tables are bounded and are emptied when full.

Whether two tokens stay apart is read off the merge table alone: undoing the
merges of both, the latest first, shows each pair of parts that ever stood at
their boundary, and with it the merges that could have crossed it.
"""

from __future__ import annotations

import base64
import gc
import hashlib
import re
import sys
from collections.abc import Iterator
from itertools import islice
from struct import pack

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from edgecsr.llm.common import documents_only, per_worker

#: How many stretches (and half as many pieces) of text and how many states a worker keeps.
MAX_STRETCHES = 600_000
MAX_STATES = 200_000


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class _State:
    """All places at which a token may stand unfinished or just ended, told by ``path``.

    ``path``: the longest end of the bytes read so far that a token begins with. ``ending``: the tokens that end
    here, the longest first, as (token, how long, the token as the left one of a pair).
    """

    __slots__ = ("arcs", "ending", "path")

    def __init__(self, path, ending):
        self.path, self.ending, self.arcs = path, ending, {}


class Transducer:
    """Byte string to token ids under ``ranks`` (token bytes to merge rank, which is also the id)."""

    def __init__(self, ranks: dict[bytes, int], max_states: int = MAX_STATES):
        self.ranks, self.max_states = ranks, max_states
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.prefixes = {t[:n] for t in ranks for n in range(1, len(t) + 1)} | {b""}
        self.parts = {i: self._parts(i) for i in self.bytes_of}
        #: A pair is the number left * width + right; ``nothing`` is the left one of a first token.
        self.width = max(self.bytes_of, default=0) + 1
        self.nothing = self.width * self.width
        self.made = {self.bytes_of[i]: (i, len(self.bytes_of[i]), i * self.width) for i, p in self.parts.items() if p != (-1, -1)}
        self.apart: dict[int, bool] = {}
        self._reset()

    def _reset(self):
        self.start = _State(b"", ())
        self.states = {b"": self.start}

    def _parts(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; None for a single byte, (-1, -1) if merging never makes it."""
        data, get, none = self.bytes_of[token], self.ranks.get, 1 << 40
        if len(data) == 1:
            return None
        parts = [data[i : i + 1] for i in range(len(data))]
        rank = [get(a + b, none) for a, b in zip(parts, parts[1:])]
        while len(rank) > 1 and (least := min(rank)) < none:
            i = rank.index(least)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del rank[i]
            if i < len(rank):
                rank[i] = get(parts[i] + parts[i + 1], none)
            if i:
                rank[i - 1] = get(parts[i - 1] + parts[i], none)
        return (self.ranks[parts[0]], self.ranks[parts[1]]) if len(parts) == 2 else (-1, -1)

    def _stay_apart(self, pair: int) -> bool:
        """Whether merging leaves both tokens of the pair as they are."""
        ok = pair >= self.nothing or self._never_crossed(*divmod(pair, self.width))
        if len(self.apart) > 4 * self.max_states:
            self.apart.clear()
        self.apart[pair] = ok
        return ok

    def _never_crossed(self, a: int, b: int) -> bool:
        bytes_of, get, parts, limit = self.bytes_of, self.ranks.get, self.parts, 1 << 40
        while True:
            across = get(bytes_of[a] + bytes_of[b])
            if across is not None and across < limit:
                return False  # this merge comes before the one that made a part of either side
            left, right = parts[a], parts[b]
            if left is not None and (right is None or a > b):
                limit, a = a, left[1]
            elif right is not None:  # of equal merges the left one comes first, so it crosses before this one
                limit, b = b + 1, right[0]
            else:
                return True

    def _after(self, state: _State, byte: int) -> _State:
        """The state after one more byte; one that is not known yet is made, but not kept."""
        path, prefixes, made = state.path + bytes((byte,)), self.prefixes, self.made
        while path not in prefixes:
            path = path[1:]
        return self.states.get(path) or _State(path, tuple(made[path[i:]] for i in range(len(path)) if path[i:] in made))

    def _arc(self, state: _State, byte: int) -> _State:
        then = self._after(state, byte)
        if then.path not in self.states:
            if len(self.states) > self.max_states:
                self._reset()
            self.states[then.path] = then
        state.arcs[byte] = then
        return then

    def encode(self, data: bytes) -> list[int]:
        """The last byte asks for no state after it: where it has no arc yet, nothing is kept that only longer texts would use."""
        if not data:
            return []
        state, before, last, apart, final = self.start, [self.nothing], [], self.apart.get, len(data) - 1
        for n, byte in enumerate(data):
            state = state.arcs.get(byte) or (self._arc if n < final else self._after)(state, byte)
            for entry in state.ending:  # just one is right
                token, size, left = entry
                pair = before[-size] + token
                ok = apart(pair)
                if ok or ok is None and self._stay_apart(pair):
                    before.append(left)
                    last.append(entry)
                    break
            else:
                raise ValueError(f"no token ends at byte {byte} of this table")
        out, n = [], len(data)
        while n:
            token, size, _ = last[n - 1]
            out.append(token)
            n -= size
        return out[::-1]


class PieceTable(dict):
    """Text to its ids, packed as little-endian unsigned 32-bit integers; misses go through ``make``.

    Two generations: when the young one is full it becomes the old one, from
    which texts that recur come back.
    """

    def __init__(self, make, max_pieces: int = MAX_STRETCHES):
        super().__init__()
        self.make, self.max_pieces, self.old = make, max_pieces, {}

    def __missing__(self, piece: str) -> bytes:
        packed = self.old.get(piece)
        if packed is None:
            packed = self.make(piece)
            if len(piece) > 64:  # long ones hardly recur
                return packed
        if len(self) >= self.max_pieces:
            self.old = dict(self)
            self.clear()
        self[piece] = packed
        return packed


class Encoder:
    """Whole texts: split by ``pattern``, each piece on its own.

    A lone space between two characters that are no white space always begins
    a piece, so the stretches between such spaces are encoded apart and kept.
    A stretch of letters alone is one piece, and the one that others begin with.
    """

    #: Such spaces; ``re`` counts all that ``regex`` does as white space, and more.
    LONE = re.compile(r"(?<=\S) (?=\S)")
    #: Other white space of ASCII, before and behind a space.
    BESIDE = [x for c in "\t\n\x0b\x0c\r\x1c\x1d\x1e\x1f" for x in (c + " ", " " + c)] + ["  "]

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.find = regex.compile(pattern).findall
        letters = " " + "".join(filter(str.isalpha, map(chr, range(sys.maxunicode + 1))))
        #: Whether the pattern takes a space and all letters behind it, as Python tells letters, in one piece.
        self.words = self.find(letters) == [letters]
        self.transducer = Transducer(ranks)
        self.pieces = PieceTable(self._piece, MAX_STRETCHES // 2)
        self.stretches = PieceTable(self._stretch)

    def _piece(self, piece: str) -> bytes:
        data = piece.encode()
        whole = self.transducer.ranks.get(data)
        ids = [whole] if whole is not None else self.transducer.encode(data)
        return pack(f"<{len(ids)}I", *ids)

    def _split(self, text: str) -> bytes:
        return b"".join(map(self.pieces.__getitem__, self.find(text)))

    def _stretch(self, after_space: str) -> bytes:
        if self.words and after_space.isalpha():
            return self._piece(" " + after_space)
        first, *rest = self.find(" " + after_space)
        word = first[1:]
        if self.words and first[0] == " " and word.isalpha():  # a stretch too, with or without what is behind it
            return self.stretches[word] + b"".join(map(self.pieces.__getitem__, rest))
        return b"".join(map(self.pieces.__getitem__, (first, *rest)))

    def encode_packed(self, text: str) -> bytes:
        plain = text.isascii() and text[:1] != " " and text[-1:] != " " and not any(map(text.__contains__, self.BESIDE))
        first, *rest = text.split(" ") if plain else self.LONE.split(text)
        return self._split(first) + b"".join(map(self.stretches.__getitem__, rest))

    def encode(self, text: str) -> list[int]:
        packed = self.encode_packed(text)
        return list(memoryview(packed).cast("I")) if packed else []


def _utf8_steps() -> list[list[int]]:
    """Transitions (state by byte) of well-formed UTF-8: 0 between characters, 1 to 3 that many plain continuation bytes to come, -1 ill-formed.

    States 4 to 7 take the second byte of the leads that allow only some: after E0, ED, F0 and F4.
    """
    steps = [[-1] * 256 for _ in range(8)]
    for byte in range(256):
        if byte < 0x80:
            steps[0][byte] = 0
        elif 0xC2 <= byte < 0xF5:
            steps[0][byte] = {0xE0: 4, 0xED: 5, 0xF0: 6, 0xF4: 7}.get(byte, 1 if byte < 0xE0 else 2 if byte < 0xF0 else 3)
        elif byte < 0xC0:
            for state in (1, 2, 3):
                steps[state][byte] = state - 1
            for state, low, high, then in ((4, 0xA0, 0xBF, 1), (5, 0x80, 0x9F, 1), (6, 0x90, 0xBF, 2), (7, 0x80, 0x8F, 2)):
                if low <= byte <= high:
                    steps[state][byte] = then
    return steps


class Utf8Machine:
    """Incremental UTF-8: bytes in any cuts, text out; a sequence that is not whole yet waits with its state.

    Only the last character of a part can be cut, so the machine walks from its
    lead byte on; whole characters before it are decoded in bulk.
    """

    STEPS = _utf8_steps()

    def __init__(self, errors: str = "strict"):
        self.errors, self.waiting = errors, b""

    def _unfinished(self, data: bytes) -> int:
        """How many bytes at the end begin a character that goes on after them."""
        back = 1
        while back < min(4, len(data)) and 0x80 <= data[-back] < 0xC0:
            back += 1
        state = 0
        for byte in data[len(data) - back :]:
            state = self.STEPS[state][byte]
            if state < 0:
                return 0  # ill-formed: for the decoder to tell
        return back if state else 0

    def feed(self, data: bytes) -> str:
        data = self.waiting + data
        cut = len(data) - self._unfinished(data)
        self.waiting = data[cut:]
        return data[:cut].decode("utf-8", self.errors)

    def finish(self) -> str:
        data, self.waiting = self.waiting, b""
        return data.decode("utf-8", self.errors)


def decode_stream(ids, bytes_of: dict[int, bytes], chunk: int = 8192, errors: str = "strict") -> Iterator[str]:
    """Text of a stream of ids, in parts, never cutting a character."""
    machine, ids = Utf8Machine(errors), iter(ids)
    while held := list(islice(ids, chunk)):
        yield machine.feed(b"".join(map(bytes_of.__getitem__, held)))
    yield machine.finish()


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, with_ids: bool = False) -> DataFrame:
    """Every whole text to ids and back: doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids).

    A null text counts as empty: no ids, digests of nothing. Repeated rows are
    encoded each; a null doc_id stays null. Rows are independent, so there is
    no shuffle, and a lost task is simply run again.
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if with_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = per_worker(("byte_bpe", ranks_path, pattern), lambda: Encoder(load_ranks(ranks_path), pattern))
        bytes_of = encoder.transducer.bytes_of
        collecting = gc.isenabled()
        gc.disable()  # the tables hold very many small objects and no garbage
        try:
            for batch in batches:
                counts, digests, back, ids = [], [], [], []
                for text in batch.column(1):
                    packed = encoder.encode_packed(text.as_py() or "")
                    tokens = memoryview(packed).cast("I").tolist() if packed else []
                    decoded = hashlib.sha256()
                    for part in decode_stream(tokens, bytes_of):
                        decoded.update(part.encode())
                    counts.append(len(tokens))
                    digests.append(hashlib.sha256(packed).hexdigest())
                    back.append(decoded.hexdigest())
                    if with_ids:
                        ids.append(tokens)
                columns = [batch.column(0), pa.array(counts, pa.int64()), pa.array(digests, pa.string()), pa.array(back, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    columns.append(pa.array(ids, pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)
        finally:
            if collecting:
                gc.enable()

    return documents_only(docs).mapInArrow(run, schema)
