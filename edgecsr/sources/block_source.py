"""Python data sources over text edge lists; paths are URIs that pyarrow's file systems open.

``edgeblocks``: byte blocks, parsed in bulk. Batch: one input partition per
``split_bytes``, or ``slices`` equal ones for all files together; inside it blocks of
``block_bytes`` are aligned and parsed one by one. Stream: offsets are files,
each read once.

``edgelines``: data lines one after the other through a file buffer, numbered
within their input partition. ``edgechunks``: the same lines, ``chunk`` of them
at a time as one text that its reader takes apart; no chunk spans two blocks of
``lines_per_block`` lines.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

from edgecsr.functions.parse import BLANKS, parse_buffer


def opened(path: str):
    if "://" not in path and not path.startswith("file:"):
        return fs.LocalFileSystem(), path
    return fs.FileSystem.from_uri(path if not path.startswith("file:/") or path.startswith("file:///") else "file://" + path[5:])


def listed(path: str) -> list[tuple[str, int]]:
    system, at = opened(path)
    info = system.get_file_info(at)
    if info.type == fs.FileType.File:
        return [(path, info.size)]
    found = system.get_file_info(fs.FileSelector(at, recursive=True))
    prefix = path[: len(path) - len(at)] if path.endswith(at) else ""
    return sorted((prefix + f.path, f.size) for f in found if f.type == fs.FileType.File and not f.base_name.startswith(("_", ".")))


class Split(InputPartition):
    def __init__(self, path: str, start: int, length: int, size: int):
        self.path, self.start, self.length, self.size = path, start, length, size


def lines_of(split: Split) -> bytes:
    """The whole lines that begin inside the split; reads on past its end for the last one."""
    system, at = opened(split.path)
    with system.open_input_file(at) as f:
        begin = max(0, split.start - 1)
        f.seek(begin)
        data = bytearray(f.read(split.start + split.length - begin))
        while split.start + split.length < split.size and data and data[-1] != 0x0A:
            more = f.read(1 << 16)
            if not more:
                break
            end = more.find(b"\n")
            data += more if end < 0 else more[: end + 1]
            if end >= 0:
                break
    if split.start:
        first = data.find(b"\n")  # the byte before the split tells whether a line begins with it
        return bytes(data[first + 1 :]) if first >= 0 else b""
    return bytes(data)


def batches(split: Split, options: dict):
    from edgecsr.sources.blocks import align_block

    data = lines_of(split)
    block = int(options.get("block_bytes", 262144))
    weighted, base = options.get("weighted", "true") == "true", int(options.get("index_base", 1))
    for at in range(0, len(data), block):
        begin, end = align_block(data, at, block)
        if begin < end:
            src, dst, weight = parse_buffer(data[begin:end], weighted, base)
            part = np.full(len(src), (split.start + begin) // block, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(weight, pa.float32()), pa.array(part)], ["src", "dst", "weight", "block"])


def equal_slices(files: list[tuple[str, int]], n: int) -> list[list[Split]]:
    """All bytes in ``n`` slices of the same length; a slice may span files, a file many slices."""
    total = sum(size for _, size in files)
    cuts, out, before = [total * i // n for i in range(n + 1)], [[] for _ in range(n)], 0
    for path, size in files:
        for i in range(n):
            a, b = max(cuts[i], before), min(cuts[i + 1], before + size)
            if a < b:
                out[i].append(Split(path, a - before, b - a, size))
        before += size
    return out


class Slice(InputPartition):
    """The splits of one input partition, and its number."""

    def __init__(self, number: int, splits: list[Split]):
        self.number, self.splits = number, splits


def planned(options: dict) -> list[Slice]:
    files = listed(options["path"])
    if "slices" in options:
        return [Slice(i, x) for i, x in enumerate(equal_slices(files, int(options["slices"])))]
    most = int(options.get("split_bytes", 128 << 20))
    cut = [[Split(p, at, min(most, size - at), size)] for p, size in files for at in range(0, size, most)]
    return [Slice(i, x) for i, x in enumerate(cut or [[]])]


def buffered_lines(split: Split, buffer_bytes: int = 1 << 20):
    """The lines that begin inside the split, whole, as many at a time as a buffer holds."""
    system, at = opened(split.path)
    end, held = split.start + split.length, bytearray()
    with system.open_input_file(at) as f:
        here = max(0, split.start - 1)  # the byte before the split tells whether a line begins with it
        f.seek(here)
        inside = split.start == 0
        while got := f.read(buffer_bytes):
            new = len(held)
            held += got
            if not inside:
                first = held.find(b"\n", new)
                if first < 0:
                    continue
                here, inside, new = here + first + 1, True, 0
                del held[: first + 1]
            if here >= end:
                return
            past = here + len(held) >= end
            cut = (held.find(b"\n", max(new, end - here - 1)) if past else held.rfind(b"\n", new)) + 1
            if cut:
                yield bytes(held[:cut])
                here += cut
                del held[:cut]
                if past:
                    return
    if inside and held:
        yield bytes(held)


#: First bytes of lines that may be blank or comments.
_MAYBE_NONE = np.isin(np.arange(256), list(BLANKS + b"%#"))


def _line_ends(text: bytes) -> np.ndarray:
    return np.flatnonzero(np.frombuffer(text, np.uint8) == 0x0A)


def data_text(text: bytes) -> tuple[bytes, np.ndarray]:
    """The data lines of whole lines, each with its end, as UTF-8; and where they end."""
    if not text.endswith(b"\n"):
        text += b"\n"
    if not text.isascii():
        text = text.decode("utf-8", "replace").encode()
    ends = _line_ends(text)
    starts = np.concatenate([[0], ends[:-1] + 1])
    every = np.frombuffer(text, np.uint8)
    odd = np.flatnonzero(_MAYBE_NONE[every[starts]])
    none = [i for i in odd if (bare := text[starts[i] : ends[i]].strip(BLANKS))[:1] in b"%#"]
    if none:
        keep = np.ones(len(ends), bool)
        keep[none] = False
        text = every[np.repeat(keep, ends - starts + 1)].tobytes()
        ends = _line_ends(text)
    return text, ends


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self):
        return planned(self.options)

    def read(self, partition):
        for split in partition.splits:
            yield from batches(split, self.options)


class _LineReader(_Reader):
    def read(self, partition):
        n = 0
        for split in partition.splits:
            for whole in buffered_lines(split):
                text, ends = data_text(whole)
                if not len(ends):
                    continue
                at = np.concatenate([[0], ends - np.arange(len(ends))]).astype(np.int32)  # places in the text without line ends
                lines = pa.StringArray.from_buffers(len(ends), pa.py_buffer(at), pa.py_buffer(text.translate(None, b"\n")))
                yield pa.RecordBatch.from_arrays([lines, pa.array(np.full(len(ends), partition.number, np.int64)), pa.array(np.arange(n, n + len(ends)))], ["value", "slice", "at"])
                n += len(ends)


class _ChunkReader(_Reader):
    def read(self, partition):
        chunk, block = int(self.options.get("chunk", 1024)), int(self.options.get("lines_per_block", 131072))
        n, held = 0, b""

        def taken(text, ends, last=False):
            nonlocal n, held
            i, at, rows = 0, 0, []
            while i < len(ends):
                more = min(chunk, block - n % block)
                if i + more > len(ends):
                    if not last:
                        break
                    more = len(ends) - i
                stop = ends[i + more - 1]
                rows.append((text[at:stop], n // block))
                at, i, n = stop + 1, i + more, n + more
            held = text[at:]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()).cast(pa.string()), pa.array([r[1] for r in rows], pa.int64())], ["value", "block"])

        for split in partition.splits:
            for whole in buffered_lines(split):
                text = held + data_text(whole)[0]
                yield from taken(text, _line_ends(text))
        yield from taken(held, _line_ends(held), last=True)


class _StreamReader(DataSourceStreamReader):
    """Offsets count files in name order."""

    def __init__(self, options: dict):
        self.options = options

    def initialOffset(self):
        return {"files": 0}

    def latestOffset(self):
        return {"files": len(listed(self.options["path"]))}

    def partitions(self, start, end):
        return [Split(p, 0, size, size) for p, size in listed(self.options["path"])[start["files"] : end["files"]]]

    def read(self, partition):
        yield from batches(partition, self.options)

    def commit(self, end):
        pass


class EdgeBlockSource(DataSource):
    @classmethod
    def name(cls):
        return "edgeblocks"

    def schema(self):
        return "src long, dst long, weight float, block long"

    def reader(self, schema):
        return _Reader(dict(self.options))

    def streamReader(self, schema):
        return _StreamReader(dict(self.options))


class EdgeLineSource(DataSource):
    @classmethod
    def name(cls):
        return "edgelines"

    def schema(self):
        return "value string, slice long, at long"

    def reader(self, schema):
        return _LineReader(dict(self.options))


class EdgeChunkSource(DataSource):
    @classmethod
    def name(cls):
        return "edgechunks"

    def schema(self):
        return "value string, block long"

    def reader(self, schema):
        return _ChunkReader(dict(self.options))


def register(spark) -> None:
    for source in (EdgeBlockSource, EdgeLineSource, EdgeChunkSource):
        spark.dataSource.register(source)


def scan_slices(spark, path: str, slices: int):
    """value, slice and at (the line's number among the slice's data lines) of equal static slices."""
    register(spark)
    return spark.read.format("edgelines").options(path=path, slices=slices).load()


def scan_chunks(spark, path: str, chunk: int, lines_per_block: int):
    """value (``chunk`` data lines as one text, fewer at the end of a block) and block, by one task in order."""
    register(spark)
    return spark.read.format("edgechunks").options(path=path, slices=1, chunk=chunk, lines_per_block=lines_per_block).load()
