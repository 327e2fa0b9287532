"""Lines are taken by the buffer and dealt by the chunk."""

import numpy as np
import pytest

from edgecsr.operators.readers import read_edges
from edgecsr.sources.block_source import Split, buffered_lines, data_text, scan_chunks, scan_slices

TEXT = b"% head\n\n1 2 3\n \t\n2 3\n  # c\n4\xff 5 6\n\t7 8 9\n" + b"".join(b"%d %d %d.5\n" % (i, i * i, i) for i in range(1, 300)) + b"9 9 1"
DATA = [x.decode("utf-8", "replace") for x in TEXT.split(b"\n") if x.strip() and x.strip()[:1] not in b"%#"]


@pytest.mark.parametrize("buffer", [1, 7, 64, 1 << 20])
def test_every_split_gives_the_lines_that_begin_in_it(tmp_path, buffer):
    (tmp_path / "e.txt").write_bytes(TEXT)
    path, size = str(tmp_path / "e.txt"), len(TEXT)
    starts = np.flatnonzero(np.frombuffer(b"\n" + TEXT, np.uint8) == 10)
    for cuts in ([0, size], [0, 1, 7, 8, 100, size - 2, size], list(range(0, size, 37)) + [size]):
        for a, b in zip(cuts, cuts[1:]):
            own = [TEXT[s:].split(b"\n")[0] for s in starts if a <= s < b]
            found = b"".join(buffered_lines(Split(path, a, b - a, size), buffer))
            assert found.rstrip(b"\n").split(b"\n") == b"\n".join(own).rstrip(b"\n").split(b"\n")


def test_data_text_leaves_blank_lines_and_comments_out():
    text, ends = data_text(TEXT)
    assert text.decode().split("\n")[:-1] == DATA and len(ends) == len(DATA)
    assert data_text(b"\n % x\n")[0] == b""


@pytest.mark.parametrize(("chunk", "block"), [(1, 5), (7, 20), (64, 64), (100, 64), (1000, 1 << 17)])
def test_chunks_hold_every_line_once_and_end_with_their_block(spark, tmp_path, chunk, block):
    (tmp_path / "e.txt").write_bytes(TEXT)
    rows = scan_chunks(spark, str(tmp_path), chunk, block).collect()
    assert [x for r in rows for x in r.value.split("\n")] == DATA
    assert all(len(r.value.split("\n")) <= chunk for r in rows)
    assert [r.block for r in rows for _ in r.value.split("\n")] == [i // block for i in range(len(DATA))]
    lines = scan_slices(spark, str(tmp_path), 3).orderBy("slice", "at").collect()
    assert [r.value for r in lines] == DATA
    dealt = read_edges(spark, str(tmp_path), "line_block", line_source="buffered", lines_per_block=block, parse_chunk=chunk)
    own = read_edges(spark, str(tmp_path), "block")
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(dealt.edges.select("src", "dst", "weight")) == key(own.edges.select("src", "dst", "weight")) and key(dealt.bad) == key(own.bad)
