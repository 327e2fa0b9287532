"""Byte blocks of a text file that begin and end at line starts."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class BlockRange:
    path: str
    start: int
    length: int


def _line_start(data, at: int) -> int:
    """The first place at or after ``at`` where a line begins."""
    if at <= 0:
        return 0
    if at >= len(data):
        return len(data)
    if data[at - 1] == 0x0A:
        return at
    found = data.find(b"\n", at)
    return len(data) if found < 0 else found + 1


def align_block(data, start: int, block_bytes: int) -> tuple[int, int]:
    """[begin, end) of the block that is cut at ``start``: both cuts move on to the next line start.

    A line longer than a block leaves empty blocks behind it; the blocks of a
    file tile it and hold every line once. ``data`` is bytes or a memory map.
    """
    return _line_start(data, start), _line_start(data, start + block_bytes)


def plan_blocks(files: list[tuple[str, int]], block_bytes: int) -> list[BlockRange]:
    """Cuts every ``block_bytes`` of (path, size) files."""
    if block_bytes < 1:
        raise ValueError("block_bytes must be positive")
    return [BlockRange(path, at, min(block_bytes, size - at)) for path, size in files for at in range(0, size, block_bytes)]
