"""Columns of a block through column buffers, in the three tagging modes: the transposition of the method inside the kernel.

Bytes of a column are gathered into one buffer, in record order; where each record's field lies in it is then read back
from what the mode keeps beside the bytes: four bytes of record number a byte, a terminator a field, or a bit a byte.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from .kernel import Parsed

TERMINATOR = 0x1F


def mode_of(p: Parsed, terminator: int = TERMINATOR) -> str:
    """Cheapest mode that fits a block: ragged records need tags, a terminator in the data needs the vector."""
    width = np.diff(np.concatenate([[0], p.ends]))
    if len(width) and width.min() != width.max():
        return "record_tags"
    return "vector" if (p.text == terminator).any() else "inline"


def _gather(text: np.ndarray, begin: np.ndarray, size: np.ndarray, room: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Fields one after the other, ``room`` places behind each; and the place behind each field's last byte."""
    ends = np.cumsum(size + room)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    n = int(size.sum())
    within = np.arange(n) - np.repeat(np.cumsum(size) - size, size)
    out[np.repeat(ends - size - room, size) + within] = text[np.repeat(begin, size) + within]
    return out, ends - room


def by_buffers(p: Parsed, columns: list[int], mode: str = "auto", empty_null: bool = True, terminator: int = TERMINATOR) -> list[pa.Array]:
    """The wanted columns of a block, as ``kernel.columns_of`` gives them.

    The inline and vector modes need records of one width, inline also data without the terminator; ``auto`` picks by
    block.
    """
    mode = mode_of(p, terminator) if mode == "auto" else mode
    if mode not in ("record_tags", "inline", "vector"):
        raise ValueError(f"no tagging mode {mode}")
    first = np.concatenate([[0], p.ends[:-1]]) if len(p.ends) else np.zeros(0, np.int64)
    width = p.ends - first
    if mode != "record_tags" and len(width) and width.min() != width.max():
        raise ValueError(f"records of {width.min()} to {width.max()} columns need record tags")
    if mode == "inline" and (p.text == terminator).any():
        raise ValueError("the terminator occurs in the data; use the vector mode")
    out = []
    for c in columns:
        held = np.flatnonzero(width > c)  # records that have the column
        at = first[held] + c
        begin, size = p.offsets[at], p.offsets[at + 1] - p.offsets[at]
        if mode == "record_tags":
            css, _ = _gather(p.text, begin, size)
            tags = np.repeat(held.astype(np.uint32), size)
            edge = np.flatnonzero(np.concatenate([[True], tags[1:] != tags[:-1]])) if len(tags) else np.zeros(0, np.int64)
            length = np.zeros(len(width), np.int64)  # runs of equal tags; a field without bytes has none
            length[tags[edge]] = np.diff(np.append(edge, len(tags)))
        elif mode == "inline":
            buffer, ends = _gather(p.text, begin, size, 1)
            buffer[ends] = terminator
            mark = buffer == terminator
            css, length = buffer[~mark], np.diff(np.concatenate([[-1], np.flatnonzero(mark)])) - 1
        else:
            css, ends = _gather(p.text, begin, size)
            bits = np.zeros(len(css) + len(size), bool)  # a place more a field, so empty ones show
            bits[ends + np.arange(len(size))] = True
            length = np.diff(np.concatenate([[-1], np.flatnonzero(bits)])) - 1
        if mode != "record_tags":
            full = np.zeros(len(width), np.int64)
            full[held] = length
            length = full
        gone = np.ones(len(width), bool)
        gone[held] = False
        if empty_null:
            plain = np.zeros(len(width), bool)
            plain[held] = ~p.quoted[at]
            gone |= (length == 0) & plain
        offsets = np.concatenate([[0], np.cumsum(length)]).astype(np.int64)
        valid = pa.array(~gone).buffers()[1] if gone.any() else None
        out.append(pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(width), [valid, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(css))]))
    return out
