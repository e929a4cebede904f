"""Cutting bytes into chunks, and moving chunk edges to whole symbols."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def split(blocks: DataFrame, lane_bytes: int = 31, data: str = "data") -> DataFrame:
    """Chunks of equal size as rows: the columns beside ``data``, and ``(chunk, data)``."""
    count = F.greatest(F.ceil(F.octet_length(data) / lane_bytes), F.lit(1)).cast("int")
    pieces = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.substring(F.col(data), i * lane_bytes + 1, F.lit(lane_bytes)))
    return blocks.select(*[c for c in blocks.columns if c != data], F.posexplode(pieces).alias("chunk", "data"))


def align(width: int, size: int) -> int:
    """Largest chunk size up to ``size`` that holds whole symbols of ``width`` bytes."""
    return max(width, size // width * width)


def utf8_edges(data: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Chunk edges moved past continuation bytes, which belong to the chunk of their lead byte."""
    at = edges.copy()
    for _ in range(3):
        inside = at < len(data)
        at[inside] += (data[at[inside]] & 0xC0) == 0x80
    return at


def utf16_slice(data: np.ndarray, size: int, big_endian: bool = False) -> bytes:
    """Whole code points that begin in the first ``size`` bytes; ``data`` holds up to two bytes more.

    A leading low surrogate (DC00 to DFFF) belongs to the piece before; a trailing high one (D800 to DBFF) takes the
    unit that follows.
    """
    unit = data[: len(data) // 2 * 2].view(">u2" if big_endian else "<u2")
    n = min(size // 2, len(unit))
    lo = int(n > 0 and 0xDC00 <= unit[0] <= 0xDFFF)
    hi = n + int(n > 0 and n < len(unit) and 0xD800 <= unit[n - 1] <= 0xDBFF)
    return unit[lo:hi].tobytes()


def bytewise_safe(*symbols: str) -> bool:
    """Whether an automaton over bytes is exact for UTF-8: no special symbol is longer than a byte."""
    return all(ord(c) < 128 for s in symbols for c in s)


def byte_at(data: Column, i: Column) -> Column:
    """Byte ``i`` (from 0) of a binary column as an integer."""
    return F.conv(F.hex(F.substring(data, i + 1, F.lit(1))), 16, 10).cast("int")
