"""Second run with the one right automaton: classes of bytes as three bitmap indexes, and their counts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.dialect import CONTROL, FIELD, RECORD, Dfa
from .kernel import classify


def build(chunks: DataFrame, dfa: Dfa, data: str = "data", state: str = "start_state", lane: int = 256) -> DataFrame:
    """``chunks`` with ``rec_bm``, ``fld_bm``, ``ctl_bm`` (bit i of byte i // 8, lowest first, is byte i) and ``size``."""
    keep = [c for c in chunks.columns if c not in (data, state)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            maps: list[list[bytes]] = [[], [], []]
            sizes = []
            for x, s in zip(b.column(len(keep)).to_pylist(), b.column(len(keep) + 1).to_pylist(), strict=True):
                classes, _ = classify(np.frombuffer(x or b"", np.uint8), dfa, s, lane)
                for m, c in zip(maps, (RECORD, FIELD, CONTROL), strict=True):
                    m.append(np.packbits(classes == c, bitorder="little").tobytes())
                sizes.append(len(classes))
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], *[pa.array(m, pa.binary()) for m in maps], pa.array(sizes, pa.int32())], [*keep, "rec_bm", "fld_bm", "ctl_bm", "size"])

    kind = chunks.select(*keep).schema.add("rec_bm", "binary").add("fld_bm", "binary").add("ctl_bm", "binary").add("size", "integer")
    return chunks.select(*keep, data, state).mapInArrow(run, kind)


def words(bitmap: Column) -> Column:
    """A bitmap as an array of integers of 32 bits each, the lowest bits first."""
    n = F.ceil(F.octet_length(bitmap) / 4).cast("int")
    byte = lambda i: F.coalesce(F.conv(F.hex(F.substring(bitmap, i + 1, F.lit(1))), 16, 10).cast("long"), F.lit(0).cast("long"))
    one = lambda w: byte(w * 4) + F.shiftleft(byte(w * 4 + 1), 8) + F.shiftleft(byte(w * 4 + 2), 16) + F.shiftleft(byte(w * 4 + 3), 24)
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), one)).otherwise(F.array().cast("array<bigint>"))


def popcount(bitmap: Column) -> Column:
    return F.aggregate(words(bitmap), F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w))


def positions(bitmap: Column, size: Column) -> Column:
    """Positions of set bits."""
    w = words(bitmap)
    every = F.when(size > 0, F.sequence(F.lit(0), size - 1)).otherwise(F.array().cast("array<int>"))
    return F.filter(every, lambda i: F.call_function("shiftright", F.element_at(w, (F.floor(i / 32) + 1).cast("int")), F.pmod(i, F.lit(32))).bitwiseAND(F.lit(1).cast("long")) == 1)
