"""Helpers shared by the training-data operators: durable tables, Arrow slicing, word spans, hashing."""

from __future__ import annotations

import ctypes
import os
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 1 << 20  # text bytes that one numpy pass holds, so worker memory does not follow the batch size


def shared_dir(spark: SparkSession) -> str:
    """This application's folder below ``spark.checkpoint.dir``, which all executors share.

    Where that is unset, local mode gets a folder of its own; on a cluster it is an error, since executors would each
    write to a disk of their own.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = os.path.join(os.environ.get("TMPDIR", "/tmp"), "delimscan-shared")
    return f"{base.rstrip('/')}/delimscan-{spark.sparkContext.applicationId}"


def sweep(spark: SparkSession) -> bool:
    """Delete what this application wrote to the shared folder; every frame that still reads from it is lost."""
    path = spark._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    return path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def durable(df: DataFrame, codec: str = "zstd") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage ends there and lost executors cost nothing."""
    path = f"{shared_dir(df.sparkSession)}/{uuid.uuid4().hex}.parquet"
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def fresh(name: str, taken: list[str]) -> str:
    """``name``, with underscores behind it until no column in ``taken`` has it in any case."""
    used = {c.lower() for c in taken}
    while name.lower() in used:
        name += "_"
    return name


def let(value: Column, body) -> Column:
    """``body(v)`` with ``value`` evaluated once: a lambda variable is bound, an inlined expression is not."""
    return F.element_at(F.transform(F.array(value), body), 1)


def text_buffers(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """``(bytes, offsets)`` of a string column, offsets from 0; a null counts as empty."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    if not pa.types.is_large_string(array.type) and not pa.types.is_large_binary(array.type):
        array = array.cast(pa.large_binary() if pa.types.is_binary(array.type) else pa.large_string())
    if array.null_count:
        array = array.fill_null("" if pa.types.is_large_string(array.type) else b"")
    if not len(array):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = array.buffers()
    off = np.frombuffer(offs, np.int64, len(array) + 1, array.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Cut Arrow batches into runs of whole rows of about ``limit`` text bytes; yields ``(rows, bytes, offsets)``."""
    for batch in batches:
        raw, off = text_buffers(batch.column(batch.schema.get_field_index(column)))
        lo, n = 0, batch.num_rows
        while lo < n:
            hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, "right")) - 1)
            yield batch.slice(lo, hi - lo), raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
            lo = hi
    tidy()


def tidy() -> None:
    """Give unused memory back: a Python worker stays for other tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def word_spans(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte spans of words ``[^\\x20\\x09-\\x0D]+`` in a concatenation of texts.

    Returns ``(starts, ends, first)``; ``first[i]:first[i+1]`` are the words of text ``i``.
    """
    if not raw.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    gap = SPACE[raw]
    begins = ~gap
    ends = begins.copy()
    begins[1:] &= gap[:-1]
    ends[:-1] &= gap[1:]
    cut = off[(off > 0) & (off < raw.size)]
    begins[cut] |= ~gap[cut]
    ends[cut - 1] |= ~gap[cut - 1]
    starts = np.flatnonzero(begins)
    return starts, np.flatnonzero(ends) + 1, np.searchsorted(starts, off)


_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261))  # fixed values of XXH64


def _rot(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def _lane(acc: np.ndarray, word: np.ndarray) -> np.ndarray:
    return _rot(acc + word * _P2, 31) * _P1


def xxh64_spans(raw: np.ndarray, starts: np.ndarray, lengths: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of many byte spans at once (unsigned)."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    wide = np.ndarray((len(padded) - 7,), "<u8", padded, 0, (1,))
    half = np.ndarray((len(padded) - 7,), "<u4", padded, 0, (1,))
    s = np.uint64(seed)
    pos, left = starts.astype(np.int64), lengths.astype(np.int64)
    with np.errstate(over="ignore"):
        h = np.full(len(starts), s + _P5, np.uint64)
        if len(big := np.flatnonzero(left >= 32)):
            p, n = pos[big].copy(), left[big].copy()
            acc = [np.full(len(big), v, np.uint64) for v in (s + _P1 + _P2, s + _P2, s, s - _P1)]
            live = np.arange(len(big))
            while len(live):
                at = p[live]
                for k in range(4):
                    acc[k][live] = _lane(acc[k][live], wide[at + 8 * k])
                p[live] += 32
                n[live] -= 32
                live = live[n[live] >= 32]
            x = _rot(acc[0], 1) + _rot(acc[1], 7) + _rot(acc[2], 12) + _rot(acc[3], 18)
            for a in acc:
                x = (x ^ _lane(np.zeros_like(a), a)) * _P1 + _P4
            h[big] = x
            pos, left = pos.copy(), left.copy()
            pos[big], left[big] = p, n
        h += lengths.astype(np.uint64)
        for _ in range(3):
            at = np.flatnonzero(left >= 8)
            if not len(at):
                break
            h[at] = _rot(h[at] ^ _lane(np.zeros(len(at), np.uint64), wide[pos[at]]), 27) * _P1 + _P4
            pos[at] += 8
            left[at] -= 8
        if len(at := np.flatnonzero(left >= 4)):
            h[at] = _rot(h[at] ^ (half[pos[at]].astype(np.uint64) * _P1), 23) * _P2 + _P3
            pos[at] += 4
            left[at] -= 4
        for _ in range(3):
            at = np.flatnonzero(left >= 1)
            if not len(at):
                break
            h[at] = _rot(h[at] ^ (padded[pos[at]].astype(np.uint64) * _P5), 11) * _P1
            pos[at] += 1
            left[at] -= 1
        h = (h ^ (h >> np.uint64(33))) * _P2
        h = (h ^ (h >> np.uint64(29))) * _P3
        return h ^ (h >> np.uint64(32))


def ragged_take(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenate ``flat[starts[i]:starts[i]+lengths[i]]`` over all ``i``."""
    ends = np.cumsum(lengths)
    total = int(ends[-1]) if len(ends) else 0
    return flat[np.repeat(starts - (ends - lengths), lengths) + np.arange(total)]
