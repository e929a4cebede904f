"""Packing token sequences with Karmarkar-Karp multiway differencing.

A document is its ids plus an end id.  Whole windows of ``capacity`` ids are cut off its front; what is left over
(shorter than a window) is cut into segments of at most ``segment`` ids, since small parts even out better, and
packed.  Segments are dealt by hash into pools of about ``pool_windows`` windows; in a
pool, partial partitions are merged largest first, the fullest window of one with the emptiest of the other, which
leaves windows of nearly equal length.  If the largest exceeds the capacity, the window count rises and the pool is
done again, so the padding of a pool is about its rounding to whole windows.

Defined results: a null text is empty (its document is the end id alone); repeated rows are packed as often as they
occur; null ids are kept; an empty table gives no piece.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe_cache import ROOM, encoder
from .common import durable, slices


def differencing(sizes: np.ndarray, ways: int) -> np.ndarray:
    """Window of each size, by multiway largest differencing into ``ways`` windows."""
    n = len(sizes)
    if ways <= 1:
        return np.zeros(n, np.int64)
    # a partial partition: loads in descending order less their least; only the loads above zero are held
    loads: dict[int, np.ndarray] = {i: np.array([s], np.int64) for i, s in enumerate(sizes.tolist())}
    merged: list[tuple[int, int, np.ndarray, np.ndarray]] = []
    heap = [(-int(s), i) for i, s in enumerate(sizes.tolist())]
    heapq.heapify(heap)
    for node in range(n, 2 * n - 1):
        (_, a), (_, b) = heapq.heappop(heap), heapq.heappop(heap)
        x, y = loads.pop(a), loads.pop(b)
        if len(x) + len(y) <= ways:
            total, left, right = np.concatenate([x, y]), np.arange(len(x)), len(x) + np.arange(len(y))
        else:
            total = np.zeros(ways, np.int64)
            left, right = np.arange(len(x)), ways - 1 - np.arange(len(y))
            total[left] += x
            total[right] += y
        order = np.argsort(-total, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        merged.append((a, b, place[left], place[right]))
        total = total[order]
        if len(total) == ways:
            total = total - total[-1]
        loads[node] = total
        heapq.heappush(heap, (-int(total[0]) if len(total) else 0, node))
    where = {2 * n - 2: np.arange(ways)}
    for node in range(2 * n - 2, n - 1, -1):
        a, b, left, right = merged[node - n]
        own = where.pop(node)
        where[a], where[b] = own[left], own[right]
    return np.array([where[i][0] for i in range(n)], np.int64)


def pack_sizes(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, int]:
    """``(window of each size, windows)``: as few near-equal windows as hold them."""
    ways = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        at = differencing(sizes, ways)
        if len(sizes) == 0 or np.bincount(at, weights=sizes, minlength=ways).max() <= capacity:
            return at, ways
        ways += 1


def encode_pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, segment: int, id_col: str = "doc_id", text_col: str = "text", room: int = ROOM, slice_bytes: int = 4 << 20) -> DataFrame:
    """``(doc_id, start, length, ids_crc32, doc_tokens, piece)``: each document cut at whole windows; ``piece`` is unique."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, piece = encoder(tokenizer, room), TaskContext.get().partitionId() << 33
        for rows, raw, off in slices(batches, "text", slice_bytes):
            ids, at = enc.encode(raw, off)
            ids = np.insert(ids, at[1:], end_id).astype("<u4")
            at = at + np.arange(len(at))
            tokens = np.diff(at)
            front = tokens // capacity
            count = front + -(-(tokens % capacity) // segment)
            doc = np.repeat(np.arange(len(tokens)), count)
            nth = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
            start = np.minimum(nth, front[doc]) * capacity + np.maximum(nth - front[doc], 0) * segment
            length = np.minimum(np.where(nth < front[doc], capacity, segment), tokens[doc] - start)
            lo = at[doc] + start
            crc = [zlib.crc32(ids[a:b]) for a, b in zip(lo.tolist(), (lo + length).tolist(), strict=True)]
            cols = [rows.column(0).take(pa.array(doc)), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(tokens[doc]), pa.array(piece + np.arange(len(doc)))]
            piece += len(doc)
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "piece"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, piece long")


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = 2048, segment: int = 512, pool_windows: int = 384, id_col: str = "doc_id", text_col: str = "text", room: int = ROOM, slice_bytes: int = 4 << 20) -> DataFrame:
    """Pieces with ``sequence_id`` and ``offset``; a pool's sequences are numbered from pool * 2**20, whole windows from 2**62."""
    pieces = durable(encode_pieces(docs, tokenizer, end_id, capacity, segment, id_col, text_col, room, slice_bytes))
    whole = pieces.where(F.col("length") == capacity)
    rest = pieces.where(F.col("length") < capacity)
    pools = max(1, round((rest.agg(F.sum("length")).first()[0] or 0) / (capacity * pool_windows)))

    def pack(pool: pd.DataFrame) -> pd.DataFrame:
        pool = pool.sort_values("piece", ignore_index=True)
        at, _ = pack_sizes(pool["length"].to_numpy(), capacity)
        pool["sequence_id"] = pool["pool"].astype("int64") * (1 << 20) + at
        pool["offset"] = pool.groupby("sequence_id")["length"].cumsum() - pool["length"]
        return pool[columns]

    columns = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    dealt = rest.withColumn("pool", F.pmod(F.xxhash64("piece"), F.lit(pools)))
    packed = dealt.groupBy("pool").applyInPandas(pack, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
    return whole.withColumn("sequence_id", F.lit(1 << 62) + F.col("piece")).withColumn("offset", F.lit(0).cast("long")).select(*columns).unionByName(packed)
