"""Which record and column bytes belong to: tags of single symbols (a trace) and of runs (production), three modes of buffers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dialect import DATA, FIELD, RECORD, Dfa
from .kernel import classify, field_array
from .layout import _gather
from ..plans.reader import parse_range

MODES = ("record_tags", "inline", "vector")


def tag_symbols(seeds: DataFrame, dfa: Dfa, data: str = "data") -> DataFrame:
    """One row a data byte: ``(file, chunk, pos, symbol, record_no, column_no)``; chunks carry their start state, record and column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, chunk, raw, s, rec, col in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                d = np.frombuffer(raw, np.uint8)
                classes, _ = classify(d, dfa, s)
                is_rec, is_fld = classes == RECORD, classes == FIELD
                record = rec + np.cumsum(is_rec) - is_rec
                total = np.cumsum(is_fld) - is_fld
                base = np.where(is_rec, np.cumsum(is_fld), 0)
                since = np.maximum.accumulate(np.concatenate([[0], base[:-1]])) if len(d) else base
                column = total - since + np.where(record == rec, col, 0)
                own = np.flatnonzero(classes == DATA)
                yield pa.RecordBatch.from_arrays([pa.array([file] * len(own)), pa.array(np.full(len(own), chunk, np.int64)), pa.array(own), pa.array(d[own].astype(np.int32)), pa.array(record[own]), pa.array(column[own].astype(np.int32))], ["file", "chunk", "pos", "symbol", "record_no", "column_no"])

    return seeds.select("file", "chunk", data, "start_state", "first_record", "first_column").mapInArrow(run, "file string, chunk long, pos long, symbol int, record_no long, column_no int")


def tag_runs(ranges: DataFrame, dfa: Dfa, lane: int = 256) -> DataFrame:
    """One row a field: ``(file, record_no, column_no, len, quoted, text)`` from record-aligned ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, begin, stop, record, final in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                for p in parse_range(file, begin, stop, final, dfa, lane):
                    begins = np.concatenate([[0], p.ends[:-1]])
                    width = p.ends - begins
                    n = len(p.offsets) - 1
                    rec = np.repeat(np.arange(p.records), width)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([file] * n), pa.array(record + rec), pa.array((np.arange(n) - begins[rec]).astype(np.int32)), pa.array(np.diff(p.offsets)), pa.array(p.quoted), field_array(p).cast(pa.binary())],
                        ["file", "record_no", "column_no", "len", "quoted", "text"])
                    record += p.records

    return ranges.select("file", "begin", "stop", "record", "final").mapInArrow(run, "file string, record_no long, column_no int, len long, quoted boolean, text binary")


def check_terminator(runs: DataFrame, terminator: int = 0x1F) -> bool:
    """Whether the terminator byte occurs in no field, so that the inline mode is safe."""
    hit = F.max(F.locate(chr(terminator), F.decode(F.col("text"), "ISO-8859-1"))).alias("n")
    return not (runs.agg(hit).first()["n"] or 0)


def choose_tagging(min_columns: int, max_columns: int, terminator_free: bool, reject_ragged: bool = False) -> str:
    """Cheapest mode that fits: ragged records need tags, unless they are rejected; a terminator in the data needs the vector."""
    if min_columns != max_columns and not reject_ragged:
        return "record_tags"
    return "inline" if terminator_free else "vector"


TAGS = pa.list_(pa.struct([("record_no", pa.int64()), ("len", pa.int64())]))
BUFFERS = pa.schema([("file", pa.string()), ("column_no", pa.int32()), ("bucket", pa.int64()), ("css", pa.binary()), ("tags", TAGS), ("ends", pa.binary()), ("first", pa.int64()), ("size", pa.int64())])
BUFFER_DDL = "file string, column_no int, bucket long, css binary, tags array<struct<record_no: bigint, len: bigint>>, ends binary, first long, size long"


def _buffer(file: str, column: int, bucket: int, text: np.ndarray, begin: np.ndarray, size: np.ndarray, records: np.ndarray, mode: str, terminator: int) -> pa.RecordBatch:
    """One row of buffers: the fields ``text[begin : begin + size]`` of one column."""
    css, at = _gather(text, begin, size, int(mode == "inline"))
    tags, ends = pa.nulls(1, TAGS), None
    if mode == "inline":
        css[at] = terminator
    elif mode == "vector":
        bits = np.zeros(len(css) + len(size), bool)  # one slot more a field, for its end
        bits[at + np.arange(len(size))] = True
        ends = np.packbits(bits, bitorder="little").tobytes()
    else:
        pairs = pa.StructArray.from_arrays([pa.array(records, pa.int64()), pa.array(size, pa.int64())], ["record_no", "len"])
        tags = pa.ListArray.from_arrays(pa.array([0, len(size)], pa.int32()), pairs)
    one = [[file], [column], [bucket], [css.tobytes()], None, [ends], [int(records[0])], [int(size.sum())]]
    return pa.RecordBatch.from_arrays([tags if x is None else pa.array(x, f.type) for x, f in zip(one, BUFFERS, strict=True)], schema=BUFFERS)


def column_buffers(runs: DataFrame, mode: str = "record_tags", terminator: int = 0x1F, bucket: int = 4096) -> DataFrame:
    """``(file, column_no, bucket, css, tags | ends, first, size)``: bytes of a column for ``bucket`` records at a time, in record order.

    record_tags: ``tags`` holds record and length of each field; inline: every field is followed by the terminator;
    vector: ``ends`` is a bitmap with a bit at each field's last byte, shifted by one so that empty fields show.
    ``first`` is the first record's number, ``size`` the bytes of all fields.  A task holds the fields of one buffer.
    """
    key = ["file", "column_no", "bucket"]
    flat = runs.select("file", "column_no", F.floor(F.col("record_no") / bucket).alias("bucket"), "record_no", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []

        def made() -> pa.RecordBatch:
            t = pa.concat_tables(held)
            fields = t.column("text").combine_chunks().cast(pa.large_binary())
            fields = fields.combine_chunks() if isinstance(fields, pa.ChunkedArray) else fields
            edge = np.frombuffer(fields.buffers()[1], np.int64)[fields.offset : fields.offset + len(fields) + 1]
            text = np.frombuffer(fields.buffers()[2], np.uint8) if fields.buffers()[2] else np.zeros(0, np.uint8)
            file, column, bk = (t.column(i)[0].as_py() for i in range(3))
            return _buffer(file, column, bk, text, edge[:-1], np.diff(edge), t.column("record_no").to_numpy(), mode, terminator)

        last = None
        for b in batches:
            kinds = list(zip(*(b.column(i).to_pylist() for i in range(3)), strict=True))
            begin = 0
            for i, k in enumerate(kinds):
                if k != last:
                    if i > begin:
                        held.append(pa.Table.from_batches([b.slice(begin, i - begin)]))
                    if held:
                        yield made()
                    held, last, begin = [], k, i
            if len(kinds) > begin:
                held.append(pa.Table.from_batches([b.slice(begin)]))
        if held:
            yield made()

    return flat.repartition(*key).sortWithinPartitions(*key, "record_no").mapInArrow(run, BUFFER_DDL)


def range_buffers(ranges: DataFrame, dfa: Dfa, mode: str = "record_tags", terminator: int = 0x1F, lane: int = 256) -> DataFrame:
    """Buffers as :func:`column_buffers` gives them, straight from record-aligned ranges: one a column and block, numbered by its first record.

    A block's fields are gathered where they are parsed, so no field is a row and none is shuffled.
    """
    if mode not in MODES:
        raise ValueError(f"no tagging mode {mode}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, begin, stop, record, final in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                for p in parse_range(file, begin, stop, final, dfa, lane):
                    first = np.concatenate([[0], p.ends[:-1]])
                    width = p.ends - first
                    if mode != "record_tags" and width.min() != width.max():
                        raise ValueError(f"records of {width.min()} to {width.max()} columns need record tags")
                    if mode == "inline" and (p.text == terminator).any():
                        raise ValueError("the terminator occurs in the data; use the vector mode")
                    for c in range(int(width.max())):
                        held = np.flatnonzero(width > c)
                        at = first[held] + c
                        yield _buffer(file, c, record, p.text, p.offsets[at], p.offsets[at + 1] - p.offsets[at], record + held, mode, terminator)
                    record += p.records

    return ranges.select("file", "begin", "stop", "record", "final").mapInArrow(run, BUFFER_DDL)


def field_index(buffers: DataFrame, mode: str = "record_tags", terminator: int = 0x1F, bucket: int = 4096) -> DataFrame:
    """``(file, column_no, record_no, off, len)`` read back from buffers; ``off`` counts bytes of the column's text before the field."""
    before = Window.partitionBy("file", "column_no").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sizes = buffers.select("file", "column_no", "bucket", "size")
    base = sizes.select("file", "column_no", "bucket", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("base"))
    placed = buffers.join(F.broadcast(base), ["file", "column_no", "bucket"])  # a row a buffer, of thousands of fields

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                file, col, css, ends, first, base = (b.column(k)[i].as_py() for k in (0, 1, 2, 4, 5, 6))
                if mode == "record_tags":
                    tags = b.column(3)[i].values
                    rec, size = tags.field(0).to_numpy(), tags.field(1).to_numpy()
                else:
                    if mode == "inline":
                        at = np.flatnonzero(np.frombuffer(css, np.uint8) == terminator)
                    else:
                        at = np.flatnonzero(np.unpackbits(np.frombuffer(ends, np.uint8), bitorder="little"))
                    size = np.diff(np.concatenate([[-1], at])) - 1
                    rec = first + np.arange(len(at))
                n = len(rec)
                yield pa.RecordBatch.from_arrays([pa.repeat(file, n), pa.array(np.full(n, col, np.int32)), pa.array(rec), pa.array(base + np.cumsum(size) - size), pa.array(size)], ["file", "column_no", "record_no", "off", "len"])

    return placed.select("file", "column_no", "css", "tags", "ends", "first", "base").mapInArrow(run, "file string, column_no int, record_no long, off long, len long")


def tag_bytes(fields: int, data_bytes: int, mode: str) -> int:
    """Memory of a mode's tags: four bytes a symbol, one a field, or one bit a symbol and field."""
    return {"record_tags": 4 * data_bytes, "inline": fields, "vector": -(-(data_bytes + fields) // 8)}[mode]


