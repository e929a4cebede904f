"""Streams of byte slices: each micro-batch is parsed in parallel, and what it leaves unfinished is carried into the next.

A stream is one long byte sequence that arrives as files in name order.  A batch's slices are summarised from every
start state; their scan (with the carry in front) tells where records begin, so slices parse in parallel, and only the
record that crosses a slice edge is put together from its pieces.  Rows and carry are written under the batch id before
the source may advance, so a batch that is run again replaces its own output.

What is carried is the unfinished record's bytes, or, where these exceed a limit, only the state behind them: the
automaton's, the record's number and the column.  The record then goes out as fragments of its fields, batch by batch,
and becomes a row when they are read back.  So the carry is bounded however long a record is.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dialect import compile_dialect
from ..operators import convert
from ..operators.kernel import columns_of, decode, parse_block, summarize
from ..plans.reader import Options, field_runs, giant_rows
from ..sources.files import _store, fresh_path


@dataclass
class Carry:
    """State between batches: the unfinished record's bytes, the next record's number, the bytes consumed.

    ``state`` is null while bytes are carried; else the automaton's state behind the record's part so far, in ``column``.
    """

    data: bytes = b""
    next_record: int = 0
    byte_off: int = 0
    state: int | None = None
    column: int = 0


CARRY_BYTES = 64 << 20  # unfinished bytes that are carried as such
FRAGMENTS = "_record_no long, column_no int, seq long, n long, quoted boolean, text binary"


def _store_carry(spark: SparkSession, root: str, batch: int, c: Carry) -> None:
    row = spark.createDataFrame([(batch, bytearray(c.data), c.next_record, c.byte_off, c.state, c.column)], "batch long, carry binary, next_record long, byte_off long, state int, column int")
    row.coalesce(1).write.mode("overwrite").parquet(f"{root}/carry/batch={batch}")


def _load_carry(spark: SparkSession, root: str, batch: int) -> Carry:
    if batch < 0:
        return Carry()
    r = spark.read.parquet(f"{root}/carry/batch={batch}").first()
    return Carry(bytes(r["carry"]), r["next_record"], r["byte_off"], r["state"], r["column"])


def parse_slices(spark: SparkSession, slices: DataFrame, carry: Carry, dialect, schema: T.StructType, last: bool = False, carry_bytes: int = CARRY_BYTES) -> tuple[DataFrame, Carry, DataFrame | None]:
    """Rows of a batch ``slices(n, content)``, n from 0 in order, the carry it leaves, and fragments of records too long to carry (null if none)."""
    dfa, names = compile_dialect(dialect), schema.fieldNames()

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for n, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                raw = np.frombuffer(data, np.uint8)
                s = summarize(raw, dfa)
                longs = [pa.array([[getattr(x, f) for x in s]], pa.list_(pa.int64())) for f in ("recs", "first_end", "last_end", "col")]
                yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([[x.end for x in s]], pa.list_(pa.int32())), *longs, pa.array([len(raw)], pa.int64())], ["n", "end", "recs", "first_end", "last_end", "col", "size"])

    kind = "n long, end array<int>, recs array<long>, first_end array<long>, last_end array<long>, col array<long>, size long"
    seen = slices.select("n", "content").mapInArrow(look, kind).orderBy("n").collect()  # a row a slice of one batch
    at = summarize(np.frombuffer(carry.data, np.uint8), dfa)[dfa.start]
    state, column, record = (at.end, at.col, carry.next_record) if carry.state is None else (carry.state, carry.column, carry.next_record)
    # edges: a slice's own records lie between its first and last record end; the rest belongs to the record across its edge
    plan, open_record, rest_bytes = [], record, len(carry.data)
    for r in seen:
        recs, first, end = r["recs"][state], r["first_end"][state], r["last_end"][state]
        plan.append((r["n"], first if recs else -1, end if recs else -1, open_record, recs, state, column))
        open_record += recs
        rest_bytes = r["size"] - end if recs else rest_bytes + r["size"]
        column = r["col"][state] + (0 if recs else column)
        state = r["end"][state]
    apart = {record} if carry.state is not None else set()  # records that go out as fragments
    if not last and (rest_bytes > carry_bytes or carry.state is not None and open_record == record):
        apart.add(open_record)
    edges = spark.createDataFrame(plan or [(0, -1, -1, 0, 0, 0, 0)], "n long, first long, last long, record long, recs long, state int, column int")
    planned = slices.join(F.broadcast(edges), "n")

    def inner(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for data, first, end, rec in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                p = parse_block(np.frombuffer(data, np.uint8)[first:end], dfa)
                yield pa.RecordBatch.from_arrays([pa.array(rec + 1 + np.arange(p.records)), *[decode(c) for c in columns_of(p, list(range(len(names))))]], ["_record_no", *names])

    wide = T.StructType([T.StructField("_record_no", T.LongType()), *[T.StructField(n, T.StringType()) for n in names]])
    whole = planned.where("last > first and first >= 0").select("content", "first", "last", "record").mapInArrow(inner, wide)
    # pieces of the records across edges: the head of a slice ends the open record, its tail begins the next
    head = planned.select("record", "n", F.when(F.col("first") >= 0, F.expr("substring(content, 1, int(first))")).otherwise(F.col("content")).alias("piece"), "state", "column")
    tail = planned.where("first >= 0").select((F.col("record") + F.col("recs")).alias("record"), "n", F.expr("substring(content, int(last) + 1)").alias("piece"), F.lit(dfa.start).alias("state"), F.lit(0).alias("column"))
    start = spark.createDataFrame([(carry.next_record, -1, bytearray(carry.data), dfa.start, 0)], "record long, n long, piece binary, state int, column int")
    pieces = start.unionByName(head).unionByName(tail)
    crossing = pieces.where(~F.col("record").isin(*apart) if apart else F.lit(True)).groupBy("record").agg(F.expr("listagg(piece) WITHIN GROUP (ORDER BY n)").alias("data"))

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rec, n, data, s, c in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                for col, place, quoted, text in field_runs(np.frombuffer(data or b"", np.uint8), s, c, dfa)[0] if data else ():
                    yield pa.RecordBatch.from_arrays([pa.array([rec], pa.int64()), pa.array([col], pa.int32()), pa.array([place], pa.int64()), pa.array([n], pa.int64()), pa.array([quoted]), pa.array([text], pa.binary())], ["_record_no", "column_no", "seq", "n", "quoted", "text"])

    fragments = pieces.where(F.col("record").isin(*apart)).mapInArrow(runs, FRAGMENTS) if apart else None

    def across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rec, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                p = parse_block(np.frombuffer(data or b"", np.uint8), dfa, final=last)
                if p.records:
                    yield pa.RecordBatch.from_arrays([pa.array([rec], pa.int64()), *[decode(c) for c in columns_of(p, list(range(len(names))))]], ["_record_no", *names])

    closed = crossing.where((F.col("record") < open_record) | F.lit(last)).mapInArrow(across, wide)
    out, off = convert.cast_fields(whole.unionByName(closed), schema), carry.byte_off + sum(r["size"] for r in seen)
    if open_record in apart:
        return out, Carry(b"", open_record, off, int(state), int(column)), fragments
    rest = crossing.where(F.col("record") == open_record).first()  # at most carry_bytes
    data = bytes(rest["data"]) if rest and rest["data"] is not None and not last else b""
    return out, Carry(data, open_record, off), fragments


def parse_stream(spark: SparkSession, folder: str, schema: T.StructType, dialect="rfc4180", files_per_batch: int = 4, out: str | None = None, checkpoint: str | None = None, carry_bytes: int = CARRY_BYTES) -> str:
    """Parse all slices that have arrived (``availableNow``); rows go to ``out/rows``, one folder a batch.  Returns ``out``."""
    out = out or fresh_path(spark, "stream")

    def batch(df: DataFrame, n: int) -> None:
        own = df.sparkSession
        order = df.select("path").orderBy("path").toPandas()["path"].tolist()  # names of a batch's slices
        index = own.createDataFrame([(p, i) for i, p in enumerate(order)] or [("", 0)], "path string, n long")
        rows, carry, fragments = parse_slices(own, df.join(F.broadcast(index), "path").select("n", "content"), _load_carry(own, out, n - 1), dialect, schema, carry_bytes=carry_bytes)
        rows.write.mode("overwrite").parquet(f"{out}/rows/batch={n}")
        if fragments is not None:
            fragments.write.mode("overwrite").parquet(f"{out}/fragments/batch={n}")
        _store_carry(own, out, n, carry)

    stream = spark.readStream.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").option("maxFilesPerTrigger", files_per_batch).load(folder)
    query = stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint or f"{out}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return out


def parsed_rows(spark: SparkSession, out: str, schema: T.StructType) -> DataFrame:
    """Rows that a stream has written; records that went out as fragments are put together once their end has come."""
    wide = T.StructType([T.StructField("_record_no", T.LongType()), *schema.fields])
    rows = spark.read.schema(wide).parquet(f"{out}/rows")
    store, root = _store(out)
    from pyarrow import fs

    if store.get_file_info(f"{root}/fragments").type == fs.FileType.NotFound:
        return rows
    carried = spark.read.parquet(f"{out}/carry")
    still_open = carried.orderBy(F.desc("batch")).limit(1).where("state is not null").select(F.col("next_record").alias("_record_no"))
    pieces = spark.read.parquet(f"{out}/fragments").join(F.broadcast(still_open), "_record_no", "left_anti")
    names = schema.fieldNames()
    ordered = pieces.withColumn("seq", F.struct("batch", "n", "seq")).withColumn("_file", F.lit(""))
    late = giant_rows(ordered, names, names, Options(giant_fields="row"))[0].drop("_file", "_width", "_extra")
    return rows.select(*wide.fieldNames()).unionByName(convert.cast_fields(late, schema))


def cut(spark: SparkSession, path: str, partition_bytes: int) -> str:
    """The files below ``path``, in name order, cut into slices of equal size: the arriving input of a stream.

    Slices are written one after the other with growing time stamps, as the file source takes them in that order.
    """
    import time

    from ..sources.files import _store, list_files, read_range, splits

    target = fresh_path(spark, "slices")
    files = {r["file"]: i for i, r in enumerate(list_files(spark, path).where("size > 0").orderBy("file").collect())}  # a row a file

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                store, root = _store(target)
                store.create_dir(root, recursive=True)
                with store.open_output_stream(f"{root}/s{files[file]:06d}-{split:09d}") as f:
                    f.write(read_range(file, off, size).tobytes())
                time.sleep(0.004)
                yield pa.RecordBatch.from_arrays([pa.array([size], pa.int64())], ["n"])

    splits(list_files(spark, path), partition_bytes).coalesce(1).sortWithinPartitions("file", "split").mapInArrow(write, "n long").agg(F.sum("n")).first()
    return target


