"""Baselines: other ways to find the parsing context or to load delimited text, with their limits kept."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dialect import PLAIN, QUOTED, Dfa, compile_dialect
from ..plans.reader import EXTRA, FILE, RECORD_NO, Options, _records, aligned_ranges, seed_table, summary_table
from ..sources.files import _store, durable, list_files, read_range, splits, spread
from . import convert
from .kernel import classify, summarize
from .tagging import tag_runs


def _typed(text: DataFrame, schema: T.StructType) -> DataFrame:
    return convert.cast_fields(text, schema).select(FILE, RECORD_NO, *schema.fieldNames())


def _whole_files(spark: SparkSession, path: str) -> DataFrame:
    return list_files(spark, path).where("size > 0").select("file", F.lit(0).cast("long").alias("split"), F.lit(0).cast("long").alias("begin"), F.col("size").alias("stop"), F.lit(0).cast("long").alias("record"), F.lit(True).alias("final"))


def sequential(spark: SparkSession, path: str, schema: T.StructType, dialect="rfc4180") -> DataFrame:
    """One task runs over everything."""
    names = schema.fieldNames()
    return _typed(_records(spark, _whole_files(spark, path).coalesce(1), compile_dialect(dialect), names, names, Options(), len(names)), schema)


def prepass(spark: SparkSession, path: str, schema: T.StructType, dialect="rfc4180", split_bytes: int = 1 << 20) -> DataFrame:
    """One task finds the state at every split start, one split after the other; only then the rest runs in parallel."""
    dfa = compile_dialect(dialect)
    ranges = splits(list_files(spark, path), split_bytes)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, last = dfa.start, None
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                state = dfa.start if file != last else state
                own = summarize(read_range(file, off, size), dfa)[state]
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), pa.array([state], pa.int32()), pa.array([own.recs], pa.int64()), pa.array([own.first_end], pa.int64())], ["file", "split", "start_state", "recs", "first_end"])
                state, last = own.end, file

    states = durable(ranges.coalesce(1).sortWithinPartitions("file", "split").mapInArrow(walk, "file string, split long, start_state int, recs long, first_end long"), "prepass")
    return _from_states(spark, ranges.join(states, ["file", "split"]), dfa, schema)


def _from_states(spark: SparkSession, found: DataFrame, dfa: Dfa, schema: T.StructType) -> DataFrame:
    """Parallel parse once every split knows how many records it ends and where its first one ends."""
    before = F.coalesce(F.sum("recs").over(Window.partitionBy("file").orderBy("split").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # a row a split
    seeds = found.select("file", "split", "off", "len", before.cast("long").alias("first_record"), F.struct(F.col("recs"), F.col("first_end")).alias("own"))
    names = schema.fieldNames()
    return _typed(_records(spark, spread(aligned_ranges(seeds)), dfa, names, names, Options(), len(names)), schema)


def line_split(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """Every line break ends a record: wrong wherever a field holds one."""
    return spark.read.text(path).select(F.split("value", f"\\Q{sep}\\E").alias("fields"))


def parallel_line_loader(spark: SparkSession, path: str, schema: T.StructType) -> tuple[DataFrame, int]:
    """Lines parsed in parallel with typed columns; also the number of lines that do not fit the schema (0: it can load this input)."""
    lines = spark.read.text(path)
    strings = T.StructType([T.StructField(n, T.StringType()) for n in schema.fieldNames()])
    wide = strings.add("_bad", "string")
    got = lines.select(F.from_csv("value", wide.simpleString()[7:-1].replace(":", " "), {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_bad"}).alias("r")).select("r.*")
    failed = got.where("_bad is not null").count()
    good = got.drop("_bad")
    return good.select(*[convert.typed(F.col(f.name), f.dataType).alias(f.name) for f in schema.fields]), failed


def quote_parity(chunks: DataFrame, key: str = "file", order: str = "chunk", data: str = "data") -> DataFrame:
    """Context by the number of quotes before a chunk, odd being inside: exact for plain quoted text only."""
    text = F.decode(F.col(data), "ISO-8859-1")
    quotes = F.length(text) - F.length(F.replace(text, F.lit('"'), F.lit("")))
    before = Window.partitionBy(key).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return chunks.withColumn("_q", quotes).select(key, order, (F.coalesce(F.sum("_q").over(before), F.lit(0)) % 2).cast("int").alias("inside"))


def guess(data: np.ndarray, dfa: Dfa) -> int:
    """Start state guessed from the first telling place: a quote next to a separator on one side and text on the other."""
    at = np.flatnonzero(data == 34)[:200]
    for i in at[(at > 0) & (at < len(data) - 1)]:
        left, right = chr(data[i - 1]), chr(data[i + 1])
        opens, closes = left in ",\n" and right not in ',\n"', right in ",\n" and left not in ',\n"'
        if opens != closes:
            quotes = int((data[:i] == 34).sum())
            return dfa.states.index(QUOTED if (quotes + closes) % 2 else PLAIN)
    return dfa.states.index(PLAIN)


def speculative(spark: SparkSession, path: str, schema: T.StructType, dialect="rfc4180", split_bytes: int = 1 << 20, rounds: int = 1000) -> tuple[DataFrame, int, int]:
    """Guess every split's start, parse, compare with the predecessor's end, parse misses again: ``(records, misses, rounds)``."""
    dfa = compile_dialect(dialect)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, split, off, size, start in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                data = read_range(file, off, size)
                claimed = start if start is not None else dfa.start if split == 0 else guess(data[:4096], dfa)
                classes, end = classify(data, dfa, claimed)
                rec = np.flatnonzero(classes == 2)
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), pa.array([off], pa.int64()), pa.array([size], pa.int64()), pa.array([claimed], pa.int32()), pa.array([end], pa.int32()), pa.array([len(rec)], pa.int64()), pa.array([int(rec[0]) + 1 if len(rec) else -1], pa.int64())], ["file", "split", "off", "len", "claimed", "end", "recs", "first_end"])

    kind = "file string, split long, off long, len long, claimed int, end int, recs long, first_end long"
    ranges = splits(list_files(spark, path), split_bytes).withColumn("start", F.lit(None).cast("int"))
    found = durable(spread(ranges).mapInArrow(run, kind), "speculated")
    misses = done = 0
    for done in range(1, rounds + 1):
        want = F.coalesce(F.lag("end").over(Window.partitionBy("file").orderBy("split")), F.lit(dfa.start))
        judged = found.withColumn("want", want)
        wrong = judged.where("claimed <> want")
        n = wrong.count()
        if not n:
            break
        misses += n
        again = spread(wrong.select("file", "split", "off", "len", F.col("want").alias("start"))).mapInArrow(run, kind)
        found = durable(found.join(wrong, ["file", "split"], "left_anti").unionByName(again), "speculated")
    return _from_states(spark, found, dfa, schema), misses, done


def structural_bitmap(spark: SparkSession, path: str, split_bytes: int = 1 << 20) -> DataFrame:
    """``(file, split, records, fields)`` from bitmaps of quotes, delimiters and line feeds and a running XOR of the quote bits."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                d = read_range(file, off, size)
                inside = np.cumsum(d == 34) & 1
                rec, fld = (d == 10), (d == 44)
                cols = [int((rec & (inside == k)).sum()) for k in (0, 1)] + [int((fld & (inside == k)).sum()) for k in (0, 1)] + [int((d == 34).sum())]
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), *[pa.array([c], pa.int64()) for c in cols]], ["file", "split", "r0", "r1", "f0", "f1", "q"])

    got = spread(splits(list_files(spark, path), split_bytes)).mapInArrow(count, "file string, split long, r0 long, r1 long, f0 long, f1 long, q long")
    odd = F.coalesce(F.sum("q").over(Window.partitionBy("file").orderBy("split").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) % 2
    return got.withColumn("odd", odd).select("file", "split", F.when(F.col("odd") == 0, F.col("r0")).otherwise(F.col("r1")).alias("records"), F.when(F.col("odd") == 0, F.col("f0")).otherwise(F.col("f1")).alias("delimiters"))


def chained(spark: SparkSession, path: str, dialect="rfc4180", split_bytes: int = 1 << 20) -> DataFrame:
    """Every split waits for its predecessor: a job a split (small inputs only).  ``(file, split, start_state)``."""
    dfa = compile_dialect(dialect)
    out, state, last = [], dfa.start, None
    for r in splits(list_files(spark, path), split_bytes).orderBy("file", "split").collect():  # a row a split
        state = dfa.start if r["file"] != last else state
        one = summary_table(spark.createDataFrame([tuple(r)], "file string, split long, off long, len long"), dfa).first()
        out.append((r["file"], r["split"], state))
        state, last = one["per_state"][state]["end"], r["file"]
    return spark.createDataFrame(out, "file string, split long, start_state int")


def spark_csv(spark: SparkSession, path: str, schema: T.StructType, multiline: bool = True) -> DataFrame:
    """The built-in reader: whole files a task where records may hold line breaks, or line by line."""
    strings = T.StructType([T.StructField(n, T.StringType()) for n in schema.fieldNames()])
    raw = spark.read.csv(path, schema=strings, multiLine=multiline, quote='"', escape='"', ignoreLeadingWhiteSpace=False, ignoreTrailingWhiteSpace=False, emptyValue="", nullValue=None, maxCharsPerColumn=-1)
    return raw.select(*[convert.typed(F.col(f.name), f.dataType).alias(f.name) for f in schema.fields])


MOST_BLOCK = (1 << 31) - 1  # bytes, a limit of the reader


def _arrow_csv(names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import csv

        for b in batches:
            for file, size in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                opts = csv.ConvertOptions(column_types={n: pa.string() for n in names}, strings_can_be_null=True, quoted_strings_can_be_null=False, null_values=[""])
                data = pa.py_buffer(read_range(file, 0, size))
                block = 1 << 24
                while True:
                    try:
                        table = csv.read_csv(pa.BufferReader(data), csv.ReadOptions(column_names=names, block_size=block), csv.ParseOptions(newlines_in_values=True), opts)
                        break
                    except pa.ArrowInvalid:
                        if block >= min(size, MOST_BLOCK):
                            raise
                        block = min(2 * block, MOST_BLOCK)  # a record longer than a block is an error of the reader
                yield from table.to_batches()

    return run


def _strings(files: DataFrame, run, schema: T.StructType) -> DataFrame:
    raw = files.mapInArrow(run, T.StructType([T.StructField(n, T.StringType()) for n in schema.fieldNames()]))
    return raw.select(*[convert.typed(F.col(f.name), f.dataType).alias(f.name) for f in schema.fields])


def single_node(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    """One task with a vectorised in-memory CSV reader."""
    return _strings(list_files(spark, path).where("size > 0").select("file", "size").coalesce(1), _arrow_csv(schema.fieldNames()), schema)


def coarse_split(spark: SparkSession, path: str | list[str], schema: T.StructType) -> DataFrame:
    """The same reader with a file a task: parallel by files only, so a large file, or one with a dominating record, holds up all."""
    files = list_files(spark, path).where("size > 0").select("file", "size")
    return _strings(files.repartitionByRange(max(1, files.count()), "file"), _arrow_csv(schema.fieldNames()), schema)


def column_store_load(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    """Bulk load of every file into a temporary table of a columnar database (duckdb, where it is installed), then read back."""
    names = schema.fieldNames()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import duckdb

        for b in batches:
            for file in b.column(0).to_pylist():
                store, name = _store(file)
                kinds = "{" + ", ".join(f"'{n}': 'VARCHAR'" for n in names) + "}"
                with duckdb.connect() as con:
                    con.execute(f"CREATE TEMP TABLE t AS SELECT * FROM read_csv('{name}', header = false, delim = ',', quote = '\"', escape = '\"', columns = {kinds}, nullstr = '', allow_quoted_nulls = false, max_line_size = 134217728, new_line = '\\n')")
                    yield from con.execute("SELECT * FROM t").to_arrow_table().to_batches(1 << 16)

    return _strings(list_files(spark, path).where("size > 0").select("file", "size").coalesce(1), run, schema)


def one_task_per_field(spark: SparkSession, path: str, schema: T.StructType, dialect="rfc4180", split_bytes: int = 1 << 20) -> DataFrame:
    """Every field travels alone to one worker, then records are put together again: two shuffles of all bytes."""
    dfa = compile_dialect(dialect)
    ranges = aligned_ranges(durable(seed_table(summary_table(spread(splits(list_files(spark, path), split_bytes)), dfa), dfa), "seeds"))
    fields = tag_runs(spread(ranges), dfa).repartition("file", "record_no", "column_no")
    text = F.when((F.col("len") == 0) & ~F.col("quoted"), None).otherwise(F.decode("text", "UTF-8"))
    wide = [F.max(F.when(F.col("column_no") == i, F.col("t"))).alias(n) for i, n in enumerate(schema.fieldNames())]
    rows = fields.withColumn("t", text).groupBy(F.col("file").alias(FILE), F.col("record_no").alias(RECORD_NO)).agg(*wide)
    return _typed(rows.withColumn(EXTRA, F.lit(None).cast("array<string>")), schema)


def bulk_then_parse(spark: SparkSession, path: str, schema: T.StructType, dialect="rfc4180") -> DataFrame:
    """No overlap: copy all input, then parse all of it, then write all of it."""
    from ..plans.reader import read_delimited
    from ..sources.files import blocks

    raw = durable(blocks(spark, path), "transfer")
    raw.select(F.sum(F.octet_length("data"))).first()
    parsed = durable(read_delimited(spark, path, Options(dialect=dialect, schema=schema)).df, "parsed")
    return durable(parsed, "returned").select(FILE, RECORD_NO, *schema.fieldNames())
