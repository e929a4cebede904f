"""Fixtures rendered from the given tables: the inputs of the paper's workloads and of the dialects."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dialect import Dialect
from ..sources.files import _store, fresh_path, listed_all, part_list
from ..sources.render import cell, lines, rendered, write_lines
from .reader import ParseResult, read_delimited


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text9(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The text-heavy set: documents with their labels as nine columns of text, numbers and dates."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return docs.join(labels, "doc_id", "left").select(
        "doc_id", "source", "lang", "n_chars", "quality", "toxic", F.date_add(F.lit("2015-01-01").cast("date"), (F.col("doc_id") % 1500).cast("int")).alias("day"), (F.col("n_chars") / 100).cast("decimal(10,2)").alias("score"), "text")


def num17(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The narrow numeric set: 17 columns of lineitem and orders."""
    return table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders"), F.expr("l_orderkey = o_orderkey"))


def key_of(df: DataFrame) -> list[str]:
    return df.columns if "l_orderkey" in df.columns else df.columns[:2]


FRAMES = {"text9": text9, "num17": num17}
QUOTED = {"text9", "documents", "conversations", "pages", "benchmark"}


def frame(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return FRAMES[name](spark, sf_dir) if name in FRAMES else table(spark, sf_dir, name)


def fixture(spark: SparkSession, sf_dir: str, name: str, sep: str = ",", quote: bool | None = None, line_sep: str = "\n") -> str:
    """Path of a table rendered in key order; text-heavy sets quote every field."""

    def make(spark: SparkSession, sf_dir: str) -> str:
        df = frame(spark, sf_dir, name)
        ordered = df.orderBy(*key_of(df))
        return write_lines(lines(ordered, sep, quote if quote is not None else (True if name in QUOTED else False if sep != "," else None)), name, line_sep)

    return rendered(spark, sf_dir, f"{name}|{sep}|{quote}|{line_sep}", make)


def split_size(spark: SparkSession, path: str) -> int:
    """Small inputs are still cut, so that every query crosses split edges; large ones use the production size."""
    from ..sources.files import list_files

    total = list_files(spark, path).agg(F.sum("size")).first()[0] or 1
    return int(min(128 << 20, max(1009, total // 7)))


def parsed(spark: SparkSession, sf_dir: str, name: str, sep: str = ",", dialect: str | Dialect = "rfc4180", line_sep: str = "\n", **options) -> ParseResult:
    path = fixture(spark, sf_dir, name, sep, line_sep=line_sep)
    options.setdefault("split_bytes", split_size(spark, path))
    return read_delimited(spark, path, dialect=dialect, schema=options.pop("schema", frame(spark, sf_dir, name).schema), **options)


_FRAMES: dict[tuple[str, str, str], DataFrame] = {}


def parsed_frame(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table parsed back from its text: lazy, the two passes are planned once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _FRAMES:
        _FRAMES[key] = parsed(spark, sf_dir, name, dialect="bracket_array" if name == "embeddings" else "rfc4180").df.select(*frame(spark, sf_dir, name).columns)
    return _FRAMES[key]


def one_file(spark: SparkSession, sf_dir: str, name: str, data) -> str:
    """A small literal fixture: bytes of one file."""

    def make(spark: SparkSession, sf_dir: str) -> str:
        path = fresh_path(spark, name)
        store, root = _store(path)
        store.create_dir(root, recursive=True)
        with store.open_output_stream(f"{root}/part-0") as f:
            f.write(data(spark, sf_dir) if callable(data) else data)
        return path

    return rendered(spark, sf_dir, f"one|{name}", make)


def one_stream(spark: SparkSession, sf_dir: str, name: str, copies: int = 1) -> str:
    """The rendering of a table as one file, ``copies`` times over: a list of its parts in key order, no bytes are copied or collected."""

    def make(spark: SparkSession, sf_dir: str) -> str:
        parts = sorted((f, n) for f, n in listed_all(spark, fixture(spark, sf_dir, name)) if n)
        return part_list(spark, parts * copies, f"{name}-stream")

    return rendered(spark, sf_dir, f"stream|{name}|{copies}", make)


def one_large(spark: SparkSession, sf_dir: str, name: str, copies: int = 1) -> str:
    """The rendering of a table as one file, ``copies`` times over: an input for timings, copied block by block by this process."""

    def make(spark: SparkSession, sf_dir: str) -> str:
        from ..sources.files import listed, read_range

        parts, path = sorted(listed(spark, fixture(spark, sf_dir, name))), fresh_path(spark, f"{name}-large")
        store, root = _store(path)
        store.create_dir(root, recursive=True)
        with store.open_output_stream(f"{root}/part-0") as f:
            for _ in range(copies):
                for file, size in parts:
                    for lo in range(0, size, 32 << 20):
                        f.write(read_range(file, lo, min(32 << 20, size - lo)).tobytes())
        return path

    return rendered(spark, sf_dir, f"large|{name}|{copies}", make)


def text_of(spark: SparkSession, sf_dir: str, name: str, quote: bool = True) -> DataFrame:
    """A small table's whole rendering as one row ``(file, data)``: input of the byte-level methods."""
    df = table(spark, sf_dir, name)
    row = df.select(F.struct(F.col(df.columns[0]), lines_of(df, quote).alias("v")).alias("x"))
    text = F.array_join(F.transform(F.array_sort(F.collect_list("x")), lambda x: F.concat(x["v"], F.lit("\n"))), "")
    return row.agg(text.cast("binary").alias("data")).select(F.lit(name).alias("file"), "data")


def lines_of(df: DataFrame, quote: bool):
    out = None
    for f in df.schema.fields:
        c = cell(F.col(f.name), f.dataType.simpleString(), quote)
        out = c if out is None else F.concat(out, F.lit(","), c)
    return out


def skewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents with one record of about two fifths of all bytes: its text is the ordered texts of every third document, put together by one task and not broadcast."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    langs = [r["lang"] for r in docs.where("doc_id = 0").select("lang").collect()]  # the rows of one id
    third = docs.where("doc_id % 3 = 1 AND text IS NOT NULL").select("doc_id", "text").repartition(1).sortWithinPartitions("doc_id").select("text")

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        big, any_row = bytearray(), False
        for b in batches:
            for text in b.column(0):
                if any_row:
                    big += b"\n"
                big += text.as_buffer() or b""
                any_row = True
        whole = pa.array([None], pa.string())
        if any_row:
            whole = pa.StringArray.from_buffers(1, pa.py_buffer(np.array([0, len(big)], np.int32)), pa.py_buffer(big))
        for lang in langs:
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int64()), whole, pa.array([lang], pa.string())], ["doc_id", "text", "lang"])

    return docs.where("doc_id <> 0 OR doc_id IS NULL").unionByName(third.mapInArrow(join, "doc_id long, text string, lang string"))


def skewed_parts(spark: SparkSession, sf_dir: str) -> tuple[str, list[tuple[str, int]], str]:
    """The rendering of :func:`skewed` in order of ids: a folder, the parts of the records with the long text, and a folder.

    The long text is a row of no task and goes to no driver.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")

    def literal(text: str) -> tuple[str, int]:
        path = fresh_path(spark, "skew-edge")
        store, root = _store(path)
        store.create_dir(root, recursive=True)
        with store.open_output_stream(f"{root}/part-0") as f:
            f.write(text.encode())
        return f"{root}/part-0" if ":/" not in path else f"{path}/part-0", len(text.encode())

    long = docs.where("doc_id % 3 = 1 AND text IS NOT NULL").orderBy("doc_id").select(F.replace("text", F.lit('"'), F.lit('""')).alias("value"))
    big = _written(spark, write_lines(long, "skew-long"))
    if big:
        big[-1] = (big[-1][0], big[-1][1] - 1)  # no line end behind the last text
    before = write_lines(lines(docs.where("doc_id < 0 OR doc_id IS NULL").orderBy("doc_id"), quote=True), "skew-before")
    parts = []
    for (lang,) in lines(docs.where("doc_id = 0").select("lang"), quote=True).collect():  # the rows of one id
        quote = '"' if big else ""
        parts += [literal(f'"0",{quote}'), *big, literal(f"{quote},{lang}\n")]
    return before, parts, write_lines(lines(docs.where("doc_id > 0").orderBy("doc_id"), quote=True), "skew-after")


def _written(spark: SparkSession, path: str) -> list[tuple[str, int]]:
    return sorted((f, n) for f, n in listed_all(spark, path) if n)


def skewed_stream(spark: SparkSession, sf_dir: str) -> str:
    """:func:`skewed_parts` as one file."""
    before, parts, after = skewed_parts(spark, sf_dir)
    return part_list(spark, [*_written(spark, before), *parts, *_written(spark, after)], "skew")


def skewed_files(spark: SparkSession, sf_dir: str) -> list[str]:
    """:func:`skewed_parts` as files of whole records, the long one's a list of parts."""
    before, parts, after = skewed_parts(spark, sf_dir)
    return [before, *([part_list(spark, parts, "skew")] if parts else []), after]


STRING = T.StringType()
