"""Data sources for SQL and streams: ``delimscan`` (parsed rows), ``raw_blocks`` (byte blocks, batch and stream).

    spark.dataSource.register(DelimitedSource); CREATE TEMP VIEW v USING delimscan OPTIONS (path '...', schema '...')
"""

from __future__ import annotations

import os
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, EqualTo, Filter, InputPartition

from ..functions.dialect import compile_dialect
from ..operators.kernel import BLOCK, Summary, columns_of, decode, summarize
from .files import read_range

BLOCK_SCHEMA = "file string, block long, off long, data binary"


def _files(path: str) -> list[tuple[str, int]]:
    from pyarrow import fs

    store, root = fs.FileSystem.from_uri(path if ":/" in path else f"file://{os.path.abspath(path)}")
    info = store.get_file_info(root)
    found = [info] if info.type == fs.FileType.File else store.get_file_info(fs.FileSelector(root, recursive=True))
    scheme = path.split(":/")[0] + "://" if ":/" in path else "file://"
    return sorted((f"{scheme}{f.path}", f.size) for f in found if f.type == fs.FileType.File and f.size and not f.base_name.startswith((".", "_")))


@dataclass
class Range(InputPartition):
    file: str
    block: int
    off: int
    size: int
    final: bool = False


class _BlockReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.step, self.only = options["path"], int(options.get("blockbytes", 4 << 20)), None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("block",):
                self.only = f.value
            else:
                yield f

    def partitions(self) -> Sequence[InputPartition]:
        out = [Range(f, k, o, min(self.step, n - o)) for f, n in _files(self.path) for k, o in enumerate(range(0, n, self.step)) if self.only is None or k == self.only]
        return out or [Range("", -1, 0, 0)]

    def read(self, p: Range) -> Iterator[pa.RecordBatch]:
        if p.size:
            yield pa.RecordBatch.from_arrays([pa.array([p.file]), pa.array([p.block], pa.int64()), pa.array([p.off], pa.int64()), pa.array([read_range(p.file, p.off, p.size).tobytes()], pa.binary())], ["file", "block", "off", "data"])


class _BlockStream(DataSourceStreamReader):
    """One growing byte sequence (the files below a path, in name order) by position; several blocks a batch.

    ``latestOffset`` is not told where a restarted query stands, so the position is taken from the first range that
    is asked for; until then nothing new is offered beyond one batch from the start.
    """

    def __init__(self, options):
        self.path, self.step, self.batch = options["path"], int(options.get("blockbytes", 1 << 20)), int(options.get("maxbytesperbatch", 16 << 20))
        self.at = 0

    def initialOffset(self) -> dict:
        return {"pos": 0}

    def latestOffset(self) -> dict:
        total = sum(n for _, n in _files(self.path))
        self.at = min(total, self.at + self.batch)
        return {"pos": self.at}

    def partitions(self, start: dict, end: dict) -> Sequence[InputPartition]:
        self.at = max(self.at, end["pos"])
        out, base = [], 0
        for f, n in _files(self.path):
            lo, hi = max(start["pos"], base), min(end["pos"], base + n)
            out += [Range(f, o // self.step, o - base, min(self.step, hi - o)) for o in range(lo, hi, self.step)]
            base += n
        return out or [Range("", -1, 0, 0)]

    def commit(self, end: dict) -> None:
        self.at = max(self.at, end["pos"])

    read = _BlockReader.read


class RawBlocks(DataSource):
    @classmethod
    def name(cls) -> str:
        return "raw_blocks"

    def schema(self) -> str:
        return BLOCK_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _BlockReader(self.options)

    def streamReader(self, schema) -> DataSourceStreamReader:
        return _BlockStream(self.options)


class _RecordReader(DataSourceReader):
    """Record-aligned ranges are found while partitions are planned, so this source suits inputs of moderate size; the
    reader in ``plans`` plans in Spark itself and has no such bound."""

    def __init__(self, options, schema):
        self.path, self.dialect, self.step, self.names = options["path"], options.get("dialect", "rfc4180"), int(options.get("splitbytes", 32 << 20)), schema.fieldNames()

    def partitions(self) -> Sequence[InputPartition]:
        dfa, out = compile_dialect(self.dialect), []
        for file, n in _files(self.path):
            total, begin, k = Summary(dfa.start), 0, 0
            for o in range(0, n, self.step):
                own = summarize(read_range(file, o, min(self.step, n - o)), dfa)[total.end]
                if o and own.recs:
                    out.append(Range(file, k, begin, o + own.first_end - begin))
                    begin, k = o + own.first_end, k + 1
                total = total.then(own)
            if n > begin:
                out.append(Range(file, k, begin, n - begin, True))
        return out or [Range("", -1, 0, 0)]

    def read(self, p: Range) -> Iterator[pa.RecordBatch]:
        from ..plans.reader import parse_range

        if p.size:
            for x in parse_range(p.file, p.off, p.off + p.size, p.final, compile_dialect(self.dialect), 256, BLOCK):
                yield pa.RecordBatch.from_arrays([decode(c) for c in columns_of(x, list(range(len(self.names))))], self.names)


class DelimitedSource(DataSource):
    """Options: path, schema of strings (``columns``: names joined by commas), dialect, splitbytes."""

    @classmethod
    def name(cls) -> str:
        return "delimscan"

    def schema(self) -> str:
        return ", ".join(f"`{c.strip()}` string" for c in self.options["columns"].split(","))

    def reader(self, schema) -> DataSourceReader:
        return _RecordReader(self.options, schema)


def register(spark: SparkSession) -> None:
    """Both sources, and ``dfa_end_state(data, start)`` and ``swar_group(byte)`` for SQL."""
    import pandas as pd
    from pyspark.sql import functions as F

    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # a session setting; raw_blocks takes block = n
    spark.dataSource.register(RawBlocks)
    spark.dataSource.register(DelimitedSource)

    def end_state(data, start):
        from delimscan.operators.kernel import block_vector

        dfa = compile_dialect("rfc4180")
        return pd.Series([None if d is None else int(block_vector(np.frombuffer(bytes(d), np.uint8), dfa)[s]) for d, s in zip(data, start, strict=True)], dtype="Int32")

    def group(byte):
        lut = compile_dialect("rfc4180").lut
        return byte.map(lambda b: int(lut[int(b)])).astype("int32")

    end_state.__annotations__ = {"data": pd.Series, "start": pd.Series, "return": pd.Series}
    group.__annotations__ = {"byte": pd.Series, "return": pd.Series}
    spark.udf.register("dfa_end_state", F.pandas_udf(end_state, "int"))
    spark.udf.register("swar_group", F.pandas_udf(group, "int"))
