"""Files by byte range: listing through Spark, reading through Arrow file systems, cutting into splits."""

from __future__ import annotations

import os
import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

SPLIT_BYTES = 128 << 20


def shared_dir(spark: SparkSession) -> str:
    """This application's folder below ``spark.checkpoint.dir``, which all executors share.

    Where that is unset, local mode gets a folder of its own; on a cluster it is an error, since executors would each
    write to a disk of their own.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = os.path.join(os.environ.get("TMPDIR", "/tmp"), "delimscan-shared")
    return f"{base.rstrip('/')}/delimscan-{spark.sparkContext.applicationId}"


def sweep(spark: SparkSession) -> bool:
    """Delete what this application wrote to the shared folder; every frame that still reads from it is lost."""
    path = spark._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    return path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def durable(df: DataFrame, name: str = "table") -> DataFrame:
    """Write once to the shared folder and read back: lineage ends there."""
    path = fresh_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _store(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if ":/" in path else f"file://{os.path.abspath(path)}")


PARTS = "parts:"  # before the path of a list of parts that are read as one file
LISTED = 4096  # files that the driver lists by itself


@lru_cache(maxsize=64)
def _parts(path: str) -> tuple[list[str], np.ndarray]:
    """``(files, ends)`` of a list of parts."""
    store, name = _store(path)
    with store.open_input_file(name) as f:
        rows = [line.rsplit("\t", 1) for line in f.read().decode().splitlines()]
    return [r[0] for r in rows], np.cumsum([int(r[1]) for r in rows])


def read_range(path: str, offset: int, length: int) -> np.ndarray:
    """``length`` bytes of a file, or of a list of parts, from ``offset`` (fewer at its end)."""
    if path.startswith(PARTS):
        files, ends = _parts(path[len(PARTS) :])
        stop = min(offset + length, int(ends[-1]) if len(ends) else 0)
        out = None
        for i in range(int(np.searchsorted(ends, offset, "right")), len(files)):
            begin = int(ends[i - 1]) if i else 0
            if begin >= stop:
                break
            lo, hi = max(offset, begin), min(stop, int(ends[i]))
            part = read_range(files[i], lo - begin, hi - lo)
            if lo == offset and hi == stop:
                return part
            out = np.empty(stop - offset, np.uint8) if out is None else out  # the parts go to their places, none is kept
            out[lo - offset : hi - offset] = part
        return np.zeros(0, np.uint8) if out is None else out
    store, name = _store(path)
    with store.open_input_file(name) as f:
        return np.frombuffer(f.read_at(length, offset), np.uint8)


def listed(spark: SparkSession, path: str | list[str], most: int = LISTED) -> list[tuple[str, int]] | None:
    """``(file, size)`` of every file below ``path``, listed without a job; null for patterns and for more than ``most`` files."""
    out = []
    for one in [path] if isinstance(path, str) else path:
        if one.startswith(PARTS):
            one = one[len(PARTS) :]
            rows = spark.read.text(one, wholetext=True).select("value", F.col("_metadata.file_path").alias("file")).limit(most + 1).collect()  # names and sizes
            out += [(PARTS + r["file"], sum(int(x.rsplit("\t", 1)[1]) for x in r["value"].splitlines())) for r in rows]
        elif any(c in one for c in "*?[{"):
            return None
        else:
            root = spark._jvm.org.apache.hadoop.fs.Path(one)
            store = root.getFileSystem(spark._jsc.hadoopConfiguration())
            base, found = len(store.makeQualified(root).toUri().getPath()), store.listFiles(root, True)
            while found.hasNext():
                f = found.next()
                inner = f.getPath().toUri().getPath()[base:]
                if not any(x[:1] in "._" for x in inner.split("/") if x):
                    out.append((f.getPath().toString(), f.getLen()))
                if len(out) > most:
                    return None
        if len(out) > most:
            return None
    return out


def listed_all(spark: SparkSession, path: str | list[str]) -> list[tuple[str, int]]:
    """``(file, size)`` of every file below ``path``, however many: names and sizes only."""
    few = listed(spark, path)
    return few if few is not None else [tuple(r) for r in list_files(spark, path).collect()]


def part_list(spark: SparkSession, parts: list[tuple[str, int]], name: str) -> str:
    """A list of ``(file, size)`` in its order, to be read as one file; no bytes are copied."""
    out = fresh_path(spark, name)
    store, root = _store(out)
    store.create_dir(root, recursive=True)
    with store.open_output_stream(f"{root}/f000000") as sink:
        sink.write("\n".join(f"{f}\t{n}" for f, n in parts).encode())
    return PARTS + out


def list_files(spark: SparkSession, path: str | list[str]) -> DataFrame:
    """``(file, size)`` of every file below ``path``; contents are not read.  Few files are listed by the driver, many by Spark."""
    few = listed(spark, path)
    if few is not None:
        return spark.createDataFrame(pa.table({"file": pa.array([f for f, _ in few], pa.string()), "size": pa.array([n for _, n in few], pa.int64())}))
    found = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    return found.select(F.col("path").alias("file"), F.col("length").alias("size"))


def local_splits(spark: SparkSession, path: str | list[str], split_bytes: int = SPLIT_BYTES, most: int = 4096) -> list[tuple[str, int, int, int]] | None:
    """``(file, split, off, len)`` as :func:`splits` gives them, without a job; null if there are more than ``most``."""
    files = listed(spark, path)
    if files is None or sum(-(-n // split_bytes) for _, n in files) > most:
        return None
    return [(f, k, k * split_bytes, min(split_bytes, n - k * split_bytes)) for f, n in sorted(files) for k in range(-(-n // split_bytes))]


def each(spark: SparkSession, rows: list[tuple], run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], kinds: pa.Schema, out: str | StructType, size: int = 0) -> DataFrame:
    """``run`` over ``rows``, one row a task: a lost executor costs the rows that it held, and no two share a task.

    ``size`` is the number of bytes that the planner is to expect of all tasks.  It sees the size of the range below, not
    what ``run`` gives; one row a task would look small enough to broadcast, whatever the input.
    """
    if not rows:
        return spark.createDataFrame([], out)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in b.column(0).to_pylist():
                yield from run(iter([pa.RecordBatch.from_arrays([pa.array([v], k.type) for v, k in zip(rows[i], kinds, strict=True)], schema=kinds)]))

    step = size // (8 * len(rows))  # a number of the range counts as 8 bytes
    if step <= 1:
        return spark.range(0, len(rows), 1, len(rows)).mapInArrow(task, out)
    # slices of equal length, of which the filter leaves the first number
    tasks = spark.range(0, len(rows) * step, 1, len(rows)).where(F.col("id") % step == 0)
    return tasks.select(F.expr(f"id div {step}").alias("id")).mapInArrow(task, out)


def splits(files: DataFrame, split_bytes: int = SPLIT_BYTES, align: int = 1) -> DataFrame:
    """``(file, split, off, len)``: equal ranges, multiples of ``align`` bytes (the width of fixed-width symbols)."""
    step = max(align, split_bytes // align * align)
    count = F.greatest(F.ceil(F.col("size") / step), F.lit(0)).cast("long")
    cut = files.where("size > 0").select("file", "size", F.explode(F.sequence(F.lit(0).cast("long"), count - 1)).alias("split"))
    return cut.select("file", "split", (F.col("split") * step).alias("off"), F.least(F.lit(step).cast("long"), F.col("size") - F.col("split") * step).alias("len"))


def spread(ranges: DataFrame, tasks: int | None = None) -> DataFrame:
    """Ranges dealt evenly, one a task as far as the session's parallelism asks for more than one; by range, so none share a task by chance."""
    spark = ranges.sparkSession
    n = tasks or max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return ranges.repartitionByRange(n, "file", "split")


def blocks(spark: SparkSession, path: str, block_bytes: int = 1 << 20) -> DataFrame:
    """``RAW_BLOCK(file, block, off, data)`` rows, for the methods that work on bytes as rows."""

    def run(batches):
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), pa.array([off], pa.int64()), pa.array([read_range(file, off, size).tobytes()], pa.binary())], ["file", "block", "off", "data"])

    return spread(splits(list_files(spark, path), block_bytes)).mapInArrow(run, "file string, block long, off long, data binary")
