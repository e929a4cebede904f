"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.dialect import Dfa, compile_dialect
from ..operators.kernel import BLOCK, COUNTERS, Lanes, Parsed, columns_of, decode, exclusive_prefix, partitioned, tagged
from ..sources.files import read_range
from .reader import ParseResult


def rate(size: int, seconds: float) -> float:
    """GB/s."""
    return size / 1e9 / max(seconds, 1e-9)


def relative_rate(rates: dict[int, float]) -> dict[int, float]:
    """Rate at each size as a share of the peak."""
    top = max(rates.values())
    return {k: v / top for k, v in rates.items()}


def speedup(seconds: float, baseline_seconds: float) -> float:
    return baseline_seconds / max(seconds, 1e-9)


def skew_ratio(skewed_seconds: float, seconds: float) -> float:
    return skewed_seconds / max(seconds, 1e-9)


class StepTimer:
    """Seconds of named steps, each forced to its end, and their shares."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def step(self, name: str):
        began = time.perf_counter()
        yield
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began

    def shares(self) -> dict[str, float]:
        total = sum(self.seconds.values()) or 1.0
        return {k: v / total for k, v in self.seconds.items()}


def block_steps(raw: np.ndarray, dfa: Dfa, lane: int, columns: int, final: bool) -> tuple[StepTimer, Parsed]:
    """One parse of a block that begins at a record, its steps timed one after the other, each on what the last one gave."""
    t = StepTimer()
    with t.step("parse"):
        lanes = Lanes(raw, dfa, lane)
        v = lanes.vectors()
    with t.step("scan"):
        before = exclusive_prefix(v)
    with t.step("tag"):
        classes, end = tagged(lanes, before[:, dfa.start])
    with t.step("partition_convert"):
        p = partitioned(raw, dfa, classes, end, final)
        if p.records:
            [decode(c) for c in columns_of(p, list(range(columns)))]
    return t, p


def step_seconds(ranges: DataFrame, lane_sizes: tuple[int, ...], columns: int, block: int = BLOCK) -> DataFrame:
    """``(lane, step, seconds, bytes)`` of every block of record-aligned ranges, timed where it is read."""

    def run(batches):
        dfa = compile_dialect("rfc4180")
        for b in batches:
            for file, lo, stop, final in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                carry = np.zeros(0, np.uint8)
                while lo < stop:
                    hi = min(stop, lo + max(block, len(carry)))
                    raw = np.concatenate([carry, read_range(file, lo, hi - lo)])
                    for lane in lane_sizes:
                        t, p = block_steps(raw, dfa, lane, columns, final and hi == stop)
                        n = len(t.seconds)
                        yield pa.RecordBatch.from_arrays([pa.array([lane] * n, pa.int32()), pa.array(list(t.seconds)), pa.array(list(t.seconds.values())), pa.array([p.consumed] * n, pa.int64())], ["lane", "step", "seconds", "bytes"])
                    carry, lo = raw[p.consumed :], hi

    return ranges.select("file", "begin", "stop", "final").mapInArrow(run, "lane int, step string, seconds double, bytes long")


def force(df: DataFrame) -> float:
    """Seconds to compute every row."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def forced(df: DataFrame, content: bool = False) -> tuple[float, tuple]:
    """Seconds to compute every row, and what came out in that same pass: the number of rows and, with ``content``, two sums of 64-bit row hashes.

    Equal numbers stand for equal rows in any order: sums differ for any other rows, but for a collision of both hashes.
    """
    seen = Observation()
    out = [F.count(F.lit(1)).alias("rows")]
    if content:
        cols = [F.col(c) for c in df.columns]
        lost = F.concat(*[F.when(c.isNull(), "1").otherwise("0") for c in cols])  # the hash passes over nulls
        out += [F.sum(F.xxhash64(F.lit(seed), lost, *cols).cast("decimal(38,0)")).alias(f"h{seed}") for seed in (0, 1)]
    began = time.perf_counter()
    df.observe(seen, *out).write.format("noop").mode("overwrite").save()
    seconds = time.perf_counter() - began
    got = seen.get
    return seconds, tuple(got[k] for k in ("rows", "h0", "h1")[: len(out)])


def exported(df: DataFrame) -> Iterator[pa.RecordBatch]:
    """All rows as Arrow batches at this process, a batch at a time: neither the rows nor their number must fit its memory.

    All tasks write at once, each a file of the shared folder; this process reads the files in the order of partitions and deletes what it has read.
    """
    from ..sources.files import _store, fresh_path

    root = fresh_path(df.sparkSession, "export")
    store, folder = _store(root)
    store.create_dir(folder, recursive=True)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import uuid

        name, out = f"{root}/{uuid.uuid4().hex}", None  # an attempt that is run again writes another file
        store, file = _store(name)
        for b in batches:
            if out is None:
                sink = store.open_output_stream(file)
                out = pa.ipc.new_stream(sink, b.schema, options=pa.ipc.IpcWriteOptions(compression="lz4"))
            out.write_batch(b)
        if out is not None:
            out.close()
            sink.close()
            yield pa.RecordBatch.from_arrays([pa.array([name])], ["file"])

    for row in df.mapInArrow(write, "file string").collect():  # a name a partition
        store, file = _store(row["file"])
        with store.open_input_stream(file) as source:
            yield from pa.ipc.open_stream(source)
        store.delete_file(file)


def sink_seconds(df: DataFrame, sink: str, input_bytes: int) -> tuple[float, int]:
    """Seconds until all rows are ``held`` by the executors, ``written`` as Parquet, or ``exported`` to the driver as Arrow; and the rows.

    An export passes through one process, a batch at a time, whatever ``input_bytes``.
    """
    from ..sources.files import fresh_path

    began = time.perf_counter()
    if sink == "held":
        kept = df.persist()
        n = kept.count()
        seconds = time.perf_counter() - began
        kept.unpersist()
        return seconds, n
    if sink == "written":
        path = fresh_path(df.sparkSession, "sink")
        df.write.parquet(path)
        return time.perf_counter() - began, df.sparkSession.read.parquet(path).count()
    n = sum(b.num_rows for b in exported(df))
    return time.perf_counter() - began, n


def exactness(got: DataFrame, want: DataFrame) -> int:
    """Differing rows, both ways; 0 for an exact parse."""
    got = got.select(*want.columns)
    return got.exceptAll(want).count() + want.exceptAll(got).count()


def profile(spark: SparkSession, inputs: dict[str, ParseResult]) -> DataFrame:
    """``(input, bytes, records, columns, bytes_per_record, bytes_per_field)``."""
    out = None
    for name, r in inputs.items():
        size = r.seeds.agg(F.sum("len").alias("bytes"))
        shape = r.report.agg(F.sum("records").alias("records"), F.max("max_columns").alias("columns"))
        one = size.crossJoin(shape).select(F.lit(name).alias("input"), "bytes", "records", "columns", (F.col("bytes") / F.col("records")).alias("bytes_per_record"), (F.col("bytes") / F.col("records") / F.col("columns")).alias("bytes_per_field"))
        out = one if out is None else out.unionByName(one)
    return out


def automaton_factor() -> float:
    """Automaton steps a symbol in this process so far: about the number of states plus one."""
    return COUNTERS.steps / max(1, COUNTERS.symbols)


def launch_counts(spark: SparkSession, run) -> dict[str, int]:
    """Jobs, stages and tasks that ``run()`` starts."""
    group = f"measure-{time.monotonic_ns()}"
    spark.sparkContext.setJobGroup(group, group)
    try:
        run()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    tracker = spark.sparkContext.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    stages = [s for j in jobs if (i := tracker.getJobInfo(j)) for s in i.stageIds]
    return {"jobs": len(jobs), "stages": len(stages), "tasks": sum(i.numTasks for s in stages if (i := tracker.getStageInfo(s)))}


def io_floor(spark: SparkSession, path: str, split_bytes: int = 128 << 20) -> float:
    """Seconds only to read the input: the bound that a parse cannot beat."""
    from ..sources.files import blocks

    began = time.perf_counter()
    blocks(spark, path, min(split_bytes, 4 << 20)).select(F.sum(F.octet_length("data"))).first()
    return time.perf_counter() - began
