"""Reading delimited text: two passes over byte ranges, and a scan of small summaries between them.

Pass one summarises every split from every start state.  A scan over the summaries gives each split its true start
state, first record and column, and the byte at which its first record ends.  Pass two reads ranges that begin and end
at records, so raw bytes are never shuffled, whatever records cross split edges.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dialect import CONTROL, DATA, FIELD, RECORD, Dfa, Dialect, compile_dialect
from ..operators import convert
from ..operators.kernel import BLOCK, FIELDS, LANE, SUMMARY_DDL, Parsed, Summary, classify, columns_of, decode, parse_block, summarize
from ..operators.layout import by_buffers
from ..operators.scan import Monoid, exclusive_scan, sum_monoid
from ..sources.files import PARTS, SPLIT_BYTES, durable, each, fresh_path, list_files, local_splits, read_range, splits, spread

EXTRA, RECORD_NO, FILE = "_extra", "_record_no", "_file"


@dataclass
class Options:
    dialect: Dialect | str | Dfa = "rfc4180"
    schema: T.StructType | str | None = None
    columns: list[str] | None = None
    skip_rows: int = 0
    skip_records: int | Sequence[int] | DataFrame = 0  # a number skips that many first records, numbers or a frame skip those
    tagging: str | None = None  # "record_tags", "inline", "vector" or "auto": how fields find their column; by default straight from their spans
    on_ragged: str = "keep"  # or "reject", "fail"
    on_error: str = "report"  # or "fail"
    defaults: dict[str, object] = field(default_factory=dict)
    null_values: tuple[str, ...] = ()
    empty_null: bool = True
    encoding: str = "utf-8"
    lane_bytes: int = LANE
    split_bytes: int = SPLIT_BYTES
    giant_bytes: int = 256 << 20  # a record that covers whole splits of so many bytes is parsed by all of their tasks
    giant_fields: str = "row"  # or "fragments": fields of such a record above that size stay null and go to ``giant``
    fan: int = 1024
    driver_splits: int = 4096


class ParseResult:
    """``df`` and ``rejects``; ``giant``, fragments of fields too large for a row (null if there are none); ``seeds`` and ``report`` are planned when they are first asked for."""

    def __init__(self, df: DataFrame, rejects: DataFrame, seeds: Callable[[], DataFrame], dfa: Dfa, giant: DataFrame | None = None):
        self.df, self.rejects, self._seeds, self._dfa, self.giant = df, rejects, seeds, dfa, giant

    @cached_property
    def seeds(self) -> DataFrame:
        return self._seeds()

    @cached_property
    def report(self) -> DataFrame:
        return format_report(self.seeds, self._dfa)


SPLIT_KIND = pa.schema([("file", pa.string()), ("split", pa.int64()), ("off", pa.int64()), ("len", pa.int64())])
RANGE_KIND = pa.schema([("file", pa.string()), ("begin", pa.int64()), ("stop", pa.int64()), ("record", pa.int64()), ("final", pa.bool_())])
SUMMARY_KIND = f"file string, split long, off long, len long, per_state array<{SUMMARY_DDL}>"


def _summarizer(dfa: Dfa, lane: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                total: list[Summary] | None = None
                for lo in range(off, off + size, BLOCK):
                    own = summarize(read_range(file, lo, min(BLOCK, off + size - lo)), dfa, lane)
                    total = own if total is None else [x.then(own[x.end]) for x in total]
                rows = [[{f: getattr(s, f) for f in FIELDS} for s in total]]
                kind = pa.list_(pa.struct([(f, pa.int32() if f == "end" else pa.bool_() if f == "is_abs" else pa.int64()) for f in FIELDS]))
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), pa.array([off], pa.int64()), pa.array([size], pa.int64()), pa.array(rows, kind)], ["file", "split", "off", "len", "per_state"])

    return run


def summary_table(ranges: DataFrame, dfa: Dfa, lane: int = LANE) -> DataFrame:
    """Pass one: ``(file, split, off, len, per_state)``, one row a split."""
    return ranges.select("file", "split", "off", "len").mapInArrow(_summarizer(dfa, lane), SUMMARY_KIND)


def _join_summaries(x, y):
    """Struct form of :meth:`Summary.then`."""
    both = (x["recs"] > 0) & (y["recs"] > 0)
    seam = x["col"] + y["head"] + 1
    known = lambda v: F.when(v >= 0, v)
    least = F.least(known(x["mn"]), known(y["mn"]), F.when(both, seam))
    most = F.greatest(known(x["mx"]), known(y["mx"]), F.when(both, seam))
    return F.struct(
        y["end"].alias("end"), (x["recs"] + y["recs"]).alias("recs"), (x["is_abs"] | y["is_abs"]).alias("is_abs"), F.when(y["is_abs"], y["col"]).otherwise(x["col"] + y["col"]).alias("col"),
        F.when(x["recs"] > 0, x["head"]).when(y["recs"] > 0, x["col"] + y["head"]).otherwise(F.lit(0).cast("long")).alias("head"),
        F.coalesce(least, F.lit(-1).cast("long")).alias("mn"), F.coalesce(most, F.lit(-1).cast("long")).alias("mx"),
        F.when(x["bad"] >= 0, x["bad"]).when(y["bad"] >= 0, x["length"] + y["bad"]).otherwise(F.lit(-1).cast("long")).alias("bad"),
        F.when(x["recs"] > 0, x["first_end"]).when(y["recs"] > 0, x["length"] + y["first_end"]).otherwise(F.lit(-1).cast("long")).alias("first_end"),
        F.when(y["recs"] > 0, x["length"] + y["last_end"]).otherwise(x["last_end"]).alias("last_end"), (x["length"] + y["length"]).alias("length"),
    )


def summary_monoid(states: int) -> Monoid:
    """Summaries from every start state: the right side is read from where the left one ends."""
    blank = lambda s: F.struct(*[(F.lit(s).cast("int") if f == "end" else F.lit(False) if f == "is_abs" else F.lit(-1 if f in ("mn", "mx", "bad", "first_end", "last_end") else 0).cast("long")).alias(f) for f in FIELDS])
    return Monoid(F.array(*[blank(s) for s in range(states)]), lambda a, b: F.transform(a, lambda x: _join_summaries(x, F.element_at(b, x["end"] + 1))))


SEED_DDL = f"file string, split bigint, off bigint, len bigint, start_state int, first_record bigint, first_column bigint, before {SUMMARY_DDL}, own {SUMMARY_DDL}"
DRIVER_SPLITS = 4096  # up to so many summaries (about 1 kB each) are folded on the driver, more by the scan tree


def _fold(spark: SparkSession, known: list[tuple], dfa: Dfa, lane: int) -> tuple[list[tuple], list[tuple]]:
    """Seeds and record-aligned ranges of splits that the driver knows, from one job that sends back a summary a split."""
    own = lambda r: Summary(*[r[f] for f in FIELDS])
    flat = lambda s: tuple(getattr(s, f) for f in FIELDS)
    rows, last, total = [], None, Summary(dfa.start)
    cut: list[list] = []
    found = each(spark, known, _summarizer(dfa, lane), SPLIT_KIND, SUMMARY_KIND).collect()
    for r in sorted(found, key=lambda r: (r["file"], r["split"])):
        if r["file"] != last:
            last, total = r["file"], Summary(dfa.start)
            cut.append([r["file"], 0, 0, 0, True])
        mine = own(r["per_state"][total.end])
        rows.append((r["file"], r["split"], r["off"], r["len"], total.end, total.recs, total.col, flat(total), flat(mine)))
        if r["split"] and mine.recs:
            cut[-1][2], cut[-1][4] = r["off"] + mine.first_end, False
            cut.append([r["file"], r["off"] + mine.first_end, 0, total.recs + 1, True])
        cut[-1][2] = r["off"] + r["len"]
        total = total.then(mine)
    return rows, [tuple(c) for c in cut if c[2] > c[1]]


def _known(spark: SparkSession, ranges: DataFrame, most: int) -> list[tuple] | None:
    rows = ranges.select("file", "split", "off", "len").limit(most + 1).collect() if most else []  # names and numbers of ranges, no contents
    return [tuple(r) for r in rows] if most and len(rows) <= most else None


def seeds_of(ranges: DataFrame, dfa: Dfa, lane: int = LANE, fan: int = 1024, driver_splits: int = DRIVER_SPLITS) -> tuple[DataFrame, DataFrame]:
    """Pass one and the scan: seeds, and record-aligned ranges.  The number of splits comes from the listing, so the way is chosen by a checked size."""
    spark = ranges.sparkSession
    known = _known(spark, ranges, driver_splits)
    if known is None:
        seeds = durable(seed_table(summary_table(spread(ranges), dfa, lane), dfa, fan), "seeds")
        return seeds, spread(aligned_ranges(seeds))
    rows, cut = _fold(spark, known, dfa, lane)
    at = {c[:2]: k for k, c in enumerate(cut)}
    aligned = spark.createDataFrame([(c[0], at[c[:2]], *c[1:]) for c in cut], "file string, split bigint, begin bigint, stop bigint, record bigint, final boolean")
    return spark.createDataFrame(rows, SEED_DDL).coalesce(1), aligned


def seed_table(summaries: DataFrame, dfa: Dfa, fan: int = 1024) -> DataFrame:
    """``(file, split, off, len, start_state, first_record, first_column, before, own)`` with summaries from the file's start state."""
    before = exclusive_scan(summaries, "file", "split", "per_state", summary_monoid(dfa.n_states), fan)
    own = summaries.join(before, ["file", "split"]).withColumn("before", F.element_at("prefix", dfa.start + 1))
    return own.select("file", "split", "off", "len", F.col("before.end").alias("start_state"), F.col("before.recs").alias("first_record"), F.col("before.col").alias("first_column"), "before", F.element_at("per_state", F.col("before.end") + 1).alias("own"))


def aligned_ranges(seeds: DataFrame) -> DataFrame:
    """``(file, split, begin, stop, record)``: record-aligned ranges; a split without a record start has none."""
    starts = seeds.where("split = 0 or own.recs > 0").select("file", "split", F.when(F.col("split") == 0, F.lit(0).cast("long")).otherwise(F.col("off") + F.col("own.first_end")).alias("begin"), F.when(F.col("split") == 0, F.lit(0).cast("long")).otherwise(F.col("first_record") + 1).alias("record"))
    size = seeds.groupBy("file").agg(F.max(F.col("off") + F.col("len")).alias("size"))
    nxt = F.lead("begin").over(Window.partitionBy("file").orderBy("split"))  # a row a split, not a record
    return starts.withColumn("nxt", nxt).join(size, "file").select("file", "split", "begin", F.coalesce("nxt", "size").alias("stop"), "record", F.col("nxt").isNull().alias("final")).where("stop > begin")


def parse_range(file: str, begin: int, stop: int, final: bool, dfa: Dfa, lane: int, block: int = BLOCK) -> Iterator[Parsed]:
    """Records of a range that begins at a record; what a block leaves unfinished is carried into the next."""
    carry, lo = np.zeros(0, np.uint8), begin
    while lo < stop:
        hi = min(stop, lo + max(block, len(carry)))  # a record longer than a block is re-read at doubled size
        data = read_range(file, lo, hi - lo)
        data = np.concatenate([carry, data]) if len(carry) else data
        p = parse_block(data, dfa, final and hi == stop, lane)
        if p.records:
            yield p
        carry, lo = data[p.consumed :], hi


def read_delimited(spark: SparkSession, path: str | list[str], options: Options | None = None, **changes) -> ParseResult:
    """Parse every file below ``path``; see :class:`Options`.

    Records are numbered per file from 0 (``_record_no``).  Short records get nulls, surplus fields go to ``_extra``;
    unquoted empty fields are null, quoted ones are ''.  Without a schema the number of columns and their types are
    inferred from all data.
    """
    o = replace(options or Options(), **changes)
    if o.encoding.lower().replace("_", "-") in ("utf-16le", "utf-16be"):
        path = to_utf8(spark, path, o.encoding, o.split_bytes)
    dfa = compile_dialect(o.dialect)
    if o.skip_rows:
        path = skip_rows(spark, path, o.skip_rows, o.split_bytes)
    ranges, seeds, spans = _plan(spark, path, dfa, o)
    trailing = isinstance(o.dialect, (str, Dialect)) and (o.dialect if isinstance(o.dialect, Dialect) else _named(o.dialect)).trailing_delimiter
    schema = T._parse_datatype_string(o.schema) if isinstance(o.schema, str) else o.schema
    if o.on_error == "fail" or schema is None:
        seeds = (lambda made: lambda: made)(seeds())
        report = format_report(seeds(), dfa)
        if o.on_error == "fail" and (bad := report.where("not ok").first()):
            raise ValueError(f"{bad['file']}: invalid at byte {bad['first_bad_byte']}, record {bad['first_bad_record']}, ends in {bad['end_state']}")
    if schema is None:
        width = (report.agg(F.max("max_columns")).first()[0] or 0) - trailing
        names = [f"c{i}" for i in range(int(width))]
    else:
        names = schema.fieldNames()
    wanted = o.columns or names
    pieces = None
    if spans is not None:
        pieces = durable(fragments_of(seeds(), spans, dfa, o.lane_bytes), "fragments")
        ranges = _without(ranges, spans)
    text = _records(spark, ranges, dfa, names, wanted, o, len(names) + trailing)
    if pieces is not None:
        rows, pieces = giant_rows(pieces, names, wanted, o)
        text = text.unionByName(rows)
    if schema is None:
        schema = _inferred(spark, ranges, dfa, names, wanted, o)
    text = _skipped(text, o.skip_records)
    ragged = F.col("_width") != len(names) + int(trailing)
    if o.on_ragged == "fail" and text.where(ragged).limit(1).count():
        raise ValueError("a record has another number of columns")
    bad = text.where(ragged) if o.on_ragged == "reject" else text.where(F.lit(False))
    rejects = bad.select(FILE, RECORD_NO, F.lit("columns").alias("reason"), F.col("_width").alias("columns_seen"))
    good = text.where(~ragged) if o.on_ragged == "reject" else text
    typed = convert.cast_fields(good, T.StructType([schema[c] for c in wanted]), o.null_values, o.defaults)
    return ParseResult(typed.select(FILE, RECORD_NO, *wanted, EXTRA), rejects.unionByName(convert.cast_errors(good, T.StructType([schema[c] for c in wanted]), o.null_values)), seeds, dfa, pieces)


def _plan(spark: SparkSession, path: str | list[str], dfa: Dfa, o: Options) -> tuple[DataFrame | list[tuple], Callable[[], DataFrame], DataFrame | None]:
    """Record-aligned ranges (a list where the driver knows them), how to get the seeds, and giant records (null if none).

    A file of one split begins in the start state and needs no first pass; then only ``seeds`` would make one.
    """
    known = local_splits(spark, path, o.split_bytes, o.driver_splits) if o.driver_splits else None
    if known is None:
        ranges = splits(list_files(spark, path), o.split_bytes)
        table, aligned = seeds_of(ranges, dfa, o.lane_bytes, o.fan, o.driver_splits)
        spans = giant_records(table, o.giant_bytes)
        return aligned, lambda: table, spans if spans.limit(1).count() else None
    cut = {r[0] for r in known if r[1]}
    single = [(f, 0, n, 0, True) for f, _, _, n in known if f not in cut]
    made, aligned = _fold(spark, [r for r in known if r[0] in cut], dfa, o.lane_bytes) if cut else ([], [])
    covered: dict[tuple[str, int], int] = {}
    for r in made:
        if r[8][FIELDS.index("recs")] == 0:
            covered[r[0], r[5]] = covered.get((r[0], r[5]), 0) + r[3]

    def seeds() -> DataFrame:
        rest = [r for r in known if r[0] not in cut]
        more = _fold(spark, rest, dfa, o.lane_bytes)[0] if rest else []
        return spark.createDataFrame(made + more, SEED_DDL).coalesce(1)

    return single + aligned, seeds, giant_records(seeds(), o.giant_bytes) if max(covered.values(), default=0) >= o.giant_bytes else None


# --- giant records ----------------------------------------------------------------------------------------------------


def giant_records(seeds: DataFrame, giant_bytes: int) -> DataFrame:
    """``(file, record, begin)`` of records that cover whole splits of ``giant_bytes`` or more; ``begin`` is their first byte."""
    inside = seeds.where("own.recs = 0").groupBy("file", F.col("first_record").alias("record")).agg(F.sum("len").alias("n")).where(F.col("n") >= giant_bytes)
    begins = seeds.where("own.recs > 0").select("file", (F.col("first_record") + F.col("own.recs")).alias("record"), (F.col("off") + F.col("own.last_end")).alias("begin"))
    return inside.join(begins, ["file", "record"], "left").select("file", "record", F.coalesce("begin", F.lit(0).cast("long")).alias("begin"))


def field_runs(raw: np.ndarray, state: int, column: int, dfa: Dfa, lane: int = LANE) -> tuple[list[tuple[int, int, bool, bytes]], int, int]:
    """``(column, place, quoted, text)`` of the parts of one record's fields in ``raw``, and the state and column behind it."""
    classes, end = classify(raw, dfa, state, lane)
    marks = np.flatnonzero((classes == FIELD) | (classes == RECORD))
    edges = np.concatenate([[0], marks + 1, [len(raw)]])
    out = []
    for i, (x, y) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
        if i < len(marks) or x < y and not (x and classes[x - 1] == RECORD):
            own = classes[x:y]
            out.append((column + i, int(x), bool((own == CONTROL).any()), raw[x:y][own == DATA].tobytes()))
    return out, end, column + int((classes == FIELD).sum())


def fragments_of(seeds: DataFrame, spans: DataFrame, dfa: Dfa, lane: int = LANE) -> DataFrame:
    """``(_file, _record_no, column_no, seq, quoted, text)`` of every field of giant records, each split's part by a task of its own.

    A part knows its start state, record and column from the scan, so a field of any length is classified by all tasks
    that hold a piece of it.
    """
    own, rec = F.col("own"), F.col("first_record")
    ends = own["recs"] > 0
    head = F.struct(rec.alias("record"), F.col("start_state").alias("state"), F.col("first_column").alias("column"), F.col("off").alias("begin"), F.when(ends, F.col("off") + own["first_end"]).otherwise(F.col("off") + F.col("len")).alias("stop"))
    tail = F.struct((rec + own["recs"]).alias("record"), F.lit(dfa.start).alias("state"), F.lit(0).cast("long").alias("column"), (F.col("off") + own["last_end"]).alias("begin"), (F.col("off") + F.col("len")).alias("stop"))
    parts = seeds.select("file", F.explode(F.when(ends, F.array(head, tail)).otherwise(F.array(head))).alias("p")).select("file", "p.*").where("stop > begin")
    mine = parts.join(F.broadcast(spans.select("file", "record")), ["file", "record"], "left_semi")  # a giant record is many splits, so they are few

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, record, state, column, begin, stop in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                col, s = column, state
                for lo in range(begin, stop, BLOCK):
                    runs, s, col = field_runs(read_range(file, lo, min(BLOCK, stop - lo)), s, col, dfa, lane)
                    for c, at, quoted, text in runs:
                        yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([record], pa.int64()), pa.array([c], pa.int32()), pa.array([lo + at], pa.int64()), pa.array([quoted]), pa.array([text], pa.binary())], [FILE, RECORD_NO, "column_no", "seq", "quoted", "text"])

    return spread(mine.withColumn("split", F.col("begin"))).select("file", "record", "state", "column", "begin", "stop").mapInArrow(run, f"{FILE} string, {RECORD_NO} long, column_no int, seq long, quoted boolean, text binary")


def _without(ranges: DataFrame | list[tuple], spans: DataFrame) -> DataFrame | list[tuple]:
    """Ranges that end where a giant record begins: it is the last of its range, as no record begins in the splits that it covers."""
    if isinstance(ranges, list):
        at = [(r["file"], r["begin"]) for r in spans.collect()]  # giant records, each of many splits
        cut = lambda r: next((x for f, x in at if f == r[0] and r[1] <= x < r[2]), None)
        out = [(r[0], r[1], x, r[3], False) if (x := cut(r)) is not None else r for r in ranges]
        return [r for r in out if r[2] > r[1]]
    giant = F.broadcast(spans.select(F.col("file").alias("_f"), F.col("begin").alias("_b")))
    hit = (F.col("file") == F.col("_f")) & (F.col("begin") <= F.col("_b")) & (F.col("_b") < F.col("stop"))
    return ranges.join(giant, hit, "left").withColumn("final", F.col("final") & F.col("_b").isNull()).withColumn("stop", F.coalesce("_b", "stop")).drop("_f", "_b").where("stop > begin")


def giant_rows(pieces: DataFrame, names: list[str], wanted: list[str], o: Options) -> tuple[DataFrame, DataFrame | None]:
    """Rows of giant records from their fragments, and the fragments of fields that stay out of them."""
    sizes = pieces.groupBy(FILE, RECORD_NO, "column_no").agg(F.sum(F.octet_length("text")).alias("n"), F.max("quoted").alias("quoted"))
    large = sizes.where(F.col("n") > o.giant_bytes).select(FILE, RECORD_NO, "column_no") if o.giant_fields == "fragments" else None
    key = [FILE, RECORD_NO, "column_no"]
    whole = pieces if large is None else pieces.join(large, key, "left_anti")
    joined = whole.groupBy(*key).agg(F.expr("listagg(text) WITHIN GROUP (ORDER BY seq)").alias("text"))
    value = F.decode("text", "UTF-8")
    empty = (F.coalesce("n", F.lit(0)) == 0) & ~F.col("quoted")
    value = F.when(empty, None).otherwise(F.coalesce(value, F.lit(""))) if o.empty_null else value
    cells = sizes.join(joined, key, "left").withColumn("value", F.when(F.col("text").isNull() & (F.col("n") > 0), None).otherwise(value))
    at = [F.max(F.when(F.col("column_no") == names.index(c), F.col("value"))).alias(c) for c in wanted]
    extra = F.expr(f"transform(array_sort(collect_list(CASE WHEN column_no >= {len(names)} THEN struct(column_no, value) END)), x -> x.value)")
    rows = cells.groupBy(FILE, RECORD_NO).agg((F.max("column_no") + 1).cast("int").alias("_width"), extra.alias(EXTRA), *at)
    rows = rows.withColumn(EXTRA, F.when(F.size(EXTRA) > 0, F.col(EXTRA))).select(FILE, RECORD_NO, "_width", EXTRA, *wanted)
    return rows, None if large is None else pieces.join(large, key, "left_semi")


def _skipped(text: DataFrame, skip: int | Sequence[int] | DataFrame) -> DataFrame:
    """Without the first ``skip`` records, those numbered in it, or those in a frame of ``_record_no`` (and ``_file``)."""
    if isinstance(skip, DataFrame):
        return text.join(skip, [c for c in (FILE, RECORD_NO) if c in skip.columns], "left_anti")  # broadcast or not as its size says
    if isinstance(skip, int):
        return text.where(F.col(RECORD_NO) >= skip) if skip else text
    return text.where(~F.col(RECORD_NO).isin([int(n) for n in skip])) if len(skip) else text


def _named(name: str) -> Dialect:
    from ..functions.dialect import DIALECTS

    return DIALECTS[name]


def _over(spark: SparkSession, ranges: DataFrame | list[tuple], run: Callable, out: str | T.StructType) -> DataFrame:
    """``run`` over record-aligned ranges, a range a task where the driver knows them; the planner then takes the result to be as large as the text."""
    if isinstance(ranges, list):
        return each(spark, ranges, run, RANGE_KIND, out, sum(r[2] - r[1] for r in ranges))
    return ranges.select(*RANGE_KIND.names).mapInArrow(run, out)


def _records(spark: SparkSession, ranges: DataFrame | list[tuple], dfa: Dfa, names: list[str], wanted: list[str], o: Options, width: int) -> DataFrame:
    """Pass two: wide string columns of every record."""
    at = [names.index(c) for c in wanted]
    lane, empty_null, tagging = o.lane_bytes, o.empty_null, o.tagging

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, begin, stop, record, final in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                for p in parse_range(file, begin, stop, final, dfa, lane):
                    begins = np.concatenate([[0], p.ends[:-1]])
                    seen = p.ends - begins
                    cols = [decode(c) for c in (by_buffers(p, at, tagging, empty_null) if tagging else columns_of(p, at, empty_null))]
                    extra = pa.nulls(p.records, pa.list_(pa.string()))
                    if (seen > width).any():
                        fields = decode(pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(p.offsets) - 1, [None, pa.py_buffer(p.offsets.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(p.text))]))
                        extra = pa.array([fields[int(x) + width : int(y)].to_pylist() if y - x > width else None for x, y in zip(begins, p.ends, strict=True)], pa.list_(pa.string()))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([file] * p.records), pa.array(record + np.arange(p.records)), pa.array(seen.astype(np.int32)), extra, *cols],
                        [FILE, RECORD_NO, "_width", EXTRA, *wanted])
                    record += p.records

    schema = T.StructType([T.StructField(FILE, T.StringType()), T.StructField(RECORD_NO, T.LongType()), T.StructField("_width", T.IntegerType()), T.StructField(EXTRA, T.ArrayType(T.StringType())), *[T.StructField(c, T.StringType()) for c in wanted]])
    return _over(spark, ranges, run, schema)


def _inferred(spark: SparkSession, ranges: DataFrame | list[tuple], dfa: Dfa, names: list[str], wanted: list[str], o: Options) -> T.StructType:
    """Types from a pass that sends back three numbers a column and block, never text."""
    at, lane, empty_null = [names.index(c) for c in wanted], o.lane_bytes, o.empty_null

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for file, begin, stop, _, final in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                for p in parse_range(file, begin, stop, final, dfa, lane):
                    stats = [convert.rank_stats(decode(c)) for c in columns_of(p, at, empty_null)]
                    yield pa.RecordBatch.from_arrays([pa.array(range(len(at)), pa.int32()), *[pa.array([s[k] for s in stats], pa.int32()) for k in range(3)]], ["c", "top", "lo", "hi"])

    found = _over(spark, ranges, run, "c int, top int, lo int, hi int").groupBy("c").agg(F.max("top").alias("top"), F.min(F.when(F.col("lo") >= 0, F.col("lo"))).alias("lo"), F.max("hi").alias("hi"))
    kinds = {r["c"]: convert.type_of(r["top"], r["lo"], r["hi"]) for r in found.collect()}  # a row a column
    return T.StructType([T.StructField(c, T._parse_datatype_string(kinds.get(i, "string"))) for i, c in enumerate(wanted)])


def format_report(seeds: DataFrame, dfa: Dfa) -> DataFrame:
    """``(file, ok, end_state, first_bad_byte, first_bad_record, min_columns, max_columns, records)``."""
    last = seeds.groupBy("file").agg(F.max_by(F.struct("before", "own", "len"), "split").alias("x"), F.min(F.when(F.col("own.bad") >= 0, F.struct((F.col("off") + F.col("own.bad")).alias("byte"), F.col("split")))).alias("bad"))
    whole = last.select("file", _join_summaries(F.col("x.before"), F.col("x.own")).alias("w"), "bad")
    names = F.array(*[F.lit(s) for s in dfa.states])
    accepted = F.array(*[F.lit(i in dfa.accepting) for i in range(dfa.n_states)])
    w = F.col("w")
    first = F.when(w["recs"] > 0, w["head"] + 1)
    open_last = F.when(w["end"] != dfa.start, w["col"] + 1)
    known = lambda v: F.when(v >= 0, v)
    return whole.select(
        "file", (F.element_at(accepted, w["end"] + 1) & (w["bad"] < 0)).alias("ok"), F.element_at(names, w["end"] + 1).alias("end_state"), F.when(w["bad"] >= 0, w["bad"]).alias("first_bad_byte"),
        F.when(w["bad"] >= 0, w["recs"]).alias("first_bad_record"), F.least(first, open_last, known(w["mn"])).cast("int").alias("min_columns"), F.greatest(first, open_last, known(w["mx"])).cast("int").alias("max_columns"),
        (w["recs"] + (w["end"] != dfa.start).cast("long")).alias("records"),
    )


def skip_rows(spark: SparkSession, path: str | list[str], rows: int, split_bytes: int = SPLIT_BYTES) -> str:
    """Copies of the files without their first ``rows`` physical lines, compacted in parallel before any context is known."""
    ranges = splits(list_files(spark, path), split_bytes)

    def count(batches):
        for b in batches:
            for file, split, off, size in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([split], pa.int64()), pa.array([off], pa.int64()), pa.array([size], pa.int64()), pa.array([int((read_range(file, off, size) == 10).sum())], pa.int64())], ["file", "split", "off", "len", "n"])

    counted = durable(spread(ranges).mapInArrow(count, "file string, split long, off long, len long, n long"), "lines")
    placed = counted.join(exclusive_scan(counted, "file", "split", "n", sum_monoid()), ["file", "split"])
    target = fresh_path(spark, "compacted")
    order = placed.select("file").distinct().select("file", F.row_number().over(Window.orderBy("file")).alias("no"))  # a row a file

    def write(batches):
        from ..sources.files import _store

        for b in batches:
            for file, split, off, size, n, before, no in zip(*(b.column(i).to_pylist() for i in range(7)), strict=True):
                if before + n < rows and size:
                    data = b""
                else:
                    raw = read_range(file, off, size)
                    ends = np.flatnonzero(raw == 10)
                    data = raw[ends[rows - before - 1] + 1 :].tobytes() if before < rows else raw.tobytes()
                store, root = _store(f"{target}/f{no:06d}")
                store.create_dir(root, recursive=True)
                if data:
                    with store.open_output_stream(f"{root}/s{split:09d}") as f:
                        f.write(data)
                yield pa.RecordBatch.from_arrays([pa.array([len(data)], pa.int64())], ["n"])

    spread(placed.join(F.broadcast(order), "file").select("file", "split", "off", "len", "n", "prefix", "no")).mapInArrow(write, "n long").agg(F.sum("n")).first()
    return _concatenated(spark, target)


def _concatenated(spark: SparkSession, folder: str) -> str:
    """A list of parts for each subfolder, in order, to be read as one file; names and sizes only, no bytes are copied."""
    out = fresh_path(spark, "streams")
    parts = list_files(spark, folder).select("file", "size", F.regexp_extract("file", r"/(f\d+)/s\d+$", 1).alias("f"))
    groups = parts.groupBy("f").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("file", "size"))), lambda x: F.concat(x["file"], F.lit("\t"), x["size"].cast("string"))), "\n").alias("parts"))

    def write(batches):
        from ..sources.files import _store

        for b in batches:
            for f, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                store, root = _store(out)
                store.create_dir(root, recursive=True)
                with store.open_output_stream(f"{root}/{f}") as sink:
                    sink.write(text.encode())
                yield pa.RecordBatch.from_arrays([pa.array([f])], ["f"])

    groups.mapInArrow(write, "f string").agg(F.count("*")).first()
    return PARTS + out


def to_utf8(spark: SparkSession, path: str | list[str], encoding: str, split_bytes: int = SPLIT_BYTES) -> str:
    """UTF-8 copies of UTF-16 files, each split decoding the code points whose first unit lies in it."""
    from ..operators.chunking import utf16_slice

    target = fresh_path(spark, "utf8")
    big = encoding.lower().endswith("be")
    files = list_files(spark, path)
    order = files.select("file").distinct().select("file", F.row_number().over(Window.orderBy("file")).alias("no"))  # a row a file

    def write(batches):
        from ..sources.files import _store

        for b in batches:
            for file, split, off, size, no in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                data = utf16_slice(read_range(file, off, size + 2), size, big).decode("utf-16-be" if big else "utf-16-le", "replace").encode()
                store, root = _store(f"{target}/f{no:06d}")
                store.create_dir(root, recursive=True)
                with store.open_output_stream(f"{root}/s{split:09d}") as f:
                    f.write(data)
                yield pa.RecordBatch.from_arrays([pa.array([len(data)], pa.int64())], ["n"])

    spread(splits(files, split_bytes, 2).join(F.broadcast(order), "file")).mapInArrow(write, "n long").agg(F.sum("n")).first()
    return _concatenated(spark, target)
