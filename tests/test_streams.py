"""Slice streams: records longer than the carry, restarts, batches that are run again."""

import os
import random
import shutil
import time

import pytest
from delimscan.streaming.slices import parse_stream, parsed_rows
from pyspark.sql import types as T

SCHEMA = T.StructType([T.StructField("a", T.IntegerType()), T.StructField("b", T.StringType()), T.StructField("c", T.StringType())])


def _rows(sizes):
    rng = random.Random(2)
    word = lambda n: "".join(rng.choice('ab,"\n é') for _ in range(n))
    return [(i, word(n), word(4)) for i, n in enumerate(sizes)]


def _bytes(rows):
    q = lambda t: '"' + t.replace('"', '""') + '"'
    return "".join(f"{a},{q(b)},{q(c)}\n" for a, b, c in rows).encode()


def _slices(folder, data, size, first=0):
    os.makedirs(folder, exist_ok=True)
    for k, lo in enumerate(range(0, len(data), size)):
        name = f"{folder}/s{first + k:06d}"
        with open(name, "wb") as f:
            f.write(data[lo : lo + size])
        stamp = 1_700_000_000 + first + k
        os.utime(name, (stamp, stamp))
    return first + k + 1


def _read(spark, out):
    return [(r.a, r.b, r.c) for r in parsed_rows(spark, out, SCHEMA).orderBy("_record_no").collect()]


@pytest.mark.parametrize("sizes, per, step", [((5, 600, 3, 2), 1, 200), ((900, 1, 700), 3, 90), ((3, 500, 500, 6), 4, 41)])
def test_long_records_leave_as_fragments(spark, tmp_path, sizes, per, step):
    rows = _rows(sizes)
    _slices(str(tmp_path / "in"), _bytes(rows), step)
    out = parse_stream(spark, str(tmp_path / "in"), SCHEMA, files_per_batch=per, out=str(tmp_path / "out"), carry_bytes=60)
    assert _read(spark, out) == rows
    carried = spark.read.parquet(f"{out}/carry").selectExpr("max(octet_length(carry)) as n", "count(state) as s").first()
    assert carried["n"] <= 60 and carried["s"] > 0


def test_an_open_record_is_no_row_yet(spark, tmp_path):
    rows = _rows((5, 700))
    _slices(str(tmp_path / "in"), _bytes(rows)[:-40], 150)
    out = parse_stream(spark, str(tmp_path / "in"), SCHEMA, files_per_batch=2, out=str(tmp_path / "out"), carry_bytes=60)
    assert _read(spark, out) == rows[:1]


@pytest.mark.parametrize("carry_bytes", [50, 1 << 20])
def test_a_restarted_stream_goes_on_where_it_was(spark, tmp_path, carry_bytes):
    rows = _rows((5, 90, 3, 200, 7, 8, 300, 1))
    data = _bytes(rows)
    folder, out = str(tmp_path / "in"), str(tmp_path / "out")
    half = len(data) // 2
    n = _slices(folder, data[:half], 97)
    parse_stream(spark, folder, SCHEMA, files_per_batch=2, out=out, carry_bytes=carry_bytes)
    before = len(_read(spark, out))
    assert 0 < before < len(rows)
    _slices(folder, data[half:], 97, n)
    parse_stream(spark, folder, SCHEMA, files_per_batch=2, out=out, carry_bytes=carry_bytes)
    assert _read(spark, out) == rows
    # the last batch loses its commit, as if the job had died behind its writes: it is run again and replaces its output
    commits = sorted((int(x) for x in os.listdir(f"{out}/checkpoint/commits") if x.isdigit()), reverse=True)
    os.remove(f"{out}/checkpoint/commits/{commits[0]}")
    crc = f"{out}/checkpoint/commits/.{commits[0]}.crc"
    if os.path.exists(crc):
        os.remove(crc)
    written = f"{out}/rows/batch={commits[0]}"
    shutil.rmtree(written, ignore_errors=True)
    time.sleep(0.01)
    parse_stream(spark, folder, SCHEMA, files_per_batch=2, out=out, carry_bytes=carry_bytes)
    assert _read(spark, out) == rows and os.path.isdir(written)
