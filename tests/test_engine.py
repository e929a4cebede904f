"""The reader, scans, baselines and streams on small inputs, and the shape of plans."""

import pytest
from delimscan.functions.dialect import compile_dialect
from delimscan.operators import baselines, columnar, scan, tagging
from delimscan.plans import measures, reader, workloads
from delimscan.plans.reader import read_delimited
from delimscan.sources import files, render
from delimscan.streaming import slices
from pyspark.sql import functions as F


def put(tmp_path, data: bytes, name="a.csv"):
    (tmp_path / name).write_bytes(data)
    return str(tmp_path)


@pytest.mark.parametrize("size", [1, 2, 3, 5, 16, 1000])
def test_split_invariance(spark, tmp_path, size):
    path = put(tmp_path, b'1,"a ""x"", \n b"\n2,\xc3\xa9\n3,""\n4,\n')
    got = read_delimited(spark, path, schema="i int, t string", split_bytes=size)
    assert [(r["_record_no"], r.i, r.t) for r in got.df.orderBy("_record_no").collect()] == [(0, 1, 'a "x", \n b'), (1, 2, "é"), (2, 3, ""), (3, 4, None)]
    r = got.report.first()
    assert (r.ok, r.records, r.min_columns, r.max_columns) == (True, 4, 2, 2)


def test_many_files_and_empty_ones(spark, tmp_path):
    put(tmp_path, b"1,a\n2,b", "x.csv")
    put(tmp_path, b"", "y.csv")
    path = put(tmp_path, b"3,c\n", "z.csv")
    got = read_delimited(spark, path, schema="i int, t string", split_bytes=3).df
    assert sorted((r.i, r["_record_no"]) for r in got.collect()) == [(1, 0), (2, 1), (3, 0)]


def test_only_line_feed(spark, tmp_path):
    got = read_delimited(spark, put(tmp_path, b"\n"), schema="i int").df.collect()
    assert [(r.i, r["_record_no"]) for r in got] == [(None, 0)]


def test_inference_and_errors(spark, tmp_path):
    path = put(tmp_path, b"1,1.5,x,2020-01-01\n300,2,y,2020-01-02\n")
    got = read_delimited(spark, path, split_bytes=5).df
    assert [f.dataType.simpleString() for f in got.schema[2:6]] == ["smallint", "double", "string", "date"]
    bad = read_delimited(spark, path, schema="a tinyint, b int, c string, d string")
    assert sorted(r.reason for r in bad.rejects.collect()) == ["value of a", "value of b"] or {r.reason for r in bad.rejects.collect()} == {"value of a", "value of b"}
    with pytest.raises(ValueError):
        read_delimited(spark, put(tmp_path / ".." if False else tmp_path, b'a"b\n', "bad.csv"), schema="a string", on_error="fail")


def test_ragged_modes(spark, tmp_path):
    path = put(tmp_path, b"1,a\n2\n3,c,d\n")
    keep = read_delimited(spark, path, schema="i int, t string", split_bytes=4).df.orderBy("_record_no").collect()
    assert [(r.i, r.t, r["_extra"]) for r in keep] == [(1, "a", None), (2, None, None), (3, "c", ["d"])]
    rej = read_delimited(spark, path, schema="i int, t string", on_ragged="reject")
    assert rej.df.count() == 1 and {r.columns_seen for r in rej.rejects.collect()} == {1, 3}
    with pytest.raises(ValueError):
        read_delimited(spark, path, schema="i int, t string", on_ragged="fail")


@pytest.mark.parametrize("fan", [2, 3, 1000])
def test_scan_tree(spark, fan):
    import random

    random.seed(fan)
    vectors = [[random.randrange(4) for _ in range(4)] for _ in range(57)]
    df = spark.createDataFrame([("k", i, v) for i, v in enumerate(vectors)], "k string, n long, v array<int>")
    got = {r.n: r.prefix for r in scan.exclusive_scan(df, "k", "n", "v", scan.vector_monoid(4), fan).collect()}
    acc = [0, 1, 2, 3]
    for i, v in enumerate(vectors):
        assert got[i] == acc
        acc = [v[s] for s in acc]


def test_column_operator(spark):
    rows = [("k", i, (a, o)) for i, (a, o) in enumerate([(False, 2), (False, 1), (True, 3), (False, 4), (True, 0)])]
    df = spark.createDataFrame(rows, "k string, n long, v struct<is_abs: boolean, off: bigint>")
    got = {r.n: (r.prefix.is_abs, r.prefix.off) for r in scan.exclusive_scan(df, "k", "n", "v", scan.column_monoid(), 2).collect()}
    assert got == {0: (False, 0), 1: (False, 2), 2: (False, 3), 3: (True, 3), 4: (True, 7)}


def test_no_raw_bytes_in_a_shuffle(spark, tmp_path):
    """What is exchanged are ranges and summaries; text columns come out of the second pass and are not dealt again."""
    path = put(tmp_path, b"1,a\n2,b\n" * 50)
    got = read_delimited(spark, path, schema="i int, t string", split_bytes=64)
    plan = got.df._jdf.queryExecution().executedPlan().toString()
    after = plan.split("MapInArrow")[0]
    assert "Exchange" not in after and "MapInArrow" in plan


def test_columns_are_pruned_in_the_kernel(spark, tmp_path):
    path = put(tmp_path, b"1,a,x\n2,b,y\n")
    got = read_delimited(spark, path, schema="i int, t string, u string", columns=["u"])
    assert [r.u for r in got.df.orderBy("_record_no").collect()] == ["x", "y"]
    assert " t#" not in got.df._jdf.queryExecution().optimizedPlan().toString()


def test_baselines_on_text_and_numbers(spark, small):
    text, num = workloads.fixture(spark, small, "conversations"), workloads.fixture(spark, small, "orders")
    ts, ns = (workloads.frame(spark, small, n) for n in ("conversations", "orders"))
    assert baselines.parallel_line_loader(spark, text, ts.schema)[1] > 0  # fails on quoted line breaks
    assert baselines.parallel_line_loader(spark, num, ns.schema)[1] == 0
    assert baselines.line_split(spark, text).count() != ts.count()
    rows, misses, rounds = baselines.speculative(spark, text, ts.schema, split_bytes=2000)
    assert measures.exactness(rows, ts) == 0 and rounds >= 1 and misses >= 0


@pytest.mark.parametrize("mode", tagging.MODES)
def test_tagging_modes_agree(spark, small, mode):
    path = workloads.fixture(spark, small, "nation")
    dfa = compile_dialect("rfc4180")
    seeds = reader.seed_table(reader.summary_table(files.splits(files.list_files(spark, path), 100), dfa), dfa)
    runs = tagging.tag_runs(reader.aligned_ranges(seeds), dfa)
    index = tagging.field_index(tagging.column_buffers(runs, mode, bucket=8), mode, bucket=8)
    want = {(r.column_no, r.record_no, r.len) for r in runs.collect()}
    got = index.collect()
    assert {(r.column_no, r.record_no, r.len) for r in got} == want
    for c in range(3):
        own = sorted((r.record_no, r.off, r.len) for r in got if r.column_no == c)
        assert [o for _, o, _ in own] == [sum(n for _, _, n in own[:i]) for i in range(len(own))]


def test_radix_partition_is_stable(spark):
    import random

    random.seed(1)
    keys = [random.randrange(16) for _ in range(200)]
    df = spark.createDataFrame([(k, i, i) for i, k in enumerate(keys)], "column_no long, pos long, was long")
    got = [r.was for r in columnar.partition_by_column(df, bits=2, key_bits=4).orderBy("pos").collect()]
    assert got == sorted(range(200), key=lambda i: keys[i])


@pytest.mark.parametrize("size", [7, 40, 1000])
def test_stream_equals_batch(spark, tmp_path, size):
    src = tmp_path / "in"
    src.mkdir()
    data = b'1,"a\nb"\n2,cc\n3,"d,""e"""\n' * 6
    (src / "a.csv").write_bytes(data)
    folder = slices.cut(spark, str(src), size)
    schema = spark.createDataFrame([], "i int, t string").schema
    out = slices.parse_stream(spark, folder, schema, files_per_batch=3)
    got = slices.parsed_rows(spark, out, schema).orderBy("_record_no").collect()
    assert [r["_record_no"] for r in got] == list(range(18))
    assert [(r.i, r.t) for r in got] == [(1, "a\nb"), (2, "cc"), (3, 'd,"e"')] * 6


def test_skew_does_not_change_the_result(spark, small):
    path = render.rendered(spark, small, "skew-test", lambda s, d: render.write_lines(render.lines(workloads.skewed(s, d).orderBy("doc_id"), quote=True), "skew"))
    got = read_delimited(spark, path, schema="doc_id bigint, text string, lang string", split_bytes=20_000).df
    assert measures.exactness(got, workloads.skewed(spark, small)) == 0


def test_skip_rows_before_context(spark, tmp_path):
    path = put(tmp_path, b'junk " line\nmore "junk\n1,a\n2,b\n')
    got = read_delimited(spark, path, schema="i int, t string", skip_rows=2, split_bytes=5).df
    assert sorted((r.i, r.t) for r in got.collect()) == [(1, "a"), (2, "b")]


def test_measures():
    timer = measures.StepTimer()
    with timer.step("parse"):
        sum(range(1000))
    with timer.step("scan"):
        pass
    assert abs(sum(timer.shares().values()) - 1) < 1e-9
    assert measures.speedup(1, 4) == 4 and measures.relative_rate({1: 1.0, 2: 2.0}) == {1: 0.5, 2: 1.0} and measures.skew_ratio(2, 1) == 2
    assert measures.rate(10**9, 1) == 1


def test_giant_numbers(spark):
    df = spark.createDataFrame([(1, 0, "123"), (1, 1, "0045"), (1, 2, "9")], "k int, seq int, text string")
    assert str(columnar.number_of_fragments(df, ["k"]).first()["value"]) == "12300459"
    assert [columnar.tier(F.lit(x)) is not None for x in (1, 2)] == [True, True]
