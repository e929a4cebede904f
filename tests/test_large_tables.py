"""What kept queries from whole results on tables of 1 GB, shown on small ones."""

import __spark_entry__ as entry
import pytest
from delimscan.operators import baselines, tagging
from delimscan.plans import experiments, measures, parse_queries, workloads
from delimscan.sources import render
from delimscan.sources.files import listed
from pyspark.sql.classic.dataframe import DataFrame
from test_catalog import duck, rows  # noqa: F401


def equals_sql(spark, small, duck, name):  # noqa: F811
    got, want = entry.queries()[name](spark, small).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert rows(got) == rows(want)


def test_planner_sees_the_size_of_the_text(spark, small, duck):  # noqa: F811
    """A parsed frame that looked like a row a task was broadcast, however large."""
    size = sum(n for _, n in listed(spark, workloads.fixture(spark, small, "lineitem")))
    seen = int(workloads.parsed(spark, small, "lineitem").df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    assert size / 2 < seen < 4 * size
    equals_sql(spark, small, duck, "r_subquery_correlated")


@pytest.mark.parametrize("name", ["skip_rows", "record_numbers", "skip_records", "skip_records_set"])
def test_one_file_is_not_gathered_on_the_driver(spark, small, duck, name, monkeypatch):  # noqa: F811
    """Records of several parts are numbered through, and no text is collected to render them."""
    table = "events" if name == "skip_rows" else "documents"
    gathered = []
    collect = DataFrame.collect
    monkeypatch.setattr(type(spark.range(1)), "collect", lambda df: gathered.append(df.columns) or collect(df))
    monkeypatch.setattr(workloads, "fixture", lambda s, d, n: _in_parts(s, d, n))
    monkeypatch.setattr(render, "_RENDERED", {})
    df = entry.queries()[name](spark, small)
    assert ["value"] not in gathered
    assert len(listed(spark, workloads.fixture(spark, small, table))) > 2
    got, want = df.toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert rows(got) == rows(want)


def _in_parts(spark, small, name):
    def make(s, d):
        df = workloads.table(s, d, name)
        return render.write_lines(render.lines(df.repartitionByRange(5, df.columns[0]).sortWithinPartitions(df.columns[0]), quote=name == "documents" or None), name)

    return render.rendered(spark, small, f"parts|{name}", make)


@pytest.mark.parametrize("mode", tagging.MODES)
def test_buffers_are_made_without_a_row_a_field(spark, small, duck, mode):  # noqa: F811
    df = entry.queries()[f"field_index_{mode}"](spark, small)
    got, want = df.toPandas(), duck.sql(entry.oracle_sql()[f"field_index_{mode}"]).df()
    assert rows(got) == rows(want)
    assert "collect_list" not in df._jdf.queryExecution().optimizedPlan().toString()


def test_packed_vectors_of_a_given_table(spark, small, duck):  # noqa: F811
    equals_sql(spark, small, duck, "compose_packed_vectors")
    assert "FileScan parquet" in entry.queries()["compose_packed_vectors"](spark, small)._jdf.queryExecution().executedPlan().toString()


def test_export_has_no_limit_of_input(spark):
    df = spark.range(0, 25_000, 1, 3)
    assert measures.sink_seconds(df, "exported", 1 << 40)[1] == 25_000
    assert sorted(x for b in measures.exported(df) for x in b.column(0).to_pylist()) == list(range(25_000))


@pytest.mark.parametrize("load", [baselines.coarse_split, baselines.single_node])
def test_in_memory_reader_takes_records_longer_than_its_block(spark, tmp_path, load):
    n = 35 << 20
    (tmp_path / "part-0").write_bytes(b'0,"' + b"a\n" * (n // 2) + b'"\n1,"b"\n')
    schema = spark.createDataFrame([], "i int, t string").schema
    got = load(spark, str(tmp_path), schema).selectExpr("i", "length(t) as n").collect()
    assert sorted((r.i, r.n) for r in got) == [(0, n), (1, 1)]


def test_long_record_is_rendered_without_a_row_that_holds_it(spark, small, duck, monkeypatch):  # noqa: F811
    def never(*a, **k):
        raise AssertionError

    monkeypatch.setattr(workloads, "skewed", never)
    monkeypatch.setattr(parse_queries, "skewed", never, raising=False)
    monkeypatch.setattr(render, "_RENDERED", {})
    equals_sql(spark, small, duck, "skewed_record_parse")


def test_export_is_one_job_and_leaves_no_file(spark):
    """An export was a job a partition, one after the other."""
    from delimscan.sources.files import listed_all, shared_dir

    df = spark.range(0, 25_000, 1, 5)
    seen = []
    assert measures.launch_counts(spark, lambda: seen.extend(x for b in measures.exported(df) for x in b.column(0).to_pylist()))["jobs"] == 1
    assert seen == list(range(25_000))
    assert not [f for f, _ in listed_all(spark, shared_dir(spark)) if "/export-" in f]
    assert list(measures.exported(spark.range(0))) == []


def test_sinks_share_one_first_pass_and_copy_nothing(spark, small, monkeypatch):
    reads = []
    read = experiments.read_delimited
    monkeypatch.setattr(experiments, "read_delimited", lambda *a, **k: reads.append(a[1]) or read(*a, **k))
    monkeypatch.setattr(workloads, "one_large", None)
    got = {(r.input, r.sink): r.rows for r in entry.queries()["measure_sinks"](spark, small).collect()}
    assert len(reads) == 2 and len(got) == 6
    assert all(n == workloads.frame(spark, small, name).count() for (name, _), n in got.items())
