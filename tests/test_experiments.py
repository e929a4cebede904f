"""Experiment queries: what must hold whatever the machine."""

import __spark_entry__ as entry
from delimscan.plans import experiments, measures
from delimscan.plans.workloads import one_large
from delimscan.sources.files import listed


def test_who_can_load_what(spark, small):
    got = {(r.input, r.system): r.failed for r in entry.queries()["exp_compare"](spark, small).collect()}
    broken = {k for k, failed in got.items() if failed}
    assert broken == {("text9", "built-in, lines"), ("text9", "line loader")}  # a line break inside quotes
    assert len(got) == 24


def test_modes_are_exact_and_cost_what_they_say(spark, small):
    rows = entry.queries()["exp_tagging"](spark, small).collect()
    assert all(r.exact for r in rows) and len(rows) == 8
    tags = {(r.input, r["mode"]): r.tag_bytes for r in rows}
    assert all(tags[i, "record_tags"] > max(tags[i, "vector"], tags[i, "inline"]) > tags[i, "spans"] == 0 for i in experiments.INPUTS)
    assert tags["text9", "vector"] > tags["text9", "inline"] and tags["num17", "vector"] < tags["num17", "inline"]  # a bit a byte against a byte a field


def test_copies_are_whole(spark, small):
    one, three = (sum(n for _, n in listed(spark, one_large(spark, small, "text9", k))) for k in (1, 3))
    assert three == 3 * one
    df = spark.range(10)
    assert [measures.sink_seconds(df, s, 80)[1] for s in ("held", "written", "exported")] == [10, 10, 10]


def test_rows_are_seen_in_the_pass_that_is_timed(spark, small, monkeypatch):
    """No copy of the input, no second parse to count or compare, and no prefix timed again for each longer one."""

    def never(*a, **k):
        raise AssertionError

    for name in ("exactness", "force"):
        monkeypatch.setattr(measures, name, never)
    monkeypatch.setattr(experiments.workloads, "one_large", never)
    assert all(r.exact for r in entry.queries()["exp_tagging"](spark, small).collect())
    batch = [r for r in entry.queries()["exp_partition"](spark, small).collect() if r.kind == "batch"]
    assert len(batch) == 12 and all(r.exact for r in batch)
    monkeypatch.setattr(experiments.kernel, "BLOCK", 64 << 10)
    rows = entry.queries()["exp_size"](spark, small).collect()
    for name in experiments.INPUTS:
        size = sum(n for _, n in listed(spark, experiments.workloads.fixture(spark, small, name)))
        assert sorted(r.bytes for r in rows if r.input == name) == [n for k in range(30) if (n := (16 << 10) << k) <= size]
    assert all(r.mb_s > 0 and 0 < r.of_peak <= 1 for r in rows)


def test_row_sums_tell_rows_apart(spark):
    seen = lambda *rows: measures.forced(spark.createDataFrame(list(rows), "a string, b string, n int"), True)[1]
    one, two = ("x", None, 1), ("y", "", None)
    assert seen(one, two, two) == seen(two, one, two)
    others = [seen(one, two), seen(one, one, two), seen((None, "x", 1), two, two), seen(one, ("y", None, None), two), seen(("x", None, 2), two, two)]
    assert len({*others, seen(one, two, two)}) == 6


def test_giant_record_is_not_broadcast_or_parsed_again_to_compare(spark, small, monkeypatch):
    def never(*a, **k):
        raise AssertionError

    monkeypatch.setattr(measures, "exactness", never)
    df = experiments.workloads.skewed(spark, small)
    assert "Broadcast" not in df._jdf.queryExecution().executedPlan().toString()
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang").toPandas().sort_values("doc_id")
    want = dict(zip(docs.doc_id, docs.text, strict=True)) | {0: "\n".join(docs.text[docs.doc_id % 3 == 1])}
    assert {r.doc_id: r.text for r in df.collect()} == want
    rows = entry.queries()["exp_skew"](spark, small).collect()
    assert len(rows) == 6 and all(r.exact for r in rows)
