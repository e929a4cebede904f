"""The timed steps of a block are one parse of it."""

import __spark_entry__ as entry
import numpy as np
import pytest
from delimscan.functions.dialect import compile_dialect
from delimscan.operators import kernel
from delimscan.plans import measures
from pyspark.sql import functions as F


@pytest.mark.parametrize("final", [False, True])
@pytest.mark.parametrize("lane", [15, 31, 64, 256])
def test_steps_of_a_block_are_one_parse(lane, final, monkeypatch):
    monkeypatch.setattr(kernel, "COUNTERS", kernel.Counters())
    raw, dfa = np.frombuffer(b'1,"a ""b"", c",\n2,plain text,3\n' * 200 + b'3,"op"', np.uint8), compile_dialect("rfc4180")
    t, got = measures.block_steps(raw, dfa, lane, 3, final)
    assert kernel.COUNTERS.bytes == len(raw)  # twice as many where the last step parsed again
    assert list(t.seconds) == ["parse", "scan", "tag", "partition_convert"]
    want = kernel.parse_block(raw, dfa, final, lane)
    assert all(np.array_equal(getattr(got, k), getattr(want, k)) for k in ("text", "offsets", "quoted", "ends", "consumed", "bad", "end_state", "spans"))
    assert got.records == 400 + final


def test_ranges_are_dealt_among_tasks(spark, small, monkeypatch):
    """Ranges are rows so small that the planner would put all of them into one task, whatever the bytes behind them."""
    timed, given = measures.step_seconds, []
    monkeypatch.setattr(measures, "step_seconds", lambda ranges, *more: timed(given.append(ranges) or ranges, *more))
    assert entry.queries()["measure_steps"](spark, small).count() == 16
    tasks = given[0].groupBy(F.spark_partition_id().alias("task")).count().collect()
    assert len(tasks) > 1 and sum(r["count"] for r in tasks) == given[0].count() > 1
