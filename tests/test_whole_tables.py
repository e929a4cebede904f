"""Steps that once saw a part of a table, on all of it."""

import __spark_entry__ as entry
import pytest
from delimscan.operators import columnar, tagging
from delimscan.plans import measures
from delimscan.plans.parse_queries import _seeded
from delimscan.plans.reader import aligned_ranges
from delimscan.plans.workloads import fixture
from pyspark.sql import functions as F
from test_catalog import duck, rows  # noqa: F401


@pytest.mark.parametrize("name", ["radix_pass_stable_whole", "radix_partition_all_passes_whole", *(f"field_index_whole_{m}" for m in tagging.MODES)])
def test_whole_table_equals_sql(spark, small, duck, name):  # noqa: F811
    got, want = entry.queries()[name](spark, small).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert len(got) == spark.read.parquet(f"{small}/lineitem.parquet").count() * (1 if "radix" in name else 11)
    assert rows(got) == rows(want)


def test_radix_over_many_blocks(spark):
    items = spark.range(1000).select((F.col("id") * 7 % 16).alias("column_no"), F.col("id").alias("pos0"), F.col("id").alias("pos"))
    got = columnar.radix_pass(items, "column_no", "pos", 0, 2, block=64).collect()
    want = sorted(range(1000), key=lambda i: (i * 7 % 16 & 3, i))
    assert {r.pos0: r.pos for r in got} == {x: n for n, x in enumerate(want)}


def test_steps_cover_all_bytes(spark, small):
    path = fixture(spark, small, "num17")
    size = spark.read.format("binaryFile").load(path).agg(F.sum("length")).first()[0]
    got = measures.step_seconds(aligned_ranges(_seeded(spark, path, 100_000)), (31,), 17, block=30_000).groupBy("step").agg(F.sum("bytes").alias("n")).collect()
    assert [r.n for r in got] == [size] * 4
    shares = entry.queries()["measure_steps"](spark, small).groupBy("lane").agg(F.sum("share").alias("s")).collect()
    assert len(shares) == 4 and all(abs(r.s - 1) < 1e-9 for r in shares)
