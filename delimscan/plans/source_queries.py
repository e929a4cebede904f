"""Queries of the sources and of SQL registration, and of the measures that depend on a run."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.datasource import register
from ..sources.files import fresh_path, spread
from . import measures
from .parse_queries import NATION, _seeded
from .reader import aligned_ranges
from .workloads import fixture, frame, one_file, parsed, split_size, text_of

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


@query("source_raw_blocks", f"SELECT i::BIGINT AS block, least(200, n - i * 200)::BIGINT AS bytes FROM (SELECT strlen(t) AS n FROM {NATION} x), unnest(range((n + 199) // 200)) AS u(i)")
def _(spark, sf_dir):
    register(spark)
    path = one_file(spark, sf_dir, "nation_plain", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]))
    return spark.read.format("raw_blocks").option("path", path).option("blockbytes", "200").load().select("block", F.octet_length("data").cast("long").alias("bytes"))


@query("source_raw_blocks_pushdown", "SELECT 1::BIGINT AS block, 200::BIGINT AS bytes")
def _(spark, sf_dir):
    register(spark)
    path = one_file(spark, sf_dir, "nation_plain", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]))
    return spark.read.format("raw_blocks").option("path", path).option("blockbytes", "200").load().where("block = 1").select("block", F.octet_length("data").cast("long").alias("bytes"))


@query("source_raw_stream", f"SELECT strlen(t)::BIGINT AS bytes FROM {NATION} x")
def _(spark, sf_dir):
    register(spark)
    path = one_file(spark, sf_dir, "nation_plain", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]))
    out = fresh_path(spark, "blocks")
    stream = spark.readStream.format("raw_blocks").option("path", path).option("blockbytes", "50").option("maxbytesperbatch", "200").load()
    q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-checkpoint").start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.read.parquet(out).agg(F.sum(F.octet_length("data")).cast("long").alias("bytes"))


@query("source_sql_view", "SELECT doc_id::VARCHAR AS doc_id, lang, text FROM documents")
def _(spark, sf_dir):
    register(spark)
    path = fixture(spark, sf_dir, "documents")
    spark.sql(f"CREATE OR REPLACE TEMP VIEW delimited_documents USING delimscan OPTIONS (path '{path}', columns 'doc_id,text,lang,source,n_chars', splitbytes '{split_size(spark, path)}')")
    return spark.sql("SELECT doc_id, lang, text FROM delimited_documents")


@query("sql_functions", "SELECT b, CASE b WHEN 10 THEN 0 WHEN 34 THEN 1 WHEN 44 THEN 2 ELSE 3 END AS g, CASE b WHEN 10 THEN 0 WHEN 34 THEN 1 WHEN 44 THEN 3 ELSE 2 END AS e FROM (SELECT unnest([10, 34, 44, 65, 124]) AS b)")
def _(spark, sf_dir):
    register(spark)
    return spark.sql("SELECT b, swar_group(b) AS g, dfa_end_state(CAST(char(b) AS BINARY), 0) AS e FROM VALUES (10), (34), (44), (65), (124) t(b)")


@query("measure_io_floor")
def _(spark, sf_dir):
    """Seconds to read the input only, to parse it, and their ratio."""
    path = fixture(spark, sf_dir, "documents")
    floor, parse = measures.io_floor(spark, path), measures.force(parsed(spark, sf_dir, "documents").df)
    return spark.createDataFrame([(floor, parse, measures.speedup(floor, parse))], "read_seconds double, parse_seconds double, ratio double")


@query("measure_launches")
def _(spark, sf_dir):
    """Jobs, stages and tasks that one parse starts."""
    n = measures.launch_counts(spark, lambda: measures.force(parsed(spark, sf_dir, "nation").df))
    return spark.createDataFrame([(n["jobs"], n["stages"], n["tasks"])], "jobs int, stages int, tasks int")


@query("measure_steps")
def _(spark, sf_dir):
    """Seconds and share of each kernel step over all blocks of the numeric set, for several lane sizes."""
    path = fixture(spark, sf_dir, "num17")
    one = measures.step_seconds(spread(aligned_ranges(_seeded(spark, path, split_size(spark, path)))), (15, 31, 64, 256), len(frame(spark, sf_dir, "num17").columns))
    total = one.groupBy("lane", "step").agg(F.sum("seconds").alias("seconds"))
    return total.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("lane")))  # a row a step


@query("measure_automaton_factor")
def _(spark, sf_dir):
    """Automaton steps a symbol: every start state once, and the right one again."""
    import numpy as np

    from ..functions.dialect import compile_dialect
    from ..operators import kernel

    kernel.COUNTERS.__init__()
    kernel.classify(np.frombuffer(bytes(text_of(spark, sf_dir, "nation").first()["data"]), np.uint8), compile_dialect("rfc4180"), 0, 31)
    return spark.createDataFrame([(6, float(measures.automaton_factor()))], "states int, steps_per_symbol double")
