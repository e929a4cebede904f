"""Event-time queries on a stream of parsed events: windows, late rows, duplicates, joins and per-key state."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.parse_queries import _stream
from ..plans.workloads import parsed_frame
from ..sources.files import fresh_path

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _events(spark: SparkSession, sf_dir: str, per_trigger: int = 2) -> DataFrame:
    """Rows that the slice parser has written, as a stream."""
    rows, out = _stream(spark, sf_dir)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", per_trigger).option("recursiveFileLookup", "true").parquet(f"{out}/rows").withColumn("ts", F.col("ts").cast("timestamp"))


def _run(df: DataFrame, mode: str = "append") -> DataFrame:
    """Everything available, to a Parquet sink (append) or the last complete result (complete)."""
    spark = df.sparkSession
    path = fresh_path(spark, "sink")
    if mode == "append":
        query = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-checkpoint").outputMode("append").trigger(availableNow=True).start()
    else:
        query = df.writeStream.foreachBatch(lambda b, n: b.write.mode("overwrite").parquet(path)).option("checkpointLocation", f"{path}-checkpoint").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def stream(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


_STATS = "count(*)::BIGINT AS n, round(sum(value), 4) AS total"


def _stats():
    return F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")


def _window(df: DataFrame) -> DataFrame:
    return df.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), *[c for c in df.columns if c != "window"])


@stream("stream_window_tumbling", f"SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, {_STATS} FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    e = _events(spark, sf_dir).groupBy(F.window("ts", "1 hour"), "event_type").agg(*_stats())
    return _window(_run(e, "complete"))


@stream("stream_window_sliding", f"SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, {_STATS} FROM (SELECT value, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY 1")
def _(spark, sf_dir):
    return _window(_run(_events(spark, sf_dir).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(*_stats()), "complete"))


@stream("stream_window_session", f"""WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, {_STATS} FROM s GROUP BY user_id, k""")
def _(spark, sf_dir):
    e = _events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("window")).agg(*_stats())
    return _window(_run(e, "complete"))


@stream("stream_late_dropped", f"""WITH e AS (SELECT event_id, ts, value, time_bucket(INTERVAL 1 HOUR, ts) AS s, event_id % 50 = 0 AS late FROM events),
w AS (SELECT (SELECT max(ts) FROM e WHERE NOT late AND event_id < (SELECT max(event_id) FROM e WHERE NOT late)) - INTERVAL 10 MINUTE AS first, max(ts) - INTERVAL 10 MINUTE AS last FROM e)
SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, {_STATS} FROM e, w WHERE s + INTERVAL 1 HOUR <= last AND (NOT late OR s + INTERVAL 1 HOUR > first) GROUP BY s""")
def _(spark, sf_dir):
    """Windows closed by the watermark, in append mode: every fiftieth event comes in the third batch, too late for windows that the first has closed.

    Rows count as late by the watermark of the batch before the last, so a second batch, of one event, lies between.
    """
    e, root = parsed_frame(spark, sf_dir, "events"), fresh_path(spark, "late")
    last = e.where("event_id % 50 <> 0").agg(F.max("event_id")).first()[0]
    for n, part in enumerate((e.where("event_id % 50 <> 0").where(F.col("event_id") != last), e.where(F.col("event_id") == last), e.where("event_id % 50 = 0"))):
        part.coalesce(1).write.parquet(f"{root}/{n}")  # the file source takes the older file first
    rows = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(root).withColumn("ts", F.col("ts").cast("timestamp"))
    return _window(_run(rows.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(*_stats())))


@stream("stream_dedup", "SELECT event_id, user_id FROM events")
def _(spark, sf_dir):
    e = _events(spark, sf_dir)
    twice = e.select("event_id", "user_id", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
    return _run(twice.withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@stream("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def _(spark, sf_dir):
    c = parsed_frame(spark, sf_dir, "customer").select("c_custkey", "c_name")
    return _run(_events(spark, sf_dir).join(c, F.expr("user_id = c_custkey")).select("event_id", "c_name"))


@stream("stream_stream_join", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _(spark, sf_dir):
    e = _events(spark, sf_dir).withWatermark("ts", "400 days")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    p = _events(spark, sf_dir).withWatermark("ts", "400 days").where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    return _run(c.join(p, F.expr("cu = pu AND pt >= ct AND pt <= ct + INTERVAL 1 HOUR")).select("click_id", "purchase_id"))


@stream("stream_state_profile", "SELECT user_id, count(*)::BIGINT AS n, max(event_id)::BIGINT AS last_id FROM events GROUP BY 1")
def _(spark, sf_dir):
    """A running profile a user in arbitrary state; the last update of each user is its result."""
    import pandas as pd

    def update(key, batches, state):
        n, last = state.get if state.exists else (0, -1)
        for b in batches:
            n, last = n + len(b), max(last, int(b["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_id": [last]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    e = _events(spark, sf_dir).select("user_id", "event_id").where("user_id is not null")
    out = e.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, last_id long", "n long, last_id long", "append", GroupStateTimeout.NoTimeout)
    return _run(out).groupBy("user_id").agg(F.max("n").alias("n"), F.max("last_id").alias("last_id"))


