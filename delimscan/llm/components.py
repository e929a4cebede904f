"""Connected components of an edge table by alternating star contraction; every round is a written table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _toward_min(pairs: DataFrame) -> DataFrame:
    """Each ``u`` with the smallest of itself and its partners."""
    return pairs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))


def connected_components(edges: DataFrame, u: str = "u", v: str = "v", max_rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of longs -> ``(node, root)``, root being the smallest node reachable.

    Loops and repeated edges are allowed, null ends are ignored, an empty table gives an empty result.  No
    vertex's neighbours are ever gathered in one place: rounds use minima (with partial aggregation) and equi joins.
    """
    e = edges.select(F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v")).where("u <> v")
    e = durable(e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = _mark(e)
    for _ in range(max_rounds if mark[0] else 0):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(_toward_min(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v"))
        nxt = durable(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        now = _mark(nxt)
        e, done, mark = nxt, now == mark, now
        if done:
            break
    else:
        if mark[0]:
            raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
