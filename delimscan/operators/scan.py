"""Exclusive scans of ordered rows with any associative operator, as a tree of small groups.

A level puts ``fan`` neighbours into one group; groups are scanned inside, their totals form the next level.  Levels
shrink by ``fan``, so no task ever holds more than ``fan`` rows of a group and the tree has log depth.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Monoid:
    """Associative ``join(left, right)`` with its ``identity``."""

    identity: Column
    join: Callable[[Column, Column], Column]


def vector_monoid(states: int) -> Monoid:
    """State-transition vectors under composition: ``right`` after ``left``."""
    return Monoid(F.array(*[F.lit(i) for i in range(states)]), lambda a, b: F.transform(a, lambda x: F.element_at(b, x + 1)))


def sum_monoid() -> Monoid:
    return Monoid(F.lit(0).cast("long"), lambda a, b: a + b)


def column_monoid() -> Monoid:
    """Column offsets ``struct(is_abs, off)``: an absolute right side wins, a relative one adds."""
    one = lambda is_abs, off: F.struct(is_abs.alias("is_abs"), off.alias("off"))
    return Monoid(one(F.lit(False), F.lit(0).cast("long")), lambda a, b: F.when(b["is_abs"], b).otherwise(one(a["is_abs"], a["off"] + b["off"])))


def exclusive_scan(df: DataFrame, key: str, order: str, value: str, monoid: Monoid, fan: int = 1024, out: str = "prefix") -> DataFrame:
    """``(key, order, out)``: the join of all values before each row of its key; ``order`` counts from 0 without gaps."""
    kind = df.schema[value].dataType
    identity = monoid.identity.cast(kind)
    level = df.select(F.col(key).alias("k"), F.col(order).cast("long").alias("n"), F.col(value).alias("v"))
    sizes = level.groupBy("k").agg(F.max("n").alias("m")).agg(F.max("m")).first()[0]
    return _level(level, identity, monoid, fan, 0 if sizes is None else int(sizes) + 1).select(F.col("k").alias(key), F.col("n").alias(order), F.col("p").alias(out))


def _level(level: DataFrame, identity: Column, monoid: Monoid, fan: int, size: int) -> DataFrame:
    members = F.array_sort(F.collect_list(F.struct("n", "v")))
    grouped = level.groupBy("k", F.floor(F.col("n") / fan).alias("g")).agg(members.alias("m"))
    step = lambda acc, x: F.struct(F.array_append(acc["p"], acc["t"]).alias("p"), monoid.join(acc["t"], x["v"]).alias("t"))
    empty = F.struct(F.slice(F.array(identity), 1, 0).alias("p"), identity.alias("t"))
    scanned = grouped.select("k", "g", "m", F.aggregate("m", empty, step).alias("s"))
    if size > fan:
        above = _level(scanned.select("k", F.col("g").alias("n"), F.col("s.t").alias("v")), identity, monoid, fan, -(-size // fan))
        scanned = scanned.join(above.select("k", F.col("n").alias("g"), F.col("p").alias("before")), ["k", "g"])
    else:
        scanned = scanned.withColumn("before", identity)
    flat = scanned.select("k", "before", F.explode(F.arrays_zip(F.col("m.n").alias("n"), F.col("s.p").alias("p"))).alias("x"))
    return flat.select("k", F.col("x.n").alias("n"), monoid.join(F.col("before"), F.col("x.p")).alias("p"))
