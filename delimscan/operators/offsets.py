"""Record and column offsets of chunks: contributions, the absolute/relative operator, and their exclusive scans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bitmaps import popcount, positions
from .scan import column_monoid, exclusive_scan, sum_monoid


def record_counts(maps: DataFrame) -> DataFrame:
    return maps.withColumn("records", popcount(F.col("rec_bm")))


def column_contrib(rec_bm: Column, fld_bm: Column, size: Column) -> Column:
    """``struct(is_abs, off)``: field delimiters after the last record delimiter, or all of them if there is none."""
    rec, fld = positions(rec_bm, size), positions(fld_bm, size)
    last = F.coalesce(F.array_max(rec), F.lit(-1))
    return F.struct((F.size(rec) > 0).alias("is_abs"), F.size(F.filter(fld, lambda p: p > last)).cast("long").alias("off"))


def combine_columns(a: Column, b: Column) -> Column:
    return column_monoid().join(a, b)


def record_offsets(counted: DataFrame, key: str, order: str, fan: int = 1024) -> DataFrame:
    """``(key, order, first_record)``."""
    return exclusive_scan(counted, key, order, "records", sum_monoid(), fan, "first_record")


def column_offsets(contrib: DataFrame, key: str, order: str, fan: int = 1024) -> DataFrame:
    """``(key, order, first_column)``."""
    return exclusive_scan(contrib, key, order, "contrib", column_monoid(), fan, "c").select(key, order, F.col("c.off").alias("first_column"))
