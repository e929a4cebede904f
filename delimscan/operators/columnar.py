"""Columnar layout as DataFrame steps: the stable radix partition, its passes and histogram, the index by run lengths, stitching."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.files import durable


def radix_pass(items: DataFrame, key: str, pos: str, shift: int, bits: int, block: int = 1 << 16) -> DataFrame:
    """One stable pass: ``items`` with ``pos`` (distinct) replaced by histogram base plus rank within the digit.

    Ranks are taken within blocks of ``block`` positions, so a digit with most of the rows is still spread over tasks.
    """
    digit = F.call_function("shiftright", F.col(key).cast("long"), F.lit(shift)).bitwiseAND(F.lit((1 << bits) - 1).cast("long"))
    tagged = items.withColumn("_d", digit).withColumn("_b", F.floor(F.col(pos) / block))
    before = Window.orderBy("_d", "_b").rowsBetween(Window.unboundedPreceding, -1)  # a row a digit value and block
    base = tagged.groupBy("_d", "_b").count().withColumn("_base", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    rank = F.row_number().over(Window.partitionBy("_d", "_b").orderBy(pos)) - 1
    return tagged.withColumn("_r", rank).join(F.broadcast(base), ["_d", "_b"]).withColumn(pos, (F.col("_base") + F.col("_r")).cast("long")).drop("_d", "_b", "_r", "_base")


def partition_by_column(items: DataFrame, key: str = "column_no", pos: str = "pos", bits: int = 2, key_bits: int = 8) -> DataFrame:
    """All passes, the lowest bits first; every pass reads its input twice, so it is written once before."""
    for shift in range(0, key_bits, bits):
        items = radix_pass(durable(items, "radix"), key, pos, shift, bits)
    return items


def histogram(runs: DataFrame) -> DataFrame:
    """``(file, column_no, bytes, off)``: size of each column's buffer, and where it begins."""
    sizes = runs.groupBy("file", "column_no").agg(F.sum("len").cast("long").alias("bytes"))
    before = Window.partitionBy("file").orderBy("column_no").rowsBetween(Window.unboundedPreceding, -1)  # a row a column
    return sizes.withColumn("off", F.coalesce(F.sum("bytes").over(before), F.lit(0)).cast("long"))


def index_by_run_lengths(symbols: DataFrame) -> DataFrame:
    """Field index from tagged symbols: lengths of runs of equal record tags, and their exclusive prefix sum."""
    runs = symbols.groupBy("file", "column_no", "record_no").agg(F.count("*").alias("len"))
    before = Window.partitionBy("file", "column_no").orderBy("record_no").rowsBetween(Window.unboundedPreceding, -1)
    return runs.withColumn("off", F.coalesce(F.sum("len").over(before), F.lit(0)).cast("long"))


def stitch(fragments: DataFrame) -> DataFrame:
    """``(file, record_no, column_no, text)``: fields joined from ``(…, seq, text)`` fragments; only fragments are shuffled."""
    joined = F.expr("listagg(text) WITHIN GROUP (ORDER BY seq)")
    return fragments.groupBy("file", "record_no", "column_no").agg(joined.alias("text"))


def number_of_fragments(fragments: DataFrame, key: list[str], seq: str = "seq", text: str = "text") -> DataFrame:
    """``(key, value, digits, number)`` of whole numbers too long for one worker.

    Pairs (digit count, value) are joined by v1 * 10 ** len2 + v2, in fragment order.  ``value`` is a DECIMAL(38,0), null
    beyond 38 digits, which no type holds; ``number`` is the value as text without leading zeros, however long (up to
    the 2 GB of a row), and ``digits`` its length.
    """
    part = F.struct(F.length(text).alias("n"), F.col(text).alias("t"))
    members = F.array_sort(F.collect_list(F.struct(F.col(seq).alias("s"), part.alias("p"))))
    whole = F.array_join(F.transform("m", lambda x: x["p"]["t"]), "")  # the same sum, written in tens
    number = F.regexp_replace(whole, "^0+(?=.)", "")
    power = lambda n: F.concat(F.lit("1"), F.repeat(F.lit("0"), n)).cast("decimal(38,0)")
    step = lambda a, x: (a * power(x["p"]["n"]) + x["p"]["t"].cast("decimal(38,0)")).cast("decimal(38,0)")
    value = F.when(F.length("number") <= 38, F.aggregate("m", F.lit(0).cast("decimal(38,0)"), step))
    return fragments.groupBy(*key).agg(members.alias("m")).withColumn("number", number).select(*key, value.alias("value"), F.length("number").cast("long").alias("digits"), "number")


def tier(length: Column, block_bytes: int = 1 << 20, giant_bytes: int = 256 << 20) -> Column:
    """Who converts a field of this length: one worker, a block, or fragments across workers."""
    return F.when(length <= block_bytes, "exclusive").when(length <= giant_bytes, "block").otherwise("fragments")
