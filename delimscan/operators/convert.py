"""Typed values from field text: nulls, defaults, casts, errors, and inferred types."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rungs of the type ladder, the smallest first.
LADDER = ("void", "tinyint", "smallint", "int", "bigint", "decimal(38,0)", "double", "date", "timestamp_ntz", "boolean", "string")


def to_array(text: Column, element: str) -> Column:
    return F.split(text, ",").try_cast(f"array<{element}>")


def typed(text: Column, kind: T.DataType) -> Column:
    if isinstance(kind, T.ArrayType):
        return to_array(F.when(text != "", text), kind.elementType.simpleString())
    return text if isinstance(kind, T.StringType) else F.trim(text).try_cast(kind)


def null_values(text: Column, nulls: tuple[str, ...]) -> Column:
    return F.when(text.isin(*nulls), None).otherwise(text) if nulls else text


def cast_fields(df: DataFrame, schema: T.StructType, nulls: tuple[str, ...] = (), defaults: dict[str, object] | None = None) -> DataFrame:
    """``df`` with its string columns typed; a default stands for an empty or missing field."""
    out = {}
    for f in schema.fields:
        text = null_values(F.col(f.name), nulls)
        value = typed(text, f.dataType)
        if defaults and f.name in defaults:
            value = F.when(text.isNull() | (text == ""), F.lit(defaults[f.name]).cast(f.dataType)).otherwise(value)
        out[f.name] = value
    return df.withColumns(out)


def cast_errors(df: DataFrame, schema: T.StructType, nulls: tuple[str, ...] = ()) -> DataFrame:
    """``(_file, _record_no, reason, columns_seen)`` of records with a value that does not convert."""
    wrong = [F.when(null_values(F.col(f.name), nulls).isNotNull() & (F.col(f.name) != "") & typed(null_values(F.col(f.name), nulls), f.dataType).isNull(), F.lit(f.name)) for f in schema.fields if not isinstance(f.dataType, T.StringType)]
    if not wrong:
        return df.where(F.lit(False)).select("_file", "_record_no", F.lit("").alias("reason"), F.col("_width").alias("columns_seen"))
    names = F.array_compact(F.array(*wrong))
    return df.withColumn("_wrong", names).where(F.size("_wrong") > 0).select("_file", "_record_no", F.concat(F.lit("value of "), F.array_join("_wrong", ", ")).alias("reason"), F.col("_width").alias("columns_seen"))


def rank_of(text: Column) -> Column:
    """Rung of the smallest type that holds a field; empty and null fields do not vote."""
    t = F.trim(text)
    whole = t.rlike(r"^[+-]?\d+$")
    out = F.when(text.isNull() | (t == ""), 0)
    for i, kind in enumerate(("tinyint", "smallint", "int", "bigint", "decimal(38,0)"), 1):
        out = out.when(whole & t.try_cast(kind).isNotNull(), i)
    out = out.when(t.rlike(r"^[+-]?(\d+\.?\d*|\.\d+)([eE][+-]?\d+)?$"), 6)
    out = out.when(t.rlike(r"^\d{4}-\d{2}-\d{2}$") & t.try_cast("date").isNotNull(), 7)
    out = out.when(t.rlike(r"^\d{4}-\d{2}-\d{2}[ T]\d{2}:\d{2}") & t.try_cast("timestamp_ntz").isNotNull(), 8)
    return out.when(F.lower(t).isin("true", "false"), 9).otherwise(10)


def type_of(top: int | None, lo: int | None, hi: int | None) -> str:
    """Type of a column from its largest rung and the least and largest family (0: numbers) of its fields."""
    if not top:
        return "string"
    mixed = lo != hi and (lo, hi) != (7, 8)
    return "string" if mixed else LADDER[top]


def rank_stats(column: pa.Array) -> tuple[int, int, int]:
    """``(top, lo, hi)`` of an Arrow string column; ``(0, -1, -1)`` if no field votes."""
    t = pc.utf8_trim_whitespace(column)
    t = t.filter(pc.fill_null(pc.not_equal(t, ""), False))
    ranks: set[int] = set()

    def take(pattern: str) -> pa.Array:
        nonlocal t
        hit = pc.match_substring_regex(t, pattern)
        found, t = t.filter(hit), t.filter(pc.invert(hit))
        return found

    if len(short := take(r"^[+-]?[0-9]{1,18}$")):
        v = pc.min_max(pc.cast(pc.replace_substring_regex(short, r"^[+]", ""), pa.int64())).as_py()
        ranks.add(next(k for k, b in ((1, 7), (2, 15), (3, 31), (4, 63)) if -(1 << b) <= v["min"] and v["max"] < 1 << b))
    if len(t):
        for x in take(r"^[+-]?[0-9]+$").to_pylist():
            ranks.add(4 if -(1 << 63) <= int(x) < 1 << 63 else 5 if abs(int(x)) < 10**38 else 6)
    if len(t) and len(take(r"^[+-]?([0-9]+\.?[0-9]*|\.[0-9]+)([eE][+-]?[0-9]+)?$")):
        ranks.add(6)
    for rung, pattern, kind in ((7, r"^[0-9]{4}-[0-9]{2}-[0-9]{2}$", pa.date32()), (8, r"^[0-9]{4}-[0-9]{2}-[0-9]{2}[ T][0-9]{2}:[0-9]{2}(:[0-9]{2}(\.[0-9]{1,6})?)?$", pa.timestamp("us"))):
        if len(t) and len(found := take(pattern)):
            try:
                pc.cast(found, kind)
                ranks.add(rung)
            except pa.ArrowInvalid:
                ranks.add(10)
    if len(t) and len(take(r"^(?i:true|false)$")):
        ranks.add(9)
    if len(t):
        ranks.add(10)
    if not ranks:
        return 0, -1, -1
    family = [0 if r <= 6 else r for r in ranks]
    return max(ranks), min(family), max(family)


def infer_types(df: DataFrame, columns: list[str]) -> DataFrame:
    """``(column, type)``: the largest rung any field of a column needs; mixed families meet at string."""
    ranked = df.select(*[rank_of(F.col(c)).alias(c) for c in columns])
    family = lambda r: F.when(r > 6, r).when(r > 0, 0)
    one = ranked.agg(*[F.struct(F.max(c).alias("top"), F.min(family(F.col(c))).alias("lo"), F.max(family(F.col(c))).alias("hi")).alias(c) for c in columns])
    names = F.array(*[F.lit(x) for x in LADDER])
    x = one.select(F.explode(F.array(*[F.struct(F.lit(c).alias("column"), F.col(c).alias("s")) for c in columns])).alias("x")).select("x.column", "x.s.*")
    mixed = (F.col("lo") != F.col("hi")) & ~((F.col("lo") == 7) & (F.col("hi") == 8))
    return x.select("column", F.when(F.coalesce("top", F.lit(0)) == 0, "string").when(mixed, "string").otherwise(F.element_at(names, F.col("top") + 1)).alias("type"))
