"""Tables rendered as delimited text files, the inputs of tests and workloads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .files import fresh_path

_RENDERED: dict[tuple[str, str, str], str] = {}


def cell(c: Column, kind: str, quote: bool | None, sep: str = ",") -> Column:
    """A value as text: quoted always, never, or (None) where it needs to be; null is an unquoted nothing."""
    if kind.startswith("array"):
        return F.coalesce(F.concat(F.lit("["), F.concat_ws(",", c.cast("array<string>")), F.lit("]")), F.lit(""))
    else:
        text = c.cast("string")
    quoted = F.concat(F.lit('"'), F.replace(text, F.lit('"'), F.lit('""')), F.lit('"'))
    if quote is None:
        text = F.when(text.rlike(r'["\r\n' + sep.replace("\\", "\\\\") + "]") | (text == ""), quoted).otherwise(text)
    elif quote:
        text = quoted
    return F.coalesce(text, F.lit(""))


def lines(df: DataFrame, sep: str = ",", quote: bool | None = None) -> DataFrame:
    """``value``: each row as one delimited record without its end."""
    cells = [cell(F.col(f.name), f.dataType.simpleString(), quote, sep) for f in df.schema.fields]
    joined = cells[0]
    for c in cells[1:]:
        joined = F.concat(joined, F.lit(sep), c)
    return df.select(joined.alias("value"))


def write_lines(rendered: DataFrame, name: str, line_sep: str = "\n") -> str:
    path = fresh_path(rendered.sparkSession, name)
    rendered.write.option("lineSep", line_sep).text(path)
    return path


def rendered(spark: SparkSession, sf_dir: str, name: str, make) -> str:
    """Path of a rendered fixture, made once a session and data folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _RENDERED:
        _RENDERED[key] = make(spark, sf_dir)
    return _RENDERED[key]
