"""Sharding by a hierarchical weighted hash tree, in DataFrame expressions only.

Shards are leaves of a tree region > rack > shard.  A row descends it: at each level every child draws
``ln(u) / weight`` with ``u`` hashed from the row's key and the child's name, and the largest draw wins.  A draw
depends on nothing but the key, the child and its weight, so a change of weights moves rows only between a changed
subtree and the rest of its level; a new region takes rows only into itself.

Defined results: a null key is hashed as an empty string; a null text has size 1 and the checksum of no bytes; repeated
rows get the same shard and different slots; an empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

Tree = dict[str, dict[str, dict[int, float]]]


def grid(shards: int, per_rack: int = 2, racks: int = 2) -> Tree:
    """Equal-weight tree of shards 0 to ``shards`` - 1: ``per_rack`` shards a rack, ``racks`` racks a region, filled in order."""
    tree: Tree = {}
    for s in range(shards):
        tree.setdefault(f"g{s // (per_rack * racks)}", {}).setdefault(f"k{s // per_rack}", {})[s] = 1.0
    return tree


def _weight(node: dict | float) -> float:
    return sum(map(_weight, node.values())) if isinstance(node, dict) else float(node)


def _draw(key: Column, name: str, weight: float) -> Column:
    """``ln(u) / weight``, ``u`` from 48 bits of the MD5 of key and name, in (0, 1)."""
    bits = F.conv(F.substring(F.md5(F.concat(key, F.lit(f"/{name}"))), 1, 12), 16, 10).cast("double")
    return F.log((bits + F.lit(0.5)) / F.lit(float(1 << 48))) / F.lit(weight)


def place(key: Column, node: dict) -> Column:
    """Shard of a key; shards of no weight take nothing."""
    children = [(name, child) for name, child in node.items() if _weight(child) > 0]
    below = [place(key, c) if isinstance(c, dict) else F.lit(int(name)) for name, c in children]
    if len(children) == 1:
        return below[0]
    draws = F.array(*[_draw(key, str(name), _weight(c)) for name, c in children])
    best = F.array_position(draws, F.array_max(draws))
    out = F.when(best == 1, below[0])
    for i, b in enumerate(below[1:], 2):
        out = out.when(best == i, b)
    return out


def with_shards(docs: DataFrame, tree: Tree, grown: Tree | None = None, id_col: str = "doc_id", text_col: str = "text", run_rows: int = 65_536) -> DataFrame:
    """``(id_col, size, text_crc32, law, shard, slot, grown_shard)`` of every row.

    ``slot`` numbers a shard's rows from 0 without gaps: rows are numbered inside hash runs of about ``run_rows`` rows
    a shard, and a run's base is the prefix sum of the runs before it, so no shard is sorted as a whole.
    """
    key = F.coalesce(F.col("id").cast("string"), F.lit(""))
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    rows = rows.withColumn("shard", place(key, tree).cast("int")).withColumn("grown_shard", (place(key, grown) if grown else F.lit(None)).cast("int"))
    runs = max(64, docs.count() // run_rows)
    # rows that repeat an id are told apart by their text, so a hot id does not make a hot run
    rows = rows.withColumn("run", F.pmod(F.xxhash64("id", "size", "text_crc32"), F.lit(runs)))
    order = Window.partitionBy("shard", "run").orderBy("id", "size", "text_crc32")
    # written behind the one exchange, so the files are as few as its partitions and not as the input's
    own = durable(rows.withColumn("at", F.row_number().over(order).cast("long") - 1))
    before = Window.partitionBy("shard").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)  # a row a run
    base = own.groupBy("shard", "run").agg((F.max("at") + 1).alias("n")).withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    return own.join(base.select("shard", "run", "base"), ["shard", "run"]).select(
        F.col("id").alias(id_col), "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("base") + F.col("at")).cast("long").alias("slot"), "grown_shard")
