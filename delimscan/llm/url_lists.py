"""URL filters by a temporal list join.

A list is a history of dated entries: at a time, an action adds or removes a pattern (a domain with its subdomains,
or a host with a path prefix).  The entries of a pattern become validity intervals, and every capture is judged against
the entries active when it was fetched, by an as-of join on each pattern that could match its address.

Defined results: a capture with a null or malformed address, or without a time, matches nothing and passes; an entry
with a null pattern, time or action is ignored; repeated equal actions change nothing; of entries of one pattern at
the same time the removal wins; an entry counts from its very second on; repeated captures are judged alike, a row
each; an empty table of captures gives no row, one of entries blocks nothing; other columns of the captures, whatever
their names, do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

MANY = 256  # lists judged in one call; each is a running sum of the window


def host_of(url: Column) -> Column:
    """Lower-case host without user, port and trailing dot; null if the address has none."""
    host = F.regexp_extract(F.coalesce(url, F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]/?#]*\]|[^/?#:]*)", 1)
    host = F.regexp_replace(F.lower(host), r"\.$", "")
    return F.when(host != "", host)


def path_of(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*([^?#]*)", 1)


def depth_of(entries: DataFrame) -> int:
    """Folders in the deepest path of any entry."""
    parts = F.filter(F.split("pattern", "/"), lambda p: p != "")
    return entries.where("pattern like 'p:%'").agg(F.max(F.size(parts) - 1).alias("n")).first()["n"] or 0


def patterns_of(url: Column, depth: int) -> Column:
    """Every pattern that matches an address: its host and parent domains, and host + path prefixes down to ``depth`` folders."""
    host = host_of(url)
    labels = F.split(host, r"\.")
    domains = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat(F.lit("d:"), F.array_join(F.slice(labels, i, F.size(labels)), ".")))
    parts = F.slice(F.filter(F.split(path_of(url), "/"), lambda p: p != ""), 1, max(depth, 0))
    paths = F.transform(F.sequence(F.lit(1), F.greatest(F.size(parts), F.lit(1))), lambda i: F.concat(F.lit("p:"), host, F.lit("/"), F.array_join(F.slice(parts, 1, i), "/")))
    return F.when(host.isNotNull(), F.array_distinct(F.concat(domains, F.when(F.size(parts) > 0, paths).otherwise(F.array().cast("array<string>")))))


def intervals(entries: DataFrame) -> DataFrame:
    """``entries(list, pattern, at, action)`` -> ``(list, pattern, since, until)``; ``until`` is null while the entry holds."""
    good = entries.where("pattern is not null and at is not null and action in ('add', 'remove')")
    one = good.groupBy("list", "pattern", "at").agg(F.min(F.col("action") == "add").alias("on"))
    own = Window.partitionBy("list", "pattern").orderBy("at")
    turns = one.withColumn("was", F.lag("on").over(own)).where(F.col("on") != F.coalesce("was", F.lit(False)))
    return turns.withColumn("until", F.lead("at").over(own)).where("on").select("list", "pattern", F.col("at").alias("since"), "until")


WINDOW_ROWS = 1 << 18  # captures that one window of a pattern takes


def judge(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", time_col: str = "fetched", window_rows: int = WINDOW_ROWS) -> DataFrame:
    """Every capture with the lists that were against it: ``(id_col, url_col, time_col, lists, blocked)``.

    Captures are counted by pattern first.  A pattern with more than ``window_rows`` of them is dealt among as many
    salts as that takes, its intervals copied to each, so a host with a third of all captures is spread however large
    it is; such patterns are few, at most one for every ``window_rows`` matches.  In a window an interval is found by
    the last start at or before the fetch, in one sorted pass.
    """
    rows = durable(captures.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(time_col).alias("at")))
    turns = intervals(entries)
    # every list turns at its own times, so a pattern's state is the set of its lists after each turn
    steps = turns.select("pattern", "list", F.col("since").alias("at"), F.lit(1).alias("way")).unionByName(turns.where("until is not null").select("pattern", "list", F.col("until").alias("at"), F.lit(-1).alias("way")))
    steps = durable(steps.groupBy("pattern", "list", "at").agg(F.sum("way").alias("way")).where("way <> 0"))
    known = steps.select("pattern").distinct()
    asks = rows.where("at is not null").select("row", "at", F.explode(patterns_of(F.col("url"), depth_of(entries))).alias("pattern"))
    # counted with partial sums before the shuffle, so a hot pattern is a row a task there
    heavy = durable(asks.groupBy("pattern").count().where(F.col("count") > window_rows).join(known, "pattern", "left_semi").select("pattern", F.ceil(F.col("count") / window_rows).cast("int").alias("salts")))
    few = F.broadcast(heavy)
    salt = F.coalesce(F.pmod(F.xxhash64("row"), F.col("salts")), F.lit(0)).cast("int")
    copies = F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1))
    side = steps.join(few, "pattern", "left").select("pattern", copies.alias("salt"), "at", F.lit(None).cast("long").alias("row"), "list", "way")
    asks = asks.join(few, "pattern", "left").select("pattern", salt.alias("salt"), "at", "row").join(side.select("pattern", "salt").distinct(), ["pattern", "salt"], "left_semi")
    both = side.unionByName(asks.select("pattern", "salt", "at", "row", F.lit(None).cast("string").alias("list"), F.lit(0).alias("way")))
    upto = Window.partitionBy("pattern", "salt").orderBy("at").rangeBetween(Window.unboundedPreceding, 0)
    lists = [r["list"] for r in entries.select("list").where("list is not null").distinct().orderBy("list").limit(MANY + 1).collect()]  # names of lists
    if len(lists) > MANY:
        raise ValueError(f"more than {MANY} lists; judge them in groups")
    for i, name in enumerate(lists):
        both = both.withColumn(f"on{i}", F.sum(F.when(F.col("list") == name, F.col("way")).otherwise(0)).over(upto))
    active = F.array_compact(F.array(*[F.when(F.col(f"on{i}") > 0, F.lit(name)) for i, name in enumerate(lists)])) if lists else F.array().cast("array<string>")
    hits = both.where("row is not null").select("row", F.explode(active).alias("list")).groupBy("row").agg(F.sort_array(F.collect_set("list")).alias("lists"))
    out = rows.join(hits, "row", "left").select(F.col("id").alias(id_col), F.col("url").alias(url_col), F.col("at").alias(time_col), F.coalesce("lists", F.array().cast("array<string>")).alias("lists"))
    return out.withColumn("blocked", F.size("lists") > 0)
