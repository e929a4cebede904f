"""Relational operators over parsed frames: each query also shows that parsed text behaves like the native table.

A query is SQL over ``{name}`` placeholders, run by Spark on frames parsed back from rendered text and by the oracle
on the given tables; where the two dialects differ, both texts are given.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import symbols
from ..sources.files import durable
from .parse_queries import _CHARS, _TRANS, NATION, NUM17, TEXT9
from .workloads import parsed_frame

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
VIEWS = {"num17": f"({NUM17})", "text9": f"({TEXT9})"}
NAMES = "region nation customer supplier part orders lineitem events documents labels pages benchmark conversations embeddings num17 text9".split()


def rel(name: str, sql: str, oracle: str | None = None) -> None:
    used = [n for n in NAMES if "{" + n + "}" in sql]
    Q[name] = lambda spark, sf_dir: spark.sql(sql, **{n: parsed_frame(spark, sf_dir, n) for n in used})
    text = oracle or sql
    for n in NAMES:
        text = text.replace("{" + n + "}", VIEWS.get(n, n))
    SQL[name] = text


def frames(name: str, oracle: str):
    def put(f):
        Q[name] = f
        SQL[name] = oracle
        return f

    return put


rel("r_scan_project", "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice * (1 - l_discount) AS price, l_extendedprice * (1 - l_discount) * (1 + l_tax) AS charge FROM {num17} n")
rel("r_filter_range", "SELECT l_orderkey, l_partkey, l_quantity FROM {num17} n WHERE l_quantity >= 10 AND l_quantity < 25 AND l_discount BETWEEN 0.02 AND 0.06 AND o_totalprice > 1000")
rel("r_filter_in", "SELECT doc_id, lang FROM {text9} t WHERE lang IN ('fr', 'de') AND source NOT IN ('src0', 'src1')")
rel("r_filter_like", "SELECT doc_id FROM {text9} t WHERE text LIKE '%the%' AND source LIKE 'src1_'")
rel("r_filter_null", "SELECT doc_id, quality IS NULL AS unknown, quality IS NOT DISTINCT FROM toxic AS same FROM {text9} t WHERE quality IS NULL OR toxic = 0")
rel("r_join_broadcast", "SELECT /*+ BROADCAST(n, r) */ s_suppkey, s_name, n_name, r_name FROM {supplier} s JOIN {nation} n ON s_nationkey = n_nationkey JOIN {region} r ON n_regionkey = r_regionkey")
for _h in ("SHUFFLE_HASH", "MERGE"):
    rel(f"r_join_{_h.lower()}", f"SELECT /*+ {_h}(l, o) */ l_orderkey, l_partkey, l_linenumber, l_suppkey, o_custkey, o_orderpriority FROM {{lineitem}} l JOIN {{orders}} o ON l_orderkey = o_orderkey")
rel("r_join_left", "SELECT d.doc_id, lang, quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")
rel("r_join_right", "SELECT l.doc_id, lang, quality FROM (SELECT * FROM {documents} x WHERE lang = 'en') d RIGHT JOIN {labels} l ON d.doc_id = l.doc_id")
rel("r_join_full", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.lang, l.quality FROM (SELECT * FROM {documents} x WHERE lang = 'en') d FULL OUTER JOIN (SELECT * FROM {labels} y WHERE quality = 1) l ON d.doc_id = l.doc_id")
rel("r_join_semi", "SELECT doc_id, source FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)")
rel("r_join_anti", "SELECT doc_id, source FROM {documents} d WHERE NOT EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)")
rel("r_join_theta", "SELECT s_suppkey, count(*) AS cheaper FROM {supplier} s JOIN {part} p ON p_retailprice < s_acctbal / 4 GROUP BY s_suppkey")
rel("r_join_range", """WITH f AS (SELECT user_id, min(ts) AS t0 FROM {events} e WHERE event_type = 'error' GROUP BY user_id)
SELECT e.user_id, e.event_id FROM {events} e JOIN f ON e.user_id = f.user_id AND e.ts >= f.t0 AND e.ts <= f.t0 + INTERVAL '1' HOUR""")
rel("r_join_cross", "SELECT r_name, event_type FROM {region} r CROSS JOIN (SELECT DISTINCT event_type FROM {events} e) t")
rel("r_join_lateral", "SELECT item_id, w FROM {benchmark} b LATERAL VIEW explode(split(text, '[ \\n]+')) v AS w", "SELECT item_id, unnest(string_split_regex(text, '[ \\n]+')) AS w FROM {benchmark} b")
_PRICE, _CUT = "CAST(l_extendedprice AS DECIMAL(15,2))", "CAST(l_discount AS DECIMAL(4,2))"  # sums of decimals are the same in any order
rel("r_agg_hash", f"SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, CAST(sum({_PRICE}) AS DOUBLE) AS sum_base, CAST(sum({_PRICE} * (1 - {_CUT})) AS DOUBLE) AS sum_disc, round(CAST(sum({_CUT}) AS DOUBLE) / count(*), 6) AS avg_disc, count(*) AS n FROM {{num17}} x WHERE l_shipdate <= TIMESTAMP '1998-09-02 00:00:00' GROUP BY l_returnflag, l_linestatus")
rel("r_agg_sort", "SELECT conv_id, concat_ws(',', transform(array_sort(collect_list(struct(turn, role))), x -> x.role)) AS roles, count(*) AS n FROM {conversations} c GROUP BY conv_id", "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles, count(*) AS n FROM {conversations} c GROUP BY conv_id")
rel("r_agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers, count(DISTINCT l_suppkey) AS suppliers FROM {num17} n GROUP BY o_orderpriority")
for _n, _g in (("rollup", "ROLLUP (source, lang)"), ("cube", "CUBE (source, lang)"), ("gsets", "GROUPING SETS ((source), (lang), ())")):
    rel(f"r_agg_{_n}", f"SELECT source, lang, CAST(grouping(source) AS BIGINT) AS gs, CAST(grouping(lang) AS BIGINT) AS gl, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM {{text9}} t GROUP BY {_g}")
rel("r_agg_filter", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, sum(value) FILTER (WHERE event_type = 'purchase') AS bought FROM {events} e GROUP BY user_id", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, round(sum(value) FILTER (WHERE event_type = 'purchase'), 4) AS bought FROM {events} e GROUP BY user_id")
Q["r_agg_filter"] = lambda spark, sf_dir: spark.sql("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, round(sum(value) FILTER (WHERE event_type = 'purchase'), 4) AS bought FROM {events} e GROUP BY user_id", events=parsed_frame(spark, sf_dir, "events"))
rel("r_agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c, percentile(l_extendedprice, 0.5) AS med, min_by(l_orderkey, struct(l_extendedprice, l_orderkey)) AS least, max_by(l_orderkey, struct(l_extendedprice, l_orderkey)) AS most FROM {num17} n GROUP BY l_returnflag",
    "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c, quantile_cont(l_extendedprice, 0.5) AS med, arg_min(l_orderkey, (l_extendedprice, l_orderkey)) AS least, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS most FROM {num17} n GROUP BY l_returnflag")


@frames("r_agg_approx", f"SELECT count(DISTINCT l_partkey) AS parts, true AS parts_within, true AS median_within FROM ({NUM17}) n")
def _(spark, sf_dir):
    """Approximate aggregates within their bounds: three deviations of 5 % for the count, a rank error of 1 in 1,000 for the median."""
    n = parsed_frame(spark, sf_dir, "num17")
    got = n.agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey").alias("about"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("median"))
    low, high = F.count_if(F.col("l_extendedprice") < F.col("median")), F.count_if(F.col("l_extendedprice") <= F.col("median"))
    rank = n.select("l_extendedprice").crossJoin(F.broadcast(got)).groupBy("parts", "about").agg((low / F.count("*")).alias("low"), (high / F.count("*")).alias("high"))  # one row beside the table
    return rank.select("parts", (F.abs(F.col("about") - F.col("parts")) <= 0.15 * F.col("parts")).alias("parts_within"), ((F.col("low") <= 0.501) & (F.col("high") >= 0.499)).alias("median_within"))


rel("r_win_rank", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER w AS n, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS p FROM {orders} o WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)")
rel("r_win_lag", "SELECT event_id, CAST(unix_micros(CAST(ts AS TIMESTAMP)) - unix_micros(CAST(lag(ts) OVER w AS TIMESTAMP)) AS BIGINT) AS gap, lead(event_type) OVER w AS nxt FROM {events} e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "SELECT event_id, (epoch_us(ts) - epoch_us(lag(ts) OVER w))::BIGINT AS gap, lead(event_type) OVER w AS nxt FROM {events} e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
rel("r_win_frame_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS total, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS smooth FROM {events} e")
rel("r_win_frame_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY unix_seconds(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM {events} e", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch_us(ts) / 1000000)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM {events} e")
rel("r_win_first_last", "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS s FROM {events} e WINDOW w AS (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
rel("r_topk", "SELECT doc_id, n FROM (SELECT doc_id, octet_length(text) AS n FROM {text9} t) x ORDER BY n DESC, doc_id LIMIT 25", "SELECT doc_id, strlen(text)::INT AS n FROM {text9} t ORDER BY n DESC, doc_id LIMIT 25")
rel("r_topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM {orders} o) x WHERE n <= 3")
rel("r_limit_offset", "SELECT o_orderkey FROM {orders} o ORDER BY o_orderkey LIMIT 50 OFFSET 100")
_A, _B = "SELECT l_suppkey AS k FROM {lineitem} a WHERE l_quantity > 49", "SELECT l_suppkey AS k FROM {lineitem} b WHERE l_discount > 0.09"
for _n in ("UNION", "UNION ALL", "INTERSECT", "INTERSECT ALL", "EXCEPT", "EXCEPT ALL"):
    rel(f"r_{_n.lower().replace(' ', '_')}", f"{_A} {_n} {_B}")
rel("r_dedup", "SELECT DISTINCT text FROM {documents} d")
rel("r_subquery_scalar", "SELECT o_orderkey, (SELECT max(c_acctbal) FROM {customer} c WHERE c.c_custkey = o.o_custkey) AS bal FROM {orders} o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders} p)")
rel("r_subquery_correlated", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders} p WHERE p.o_custkey = o.o_custkey)")
rel("r_cte", "WITH a AS (SELECT o_custkey, sum(o_totalprice) AS t FROM {orders} o GROUP BY o_custkey), b AS (SELECT o_custkey FROM a WHERE t > 100000) SELECT c_custkey, c_name FROM {customer} c JOIN b ON c_custkey = o_custkey")
rel("r_str", "SELECT doc_id, upper(source) AS u, substring(text, 1, 10) AS head, length(text) AS chars, octet_length(text) AS bytes, lpad(lang, 5, '*') AS p, trim(concat('  ', lang, ' ')) AS t, replace(source, 'src', 'S') AS r, regexp_extract(source, '([0-9]+)', 1) AS d, size(split(text, ' ')) AS parts FROM {text9} t",
    "SELECT doc_id, upper(source) AS u, substring(text, 1, 10) AS head, length(text)::INT AS chars, strlen(text)::INT AS bytes, lpad(lang, 5, '*') AS p, trim(concat('  ', lang, ' ')) AS t, replace(source, 'src', 'S') AS r, regexp_extract(source, '([0-9]+)', 1) AS d, len(string_split(text, ' '))::INT AS parts FROM {text9} t")
rel("r_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS STRING) AS m, year(o_orderdate) AS y, month(o_orderdate) AS mo, day(o_orderdate) AS d, datediff(o_orderdate, DATE '1992-01-01') AS n, CAST(add_months(o_orderdate, 1) AS STRING) AS nxt FROM {orders} o",
    "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP::VARCHAR AS m, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS mo, day(o_orderdate)::INT AS d, (o_orderdate::DATE - DATE '1992-01-01')::INT AS n, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE::VARCHAR AS nxt FROM {orders} o")
rel("r_math", "SELECT l_orderkey, l_partkey, l_orderkey % 7 AS m, round(power(l_tax + 1, 3), 6) AS p, round(ln(l_quantity + 1), 6) AS g, CAST(floor(l_extendedprice) AS BIGINT) AS f, CAST(ceil(l_extendedprice) AS BIGINT) AS c, greatest(l_discount, l_tax) AS hi, least(l_discount, l_tax) AS lo FROM {num17} n")
rel("r_array", "SELECT vec_id, size(embedding) AS n, round(aggregate(embedding, 0D, (a, x) -> a + x), 4) AS s, round(sqrt(aggregate(embedding, 0D, (a, x) -> a + x * x)), 4) AS norm, slice(array_sort(embedding), 1, 2) AS least FROM {embeddings} e",
    "SELECT vec_id, len(embedding)::INT AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 4) AS s, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 4) AS norm, list_sort(embedding)[1:2] AS least FROM {embeddings} e")
Q["r_array"] = lambda spark, sf_dir: spark.sql("SELECT vec_id, size(embedding) AS n, round(aggregate(embedding, 0D, (a, x) -> a + double(x)), 4) AS s, round(sqrt(aggregate(embedding, 0D, (a, x) -> a + double(x) * x)), 4) AS norm, slice(array_sort(embedding), 1, 2) AS least FROM {embeddings} e", embeddings=parsed_frame(spark, sf_dir, "embeddings"))
rel("r_array_explode", "SELECT vec_id, pos, x FROM {embeddings} e LATERAL VIEW posexplode(embedding) v AS pos, x", "SELECT vec_id, (i - 1)::INT AS pos, embedding[i] AS x FROM {embeddings} e, unnest(range(1, len(embedding) + 1)) AS u(i)")
rel("r_map", "SELECT user_id, element_at(map_from_entries(collect_list(struct(event_type, n))), 'click') AS clicks, sum(n) AS n FROM (SELECT user_id, event_type, count(*) AS n FROM {events} e GROUP BY user_id, event_type) x GROUP BY user_id", "SELECT user_id, max(n) FILTER (WHERE event_type = 'click') AS clicks, sum(n)::BIGINT AS n FROM (SELECT user_id, event_type, count(*) AS n FROM {events} e GROUP BY user_id, event_type) x GROUP BY user_id")
rel("r_struct", "SELECT o_orderkey, l.n AS n, round(l.q, 2) AS q FROM (SELECT o_orderkey, struct(count(*) AS n, sum(l_quantity) AS q) AS l FROM {num17} x GROUP BY o_orderkey) y", "SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM {num17} x GROUP BY o_orderkey")
rel("r_json", "SELECT event_type, sum(CAST(get_json_object(props, '$.k') AS BIGINT)) AS k, sum(from_json(props, 'k INT').k) AS k2, count(*) AS n FROM {events} e GROUP BY event_type", "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k, sum((props->>'$.k')::INT)::BIGINT AS k2, count(*) AS n FROM {events} e GROUP BY event_type")
rel("r_json_variant", "SELECT event_id, variant_get(parse_json(props), '$.k', 'int') AS k FROM {events} e", "SELECT event_id, (props->>'$.k')::INT AS k FROM {events} e")
rel("r_url", "SELECT page_id, parse_url(url, 'HOST') AS host, parse_url(url, 'PATH') AS path, coalesce(parse_url(url, 'QUERY', 'utm_source'), '') AS utm FROM {pages} p", "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) AS path, regexp_extract(url, 'utm_source=([^&#]*)', 1) AS utm FROM {pages} p")
rel("r_cast_matrix", "SELECT v, try_cast(v AS TINYINT) AS i8, try_cast(v AS INT) AS i32, try_cast(v AS BIGINT) AS i64, try_cast(v AS DOUBLE) AS f, CAST(try_cast(v AS DATE) AS STRING) AS d FROM (VALUES ('1'), ('127'), ('128'), ('2147483648'), ('9223372036854775807'), ('9223372036854775808'), ('1.5'), ('x'), ('2020-02-29'), ('2021-02-29')) t(v)",
    "SELECT * FROM (VALUES ('1', 1, 1, 1, 1.0, NULL), ('127', 127, 127, 127, 127.0, NULL), ('128', NULL, 128, 128, 128.0, NULL), ('2147483648', NULL, NULL, 2147483648, 2147483648.0, NULL), ('9223372036854775807', NULL, NULL, 9223372036854775807, 9223372036854775807.0, NULL), ('9223372036854775808', NULL, NULL, NULL, 9223372036854775808.0, NULL), ('1.5', NULL, NULL, NULL, 1.5, NULL), ('x', NULL, NULL, NULL, NULL, NULL), ('2020-02-29', NULL, NULL, NULL, NULL, '2020-02-29'), ('2021-02-29', NULL, NULL, NULL, NULL, NULL)) t(v, i8, i32, i64, f, d)")
SQL["r_cast_matrix"] = "SELECT v, i8::TINYINT AS i8, i32::INT AS i32, i64::BIGINT AS i64, f::DOUBLE AS f, d FROM (" + SQL["r_cast_matrix"] + ")"


@frames("r_partition_pruned", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem WHERE l_returnflag = 'R'")
def _(spark, sf_dir):
    from ..sources.files import fresh_path

    path = fresh_path(spark, "bulk")
    parsed_frame(spark, sf_dir, "num17").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    return spark.read.parquet(path).where("l_returnflag = 'R'").drop("l_returnflag")


@frames("r_join_bucketed", "SELECT o_orderpriority, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, sf_dir):
    """Both sides bulk-loaded into tables bucketed by the order key, so the join needs no exchange."""
    import uuid

    tag = uuid.uuid4().hex[:8]
    parsed_frame(spark, sf_dir, "lineitem").select("l_orderkey").write.bucketBy(8, "l_orderkey").sortBy("l_orderkey").saveAsTable(f"bucketed_l_{tag}")
    parsed_frame(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority").write.bucketBy(8, "o_orderkey").sortBy("o_orderkey").saveAsTable(f"bucketed_o_{tag}")
    return spark.table(f"bucketed_l_{tag}").join(spark.table(f"bucketed_o_{tag}").hint("merge"), F.expr("l_orderkey = o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


_ASOF = "SELECT event_id, (SELECT max(struct_pack(ts := v.ts, event_id := v.event_id)).event_id FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'view' AND (v.ts, v.event_id) < (e.ts, e.event_id)) AS view_id FROM events e WHERE event_type = 'purchase'"


@frames("r_join_asof", _ASOF)
def _(spark, sf_dir):
    own = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(own)
    return parsed_frame(spark, sf_dir, "events").withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", "view_id")


@frames("r_agg_pivot", "SELECT ts::DATE::VARCHAR AS d, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in ("click", "view", "purchase")) + " FROM events WHERE event_type IN ('click', 'view', 'purchase') GROUP BY 1")
def _(spark, sf_dir):
    kinds = ["click", "view", "purchase"]
    e = parsed_frame(spark, sf_dir, "events").where(F.col("event_type").isin(*kinds)).withColumn("d", F.col("ts").cast("date").cast("string"))
    return e.groupBy("d").pivot("event_type", kinds).count().na.fill(0, kinds)


@frames("r_sort_multi", "SELECT doc_id, (row_number() OVER (ORDER BY quality NULLS LAST, lang DESC, doc_id))::INT AS n FROM documents LEFT JOIN labels USING (doc_id)")
def _(spark, sf_dir):
    """A total order by a range-partitioned sort: rows are numbered from partition counts, never in one task."""
    t = parsed_frame(spark, sf_dir, "text9").select("doc_id", "lang", "quality")
    order = [F.asc_nulls_last("quality"), F.desc("lang"), F.asc("doc_id")]
    s = durable(t.repartitionByRange(8, *order).sortWithinPartitions(*order).withColumn("p", F.spark_partition_id()).withColumn("i", F.monotonically_increasing_id()))
    base = s.groupBy("p").agg(F.count("*").alias("c"), F.min("i").alias("i0")).withColumn("b", F.coalesce(F.sum("c").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return s.join(F.broadcast(base), "p").select("doc_id", (F.col("b") + F.col("i") - F.col("i0") + 1).cast("int").alias("n"))


@frames("r_csv_fn", "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders")
def _(spark, sf_dir):
    """``from_csv`` agrees with the engine where no field holds a line break."""
    from .workloads import fixture

    kind = "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate STRING, o_orderpriority STRING"
    return spark.read.text(fixture(spark, sf_dir, "orders")).select(F.from_csv("value", kind).alias("r")).select("r.o_orderkey", "r.o_custkey", "r.o_orderstatus")


@frames("r_udf_scalar", "SELECT n_nationkey, ascii(n_name) AS b, CASE ascii(n_name) WHEN 65 THEN 0 WHEN 73 THEN 1 ELSE 2 END AS g FROM nation")
def _(spark, sf_dir):
    @F.arrow_udf("int")
    def group(b: pa.Array) -> pa.Array:
        return pc.if_else(pc.equal(b, 65), pa.scalar(0, pa.int32()), pc.if_else(pc.equal(b, 73), pa.scalar(1, pa.int32()), pa.scalar(2, pa.int32())))

    n = parsed_frame(spark, sf_dir, "nation").select("n_nationkey", F.ascii("n_name").alias("b"))
    return n.select("n_nationkey", "b", group("b").alias("g")).where(F.col("g") == symbols.swar_group(F.col("b"), [65, 73], [0, 1], 2))


_UDAF = f"""WITH RECURSIVE {_TRANS}, {_CHARS.format(source=NATION)},
w(s0, i, s) AS (SELECT DISTINCT trans.s, 0::BIGINT, trans.s FROM trans UNION ALL SELECT w.s0, w.i + 1, trans.n FROM w JOIN chars ON chars.i = w.i JOIN trans ON trans.s = w.s AND trans.c = chars.c)
SELECT 'nation' AS file, sum(s << (4 * s0))::BIGINT AS vector FROM (SELECT s0, arg_max(s, i) AS s FROM w GROUP BY s0)"""


@frames("r_udaf", _UDAF)
def _(spark, sf_dir):
    """Composition of a file's chunk vectors as a grouped aggregate."""
    from ..functions.dialect import compile_dialect
    from ..operators import chunking, context
    from .workloads import text_of

    dfa = compile_dialect("rfc4180")

    @F.pandas_udf("long")
    def compose_all(n: pd.Series, v: pd.Series) -> int:
        out = list(range(dfa.n_states))
        for x in v.iloc[n.argsort(kind="stable")]:
            out = [int(x[s]) for s in out]
        return sum(s << (4 * i) for i, s in enumerate(out))

    v = context.transition_vectors(chunking.split(text_of(spark, sf_dir, "nation"), 31), dfa)
    return v.groupBy("file").agg(compose_all("chunk", "vector").alias("vector"))


@frames("r_udtf", "SELECT r_regionkey AS k, c AS column_no, CASE c WHEN 0 THEN r_regionkey::VARCHAR ELSE r_name END AS text FROM region, (VALUES (0), (1)) v(c)")
def _(spark, sf_dir):
    """A table function from text to fields, called laterally from SQL."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="record_no int, column_no int, text string")
    class ParseText:
        def eval(self, data: str):
            import numpy as np

            from delimscan.functions.dialect import compile_dialect
            from delimscan.operators.kernel import parse_block

            p = parse_block(np.frombuffer(data.encode(), np.uint8), compile_dialect("rfc4180"), final=True)
            raw, lo = p.text.tobytes(), 0
            for r, hi in enumerate(p.ends.tolist()):
                for c, f in enumerate(range(lo, hi)):
                    yield r, c, raw[p.offsets[f] : p.offsets[f + 1]].decode()
                lo = hi

    spark.udtf.register("parse_text", ParseText)
    rows = parsed_frame(spark, sf_dir, "region").selectExpr("r_regionkey as k", "concat(r_regionkey, ',\"', r_name, '\"') as line")
    return spark.sql("SELECT r.k, t.column_no, t.text FROM {rows} r, LATERAL parse_text(r.line) t", rows=rows)
