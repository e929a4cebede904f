"""Queries of the parsing methods, each with the SQL that it must equal."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import packed, symbols
from ..functions.dialect import DIALECTS, Dialect, compile_dialect
from ..operators import baselines, bitmaps, chunking, columnar, context, convert, offsets, tagging
from ..sources.files import durable, list_files, splits, spread
from ..sources.render import lines, rendered, write_lines
from ..streaming.slices import cut, parse_stream, parsed_rows
from . import measures
from .reader import aligned_ranges, read_delimited, seed_table, summary_table
from .workloads import fixture, frame, one_file, one_stream, parsed, parsed_frame, skewed_stream, split_size, table, text_of

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


TEXT9 = """SELECT d.doc_id, d.source, d.lang, d.n_chars, l.quality, l.toxic, (DATE '2015-01-01' + (d.doc_id % 1500)::INT)::DATE AS day,
       (d.n_chars / 100)::DECIMAL(10,2) AS score, d.text FROM documents d LEFT JOIN labels l USING (doc_id)"""
NUM17 = "SELECT l.*, o.* FROM lineitem l JOIN orders o ON l_orderkey = o_orderkey"
SOURCE = {"text9": TEXT9, "num17": NUM17}


def _round_trip(name: str, source: str, **options) -> None:
    Q[name] = lambda spark, sf_dir: parsed(spark, sf_dir, source, **options).df.select(*frame(spark, sf_dir, source).columns)
    SQL[name] = SOURCE.get(source, f"SELECT * FROM {source}")


@query("parse_documents_quoted", TEXT9.replace("::DATE AS day", "::DATE::VARCHAR AS day").replace("::DECIMAL(10,2) AS score", "::DECIMAL(10,2)::VARCHAR AS score"))
def _(spark, sf_dir):
    got = parsed(spark, sf_dir, "text9").df
    return got.select("doc_id", "source", "lang", "n_chars", "quality", "toxic", F.col("day").cast("string").alias("day"), F.col("score").cast("string").alias("score"), "text")


_round_trip("parse_conversations_quoted", "conversations")
_round_trip("parse_benchmark", "benchmark")
_round_trip("parse_pages", "pages")
_round_trip("parse_lineitem_orders_17", "num17")
_round_trip("parse_events_csv", "events")
_round_trip("parse_events_tsv", "events", sep="\t", dialect="tsv")
_round_trip("parse_events_pipe", "events", sep="|", dialect="pipe")
_round_trip("parse_events_unit", "events", sep="\x1f", dialect="unit")
_round_trip("parse_nation_crlf", "nation", dialect="rfc4180_crlf", line_sep="\r\n")
_round_trip("parse_embeddings_bracket", "embeddings", dialect="bracket_array")
_round_trip("parse_customer_hash_names", "customer")


@query("parse_region_trailing_no_newline", "SELECT * FROM region")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "region_nofinal", lambda s, d: bytes(text_of(s, d, "region").first()["data"])[:-1])
    return read_delimited(spark, path, schema=table(spark, sf_dir, "region").schema, split_bytes=17).df.select("r_regionkey", "r_name")


@query("parse_blank_lines", "SELECT * FROM nation")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "nation_blank", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]).replace(b"\n", b"\n\n"))
    return read_delimited(spark, path, dialect=Dialect(blank_lines="skip"), schema=table(spark, sf_dir, "nation").schema, split_bytes=101).df.select("n_nationkey", "n_name", "n_regionkey")


@query("parse_blank_line_records", "SELECT count(*)::BIGINT AS records, sum((n IS NULL)::INT)::BIGINT AS empty_records FROM (SELECT n_nationkey AS n FROM nation UNION ALL SELECT NULL FROM nation)")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "nation_blank", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]).replace(b"\n", b"\n\n"))
    got = read_delimited(spark, path, schema=table(spark, sf_dir, "nation").schema, split_bytes=101).df
    return got.agg(F.count("*").alias("records"), F.count_if(F.col("n_nationkey").isNull()).alias("empty_records"))


@query("parse_customer_comment_lines", "SELECT * FROM customer")
def _(spark, sf_dir):
    def make(s, d):
        rows = lines(table(s, d, "customer").orderBy("c_custkey"))
        noise = F.array(F.concat(F.lit('# an "odd, comment '), F.length("value").cast("string")), F.col("value"))
        return write_lines(rows.select(F.explode(noise).alias("value")), "comments")

    path = rendered(spark, sf_dir, "customer_comments", make)
    return read_delimited(spark, path, dialect="csv_comment", schema=table(spark, sf_dir, "customer").schema, split_bytes=split_size(spark, path)).df.select(*table(spark, sf_dir, "customer").columns)


@query("parse_events_common_log", "SELECT 'u' || user_id::VARCHAR AS host, ts, event_type AS request, value, event_id FROM events")
def _(spark, sf_dir):
    def make(s, d):
        e = table(s, d, "events").orderBy("event_id")
        return write_lines(e.select(F.format_string('u%d [%s] "%s" %s %d', "user_id", F.col("ts").cast("string"), "event_type", F.coalesce(F.col("value").cast("string"), F.lit("")), "event_id").alias("value")), "clf")

    path = rendered(spark, sf_dir, "events_clf", make)
    return read_delimited(spark, path, dialect="common_log", schema="host string, ts timestamp_ntz, request string, value double, event_id bigint", split_bytes=split_size(spark, path)).df.select("host", "ts", "request", "value", "event_id")


@query("parse_events_ext_log", "SELECT event_id, user_id, event_type, value FROM events")
def _(spark, sf_dir):
    def make(s, d):
        e = table(s, d, "events").orderBy("event_id")
        line = F.concat_ws(" ", F.col("event_id"), F.col("user_id"), F.concat(F.lit('"'), "event_type", F.lit('"')), F.coalesce(F.col("value").cast("string"), F.lit("")))
        directive = F.when(F.col("event_id") % 100 == 0, F.array(F.lit("#Fields: id user \"type value"), line)).otherwise(F.array(line))
        return write_lines(e.select(F.explode(directive).alias("value")), "elf")

    path = rendered(spark, sf_dir, "events_elf", make)
    return read_delimited(spark, path, dialect="ext_log", schema="event_id bigint, user_id bigint, event_type string, value double", split_bytes=split_size(spark, path)).df.select("event_id", "user_id", "event_type", "value")


@query("parse_backslash_escapes", "SELECT c_custkey, c_name || ', \"' || c_mktsegment || '\"' AS label FROM customer")
def _(spark, sf_dir):
    def make(s, d):
        c = table(s, d, "customer").orderBy("c_custkey")
        odd = F.concat(F.col("c_custkey").cast("string"), F.lit(',"'), "c_name", F.lit(', \\"'), "c_mktsegment", F.lit('\\""'))
        even = F.concat(F.col("c_custkey").cast("string"), F.lit(","), "c_name", F.lit('\\, \\"'), "c_mktsegment", F.lit('\\"'))
        return write_lines(c.select(F.when(F.col("c_custkey") % 2 == 1, odd).otherwise(even).alias("value")), "backslash")

    path = rendered(spark, sf_dir, "customer_backslash", make)
    return read_delimited(spark, path, dialect="csv_backslash", schema="c_custkey bigint, label string", split_bytes=split_size(spark, path)).df.select("c_custkey", "label")


@query("parse_trailing_delimiter", "SELECT s_suppkey, s_name, s_nationkey, s_acctbal FROM supplier")
def _(spark, sf_dir):
    path = rendered(spark, sf_dir, "supplier_trailing", lambda s, d: write_lines(lines(table(s, d, "supplier").orderBy("s_suppkey"), "|").select(F.concat("value", F.lit("|")).alias("value")), "trailing"))
    got = read_delimited(spark, path, dialect=DIALECTS["pipe"].with_(trailing_delimiter=True), schema=table(spark, sf_dir, "supplier").schema, on_ragged="fail", split_bytes=split_size(spark, path))
    return got.df.select("s_suppkey", "s_name", "s_nationkey", "s_acctbal")


def _utf16(endian: str):
    def make(s, d):
        rows = lines(table(s, d, "conversations").orderBy("conv_id", "turn"), quote=True)
        body = rows.agg(F.expr("listagg(value || '\\n') WITHIN GROUP (ORDER BY value)").alias("t")).first()["t"]
        return (body + '"-1","0","astral","a\U0001f600b"\n').encode(endian)

    return make


for _e, _n in (("utf-16-le", "utf16le"), ("utf-16-be", "utf16be")):

    @query(f"parse_{_n}", "SELECT * FROM conversations UNION ALL SELECT -1, 0, 'astral', 'a' || chr(128512) || 'b'")
    def _(spark, sf_dir, _e=_e, _n=_n):
        path = one_file(spark, sf_dir, _n, _utf16(_e))
        return read_delimited(spark, path, encoding=_n.replace("utf16", "utf-16"), schema=table(spark, sf_dir, "conversations").schema, split_bytes=split_size(spark, path) | 1).df.select("conv_id", "turn", "role", "text")


# --- the automaton and its scans -------------------------------------------------------------------------------------

RFC = compile_dialect("rfc4180")
LANE = 31


def _rendered_sql(name: str, columns: str) -> str:
    cells = " || ',' || ".join(f"'\"' || replace({c}::VARCHAR, '\"', '\"\"') || '\"'" for c in columns.split())
    return f"(SELECT string_agg({cells} || chr(10), '' ORDER BY {columns.split()[0]}) AS t FROM {name})"


NATION, REGION, BENCH = _rendered_sql("nation", "n_nationkey n_name n_regionkey"), _rendered_sql("region", "r_regionkey r_name"), _rendered_sql("benchmark", "item_id text")
_TRANS = "trans(s, c, n, e) AS (VALUES " + ", ".join(f"({s}, {c!r}, {int(RFC.table[RFC.group(c), s])}, {int(RFC.emit[RFC.group(c), s])})" for s in range(6) for c in ('"', ",", "x")) + ", " + ", ".join(f"({s}, chr(10), {int(RFC.table[0, s])}, {int(RFC.emit[0, s])})" for s in range(6)) + ")"
_CHARS = "chars AS (SELECT i, CASE WHEN substr(t, i + 1, 1) IN ('\"', ',', chr(10)) THEN substr(t, i + 1, 1) ELSE 'x' END AS c FROM {source} x, unnest(range(length(t))) AS u(i))"


def _walk(source: str) -> str:
    """Recursive SQL: ``run(i, s)`` is the state before character i, ``kind(i, e, s)`` the class of each."""
    return f"""WITH RECURSIVE {_TRANS}, {_CHARS.format(source=source)},
run(i, s) AS (SELECT 0::BIGINT, 0 UNION ALL SELECT run.i + 1, trans.n FROM run JOIN chars ON chars.i = run.i JOIN trans ON trans.s = run.s AND trans.c = chars.c),
kind AS (SELECT chars.i, trans.e, run.s FROM chars JOIN run ON run.i = chars.i JOIN trans ON trans.s = run.s AND trans.c = chars.c)"""


def _chunks(spark, sf_dir, name, lane=LANE):
    return chunking.split(text_of(spark, sf_dir, name), lane).withColumn("chunk", F.col("chunk").cast("long"))


@query("transition_table", "SELECT * FROM (VALUES ('LF',0,0),('LF',1,1),('LF',2,0),('LF',3,0),('LF',4,0),('LF',5,5),('QUOTE',0,1),('QUOTE',1,4),('QUOTE',2,5),('QUOTE',3,1),('QUOTE',4,1),('QUOTE',5,5),('COMMA',0,3),('COMMA',1,1),('COMMA',2,3),('COMMA',3,3),('COMMA',4,3),('COMMA',5,5),('OTHER',0,2),('OTHER',1,1),('OTHER',2,2),('OTHER',3,2),('OTHER',4,5),('OTHER',5,5)) t(symbol, state, next)")
def _(spark, sf_dir):
    names = ("LF", "QUOTE", "COMMA", "OTHER")
    return spark.createDataFrame([(names[g], s, n) for s, g, n, _ in RFC.rows()], "symbol string, state int, next int")


@query("transition_vectors_nation", f"""WITH RECURSIVE {_TRANS}, {_CHARS.format(source=NATION)},
w(chunk, s0, i, s) AS (SELECT DISTINCT i // {LANE}, trans.s, (i // {LANE}) * {LANE}, trans.s FROM chars, trans
  UNION ALL SELECT w.chunk, w.s0, w.i + 1, trans.n FROM w JOIN chars ON chars.i = w.i AND chars.i // {LANE} = w.chunk JOIN trans ON trans.s = w.s AND trans.c = chars.c)
SELECT chunk::BIGINT AS chunk, list(s ORDER BY s0) AS vector FROM (SELECT chunk, s0, arg_max(s, i) AS s FROM w GROUP BY ALL) GROUP BY chunk""")
def _(spark, sf_dir):
    return context.transition_vectors(_chunks(spark, sf_dir, "nation"), RFC).select("chunk", "vector")


Q["transition_vectors_expressions"] = lambda spark, sf_dir: _chunks(spark, sf_dir, "nation").select("chunk", context.transition_vector(F.col("data"), RFC).alias("vector"))
SQL["transition_vectors_expressions"] = SQL["transition_vectors_nation"]


def _starts(name: str, source: str, lane: int = LANE, fan: int = 8):
    @query(f"chunk_start_states_{name}", f"{_walk(source)} SELECT (i // {lane})::BIGINT AS chunk, s AS start_state FROM kind WHERE i % {lane} = 0")
    def _(spark, sf_dir):
        v = durable(context.transition_vectors(_chunks(spark, sf_dir, name, lane), RFC))
        return context.start_states(v, RFC, "file", "chunk", fan=fan).select("chunk", "start_state")


_starts("nation", NATION)
_starts("region", REGION, 7, 4)


_PARITY = f"""WITH x AS (SELECT encode(t) AS b FROM {BENCH}), c AS (SELECT i, b[i + 1:i + 1] = encode('"') AS q FROM x, unnest(range(octet_length(b))) AS u(i)),
p AS (SELECT i, coalesce(sum(q::INT) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) % 2 AS inside FROM c)
SELECT (i // 256)::BIGINT AS chunk, inside::INT AS inside FROM p WHERE i % 256 = 0"""


@query("chunk_start_states_benchmark", _PARITY)
def _(spark, sf_dir):
    v = durable(context.transition_vectors(_chunks(spark, sf_dir, "benchmark", 256), RFC))
    s = context.start_states(v, RFC, "file", "chunk", fan=8)
    return s.select("chunk", (F.col("start_state") == 1).cast("int").alias("inside"))


@query("context_parity_baseline", _PARITY)
def _(spark, sf_dir):
    return baselines.quote_parity(_chunks(spark, sf_dir, "benchmark", 256)).select("chunk", "inside")


@query("sequential_end_state", f"SELECT file, end_state FROM (SELECT 'nation' AS file, 0 AS end_state UNION ALL SELECT 'region', 0)")
def _(spark, sf_dir):
    both = text_of(spark, sf_dir, "nation").unionByName(text_of(spark, sf_dir, "region"))
    return both.select("file", context.run_sequential(F.col("data"), RFC).alias("end_state"))


@query("compose_packed_vectors", """SELECT a, b, count(*)::BIGINT AS orders, [(2 - a)::INT, ((a + b) % 3)::INT, b::INT] AS first, true AS equal
FROM (SELECT o_orderkey % 3 AS a, o_custkey % 3 AS b FROM orders) GROUP BY a, b""")
def _(spark, sf_dir):
    """Packed vectors composed for every order, from its keys."""
    n = table(spark, sf_dir, "orders").selectExpr("o_orderkey % 3 a", "o_custkey % 3 b").selectExpr("a", "b", "array(int(2 - a), int((a + b) % 3), int(b)) first", "array(int(b), int(2 - b), int(a)) second")
    plain = packed.pack_vector(context.compose(F.col("first"), F.col("second")), 3)
    equal = plain == packed.compose_packed(packed.pack_vector(F.col("first"), 3), packed.pack_vector(F.col("second"), 3), 3)
    return n.groupBy("a", "b", "first").agg(F.count("*").alias("orders"), F.bool_and(equal).alias("equal")).select("a", "b", "orders", "first", "equal")


def _mapped(spark, sf_dir, name, lane=LANE):
    chunks = _chunks(spark, sf_dir, name, lane)
    v = durable(context.transition_vectors(chunks, RFC))
    return durable(bitmaps.build(chunks.join(context.start_states(v, RFC, "file", "chunk", fan=8), ["file", "chunk"]), RFC))


@query("bitmaps_counts", f"{_walk(NATION)} SELECT (i // {LANE})::BIGINT AS chunk, sum((e = 2)::INT)::BIGINT AS records, sum((e = 1)::INT)::BIGINT AS fields, sum((e = 3)::INT)::BIGINT AS controls FROM kind GROUP BY 1")
def _(spark, sf_dir):
    return _mapped(spark, sf_dir, "nation").select("chunk", *[bitmaps.popcount(F.col(f"{m}_bm")).alias(n) for m, n in (("rec", "records"), ("fld", "fields"), ("ctl", "controls"))])


@query("record_offsets", f"{_walk(NATION)} SELECT (i // {LANE})::BIGINT AS chunk, r AS first_record FROM (SELECT i, coalesce(sum((e = 2)::INT) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS r FROM kind) WHERE i % {LANE} = 0")
def _(spark, sf_dir):
    return offsets.record_offsets(offsets.record_counts(_mapped(spark, sf_dir, "nation")), "file", "chunk", 4).select("chunk", "first_record")


@query("column_offsets", f"""{_walk(NATION)}, n AS (SELECT i, e, coalesce(sum((e = 2)::INT) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS r FROM kind)
SELECT (i // {LANE})::BIGINT AS chunk, c AS first_column FROM (SELECT i, coalesce(sum((e = 1)::INT) OVER (PARTITION BY r ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS c FROM n) WHERE i % {LANE} = 0""")
def _(spark, sf_dir):
    m = _mapped(spark, sf_dir, "nation")
    c = m.select("file", "chunk", offsets.column_contrib(F.col("rec_bm"), F.col("fld_bm"), F.col("size")).alias("contrib"))
    return offsets.column_offsets(durable(c), "file", "chunk", 4).select("chunk", "first_column")


def _seeded(spark, path, split_bytes, dfa=RFC):
    return durable(seed_table(summary_table(spread(splits(list_files(spark, path), split_bytes)), dfa), dfa, 8), "seeds")


@query("conditional_summary_seeds", "SELECT count(*)::BIGINT AS records, 9 AS min_columns, 9 AS max_columns, true AS ok FROM documents")
def _(spark, sf_dir):
    return parsed(spark, sf_dir, "text9", fan=3, driver_splits=0).report.groupBy().agg(F.sum("records").alias("records"), F.min("min_columns").alias("min_columns"), F.max("max_columns").alias("max_columns"), F.bool_and("ok").alias("ok"))


@query("scan_tree_equals_fold", f"""{_walk(NATION)}, n AS (SELECT i, s, e, coalesce(sum((e = 2)::INT) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS r FROM kind),
c AS (SELECT *, coalesce(sum((e = 1)::INT) OVER (PARTITION BY r ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS f FROM n)
SELECT way, (i // 23)::BIGINT AS split, s AS start_state, r AS first_record, f AS first_column FROM c, (VALUES ('tree'), ('fold')) w(way) WHERE i % 23 = 0""")
def _(spark, sf_dir):
    """Seeds of many small splits, from the distributed scan of conditional summaries and from the fold on the driver."""
    from .reader import seeds_of

    path = one_file(spark, sf_dir, "nation_plain", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]))
    ranges = splits(list_files(spark, path), 23)
    a, b = (seeds_of(ranges, RFC, fan=5, driver_splits=n)[0].select(F.lit(w).alias("way"), "split", "start_state", "first_record", "first_column") for w, n in (("tree", 0), ("fold", 10**6)))
    return a.unionByName(b)


@query("symbol_tags_region", """WITH f AS (SELECT r_regionkey AS r, 0 AS c, r_regionkey::VARCHAR AS t FROM region UNION ALL SELECT r_regionkey, 1, r_name FROM region)
SELECT r::BIGINT AS record_no, c AS column_no, i::INT AS nth, ascii(substr(t, i, 1)) AS symbol FROM f, unnest(range(1, length(t) + 1)) AS u(i)""")
def _(spark, sf_dir):
    chunks = _chunks(spark, sf_dir, "region", 7)
    v = durable(context.transition_vectors(chunks, RFC))
    starts = context.start_states(v, RFC, "file", "chunk", fan=4)
    m = durable(bitmaps.build(chunks.join(starts, ["file", "chunk"]), RFC))
    contrib = m.select("file", "chunk", offsets.column_contrib(F.col("rec_bm"), F.col("fld_bm"), F.col("size")).alias("contrib"))
    seeds = chunks.join(starts, ["file", "chunk"]).join(offsets.record_offsets(offsets.record_counts(m), "file", "chunk", 4), ["file", "chunk"]).join(offsets.column_offsets(durable(contrib), "file", "chunk", 4), ["file", "chunk"])
    tags = tagging.tag_symbols(seeds, RFC)
    from pyspark.sql import Window

    nth = F.row_number().over(Window.partitionBy("record_no", "column_no").orderBy("chunk", "pos"))
    return tags.select("record_no", "column_no", nth.alias("nth"), "symbol")


LI = "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split()
_LI_FIELDS = " UNION ALL ".join(f"SELECT r, {i} AS column_no, strlen({c}::VARCHAR)::BIGINT AS len FROM n" for i, c in enumerate(LI))
_LI = f"n AS (SELECT *, (row_number() OVER (ORDER BY {', '.join(LI)}) - 1)::BIGINT AS r FROM lineitem), f AS ({_LI_FIELDS})"


def _li_runs(spark, sf_dir):
    path = fixture(spark, sf_dir, "lineitem")
    return durable(tagging.tag_runs(spread(aligned_ranges(_seeded(spark, path, split_size(spark, path)))), RFC), "runs")


@query("tags_runs_lineitem", f"WITH {_LI} SELECT column_no, count(*)::BIGINT AS fields, sum(len)::BIGINT AS bytes, sum(hash_r)::BIGINT AS checksum FROM (SELECT column_no, len, (r % 1000) * len AS hash_r FROM f) GROUP BY 1")
def _(spark, sf_dir):
    """Record numbers count per file; with one rendered file they are the global ones."""
    return _one_stream(_li_runs(spark, sf_dir)).groupBy("column_no").agg(F.count("*").alias("fields"), F.sum("len").alias("bytes"), F.sum((F.col("record_no") % 1000) * F.col("len")).alias("checksum"))


def _one_stream(runs: DataFrame) -> DataFrame:
    """Records of several files numbered through, in file order."""
    from pyspark.sql import Window

    sizes = runs.groupBy("file").agg((F.max("record_no") + 1).alias("n"))
    before = Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)  # a row a file
    base = sizes.select("file", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return runs.join(F.broadcast(base), "file").withColumn("record_no", F.col("record_no") + F.col("base")).withColumn("file", F.lit("all"))


@query("css_histogram", f"WITH {_LI}, s AS (SELECT column_no, sum(len)::BIGINT AS bytes FROM f GROUP BY 1) SELECT column_no, bytes, coalesce(sum(bytes) OVER (ORDER BY column_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off FROM s")
def _(spark, sf_dir):
    return columnar.histogram(_one_stream(_li_runs(spark, sf_dir))).select("column_no", "bytes", "off")


_INDEX = f"WITH {_LI} SELECT column_no, r AS record_no, coalesce(sum(len) OVER (PARTITION BY column_no ORDER BY r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off, len FROM f"
for _mode in tagging.MODES:

    @query(f"field_index_{_mode}", _INDEX)
    def _(spark, sf_dir, _mode=_mode):
        path = one_stream(spark, sf_dir, "lineitem")
        ranges = spread(aligned_ranges(_seeded(spark, path, min(16 << 20, split_size(spark, path)))))  # a task's buffers go to Python at once
        return tagging.field_index(tagging.range_buffers(ranges, RFC, _mode), _mode).select("column_no", "record_no", "off", "len")

    Q[f"field_index_whole_{_mode}"], SQL[f"field_index_whole_{_mode}"] = Q[f"field_index_{_mode}"], _INDEX  # its name while the plain one kept three columns


@query("field_index_run_lengths", "WITH f AS (SELECT r_regionkey::BIGINT AS record_no, 1 AS column_no, strlen(r_name)::BIGINT AS len FROM region) SELECT column_no, record_no, coalesce(sum(len) OVER (ORDER BY record_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off, len FROM f")
def _(spark, sf_dir):
    tags = Q["symbol_tags_region"](spark, sf_dir).withColumn("file", F.lit("region"))
    return columnar.index_by_run_lengths(tags).where("column_no = 1").select("column_no", "record_no", "off", "len")


@query("css_contents", "SELECT 1 AS column_no, string_agg(r_name, '' ORDER BY r_regionkey) AS css FROM region UNION ALL SELECT 0, string_agg(r_regionkey::VARCHAR, '' ORDER BY r_regionkey) FROM region")
def _(spark, sf_dir):
    path = fixture(spark, sf_dir, "region")
    runs = _one_stream(tagging.tag_runs(aligned_ranges(_seeded(spark, path, 13)), RFC))
    return tagging.column_buffers(runs).select("column_no", F.decode("css", "UTF-8").alias("css"))


_ITEMS = "SELECT (l_partkey % 16)::BIGINT AS column_no, row_number() OVER (ORDER BY {k}) - 1 AS pos0 FROM lineitem".format(k=", ".join(LI))


def _items(spark, sf_dir):
    """Every record of lineitem at the number that the parse gave it."""
    part = _one_stream(_li_runs(spark, sf_dir).where("column_no = 1"))
    key = (F.decode("text", "UTF-8").cast("long") % 16).alias("column_no")
    return durable(part.select(key, F.col("record_no").alias("pos0"), F.col("record_no").alias("pos")), "items")


@query("radix_pass_stable", f"WITH i AS ({_ITEMS}) SELECT pos0::BIGINT AS pos0, column_no, (row_number() OVER (ORDER BY column_no & 3, pos0) - 1)::BIGINT AS pos FROM i")
def _(spark, sf_dir):
    return columnar.radix_pass(_items(spark, sf_dir), "column_no", "pos", 0, 2).select("pos0", "column_no", "pos")


@query("radix_partition_all_passes", f"WITH i AS ({_ITEMS}) SELECT pos0::BIGINT AS pos0, column_no, (row_number() OVER (ORDER BY column_no, pos0) - 1)::BIGINT AS pos FROM i")
def _(spark, sf_dir):
    return columnar.partition_by_column(_items(spark, sf_dir), bits=2, key_bits=4).select("pos0", "column_no", "pos")


for _n in ("radix_pass_stable", "radix_partition_all_passes"):  # their names while the plain ones kept a range of keys
    Q[f"{_n}_whole"], SQL[f"{_n}_whole"] = Q[_n], SQL[_n]


# --- conversion tiers, skew, capabilities ----------------------------------------------------------------------------


@query("skewed_record_parse", "SELECT doc_id, CASE WHEN doc_id = 0 THEN (SELECT string_agg(text, chr(10) ORDER BY doc_id) FROM documents WHERE doc_id % 3 = 1) ELSE text END AS text, lang FROM documents")
def _(spark, sf_dir):
    path = rendered(spark, sf_dir, "skew", skewed_stream)
    return read_delimited(spark, path, schema="doc_id bigint, text string, lang string", split_bytes=split_size(spark, path)).df.select("doc_id", "text", "lang")


@query("giant_number_fragments", "SELECT o_orderkey, (lpad(o_orderkey::VARCHAR, 12, '7') || lpad(o_custkey::VARCHAR, 12, '3'))::VARCHAR AS value FROM orders")
def _(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.concat(F.lpad(F.col("o_orderkey").cast("string"), 12, "7"), F.lpad(F.col("o_custkey").cast("string"), 12, "3")).alias("t"))
    pieces = F.transform(F.sequence(F.lit(0), F.lit(4)), lambda i: F.struct(i.alias("seq"), F.substring(F.col("t"), i * 5 + 1, F.lit(5)).alias("text")))
    return columnar.number_of_fragments(o.select("o_orderkey", F.explode(pieces).alias("p")).select("o_orderkey", "p.*"), ["o_orderkey"]).select("o_orderkey", F.col("value").cast("string").alias("value"))


@query("stitch_fragments", "SELECT doc_id AS record_no, text FROM documents")
def _(spark, sf_dir):
    b = table(spark, sf_dir, "documents").select("doc_id", F.col("text").cast("binary").alias("b"))
    n = F.greatest(F.ceil(F.octet_length("b") / 1000), F.lit(1)).cast("int")
    pieces = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.struct(i.alias("seq"), F.substring(F.col("b"), i * 1000 + 1, F.lit(1000)).alias("text")))
    frag = b.select(F.lit("f").alias("file"), F.col("doc_id").alias("record_no"), F.lit(0).alias("column_no"), F.explode(pieces).alias("p")).select("file", "record_no", "column_no", "p.*")
    return columnar.stitch(frag).select("record_no", F.decode("text", "UTF-8").alias("text"))


@query("conversion_tiers", "SELECT CASE WHEN n <= 2000 THEN 'exclusive' WHEN n <= 20000 THEN 'block' ELSE 'fragments' END AS tier, count(*)::BIGINT AS fields, sum(n)::BIGINT AS bytes FROM (SELECT strlen(text) AS n FROM documents) GROUP BY 1")
def _(spark, sf_dir):
    d = parsed_frame(spark, sf_dir, "documents").select(F.octet_length("text").cast("long").alias("n"))
    return d.groupBy(columnar.tier(F.col("n"), 2000, 20000).alias("tier")).agg(F.count("*").alias("fields"), F.sum("n").alias("bytes"))


def _ragged_path(spark, sf_dir):
    def make(s, d):
        c = table(s, d, "customer").orderBy("c_custkey")
        short = F.concat_ws(",", *[F.col(x).cast("string") for x in c.columns[:-1]])
        return write_lines(c.select(F.when(F.col("c_custkey") % 7 == 0, short).otherwise(F.concat(short, F.lit(","), F.col("c_mktsegment"))).alias("value")), "ragged")

    return rendered(spark, sf_dir, "customer_ragged", make)


def _ragged(spark, sf_dir, **options):
    path = _ragged_path(spark, sf_dir)
    return read_delimited(spark, path, schema=table(spark, sf_dir, "customer").schema, split_bytes=split_size(spark, path), **options)


@query("infer_column_count", "SELECT 4 AS min_columns, 5 AS max_columns, count(*)::BIGINT AS records FROM customer")
def _(spark, sf_dir):
    return _ragged(spark, sf_dir).report.agg(F.min("min_columns").alias("min_columns"), F.max("max_columns").alias("max_columns"), F.sum("records").alias("records"))


@query("keep_ragged", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, CASE WHEN c_custkey % 7 = 0 THEN NULL ELSE c_mktsegment END AS c_mktsegment FROM customer")
def _(spark, sf_dir):
    return _ragged(spark, sf_dir).df.select("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")


@query("reject_ragged", "SELECT * FROM customer WHERE c_custkey % 7 <> 0")
def _(spark, sf_dir):
    return _ragged(spark, sf_dir, on_ragged="reject").df.select("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")


@query("ragged_rejects_sink", "SELECT 'columns' AS reason, 4 AS columns_seen, count(*)::BIGINT AS n FROM customer WHERE c_custkey % 7 = 0")
def _(spark, sf_dir):
    return _ragged(spark, sf_dir, on_ragged="reject").rejects.groupBy("reason", "columns_seen").agg(F.count("*").alias("n"))


@query("surplus_fields", "SELECT c_custkey, [c_acctbal::VARCHAR, c_mktsegment] AS extra FROM customer WHERE c_custkey % 7 <> 0 AND c_custkey % 1 = 0")
def _(spark, sf_dir):
    path = _ragged_path(spark, sf_dir)
    got = read_delimited(spark, path, schema="c_custkey bigint, c_name string, c_nationkey int", split_bytes=split_size(spark, path)).df
    return got.where("c_custkey % 7 <> 0").select("c_custkey", F.array(F.element_at("_extra", 1).cast("double").cast("string"), F.element_at("_extra", 2)).alias("extra"))


@query("skip_rows", "SELECT * FROM events WHERE event_id >= (SELECT min(event_id) FROM events) + 1234 % (SELECT count(*) FROM events)")
def _(spark, sf_dir):
    n = 1234 % table(spark, sf_dir, "events").count()
    path = one_stream(spark, sf_dir, "events")
    return read_delimited(spark, path, schema=table(spark, sf_dir, "events").schema, skip_rows=n, split_bytes=split_size(spark, path)).df.select(*table(spark, sf_dir, "events").columns)


@query("skip_records", "SELECT doc_id, lang FROM documents WHERE doc_id >= (SELECT min(doc_id) FROM documents) + 50")
def _(spark, sf_dir):
    path = one_stream(spark, sf_dir, "documents")
    return read_delimited(spark, path, schema=table(spark, sf_dir, "documents").schema, columns=["doc_id", "lang"], skip_records=50, split_bytes=split_size(spark, path)).df.select("doc_id", "lang")


@query("select_columns", "SELECT l_orderkey, o_orderpriority, l_tax FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def _(spark, sf_dir):
    return parsed(spark, sf_dir, "num17", columns=["l_orderkey", "o_orderpriority", "l_tax"]).df.select("l_orderkey", "o_orderpriority", "l_tax")


@query("record_numbers", "SELECT doc_id, (row_number() OVER (ORDER BY doc_id) - 1)::BIGINT AS record_no FROM documents")
def _(spark, sf_dir):
    path = one_stream(spark, sf_dir, "documents")
    return read_delimited(spark, path, schema=table(spark, sf_dir, "documents").schema, columns=["doc_id"], split_bytes=split_size(spark, path)).df.select("doc_id", F.col("_record_no").alias("record_no"))


@query("defaults_constant", "SELECT doc_id, coalesce(quality, -1) AS quality, coalesce(toxic, 9) AS toxic FROM documents LEFT JOIN labels USING (doc_id)")
def _(spark, sf_dir):
    return parsed(spark, sf_dir, "text9", columns=["doc_id", "quality", "toxic"], defaults={"quality": -1, "toxic": 9}).df.select("doc_id", "quality", "toxic")


@query("defaults_ragged", "SELECT c_custkey, CASE WHEN c_custkey % 7 = 0 THEN 'NONE' ELSE c_mktsegment END AS c_mktsegment FROM customer")
def _(spark, sf_dir):
    return _ragged(spark, sf_dir, defaults={"c_mktsegment": "NONE"}).df.select("c_custkey", "c_mktsegment")


@query("null_values", "SELECT doc_id, nullif(lang, 'en') AS lang FROM documents")
def _(spark, sf_dir):
    return parsed(spark, sf_dir, "documents", columns=["doc_id", "lang"], null_values=("en",)).df.select("doc_id", "lang")


@query("null_versus_empty", "SELECT i, CASE i % 3 WHEN 0 THEN NULL WHEN 1 THEN '' ELSE 'x' END AS v FROM (SELECT l_orderkey % 300 AS i FROM lineitem GROUP BY 1)")
def _(spark, sf_dir):
    def make(s, d):
        i = table(s, d, "lineitem").selectExpr("l_orderkey % 300 as i").distinct().orderBy("i")
        return write_lines(i.selectExpr("concat(i, ',', case i % 3 when 0 then '' when 1 then '\"\"' else 'x' end) as value"), "empties")

    path = rendered(spark, sf_dir, "empties", make)
    return read_delimited(spark, path, schema="i bigint, v string", split_bytes=101).df.select("i", "v")


@query("infer_types", "SELECT * FROM (VALUES ('l_linenumber','tinyint'),('l_quantity','double'),('l_returnflag','string'),('l_shipdate','timestamp_ntz'),('l_suppkey', CASE WHEN (SELECT max(l_suppkey) FROM lineitem) <= 127 THEN 'tinyint' WHEN (SELECT max(l_suppkey) FROM lineitem) <= 32767 THEN 'smallint' ELSE 'int' END)) t(\"column\", type)")
def _(spark, sf_dir):
    names = ["l_linenumber", "l_quantity", "l_returnflag", "l_shipdate", "l_suppkey"]
    text = parsed(spark, sf_dir, "lineitem", schema=T.StructType([T.StructField(c, T.StringType()) for c in LI]), columns=names).df
    return convert.infer_types(text, names)


@query("cast_errors_sink", "SELECT 'value of c_name' AS reason, count(*)::BIGINT AS n FROM customer")
def _(spark, sf_dir):
    got = parsed(spark, sf_dir, "customer", schema="c_custkey bigint, c_name double, c_nationkey int, c_acctbal double, c_mktsegment string")
    return got.rejects.groupBy("reason").agg(F.count("*").alias("n"))


@query("validate_format_ok", "SELECT true AS ok, 'REC_START' AS end_state, (SELECT count(*) FROM documents)::BIGINT AS records")
def _(spark, sf_dir):
    return parsed(spark, sf_dir, "text9").report.agg(F.bool_and("ok").alias("ok"), F.max("end_state").alias("end_state"), F.sum("records").alias("records"))


@query("validate_format_bad", f"SELECT false AS ok, 'BAD' AS end_state, (length(t) + 3)::BIGINT AS first_bad_byte, 25::BIGINT AS first_bad_record FROM {NATION} x")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "nation_bad", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]) + b'1,a"b,2\n3,c,4\n')
    return read_delimited(spark, path, schema=table(spark, sf_dir, "nation").schema, split_bytes=97).report.select("ok", "end_state", "first_bad_byte", "first_bad_record")


@query("validate_format_unterminated", "SELECT false AS ok, 'QUOTED' AS end_state")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "nation_open", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]) + b'1,"open\n')
    return read_delimited(spark, path, schema=table(spark, sf_dir, "nation").schema, split_bytes=97).report.select("ok", "end_state")


@query("utf8_chunk_invariance", "SELECT k::INT AS lane, item_id, text FROM benchmark, (VALUES (1), (2), (3), (5), (7)) v(k)")
def _(spark, sf_dir):
    path, out = fixture(spark, sf_dir, "benchmark"), None
    for lane in (1, 2, 3, 5, 7):
        one = read_delimited(spark, path, schema=table(spark, sf_dir, "benchmark").schema, lane_bytes=lane, split_bytes=4096 + lane).df.select(F.lit(lane).alias("lane"), "item_id", "text")
        out = one if out is None else out.unionByName(one)
    return out


@query("utf8_chunk_edges", "SELECT item_id, length(text)::BIGINT AS points FROM benchmark")
def _(spark, sf_dir):
    """Code points counted in chunks of 7 bytes, each chunk owning the characters whose lead byte it holds."""
    data = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").cast("binary").alias("data"))
    lead = F.filter(F.sequence(F.lit(0), F.octet_length("data") - 1), lambda i: chunking.byte_at(F.col("data"), i).bitwiseAND(F.lit(0xC0)) != 0x80)
    return chunking.split(data, 7).groupBy("item_id").agg(F.sum(F.size(lead)).alias("points"))


_GROUPS = "CASE b WHEN 10 THEN 0 WHEN 34 THEN 1 WHEN 44 THEN 2 WHEN 124 THEN 2 WHEN 9 THEN 2 ELSE 3 END"


@query("swar_vs_lut_groups", f"SELECT b, {_GROUPS} AS swar, {_GROUPS} AS lut, {_GROUPS} AS ladder FROM (SELECT unnest(range(256)) AS b)")
def _(spark, sf_dir):
    import numpy as np

    syms, groups = [10, 34, 44, 124, 9], [0, 1, 2, 2, 2]
    lut = np.full(256, 3)
    lut[syms] = groups
    b = spark.range(256).select(F.col("id").alias("b"))
    return b.select("b", symbols.swar_group(F.col("b"), syms, groups, 3).alias("swar"), symbols.lut_group(F.col("b"), lut).alias("lut"), symbols.branching_group(F.col("b"), syms, groups, 3).alias("ladder"))


@query("packed_array_layout", "SELECT c::INT AS items, b::INT AS bits, (32 // c)::INT AS usable, (2 ** floor(log2(32 // c)))::INT AS width, ceil(b / (2 ** floor(log2(32 // c))))::INT AS registers FROM (SELECT unnest(range(1, 17)) AS c), (SELECT unnest(range(1, 9)) AS b)")
def _(spark, sf_dir):
    rows = [(x.items, x.bits, x.usable, x.width, x.registers) for c in range(1, 17) for b in range(1, 9) for x in [packed.layout(c, b)]]
    return spark.createDataFrame(rows, "items int, bits int, usable int, width int, registers int")


@query("packed_array_items", "SELECT i, (i * 7 + 3) % 32 AS item FROM (SELECT unnest(range(10)) AS i)")
def _(spark, sf_dir):
    lay, regs = packed.layout(10, 5), [0, 0, 0]
    for i in range(10):
        regs = packed.put(regs, lay, i, (i * 7 + 3) % 32)
    r = F.array(*[F.lit(x).cast("long") for x in regs])
    return spark.range(10).select(F.col("id").alias("i"), packed.get_column(r, lay, F.col("id")).alias("item"))


@query("custom_automaton", "SELECT 3::BIGINT AS records, 7::BIGINT AS fields")
def _(spark, sf_dir):
    """An odd format given as a table: fields end with ';', records with '!', and '^' hides the next byte."""
    from ..functions.dialect import Dfa

    dfa = Dfa.from_table(("START", "IN", "HIDE"), {";": 0, "!": 1, "^": 2}, [(0, 0, 1, 1), (1, 0, 1, 1), (2, 0, 1, 0), (0, 1, 0, 2), (1, 1, 0, 2), (2, 1, 1, 0), (0, 2, 2, 3), (1, 2, 2, 3), (2, 2, 1, 0), (0, 3, 1, 0), (1, 3, 1, 0), (2, 3, 1, 0)], ("START", "IN"), 3)
    path = one_file(spark, sf_dir, "custom", b"a;b^;b!c^!;d;e!f;g^^!")
    got = read_delimited(spark, path, dialect=dfa, schema="a string, b string, c string", split_bytes=4).df
    return got.agg(F.count("*").alias("records"), F.sum((F.col("a").isNotNull()).cast("long") + F.col("b").isNotNull().cast("long") + F.col("c").isNotNull().cast("long")).alias("fields"))


# --- baselines ---------------------------------------------------------------------------------------------------------


def _baseline(name: str, f, source: str = "documents"):
    def run(spark, sf_dir):
        path = fixture(spark, sf_dir, source)
        schema = frame(spark, sf_dir, source).schema
        return f(spark, path, schema, split_size(spark, path)).select(*schema.fieldNames())

    Q[f"baseline_{name}"] = run
    SQL[f"baseline_{name}"] = SOURCE.get(source, f"SELECT * FROM {source}")


_baseline("sequential", lambda s, p, t, n: baselines.sequential(s, p, t))
_baseline("prepass", lambda s, p, t, n: baselines.prepass(s, p, t, split_bytes=n))
_baseline("speculative", lambda s, p, t, n: baselines.speculative(s, p, t, split_bytes=n)[0])
_baseline("spark_csv", lambda s, p, t, n: baselines.spark_csv(s, p, t))
_baseline("single_node", lambda s, p, t, n: baselines.single_node(s, p, t))
_baseline("one_task_per_field", lambda s, p, t, n: baselines.one_task_per_field(s, p, t, split_bytes=n))
_baseline("bulk_then_parse", lambda s, p, t, n: baselines.bulk_then_parse(s, p, t))
_baseline("parallel_line_loader_numeric", lambda s, p, t, n: baselines.parallel_line_loader(s, p, t)[0], "lineitem")
_baseline("spark_csv_lines_numeric", lambda s, p, t, n: baselines.spark_csv(s, p, t, multiline=False), "lineitem")


@query("baseline_line_split_rows", "SELECT (count(*) + sum(length(text) - length(replace(text, chr(10), ''))))::BIGINT AS lines, count(*)::BIGINT AS records FROM documents")
def _(spark, sf_dir):
    got = baselines.line_split(spark, fixture(spark, sf_dir, "documents")).agg(F.count("*").alias("lines"))
    return got.crossJoin(parsed(spark, sf_dir, "documents").report.agg(F.sum("records").alias("records")))


@query("baseline_line_loader_fails", "SELECT 'text' AS input, true AS failed UNION ALL SELECT 'numeric', false")
def _(spark, sf_dir):
    out = []
    for name, source in (("text", "documents"), ("numeric", "lineitem")):
        failed = baselines.parallel_line_loader(spark, fixture(spark, sf_dir, source), frame(spark, sf_dir, source).schema)[1]
        out.append((name, failed > 0))
    return spark.createDataFrame(out, "input string, failed boolean")


@query("baseline_structural_bitmap", "SELECT count(*)::BIGINT AS records, (4 * count(*))::BIGINT AS delimiters FROM documents")
def _(spark, sf_dir):
    path = fixture(spark, sf_dir, "documents")
    return baselines.structural_bitmap(spark, path, split_size(spark, path)).agg(F.sum("records").alias("records"), F.sum("delimiters").alias("delimiters"))


@query("baseline_chained", f"{_walk(NATION)} SELECT (i // 90)::BIGINT AS split, s AS start_state FROM kind WHERE i % 90 = 0")
def _(spark, sf_dir):
    path = one_file(spark, sf_dir, "nation_plain", lambda s, d: bytes(text_of(s, d, "nation").first()["data"]))
    return baselines.chained(spark, path, split_bytes=90).select("split", "start_state")


@query("parity_fails_on_comments", """WITH t AS (SELECT repeat('# it"s' || chr(10), 3) || repeat('1,"a,b"' || chr(10), 20) AS t), c AS (SELECT i, substr(t, i + 1, 1) AS c FROM t, unnest(range(length(t))) AS u(i)),
p AS (SELECT i, coalesce(sum((c = '"')::INT) OVER w, 0) % 2 AS inside, coalesce(sum((c = '"' AND i >= 21)::INT) OVER w, 0) % 2 AS really FROM c WINDOW w AS (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT (i // 16)::BIGINT AS chunk, inside::INT AS inside, really::INT AS really, inside <> really AS misled FROM p WHERE i % 16 = 0""")
def _(spark, sf_dir):
    """Comments that hold a quote mislead the parity baseline; the automaton is not misled."""
    data = b'# it"s\n' * 3 + b'1,"a,b"\n' * 20
    dfa = compile_dialect("csv_comment")
    chunks = chunking.split(spark.createDataFrame([("f", bytearray(data))], "file string, data binary"), 16).withColumn("chunk", F.col("chunk").cast("long"))
    right = context.start_states(durable(context.transition_vectors(chunks, dfa)), dfa, "file", "chunk").select("chunk", (F.col("start_state") == 1).cast("int").alias("really"))
    return baselines.quote_parity(chunks).join(right, "chunk").select("chunk", "inside", "really", (F.col("inside") != F.col("really")).alias("misled"))


_baseline("coarse_split", lambda s, p, t, n: baselines.coarse_split(s, p, t))
_baseline("column_store_load", lambda s, p, t, n: baselines.column_store_load(s, p, t))


@query("skip_records_set", "SELECT doc_id, lang FROM (SELECT doc_id, lang, row_number() OVER (ORDER BY doc_id) - 1 AS r FROM documents) WHERE r NOT IN (0, 3, 4, 77, 150)")
def _(spark, sf_dir):
    path = one_stream(spark, sf_dir, "documents")
    return read_delimited(spark, path, schema=table(spark, sf_dir, "documents").schema, columns=["doc_id", "lang"], skip_records=(0, 3, 4, 77, 150), split_bytes=split_size(spark, path)).df.select("doc_id", "lang")


for _mode in (*tagging.MODES, "auto"):

    @query(f"parse_tagging_{_mode}", "SELECT * FROM documents")
    def _(spark, sf_dir, _mode=_mode):
        """The reader with fields found through column buffers in one of the tagging modes."""
        return parsed(spark, sf_dir, "documents", tagging=_mode).df.select(*table(spark, sf_dir, "documents").columns)


# --- streams and measures --------------------------------------------------------------------------------------------------


def _stream(spark, sf_dir, size=None, per=4):
    path = fixture(spark, sf_dir, "events")
    n = size or split_size(spark, path)
    slices = rendered(spark, sf_dir, f"slices|{n}", lambda s, d: cut(s, path, n))
    schema = table(spark, sf_dir, "events").schema
    out = rendered(spark, sf_dir, f"streamed|{n}|{per}", lambda s, d: parse_stream(s, slices, schema, files_per_batch=per))
    return parsed_rows(spark, out, schema), out


@query("stream_parse_events", "SELECT * FROM events")
def _(spark, sf_dir):
    return _stream(spark, sf_dir)[0].select(*table(spark, sf_dir, "events").columns)


@query("carry_over_invariance", "SELECT k AS parts, count(*)::BIGINT AS records, sum(event_id)::BIGINT AS ids FROM events, (VALUES (3), (7), (20)) v(k) GROUP BY 1")
def _(spark, sf_dir):
    total = list_files(spark, fixture(spark, sf_dir, "events")).agg(F.sum("size")).first()[0]
    out = None
    for k in (3, 7, 20):
        one = _stream(spark, sf_dir, int(total // k + 1), 3)[0].agg(F.lit(k).alias("parts"), F.count("*").alias("records"), F.sum("event_id").alias("ids"))
        out = one if out is None else out.unionByName(one)
    return out


@query("cost_profile", """SELECT 'num17' AS input, count(*)::BIGINT AS records, 17 AS columns FROM lineitem UNION ALL SELECT 'text9', count(*)::BIGINT, 9 FROM documents""")
def _(spark, sf_dir):
    return measures.profile(spark, {n: parsed(spark, sf_dir, n) for n in ("num17", "text9")}).select("input", "records", "columns")


@query("exactness", "SELECT input, 0::BIGINT AS differing_rows FROM (VALUES ('documents'), ('lineitem'), ('pages')) t(input)")
def _(spark, sf_dir):
    rows = [(n, measures.exactness(parsed_frame(spark, sf_dir, n), table(spark, sf_dir, n))) for n in ("documents", "lineitem", "pages")]
    return spark.createDataFrame(rows, "input string, differing_rows bigint")


@query("tag_memory", f"WITH {_LI}, s AS (SELECT count(*) AS n, sum(len) AS b FROM f) SELECT 'record_tags' AS mode, (4 * b)::BIGINT AS bytes FROM s UNION ALL SELECT 'inline', n::BIGINT FROM s UNION ALL SELECT 'vector', ((b + n + 7) // 8)::BIGINT FROM s")
def _(spark, sf_dir):
    one = _li_runs(spark, sf_dir).agg(F.count("*").alias("n"), F.sum("len").alias("b")).first()
    return spark.createDataFrame([(m, tagging.tag_bytes(one["n"], one["b"], m)) for m in tagging.MODES], "mode string, bytes bigint")


@query("tagging_choice", "SELECT * FROM (VALUES ('customer_ragged','record_tags'),('lineitem','inline'),('terminator_in_data','vector')) t(input, mode)")
def _(spark, sf_dir):
    out = []
    for name, path in (("customer_ragged", _ragged_path(spark, sf_dir)), ("lineitem", fixture(spark, sf_dir, "lineitem")), ("terminator_in_data", one_file(spark, sf_dir, "term", b'1,"a\x1fb"\n2,c\n'))):
        seeds = _seeded(spark, path, split_size(spark, path))
        from .reader import format_report

        r = format_report(seeds, RFC).agg(F.min("min_columns").alias("lo"), F.max("max_columns").alias("hi")).first()
        out.append((name, tagging.choose_tagging(r["lo"], r["hi"], tagging.check_terminator(tagging.tag_runs(aligned_ranges(seeds), RFC)))))
    return spark.createDataFrame(out, "input string, mode string")


