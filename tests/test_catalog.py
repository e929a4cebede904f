"""Registered queries against their SQL on the smallest tables (a spread of them; the driver runs all)."""

import datetime
import decimal

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = [
    "parse_conversations_quoted", "parse_lineitem_orders_17", "parse_nation_crlf", "parse_region_trailing_no_newline", "parse_customer_comment_lines", "parse_events_common_log", "parse_utf16le",
    "transition_vectors_nation", "chunk_start_states_nation", "record_offsets", "column_offsets", "symbol_tags_region", "field_index_inline", "radix_pass_stable", "infer_column_count", "reject_ragged",
    "validate_format_bad", "swar_vs_lut_groups", "packed_array_layout", "baseline_line_split_rows", "r_agg_hash", "r_join_asof", "r_win_rank", "r_udaf", "stream_window_tumbling",
]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def plain(x):
    if x is None or x is pd.NaT or x is pd.NA or (isinstance(x, float) and x != x):
        return None
    if isinstance(x, (list, tuple)) or hasattr(x, "tolist") and getattr(x, "ndim", 0):
        return tuple(map(plain, x))
    if isinstance(x, bool):
        return x
    if isinstance(x, (int, float, decimal.Decimal)) or hasattr(x, "item"):
        return round(float(x), 6)
    return str(pd.Timestamp(x)) if isinstance(x, (datetime.date, pd.Timestamp)) else x


def rows(df):
    return sorted((tuple(map(plain, r)) for r in df[sorted(df.columns)].astype(object).itertuples(index=False)), key=repr)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, small, duck, name):
    got, want = entry.queries()[name](spark, small).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
