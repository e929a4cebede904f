"""The registered queries of the training-data operators, with production parameters, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import cascade, cotrain, curve_ann, hash_tree, html_text, packing, piece_codec, simhash, token_files, url_lists


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.codec_digest(_table(spark, sf_dir, "documents"), _vocabulary("piece_bpe_32k.model"))


def op2_curve_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curve_ann.search(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, k=20)


def op3_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op4_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract_text(_table(spark, sf_dir, "pages"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_table(spark, sf_dir, "documents"), _vocabulary("word_bpe_49k.json"), end_id=1, capacity=2048)


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = token_files.new_folder(spark)
    manifest = token_files.write_token_files(_table(spark, sf_dir, "documents"), folder, _vocabulary("byte_bpe_50k.json"), end_id=2)
    return token_files.read_token_files(manifest, folder)


def op7_hash_tree_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hash_tree.with_shards(_table(spark, sf_dir, "documents"), hash_tree.grid(8), hash_tree.grid(9))


def op8_co_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = cotrain.fit_model(docs, _table(spark, sf_dir, "labels"))
    return cotrain.score(docs.select("doc_id", "text", "lang", "source", "n_chars"), model).select("doc_id", "p_text", "p_meta", "score", "keep")


def page_captures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pages as captures; the table has no fetch time, so one within 2024 is set from the id."""
    at = F.expr("timestamp_ntz '2024-01-01 00:00:00' + make_dt_interval(int(page_id % 366), int(page_id % 24))")
    return _table(spark, sf_dir, "pages").select("page_id", "url", at.alias("fetched"))


def host_lists(captures: DataFrame) -> DataFrame:
    """A history of three lists over the hosts of ``captures``, set by the first byte of a host's MD5."""
    hosts = captures.select(url_lists.host_of(F.col("url")).alias("host")).where("host is not null").distinct()
    m = hosts.withColumn("m", F.conv(F.substring(F.md5("host"), 1, 2), 16, 10).cast("int"))
    entry = lambda name, pattern, days, action, when: F.when(F.expr(when), F.struct(F.lit(name).alias("list"), F.expr(pattern).alias("pattern"), F.expr(f"timestamp_ntz '2024-01-01 00:00:00' + make_dt_interval({days})").alias("at"), F.lit(action).alias("action")))
    history = F.array(
        entry("spam", "concat('d:', host)", "30", "add", "m % 3 = 0"), entry("spam", "concat('d:', host)", "40", "add", "m % 3 = 0"),
        entry("spam", "concat('d:', host)", "100 + m", "remove", "m % 3 = 0"), entry("spam", "concat('d:', host)", "300", "add", "m % 6 = 0"),
        entry("tracker", "concat('d:', substring(host, locate('.', host) + 1))", "120", "add", "m % 5 = 0 and locate('.', host) > 0"),
        entry("section", "concat('p:', host, '/en')", "180", "add", "m % 4 = 1"),
    )
    return m.select(F.explode(F.array_compact(history)).alias("e")).select("e.*")


def op10_url_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    captures = page_captures(spark, sf_dir)
    return url_lists.judge(captures, host_lists(captures)).select("page_id", "url", "fetched", F.array_join("lists", ",").alias("lists"), "blocked")


def op9_rule_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cascade.measured(_table(spark, sf_dir, "documents")).drop("rejected_by")  # which rule came first may change from run to run


QUERIES = {f.__name__: f for f in (op1_piece_codec, op2_curve_neighbours, op3_simhash_groups, op4_page_text, op5_packing, op6_token_files, op7_hash_tree_shards, op8_co_training, op9_rule_cascade, op10_url_lists)}
