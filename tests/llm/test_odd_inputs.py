"""Nulls, empty tables, repeated rows, and extra columns with the names that the operators use themselves."""

import corpus_pipeline
import public_tokenizers
import pytest
from delimscan.llm import cascade, cotrain, curve_ann, hash_tree, packing, piece_codec, simhash, token_files, url_lists
from pyspark.sql import functions as F
from test_operators import ODD, PIECES, WORD, _brute_measures, documents, empty
from test_methods import _jaccard

CLASH = "keep score p_text rejected_by __n __f __r __0 __text fp id text_ row file uid host lists run shard size piece pool n h part q v curve".split()


def clashing(df):
    taken = {c.lower() for c in df.columns}
    return df.select("*", *[F.lit(f"own {c}").alias(c) for c in CLASH if c not in taken])


def twice(df):
    return df.unionByName(df)


def rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)


def test_pieces(spark):
    docs = clashing(documents(spark, ODD).drop("id"))
    got = rows(piece_codec.codec_digest(docs, PIECES), "doc_id", "n_pieces", "ids_crc32", "round_trip")
    assert len(got) == len(ODD) and {i: n for i, n, *_ in got}[4] == 0 == {i: n for i, n, *_ in got}[0]
    assert rows(piece_codec.codec_digest(twice(docs), PIECES), "doc_id", "n_pieces", "ids_crc32", "round_trip") == sorted(got * 2, key=repr)
    assert piece_codec.codec_digest(docs.limit(0), PIECES).count() == 0 == piece_codec.encode_texts(docs.limit(0), PIECES).count()


def test_neighbours(spark):
    df = spark.createDataFrame([(i, [float(i % 7), float(i % 5) - 2, 1.0]) for i in range(60)], "vec_id long, embedding array<float>")
    search = lambda d: rows(curve_ann.search(d, F.col("vec_id") % 20 == 0, k=5, curves=4), "query_id", "rank", "vec_id", "score")
    assert search(twice(clashing(df))) == search(df) != []
    null = df.unionByName(df.limit(3).withColumn("vec_id", F.lit(None).cast("long")))
    assert search(null) == search(df)


def test_fingerprints(spark):
    docs = clashing(documents(spark, ODD).drop("id"))
    got = rows(simhash.near_duplicates(docs), "doc_id", "fingerprint", "component_id")
    assert rows(simhash.near_duplicates(twice(docs)), "doc_id", "fingerprint", "component_id") == sorted(got * 2, key=repr)
    assert simhash.keep_one(twice(docs)).count() == simhash.keep_one(docs).count()


@pytest.mark.parametrize("name", ["word_bpe_49k.json"])
def test_packing(spark, name):
    docs = clashing(documents(spark, ODD).drop("id")).unionByName(clashing(documents(spark, ["lost", None]).drop("id")).withColumn("doc_id", F.lit(None).cast("long")))
    got = packing.pack_documents(twice(docs), public_tokenizers.path(name)).toPandas()
    assert got.length.sum() == 2 * packing.pack_documents(docs, public_tokenizers.path(name)).agg(F.sum("length")).first()[0]
    assert got[got.doc_id.isna()].length.sum() > 0
    for _, own in got.groupby("sequence_id"):
        own = own.sort_values("offset")
        assert own.offset.tolist() == [0, *own.length.cumsum().tolist()[:-1]] and own.length.sum() <= 2048


def test_token_files(spark):
    path, folder = public_tokenizers.path("byte_bpe_50k.json"), token_files.new_folder(spark)
    docs = twice(clashing(documents(spark, ODD).drop("id")))
    got = token_files.read_token_files(token_files.write_token_files(docs, folder, path, 2), folder).orderBy("start").collect()
    assert [r.doc_id for r in got] == sorted([*range(len(ODD))] * 2)
    assert all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))


def test_shards(spark):
    docs = clashing(documents(spark, ODD).drop("id"))
    got = hash_tree.with_shards(twice(docs), hash_tree.grid(8), hash_tree.grid(9)).toPandas()
    assert len(got) == 2 * len(ODD) and all(sorted(x.slot) == list(range(len(x))) for _, x in got.groupby("shard"))
    assert (got.groupby("doc_id").shard.nunique() == 1).all()


def test_classifier(spark):
    docs = clashing(documents(spark, ODD))
    labels = spark.createDataFrame([(0, 0, 1), (1, 1, 0), (5, 1, 0), (6, 0, 0)], "doc_id long, quality int, toxic int")
    model = cotrain.fit_model(twice(docs), labels)
    got = cotrain.score(twice(docs), model)
    assert got.columns == [*docs.columns, "p_text_", "p_meta", "score_", "keep_"]
    assert {r.keep for r in got.collect()} == {"own keep"} and got.count() == 2 * len(ODD)
    assert len({(r.doc_id, r.score_) for r in got.collect()}) == len(ODD)
    kept = cotrain.kept(docs, model)
    assert kept.columns == docs.columns and kept.count() == cotrain.score(docs, model).where("keep_").count()
    assert cotrain.kept(empty(spark), model).count() == 0
    assert cotrain.fit_model(empty(spark), labels).text is None and cotrain.fit_model(docs, labels.limit(0)).text is None


def test_rules(spark):
    docs = clashing(documents(spark, ODD))
    got = cascade.cascade(twice(docs))
    assert got.columns == [*docs.columns, "rejected_by_"] and {r.rejected_by for r in got.collect()} == {"own rejected_by"}
    assert cascade.kept(docs).columns == docs.columns
    assert cascade.measured(empty(spark)).count() == 0 == cascade.kept(empty(spark)).count()
    assert rows(cascade.measured(twice(docs)), "doc_id", "kept") == sorted(rows(cascade.measured(docs), "doc_id", "kept") * 2, key=repr)


def test_lists(spark):
    at = F.expr("timestamp_ntz '2024-01-01 00:00:00'")
    caps = clashing(spark.createDataFrame([(1, "http://a.example/x"), (None, "http://a.example/"), (2, None)], "page_id long, url string").withColumn("fetched", at))
    hist = spark.createDataFrame([("l", "d:a.example", "add"), (None, "d:a.example", "add")], "list string, pattern string, action string").withColumn("at", at)
    got = url_lists.judge(twice(caps), hist)
    assert rows(got, "page_id", "url", "blocked") == sorted([(1, "http://a.example/x", True), (None, "http://a.example/", True), (2, None, False)] * 2, key=repr)
    assert got.columns == ["page_id", "url", "fetched", "lists", "blocked"]


# --- the pipeline -----------------------------------------------------------------------------------------------------------


@pytest.fixture
def tables(spark, small, tmp_path):
    def make(docs, labels=None):
        root = str(tmp_path / "tables")
        docs.write.mode("overwrite").parquet(f"{root}/documents.parquet")
        (labels if labels is not None else spark.read.parquet(f"{small}/labels.parquet")).write.mode("overwrite").parquet(f"{root}/labels.parquet")
        return root

    return make


def _lead(spark, root):
    """Documents after each stage but the last."""
    docs, out = spark.read.parquet(f"{root}/documents.parquet"), []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.durable(stage(spark, docs, root))
        out.append(docs)
    return out


def test_pipeline_of_odd_rows(spark, small, tables):
    plain = spark.read.parquet(f"{small}/documents.parquet")
    odd = documents(spark, ODD).drop("id").withColumn("doc_id", F.col("doc_id") + 10**6)
    lost = plain.limit(5).withColumn("doc_id", F.lit(None).cast("long")).withColumn("lang", F.lit(None).cast("string")).withColumn("source", F.lit(None).cast("string")).withColumn("n_chars", F.lit(None).cast("long"))
    docs = clashing(plain.unionByName(plain.limit(20)).unionByName(odd).unionByName(lost))
    root = tables(docs)
    stages = _lead(spark, root)
    assert all(s.columns == docs.columns for s in stages)
    assert {r[c] for c in ("keep", "rejected_by", "__n") for r in stages[2].select("keep", "rejected_by", "__n").distinct().collect()} == {"own keep", "own rejected_by", "own __n"}
    final = corpus_pipeline.run(spark, root)
    ids = {r.doc_id for r in stages[2].select("doc_id").collect()}
    assert {r.doc_id for r in final.select("doc_id").distinct().collect()} == ids and ids
    assert final.agg(F.sum(F.when(F.col("start") == 0, 1))).first()[0] == stages[2].count()  # a document is a row, whatever its id


def test_pipeline_of_nothing(spark, small, tables):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    labels = spark.read.parquet(f"{small}/labels.parquet")
    assert corpus_pipeline.run(spark, tables(docs.limit(0))).count() == 0
    assert corpus_pipeline.run(spark, tables(docs, labels.limit(0))).count() > 0


def test_stages_against_brute_force(spark, small, tables):
    root = tables(spark.read.parquet(f"{small}/documents.parquet"))
    before = {r.doc_id: r.text for r in spark.read.parquet(f"{root}/documents.parquet").collect()}
    one, two, three = ({r.doc_id: r.text for r in s.collect()} for s in _lead(spark, root))
    assert set(one) <= set(before) and two.items() <= one.items() and three.items() <= two.items()
    for i, t in one.items():
        n, chars, signs, lines, rep = _brute_measures(t)
        own = [x for x in (t or "").split("\n") if WORD.search(x)]
        bullets = sum(x.lstrip(" \t\n\x0b\x0c\r")[:1] in tuple("-*+•‣◦") and x.lstrip(" \t\n\x0b\x0c\r")[1:2] in (" ", "\t") for x in own)
        cut = sum(x.rstrip(" \t\n\x0b\x0c\r").endswith(("...", "…")) for x in own)
        letters = sum(any(c.isalpha() for c in w) for w in WORD.findall(t or ""))
        good = n >= 10 and 100 * rep <= 20 * n and 100 * signs <= 20 * n and not (lines > 5 and 10 * lines > n) and 2 * n <= chars <= 100 * n
        assert (i in two) == (good and 10 * bullets <= 9 * len(own) and 10 * cut <= 3 * len(own) and 10 * letters >= 6 * n), i
    alike = [(a, b) for a in two for b in two if a < b and _jaccard(two[a], two[b]) >= 0.8]
    assert sum(a in three and b in three for a, b in alike) <= 0.1 * max(1, len(alike))
    assert set(two) - set(three) <= {b for _, b in alike} | {r.doc_id for r in simhash.near_duplicates(spark.createDataFrame(list(two.items()), "doc_id long, text string")).where("doc_id <> component_id").collect()}
