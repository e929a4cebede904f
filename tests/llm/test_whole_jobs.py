"""Cases in which the training-data operators once did less than the whole job."""

import numpy as np
from delimscan.llm import cotrain, html_text, url_lists
from pyspark.sql import functions as F


def _texts(spark, rows):
    return {r.page_id: r.text for r in html_text.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}


def test_counting_judges_inside_articles_and_keeps_text_beside_them(spark):
    page = "<html><body><article><h1>Story {0}</h1><p>Words of story {0} as they were told</p><div><p>Read our other stories</p></div></article><p>Correction of story {0}</p></body></html>"
    got = _texts(spark, [(i, "http://a.example/", page.format(i)) for i in range(12)])
    assert got == {i: f"Story {i}\n\nWords of story {i} as they were told\n\nCorrection of story {i}" for i in range(12)}


def test_a_share_of_the_host_is_what_counts(spark):
    page = "<body><div><p>About this house</p></div><p>Report number {0} of the day</p>{1}</body>"
    quote = "<blockquote>A passage that some reports quote</blockquote>"
    got = _texts(spark, [(i, "http://big.example/", page.format(i, quote if i < 9 else "")) for i in range(60)] + [(100 + i, "http://small.example/", page.format(i, "")) for i in range(4)])
    assert all(got[i] == f"Report number {i} of the day" + ("\n\nA passage that some reports quote" if i < 9 else "") for i in range(60))
    assert all(got[100 + i] == f"Report number {i} of the day" for i in range(4))


def test_near_copies_keep_their_text(spark):
    page = "<html><head><title>{0}</title></head><body><!-- {0} --><div><p>The whole story, paragraph one</p><p>The whole story, paragraph two</p></div>{1}</body></html>"
    whole = "The whole story, paragraph one\n\nThe whole story, paragraph two"
    got = _texts(spark, [(i, "http://a.example/", page.format(i, "")) for i in range(12)] + [(20 + i, "http://b.example/", page.format(i, f"<p>seen {i}</p>")) for i in range(12)])
    assert all(got[i] == whole and got[20 + i] == f"{whole}\n\nseen {i}" for i in range(12))


def test_deep_path_entries_match(spark):
    at = F.expr("timestamp_ntz '2024-01-01 00:00:00'")
    caps = spark.createDataFrame([(0, "http://a.example/a/b/c/d/e?x"), (1, "http://a.example/a/b/c/x"), (2, "http://a.example/"), (3, "http://b.example/1/2/3/4/5/6")], "page_id long, url string").withColumn("fetched", at)
    hist = spark.createDataFrame([("deep", "p:a.example/a/b/c/d", "add"), ("deep", "p:b.example/1/2/3/4/5/6", "add")], "list string, pattern string, action string").withColumn("at", at)
    assert {r.page_id: r.blocked for r in url_lists.judge(caps, hist).collect()} == {0: True, 1: False, 2: False, 3: True}
    assert not url_lists.judge(caps, hist.limit(0)).where("blocked").count()


def test_every_unlabelled_document_takes_part(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    docs = docs.unionByName(docs.withColumn("doc_id", F.col("doc_id") + 10**6)).unionByName(docs.withColumn("doc_id", F.col("doc_id") + 2 * 10**6)).unionByName(docs.withColumn("doc_id", F.col("doc_id") + 3 * 10**6))
    plain = docs.select(F.col("doc_id").alias("id"), "lang", "source", "n_chars", "text")
    pool = cotrain.Pool(plain, labels.select(F.col("doc_id").alias("id")), cotrain.CoModel())
    free = docs.join(labels, "doc_id", "left_anti").count()
    assert pool.table.count() == free > 2000
    always = [(np.zeros(cotrain.META_BINS + 1), 1.0, 9.0)]
    text = [(np.zeros(cotrain.SHAPES + 2), 1.0, 9.0)]
    assert sum(r[3] for r in pool.lend(text, always, 0.98) if r[1] == r[2] == 1) == free
    x = np.array([r.x for r in pool.table.select("x").collect()])
    g, h = pool.text_sums(always, 0.98, np.array([0.5, 0.25]))(np.zeros(x.shape[1]))
    assert np.allclose(g, 0.125 * x.sum(0)) and np.allclose(h, 0.0625 * x.T @ x)
