"""The pipeline's stages against brute force on the smallest tables."""

import corpus_pipeline
import numpy as np
from test_operators import _brute_components, _brute_fingerprint, _brute_measures


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    labels = {r.doc_id: r for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality classifier", "quality rules", "near duplicates", "packing"]
    one = corpus_pipeline.classify(spark, docs, small).cache()
    assert one.columns == docs.columns
    clean = [i for i, r in labels.items() if r.quality == 1 and r.toxic == 0]
    kept = {r.doc_id for r in one.collect()}
    assert np.mean([i in kept for i in clean]) > 0.95
    two = corpus_pipeline.rules(spark, one, small).cache()
    for r in one.collect():
        n, chars, signs, lines, rep = _brute_measures(r.text)
        good = n >= 10 and 100 * rep <= 20 * n and 100 * signs <= 20 * n and not (lines > 5 and 10 * lines > n) and 2 * n <= chars <= 100 * n
        assert good == (two.where(two.doc_id == r.doc_id).count() == 1) if r.doc_id % 20 == 0 else True
    three = corpus_pipeline.near_duplicates(spark, two, small).cache()
    want = _brute_components({r.doc_id: _brute_fingerprint(r.text) for r in two.collect()})
    assert {r.doc_id for r in three.collect()} == set(want.values())
    four = corpus_pipeline.pack(spark, three, small)
    assert {r.doc_id for r in four.select("doc_id").distinct().collect()} == set(want.values())


def test_run_equals_stages(spark, small):
    assert corpus_pipeline.run(spark, small).count() > 0
