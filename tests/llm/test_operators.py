"""Each operator against brute force, an exact round trip or held-out accuracy, and on odd inputs."""

import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import xxhash
from delimscan.llm import bpe_cache, cascade, common, components, cotrain, curve_ann, hash_tree, html_text, packing, piece_codec, simhash, token_files, url_lists
from delimscan.llm import queries as Q
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

WORD = re.compile("[^\x20\x09-\x0d]+")
ODD = ["", " ", "a", "  a  b ", None, "É é x", "a\nb\r\nc\t", "x" * 3000, "w " * 5000, "日本語 text", "😀 ab"]


def documents(spark, texts):
    rows = [(i, t, "en", "s0", len(t or ""), "extra") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, id string")


def empty(spark):
    return documents(spark, []).limit(0)


# --- hashing and word spans ---------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.lists(st.binary(max_size=90), max_size=12))
def test_xxh64_of_spans(parts):
    raw = np.frombuffer(b"".join(parts), np.uint8)
    size = np.array([len(p) for p in parts], np.int64)
    got = common.xxh64_spans(raw, np.cumsum(size) - size, size)
    assert [int(x) for x in got] == [xxhash.xxh64_intdigest(p, 42) for p in parts]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="aB \n\té", max_size=30), max_size=8))
def test_word_spans(texts):
    raw, off = common.text_buffers(pa.array(texts, pa.string()))
    s, e, first = common.word_spans(raw, off)
    words = [raw[a:b].tobytes().decode() for a, b in zip(s, e)]
    assert [words[first[i] : first[i + 1]] for i in range(len(texts))] == [WORD.findall(t) for t in texts]


# --- 1: pieces ------------------------------------------------------------------------------------------------------------

PIECES = public_tokenizers.path("piece_bpe_32k.model")


def test_codec_equals_library(spark):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    random.seed(1)
    texts = [t for t in ODD if t is not None] + ["".join(random.choice("ab'the ing \n\t  é▁ <s>1😀") for _ in range(random.randrange(50))) for _ in range(300)]
    got = {r.doc_id: r for r in piece_codec.encode_texts(documents(spark, texts), PIECES).collect()}
    for i, t in enumerate(texts):
        assert got[i].ids == lib.encode(t), t
        assert got[i].decoded == lib.decode(lib.encode(t))


def _brute_viterbi(word, pieces, floor):
    best = {0: (0.0, [])}
    for end in range(1, len(word) + 1):
        options = []
        for start in range(end):
            p = word[start:end]
            s = pieces.get(p, floor if end - start == 1 else None)
            if s is not None and start in best:
                options.append((best[start][0] + s, [*best[start][1], p]))
        best[end] = max(options, key=lambda x: x[0])
    return best[len(word)][0]


def test_unigram_viterbi_is_optimal():
    random.seed(2)
    vocabulary = {"".join(random.choice("abc▁") for _ in range(random.randrange(1, 5))): -random.random() * 9 - 0.5 for _ in range(60)} | {"a": -5.5, "b": -6.25, "▁": -3.0}
    names, scores = ["<unk>", *vocabulary], [0.0, *vocabulary.values()]
    c = piece_codec.PieceCodec(names, scores, "unigram")
    for _ in range(300):
        word = "".join(random.choice("abcd▁") for _ in range(random.randrange(1, 12)))
        points = np.array([[ord(x) for x in word]], np.uint32)
        _, begins = c._viterbi(points)
        cut = [word[a:b] for a, b in zip(begins, [*begins[1:], len(word)])]
        assert "".join(cut) == word
        assert abs(sum(vocabulary.get(p, c.floor) for p in cut) - _brute_viterbi(word, vocabulary, c.floor)) < 1e-9


def test_codec_digest_round_trip(spark, small):
    got = Q.op1_piece_codec(spark, small)
    assert got.count() == spark.read.parquet(f"{small}/documents.parquet").count()
    assert got.where("not round_trip").count() == 0


# --- 2: neighbours ----------------------------------------------------------------------------------------------------------


def test_hilbert_is_a_curve():
    side = 8
    cells = np.array([[x, y, z] for x in range(side) for y in range(side) for z in range(side)])
    keys = curve_ann.hilbert_keys(cells, 3)
    assert sorted(keys.tolist()) == list(range(side**3))
    walk = cells[np.argsort(keys)]
    assert (np.abs(np.diff(walk, axis=0)).sum(axis=1) == 1).all()


def test_neighbours(spark, small):
    got = Q.op2_curve_neighbours(spark, small).toPandas()
    table = spark.read.parquet(f"{small}/embeddings.parquet").toPandas()
    x, ids = np.array(table.embedding.tolist(), float), table.vec_id.to_numpy()
    hits = total = 0
    for q in ids[ids % 20 == 0]:
        own = got[got.query_id == q].sort_values("rank")
        score = x @ x[ids == q][0]
        order = [i for i in np.lexsort((ids, -score)) if ids[i] != q][:20]
        assert list(own["rank"]) == list(range(1, len(own) + 1)) and len(own) == min(20, len(ids) - 1)
        hits += len(set(ids[order]) & set(own.vec_id))
        total += len(order)
    assert hits / total >= 0.9


def test_neighbours_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.0, 0.0]), (3, None), (4, [nan, 1.0]), (5, [inf, 1.0]), (6, [2.0, 0.0]), (7, [1.0, 0.0, 3.0]), (8, [None, 1.0]), (20, [1.0, 0.0]), (40, [0.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = curve_ann.search(df, F.col("vec_id") % 20 == 0, k=3, curves=4).orderBy("query_id", "rank").collect()
    assert [(r.query_id, r.vec_id, r.score) for r in got if r.query_id == 20] == [(20, 6, 2.0), (20, 0, 1.0), (20, 1, 1.0)]
    assert [r.vec_id for r in got if r.query_id == 40] == [0, 1, 6]
    assert curve_ann.search(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


# --- 3: near duplicates -------------------------------------------------------------------------------------------------------


def _brute_fingerprint(t):
    t = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    w = WORD.findall(t)
    runs = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    h = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def _brute_components(prints):
    ids = list(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in ids:
        for b in ids:
            if a < b and (prints[a] ^ prints[b]).bit_count() <= 3:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_simhash_groups(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    prints = {r.doc_id: _brute_fingerprint(r.text) for r in docs.collect()}
    want = _brute_components(prints)
    got = {r.doc_id: r for r in Q.op3_simhash_groups(spark, small).collect()}
    assert {i: r.fingerprint for i, r in got.items()} == {i: f"{p:016x}" for i, p in prints.items()}
    assert {i: r.component_id for i, r in got.items()} == want


@pytest.mark.parametrize("crowd", [4, 10**9])
def test_posting_links_are_complete(spark, crowd, monkeypatch):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 6).astype(np.uint64)
    fp = set()
    for b in base:
        for _ in range(60):
            x = int(b)
            for bit in rng.integers(0, 22, rng.integers(0, 6)):
                x ^= 1 << int(bit)
            fp.add(x)
    fp = np.array(sorted(fp), np.uint64)
    monkeypatch.setattr(simhash, "CROWD", crowd)
    want = _brute_components({int(x): int(x) for x in fp})
    # one posting: all that agree in the upper five bytes
    key = (fp >> np.uint64(24)).astype(np.int64)
    root = simhash.link_runs(np.zeros(len(fp)), key, fp)
    groups = defaultdict(set)
    for i, r in enumerate(root):
        groups[int(r)].add(int(fp[i]))
    assert sorted(map(sorted, groups.values())) == sorted(sorted(k for k, v in want.items() if v == r) for r in set(want.values()))


def test_simhash_odd_rows(spark):
    docs = documents(spark, ODD).unionByName(documents(spark, ODD)).unionByName(documents(spark, ["lost row"]).withColumn("doc_id", F.lit(None).cast("long")))
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == 2 * len(ODD) + 1
    blank = {r.component_id for r in got if r.fingerprint == "0" * 16}
    assert blank == {0}
    assert simhash.near_duplicates(empty(spark)).count() == 0
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    roots = {r.group_root for r in got if r.doc_id is not None}
    assert kept.where("doc_id is not null").count() == len(roots)


def test_components(spark):
    random.seed(5)
    edges = [(random.randrange(300), random.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)] + [(2000, 2000 + i) for i in range(50)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in components.connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert all(find(n) == got.get(n, n) for n in root)
    assert components.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


# --- 4: pages -----------------------------------------------------------------------------------------------------------------


def test_page_text(spark, small):
    import html

    pages = {r.page_id: r for r in spark.read.parquet(f"{small}/pages.parquet").collect()}
    got = Q.op4_page_text(spark, small).collect()
    assert len(got) == len(pages)
    for r in got:
        article = re.search(r"<article>(.*?)</article>", pages[r.page_id].html, re.S)[1]
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]+>", "", b.replace("<br>", " ")))).strip() for b in re.split(r"</?(?:p|h1)>", article)]
        assert r.text == "\n\n".join(b for b in blocks if b)
        assert r.n_chars == len(r.text)


def test_template_removal(spark):
    body = "<html><body><div><p>Our company news and address</p></div><div><p>{0}</p></div>{1}</body></html>"
    rows = [(i, f"http://a.example/{i}", body.format(f"story number {i}", "<div class='comments'><p>bad</p></div>")) for i in range(12)]
    rows += [(100, "http://b.example/1", body.format("lone story", "")), (101, None, None), (102, "::", ""), (103, "http://c.example", "<p>a<p>b &lt;c&gt; <script>if (a<b) '</p>'</script> d")]
    got = {r.page_id: r.text for r in html_text.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"story number {i}" for i in range(12))
    assert got[100] == "Our company news and address\n\nlone story"
    assert got[101] == got[102] == ""
    assert got[103] == "a\n\nb <c> d"
    assert html_text.extract_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_exact_copies_count_as_one_page(spark):
    rows = [(i, "http://a.example/x", "<div><p>same page</p></div>") for i in range(20)]
    assert {r.text for r in html_text.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()} == {"same page"}


# --- 5 and 6: packing, token files --------------------------------------------------------------------------------------------


def _ids(name, texts, end):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path(name))
    t.encode_special_tokens = True
    return [[*t.encode(x or "", add_special_tokens=False).ids, end] for x in texts]


def _crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_chunked_encoding_equals_library(name):
    random.seed(4)
    texts = [t or "" for t in ODD] + ["".join(random.choice("ab'ts \n\t  é 　́ΣÀ1.<|endoftext|>\x01\x7f\x1c😀") for _ in range(random.randrange(40))) for _ in range(1500)]
    raw, off = common.text_buffers(pa.array(texts))
    ids, at = bpe_cache.ChunkEncoder(public_tokenizers.path(name), room=500).encode(raw, off)
    assert [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:])] == [x[:-1] for x in _ids(name, texts, 0)]


def test_packing(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").unionByName(documents(spark, ODD).drop("id").withColumn("doc_id", F.col("doc_id") + 10**6))
    ids = dict(zip([r.doc_id for r in docs.collect()], _ids("word_bpe_49k.json", [r.text for r in docs.collect()], 1)))
    got = packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json")).toPandas()
    for doc, rows in got.groupby("doc_id"):
        rows = rows.sort_values("start")
        assert rows.start.tolist() == [0, *rows.length.cumsum().tolist()[:-1]] and rows.length.sum() == len(ids[doc]) == rows.doc_tokens.iloc[0]
        assert all(r.ids_crc32 == _crc(ids[doc][r.start : r.start + r.length]) for r in rows.itertuples())
    for _, rows in got.groupby("sequence_id"):
        rows = rows.sort_values("offset")
        assert rows.offset.tolist() == [0, *rows.length.cumsum().tolist()[:-1]] and rows.length.sum() <= 2048
    assert set(got.doc_id) == set(ids)
    assert got.length.sum() / (2048 * got.sequence_id.nunique()) > 0.97
    assert packing.pack_documents(empty(spark), public_tokenizers.path("word_bpe_49k.json")).count() == 0


def test_differencing_is_near_equal():
    rng = np.random.default_rng(0)
    for n in (0, 1, 2, 7, 400):
        sizes = rng.integers(1, 513, n)
        at, ways = packing.pack_sizes(sizes, 2048)
        if n:
            load = np.bincount(at, weights=sizes, minlength=ways)
            assert load.max() <= 2048 and load.sum() == sizes.sum()
            assert n < 100 or load.max() - load.min() < 60


def test_token_files(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = sorted(docs.collect(), key=lambda r: r.doc_id)
    ids = _ids("byte_bpe_50k.json", [r.text for r in rows], 2)
    got = Q.op6_token_files(spark, small).orderBy("doc_id").collect()
    at = 0
    for r, x, want in zip(got, ids, rows, strict=True):
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (want.doc_id, at, len(x), _crc(x))
        at += len(x)


def test_token_files_odd_rows(spark):
    docs = documents(spark, ODD).unionByName(documents(spark, ["no id"]).withColumn("doc_id", F.lit(None).cast("long")))
    folder = token_files.new_folder(spark)
    m = token_files.write_token_files(docs, folder, public_tokenizers.path("byte_bpe_50k.json"), 2)
    got = token_files.read_token_files(m, folder).orderBy(F.col("start")).collect()
    assert [r.doc_id for r in got] == [None, *range(len(ODD))] and got[1].n_tokens == 1
    m = token_files.write_token_files(empty(spark), token_files.new_folder(spark), public_tokenizers.path("byte_bpe_50k.json"), 2)
    assert token_files.read_token_files(m, folder).count() == 0


# --- 7: shards ----------------------------------------------------------------------------------------------------------------


def test_shards(spark, small):
    got = Q.op7_hash_tree_shards(spark, small).toPandas()
    docs = {r.doc_id: (r.text or "").encode() for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    assert all(r.size == len(docs[r.doc_id]) + 1 and r.text_crc32 == zlib.crc32(docs[r.doc_id]) for r in got.itertuples())
    for _, rows in got.groupby("shard"):
        assert sorted(rows.slot) == list(range(len(rows)))
    moved = got[got.shard != got.grown_shard]
    assert set(got.shard) <= set(range(8)) and set(moved.grown_shard) <= {8}


def test_shards_odd_rows(spark):
    docs = documents(spark, ODD)
    docs = docs.unionByName(docs).unionByName(docs.withColumn("doc_id", F.lit(None).cast("long")))
    got = hash_tree.with_shards(docs, hash_tree.grid(8)).toPandas()
    assert len(got) == 3 * len(ODD) and got.grown_shard.isna().all()
    assert all(sorted(r.slot) == list(range(len(r))) for _, r in got.groupby("shard"))
    assert hash_tree.with_shards(empty(spark), hash_tree.grid(8)).count() == 0


def test_weights_confine_movement(spark):
    tree, heavy = hash_tree.grid(8), hash_tree.grid(8)
    heavy["g1"]["k2"][5] = 3.0
    rows = spark.range(4000).select("id", hash_tree.place(F.col("id").cast("string"), tree).alias("a"), hash_tree.place(F.col("id").cast("string"), heavy).alias("b")).toPandas()
    moved = rows[rows.a != rows.b]
    assert set(moved.b) <= {4, 5, 6, 7} and 0 < len(moved) < 2000
    assert abs((rows.b == 5).mean() - 3 / 10) < 0.04


# --- 8: classifier ------------------------------------------------------------------------------------------------------------


def test_co_training_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    seen = labels.where("doc_id % 3 <> 0")
    got = cotrain.score(docs, cotrain.fit_model(docs, seen)).join(labels.where("doc_id % 3 = 0"), "doc_id").toPandas()
    good = (got.quality == 1) & (got.toxic == 0)
    assert got.keep[good].mean() > 0.98 and got.keep[got.toxic == 1].mean() < 0.2 and got.keep[got.quality == 0].mean() < 0.1


def test_co_training_odd_rows(spark):
    docs = documents(spark, ODD)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = cotrain.score(docs, cotrain.fit_model(docs, none))
    assert got.columns == [*docs.columns, "p_text", "p_meta", "score", "keep"] and got.where("keep").count() == len(ODD)
    labels = spark.createDataFrame([(0, 0, None), (1, 1, 0), (5, 1, 0), (1, None, None), (77, 1, 1)], "doc_id long, quality int, toxic int")
    assert cotrain.score(docs, cotrain.fit_model(docs, labels)).count() == len(ODD)
    assert cotrain.score(empty(spark), cotrain.CoModel()).count() == 0


# --- 9: rules -----------------------------------------------------------------------------------------------------------------


def _brute_measures(t):
    t = t or ""
    w = WORD.findall(t)
    c = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    hit = {i + k for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for k in range(5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit)


def test_measures(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").unionByName(documents(spark, [*ODD, "a b c d e " * 4, "l1\nl1\nl1 #$"]).select(F.col("doc_id") + 10**6, "text").toDF("doc_id", "text"))
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in cascade.measured(docs).collect():
        n, chars, signs, lines, rep = _brute_measures(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, signs, lines, rep)
        assert r.base_failed == (n < 10 or 100 * rep > 20 * n)
        assert not (r.kept and r.base_failed)


def test_cascade_order_does_not_matter(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    a = {r.doc_id for r in cascade.cascade(docs).where("rejected_by is null").collect()}
    b = {r.doc_id for r in cascade.measured(docs).where("kept").collect()}
    assert a == b
    assert cascade.cascade(empty(spark)).count() == 0


# --- 10: lists ----------------------------------------------------------------------------------------------------------------


def test_url_lists_against_brute_force(spark):
    random.seed(6)
    hosts = ["a.example", "b.a.example", "c.org", "x.c.org"]
    caps = [(i, f"http://{random.choice(hosts)}/p{random.randrange(3)}/q?x=1", random.randrange(100)) for i in range(400)] + [(900, None, 5), (901, "junk", 5), (902, "http://c.org/", None)]
    pats = [*(f"d:{h}" for h in hosts), "d:example", "p:c.org/p1", "p:a.example/p0/q"]
    hist = [(random.choice(["l1", "l2"]), random.choice(pats), random.randrange(100), random.choice(["add", "remove"])) for _ in range(60)] + [("l1", None, 3, "add"), ("l1", "d:c.org", None, "add")]
    at = lambda c: F.expr(f"timestamp_seconds({c} * 60)")
    c = spark.createDataFrame(caps, "page_id long, url string, m int").select("page_id", "url", at("m").alias("fetched"))
    e = spark.createDataFrame(hist, "list string, pattern string, m int, action string").select("list", "pattern", at("m").alias("at"), "action")
    got = {r.page_id: set(r.lists) for r in url_lists.judge(c, e).collect()}
    for i, url, m in caps:
        want = set()
        if url and "://" in url and m is not None:
            host, path = re.match(r"http://([^/]+)([^?]*)", url).groups()
            labels, parts = host.split("."), [p for p in path.split("/") if p]
            keys = {"d:" + ".".join(labels[k:]) for k in range(len(labels))} | {"p:" + "/".join([host, *parts[: k + 1]]) for k in range(len(parts))}
            for name in ("l1", "l2"):
                for k in keys:
                    past = [(t, a == "remove") for li, p, t, a in hist if li == name and p == k and t is not None and t <= m]
                    if past and not max(past)[1]:
                        want.add(name)
        assert got[i] == want, (i, url, m)
    assert url_lists.judge(c.limit(0), e).count() == 0
    assert url_lists.judge(c, e.limit(0)).where("blocked").count() == 0
