"""The methods themselves, at sizes and on inputs where a plainer way would not pass for them."""

import itertools
import random
import time

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from delimscan.llm import cascade, common, curve_ann, html_text, packing, piece_codec, simhash, token_files, url_lists
from delimscan.llm import queries as Q
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from test_operators import PIECES, WORD, _brute_fingerprint, _crc, documents

# --- 1: pieces ------------------------------------------------------------------------------------------------------------


def _merged(word, score):
    """Pieces left when the best adjacent pair, of equals the leftmost, merges until none can."""
    parts = list(word)
    while True:
        pairs = [(score[a + b], -i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in score]
        if not pairs:
            return parts
        i = -max(pairs)[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10**9), st.booleans())
def test_seams_give_what_merging_gives(seed, ties):
    rng = random.Random(seed)
    pieces = sorted({"".join(rng.choice("abc") for _ in range(rng.randrange(2, 6))) for _ in range(rng.randrange(1, 25))})
    rng.shuffle(pieces)
    score = {p: -float(rng.randrange(4) if ties else i) for i, p in enumerate(pieces)} | {c: -100.0 for c in "abc"}
    names = ["<unk>", *score]
    codec = piece_codec.PieceCodec(names, [0.0, *score.values()], "bpe")
    for n in (1, 2, 3, 7, 13, 40):
        words = ["".join(rng.choice("abcd") for _ in range(n)) for _ in range(12)]
        row, begin = codec._viterbi(np.array([[ord(c) for c in w] for w in words], np.uint32))
        for i, w in enumerate(words):
            cut = begin[row == i].tolist()
            want = _merged(w, {p: s for p, s in score.items() if len(p) > 1})
            assert [w[a:b] for a, b in zip(cut, [*cut[1:], n])] == want
            assert codec._viterbi_long(w) == cut


def test_windows_of_a_word(monkeypatch):
    codec = piece_codec.PieceCodec.load(PIECES)
    rng = random.Random(3)
    word = "".join(rng.choice(["the", "ing", "tion", "x", "日", "q"]) for _ in range(300))
    points = np.array([[ord(c) for c in word]], np.uint32)
    whole = codec._viterbi(points)[1].tolist()
    monkeypatch.setattr(piece_codec, "CELLS", 16)
    assert codec._viterbi(points)[1].tolist() == whole == codec._viterbi_long(word)


def test_codec_digest_equals_library(spark, small):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    for r in Q.op1_piece_codec(spark, small).collect():
        ids = lib.encode(texts[r.doc_id])
        assert (r.n_pieces, r.ids_crc32, r.decoded_crc32) == (len(ids), _crc(ids), __import__("zlib").crc32(lib.decode(ids).encode()))


# --- 2: neighbours ----------------------------------------------------------------------------------------------------------


def test_recall_where_most_pairs_are_not_scored(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(8000, 5)) @ rng.normal(size=(5, 16)) + 0.1 * rng.normal(size=(8000, 16))  # five dimensions in sixteen, and noise
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    told = {}
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = curve_ann.search(df, F.col("vec_id") % 20 == 0, k=10, curves=12, block=300, fit_queries=48, told=told).toPandas()
    assert told["curves"] * (2 * told["window"] + 1) < 4000  # entries that a query is put to, of 8,000
    hits = 0
    asked = range(0, 8000, 20)
    for q in asked:
        s = x @ x[q]
        s[q] = -np.inf
        hits += len(set(np.argsort(-s)[:10]) & set(got.vec_id[got.query_id == q]))
    assert hits / (10 * len(asked)) >= 0.9  # 400 queries, 48 of them fitted on


# --- 3: near duplicates -------------------------------------------------------------------------------------------------------


def test_position_sets_cover_what_the_tally_needs():
    eight, sixteen = simhash.position_sets(8), simhash.position_sets(16)
    assert len(eight) == 14 and len(sixteen) == 140
    assert all(any(set(s) <= set(five) for s in eight) for five in itertools.combinations(range(8), 5))
    assert all(any(set(s) <= set(seven) for s in sixteen) for seven in itertools.combinations(range(16), 7))


@pytest.mark.parametrize("crowd", [10**9, 3])
def test_links_join_what_brute_force_joins(spark, crowd, monkeypatch):
    rng = np.random.default_rng(11)
    fps = set()
    for base in rng.integers(0, 2**63, 40):
        for _ in range(12):
            x = int(base)
            for bit in rng.integers(0, 64, rng.integers(0, 5)):
                x ^= 1 << int(bit)
            fps.add(x - (1 << 64) if x >> 63 else x)
    monkeypatch.setattr(simhash, "CROWD", crowd)
    found = simhash.links(spark.createDataFrame([(f,) for f in fps], "fp long")).collect()

    def groups(pairs):
        root = {f: f for f in fps}

        def find(f):
            while root[f] != f:
                f = root[f]
            return f

        for u, v in pairs:
            root[max(find(u), find(v))] = min(find(u), find(v))
        return {f: find(f) for f in fps}

    near = [(a, b) for a, b in itertools.combinations(sorted(fps), 2) if ((a ^ b) & (2**64 - 1)).bit_count() <= 3]
    assert groups([(r.u, r.v) for r in found]) == groups(near)


def test_the_tally_filters_before_the_verification():
    a = np.array([0x0102030405060708, 0x0102030405060709, 0x0102030400000000, 0x1112131415060708], np.uint64)
    far = a[:1] ^ a
    assert simhash.shared_bytes(far).tolist() == [8, 7, 4, 3]


def _jaccard(a, b):
    sets = []
    for t in (a, b):
        w = WORD.findall((t or "").lower())
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    return len(sets[0] & sets[1]) / max(1, len(sets[0] | sets[1]))


def test_one_row_of_each_group_stays(spark):
    rng = random.Random(4)
    words = [f"w{i}" for i in range(4000)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    edited = lambda t, k: " ".join("changed" if i % k == k - 1 else w for i, w in enumerate(t.split()))
    a, b, c = text(400), text(60), text(300)
    rows = [
        (7, a, "x"), (7, b, "y"), (9, b, "z"),  # one id, two texts; a is the only one of its kind
        (20, c, "x"), (21, edited(c, 100), "x"),  # three words in 300: similarity about 0.9
        (30, c + " " + text(300), "x"),  # half of it is another's: stays
        (None, a, "n"), (None, None, "n"), (40, "", "x"), (41, None, "x"), (None, "lonely words without an id", "n"), (None, "lonely words without an id", "n"),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string, __n string").withColumn("__f", F.lit(1)).withColumn("row", F.lit(2))
    got = sorted(((r.doc_id, r.text, r["__n"]) for r in simhash.keep_one(df).collect()), key=repr)
    assert got == sorted([(7, a, "x"), (7, b, "y"), (20, c, "x"), (30, rows[5][1], "x"), (40, "", "x"), (None, "lonely words without an id", "n")], key=repr)
    assert simhash.keep_one(df).columns == df.columns
    assert simhash.keep_one(df.limit(0)).count() == 0
    shuffled = simhash.keep_one(df, bitmap_bytes=0)
    assert sorted(((r.doc_id, r.text, r["__n"]) for r in shuffled.collect()), key=repr) == got


def test_near_copies_by_similarity(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    text = {r.doc_id: r.text for r in docs.collect()}
    kept = {r.doc_id for r in simhash.keep_one(docs).collect()}
    narrow = {r.doc_id for r in simhash.keep_one(docs, least=None).collect()}
    assert kept <= narrow
    roots = {r.doc_id: r.component_id for r in simhash.near_duplicates(docs).collect()}
    assert narrow == set(roots.values())
    shingles = {}
    for i, t in text.items():
        w = WORD.findall((t or "").lower())
        for k in range(max(1, len(w) - 4)):
            shingles.setdefault(tuple(w[k : k + 5]), set()).add(i)
    pairs = {p for ids in shingles.values() if len(ids) > 1 for p in itertools.combinations(sorted(ids), 2)}
    alike = {p for p in pairs if _jaccard(text[p[0]], text[p[1]]) >= 0.8}
    both = [p for p in alike if p[0] in kept and p[1] in kept]
    assert len(both) <= 0.1 * len(alike)
    # a removed document has a kept or removed partner that is near: within three bits or similar
    for i in narrow - kept:
        assert any(i in p for p in alike)


# --- 4: pages -----------------------------------------------------------------------------------------------------------------


def _page_texts(spark, rows):
    return {r.page_id: r.text for r in html_text.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string, uid string, host string, trees string, blocks int")).collect()}


def test_odd_markup(spark):
    pages = {
        0: ("It costs <b title=it's>five</b> euros", "It costs five euros"),
        1: ("<p>a < b && c <3 d &lt;e&gt;</p>", "a < b && c <3 d <e>"),
        2: ("<p>x<!-->y<!-- z -->w", "xyw"),
        3: ('<p title="a>b" data-x=\'c>d\'>q</p>', "q"),
        4: ("<p>done <a href='x", "done"),
        5: ("<P>Upper<BR/>case</P ><script>if (a<b) '</p>'</SCRIPT>end", "Upper case\n\nend"),
        6: ("<table><tr><td>a<td>b<tr><td>c</table>d", "a\n\nb\n\nc\n\nd"),
        7: (None, ""),
    }
    got = _page_texts(spark, [(i, "http://a.example/" if i else None, h, "u", "h", "t", 1) for i, (h, _) in pages.items()])
    assert got == {i: t for i, (_, t) in pages.items()}


@pytest.mark.parametrize("page", ["<div>" * 20_000 + "x" + "</i>" * 2000 + "</p>" * 2000, "<a b" * 40_000, "<a x='" * 30_000, "<" * 100_000, "<div class='a'>" * 5000 + "<p>k</p></div>" * 5000, "<!--" * 50_000, "<ul><li>" * 20_000])
def test_pages_take_linear_time(page):
    began = time.perf_counter()
    html_text.blocks_of(page)
    assert time.perf_counter() - began < 3


def test_many_templates_are_met_without_a_broadcast_of_all(spark):
    page = "<body><div><p>About this house {1}</p></div><p>Report number {0} of the day</p></body>"
    rows = [(i, f"http://h{i % 6}.example/", page.format(i, i % 6)) for i in range(120)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    one, two = ({(r.page_id, str(r.gone)) for r in html_text.judged(df, broadcast_rows=n, heavy_pages=5).collect()} for n in (10**6, 0))
    assert one == two and all(g != "None" for _, g in one)


# --- 5 and 6: packing, token files --------------------------------------------------------------------------------------------


def test_most_left_over_ids_go_through_differencing(spark, small):
    got = Q.op5_packing(spark, small)
    share = got.agg((F.sum(F.when(F.col("length") < 2048, F.col("length"))) / F.sum("length")).alias("s")).first()["s"]
    assert share > 0.3
    load = got.where("length < 2048").groupBy("sequence_id").agg(F.sum("length").alias("n")).agg(F.max("n"), F.min("n")).first()
    assert load[0] <= 2048 and load[0] - load[1] < 128  # near-equal windows


def test_ids_must_fit_the_width():
    ids = np.array([1, 65_535, 65_536], np.uint32)
    assert token_files.packed(ids[:2], 2) == ids[:2].astype("<u2").tobytes()
    assert np.array_equal(np.frombuffer(token_files.packed(ids, 4), "<u4"), ids)
    with pytest.raises(ValueError, match="16 bits"):
        token_files.packed(ids, 2)
    path = public_tokenizers.path("byte_bpe_50k.json")
    assert token_files.id_width(path, 2) == 2 and token_files.id_width(path, 70_000) == 4


def test_token_files_of_wide_ids_and_repeated_rows(spark):
    path = public_tokenizers.path("byte_bpe_50k.json")
    docs = documents(spark, ["b text", "a text", None, "b text"]).withColumn("doc_id", F.col("doc_id") % 2)
    folder = token_files.new_folder(spark)
    manifest = token_files.write_token_files(docs, folder, path, 70_000)
    got = token_files.read_token_files(manifest, folder).orderBy("start").collect()
    assert [r.doc_id for r in got] == [0, 0, 1, 1] and {r["width"] for r in manifest.collect()} == {4}
    assert sorted(r.n_tokens for r in got) == [1, 3, 3, 3] and got[0].ids_crc32 in (_crc([70_000]), _crc([65, 2420, 70_000]))


def test_special_strings_are_ordinary_text():
    from delimscan.llm import bpe_cache

    raw, off = common.text_buffers(pa.array(["a <|endoftext|> b"]))
    for name, special in (("byte_bpe_50k.json", 50_256), ("word_bpe_49k.json", 49_407)):
        ids, _ = bpe_cache.ChunkEncoder(public_tokenizers.path(name)).encode(raw, off)
        assert special not in ids.tolist() and len(ids) > 4


# --- 9: rules -----------------------------------------------------------------------------------------------------------------


def test_a_rejected_text_is_not_put_to_later_rules(spark, monkeypatch):
    docs = documents(spark, ["few words", "one two three four five six seven eight nine ten eleven"])
    boom = lambda t, ws: F.raise_error(F.concat(F.lit("computed for "), t)).cast("long")
    monkeypatch.setitem(cascade.MEASURES, "boom", boom)
    later = cascade.Rule("boom", ("boom",), lambda m: m["boom"] > 0)
    verdict = lambda rules: docs.select("doc_id", cascade.rejected_by(F.col("text"), rules).alias("r"))
    first = [cascade.BASE[0], later]
    assert [r.r for r in verdict(first).where("doc_id = 0").collect()] == ["few_words"]
    with pytest.raises(Exception, match="computed for one two"):
        verdict(first).collect()
    with pytest.raises(Exception, match="computed for few words"):
        verdict(first[::-1]).where("doc_id = 0").collect()


def test_the_order_saves_work_and_changes_nothing(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    order = [r for r, _, _ in cascade.estimate(docs)]
    judged = docs.select("doc_id", cascade.rejected_by(cascade._text("text"), order).alias("rejected_by")).cache()
    other = docs.select("doc_id", cascade.rejected_by(cascade._text("text"), order[::-1]).alias("rejected_by"))
    assert {r.doc_id for r in judged.where("rejected_by is null").collect()} == {r.doc_id for r in other.where("rejected_by is null").collect()}
    work = {r.rule: r for r in cascade.work_saved(judged, order).collect()}
    assert work[order[0].name].put == docs.count() and work[order[-1].name].spared > 0
    assert all(r.put + r.spared == docs.count() for r in work.values())


# --- 10: lists ----------------------------------------------------------------------------------------------------------------


def test_a_hot_pattern_is_spread(spark):
    at = lambda c: F.expr(f"timestamp_seconds({c} * 60)")
    caps = spark.range(3000).select(F.col("id").alias("page_id"), F.when(F.col("id") % 3 > 0, "http://hot.example/x").otherwise(F.concat(F.lit("http://h"), F.col("id").cast("string"), F.lit(".example/"))).alias("url"), at("id % 100").alias("fetched"))
    hist = spark.createDataFrame([("l1", "d:hot.example", 10, "add"), ("l1", "d:hot.example", 50, "remove"), ("l2", "d:example", 30, "add"), ("l2", "d:h9.example", 0, "add")], "list string, pattern string, m int, action string").select("list", "pattern", at("m").alias("at"), "action")
    one, two = ({r.page_id: tuple(r.lists) for r in url_lists.judge(caps, hist, window_rows=n).collect()} for n in (10**6, 64))
    assert one == two
    for i, lists in one.items():
        m, hot = i % 100, i % 3 > 0
        assert set(lists) == ({"l1"} if hot and 10 <= m < 50 else set()) | ({"l2"} if m >= 30 or i == 9 else set())


def test_no_pair_of_a_crowded_posting_is_left_out(spark, tmp_path, monkeypatch):
    """Groups equal brute force over all pairs that share a posting, in one large family of edited copies and their twins."""
    rng = np.random.default_rng(11)
    words = [f"w{i}" for i in range(4000)]
    base, texts = rng.choice(words, 180), []
    for _ in range(300):
        t = base.copy()
        for some in (rng.integers(3, 9), rng.integers(2, 4)):  # far from the others, then near its own twin
            t[rng.choice(len(t), some, replace=False)] = rng.choice(words, some)
            texts.append(" ".join(t))
    spark.createDataFrame([(i, texts[i]) for i in rng.permutation(len(texts)).tolist()], "doc_id long, text string").repartition(3).write.parquet(str(tmp_path / "docs"))
    docs = spark.read.parquet(str(tmp_path / "docs"))

    raw, off = np.frombuffer("".join(texts).encode(), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    h, n = simhash.shingle_hashes(raw, off, 2)
    wide = np.stack([simhash.majority(h, n), simhash.majority(simhash.remixed(h), n)], axis=1)
    fp = simhash.fingerprints_of(raw, off)
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in map(str.split, texts)]
    places = simhash.position_sets(16)
    parent = list(range(len(texts)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            far, like = wide[i] ^ wide[j], False
            if int(np.bitwise_count(far).sum()) <= simhash.WIDE_RADIUS:
                same = set(np.flatnonzero(far.view(np.uint8) == 0).tolist())
                like = any(same.issuperset(c) for c in places) and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])
            if like or int(fp[i] ^ fp[j]).bit_count() <= 3:
                parent[max(find(i), find(j))] = min(find(i), find(j))
    want = {find(i) for i in range(len(texts))}

    def kept():
        return {r.doc_id for r in simhash.keep_one(docs, least=0.8, shingle=5).collect()}

    assert 50 < len(want) < 590
    assert kept() == want
    monkeypatch.setattr(simhash, "CROWD", 64)  # several cells a posting, and pairs that wait
    monkeypatch.setattr(simhash, "FIRST_TRY", 1)
    assert kept() == want


def test_sketches_bound_the_difference_of_sets():
    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 400, k).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) for k in (0, 1, 30, 300, 300, 900)]
    s = simhash.sketches(np.concatenate(sets), np.array([len(x) for x in sets]))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets):
            assert np.bitwise_count(s[i] ^ s[j]).sum() <= len(np.setxor1d(a, b))
