"""Records that cover whole splits, sets of skipped records, lists of parts, numbers of any length."""

import random

import pytest
from delimscan.operators import columnar
from delimscan.plans.reader import read_delimited
from delimscan.sources import files
from pyspark.sql import functions as F


def _write(tmp_path, data, name="in"):
    root = tmp_path / name
    root.mkdir()
    (root / "part-0").write_bytes(data)
    return str(root)


def _quote(t):
    return '"' + t.replace('"', '""') + '"'


def _rows(seed, giant_at, giant_size):
    rng = random.Random(seed)
    word = lambda n: "".join(rng.choice('ab,"\n é') for _ in range(n))
    rows = [[str(i), word(rng.randrange(12)), word(rng.randrange(9))] for i in range(40)]
    for i in giant_at:
        rows[i][1] = word(giant_size)
    return rows


@pytest.mark.parametrize("driver_splits", [4096, 0])
@pytest.mark.parametrize("giant_at", [(0,), (39,), (7, 8), (3, 20)])
def test_giant_records_are_parsed_by_many_tasks(spark, tmp_path, giant_at, driver_splits):
    rows = _rows(len(giant_at), giant_at, 900)
    path = _write(tmp_path, "".join(",".join(map(_quote, r)) + "\n" for r in rows).encode())
    plain = read_delimited(spark, path, schema="a string, b string, c string", split_bytes=64, giant_bytes=1 << 30, driver_splits=driver_splits)
    giant = read_delimited(spark, path, schema="a string, b string, c string", split_bytes=64, giant_bytes=200, driver_splits=driver_splits)
    want = [tuple(r) for r in rows]
    for got in (plain, giant):
        found = got.df.orderBy("_record_no").collect()
        assert [(r.a, r.b, r.c) for r in found] == want and [r._record_no for r in found] == list(range(40))
    apart = read_delimited(spark, path, schema="a string, b string, c string", split_bytes=64, giant_bytes=200, giant_fields="fragments", driver_splits=driver_splits)
    found = {r._record_no: r for r in apart.df.collect()}
    assert all(found[i].b is None and found[i].a == rows[i][0] and found[i].c == rows[i][2] for i in giant_at)
    text = {r["_record_no"]: r["t"] for r in apart.giant.groupBy("_record_no", "column_no").agg(F.decode(F.expr("listagg(text) WITHIN GROUP (ORDER BY seq)"), "UTF-8").alias("t")).collect()}
    assert text == {i: rows[i][1] for i in giant_at}
    assert apart.giant.count() > 5 * len(giant_at)


def test_numbers_of_any_length(spark):
    digits = {0: "0" * 30 + "12345", 1: "9" * 38, 2: "1" + "0" * 38, 3: "7" * 1200, 4: "0"}
    cut = [(k, i, t[i : i + 17]) for k, t in digits.items() for i in range(0, len(t), 17)]
    random.Random(1).shuffle(cut)
    got = {r.k: r for r in columnar.number_of_fragments(spark.createDataFrame(cut, "k int, seq int, text string"), ["k"]).collect()}
    for k, t in digits.items():
        n = int(t)
        assert got[k].number == str(n) and got[k].digits == len(str(n))
        assert got[k].value == (n if n < 10**38 else None)


def test_skipped_records(spark, tmp_path):
    path = _write(tmp_path, "".join(f"{i},x\n" for i in range(20)).encode())
    read = lambda skip: [r.a for r in read_delimited(spark, path, schema="a int, b string", split_bytes=16, skip_records=skip).df.orderBy("a").collect()]
    assert read(3) == list(range(3, 20))
    assert read((0, 5, 19, 40)) == [i for i in range(20) if i not in (0, 5, 19)]
    assert read(spark.range(2, 9).select(F.col("id").alias("_record_no"))) == [0, 1, *range(9, 20)]


def test_lists_of_parts_read_as_one_file(spark, tmp_path):
    data = bytes(range(256)) * 3
    cuts = [0, 1, 1, 200, 500, len(data)]
    lines = []
    for i, (a, b) in enumerate(zip(cuts, cuts[1:])):
        (tmp_path / f"p{i}").write_bytes(data[a:b])
        lines.append(f"{tmp_path}/p{i}\t{b - a}")
    folder = tmp_path / "lists"
    folder.mkdir()
    (folder / "f0").write_text("\n".join(lines))
    assert [r["size"] for r in files.list_files(spark, f"parts:{folder}").collect()] == [len(data)]
    name = f"parts:{folder}/f0"
    for lo in (0, 1, 199, 200, 499, 700, len(data)):
        for n in (0, 1, 3, 400, 2000):
            assert files.read_range(name, lo, n).tobytes() == data[lo : lo + n]


@pytest.mark.parametrize("mode", ["record_tags", "inline", "vector", "auto"])
def test_tagging_modes_agree(spark, tmp_path, mode):
    rows = _rows(5, (), 0)
    path = _write(tmp_path, "".join(",".join(map(_quote, r)) + "\n" for r in rows).encode())
    got = read_delimited(spark, path, schema="a string, b string, c string", split_bytes=97, tagging=mode).df.orderBy("_record_no").collect()
    assert [(r.a, r.b, r.c) for r in got] == [tuple(r) for r in rows]


def test_tagging_modes_refuse_what_they_cannot_hold(spark, tmp_path):
    ragged, unit = _write(tmp_path, b"1,a\n2\n", "ragged"), _write(tmp_path, b'1,"a\x1fb"\n2,c\n', "unit")
    for path, mode in ((ragged, "inline"), (ragged, "vector"), (unit, "inline")):
        with pytest.raises(Exception, match="record tags|vector mode"):
            read_delimited(spark, path, schema="a int, b string", tagging=mode).df.collect()
    assert [r.b for r in read_delimited(spark, ragged, schema="a int, b string", tagging="auto").df.collect()] == ["a", None]
    assert [r.b for r in read_delimited(spark, unit, schema="a int, b string", tagging="auto").df.collect()] == ["a\x1fb", "c"]
