"""Automata, kernels, symbol matching and packed arrays: printed examples, algebra, and invariance."""

import csv
import io
import random

import numpy as np
import pytest
from delimscan.functions import packed, symbols
from delimscan.functions.dialect import DIALECTS, FIELD, INVALID, RECORD, Dfa, Dialect, compile_dialect
from delimscan.operators import chunking, kernel
from hypothesis import given, settings
from hypothesis import strategies as st

ALPHABET = b'ab,\n"\r\t|\\#[] x,\n'


def walk(data, dfa, state):
    out = []
    for b in data:
        g = dfa.lut[b]
        out.append(int(dfa.emit[g, state]))
        state = int(dfa.table[g, state])
    return out, state


def summary(data, dfa, state):
    classes, end = walk(data, dfa, state)
    s = kernel.Summary(end, length=len(data))
    rec = [i for i, c in enumerate(classes) if c == RECORD]
    s.recs, s.is_abs = len(rec), bool(rec)
    s.col = sum(c == FIELD for c in classes[rec[-1] if rec else 0 :])
    if rec:
        s.head = sum(c == FIELD for c in classes[: rec[0]])
        widths = [sum(c == FIELD for c in classes[a:b]) + 1 for a, b in zip(rec, rec[1:])]
        if widths:
            s.mn, s.mx = min(widths), max(widths)
        s.first_end, s.last_end = rec[0] + 1, rec[-1] + 1
    bad = [i for i, c in enumerate(classes) if c == INVALID]
    if bad:
        s.bad = bad[0]
    return s


def test_printed_transition_table():
    dfa = compile_dialect("rfc4180")
    # fixed values: rows LF, quote, comma, other; states in the printed order
    want = [[0, 1, 0, 0, 0, 5], [1, 4, 5, 1, 1, 5], [3, 1, 3, 3, 3, 5], [2, 1, 2, 2, 5, 5]]
    assert dfa.table.tolist() == want
    assert [dfa.group(c) for c in '\n",x'] == [0, 1, 2, 3]


@pytest.mark.parametrize("name", list(DIALECTS))
def test_kernel_equals_sequential_run(name):
    dfa = compile_dialect(name)
    random.seed(name)
    for _ in range(80):
        data = bytes(random.choice(ALPHABET) for _ in range(random.randrange(120)))
        a = np.frombuffer(data, np.uint8)
        lane, block = random.choice([1, 2, 3, 7, 31]), random.choice([5, 16, 1000])
        got = kernel.summarize(a, dfa, lane, block)
        for s in range(dfa.n_states):
            assert got[s] == summary(data, dfa, s)
            classes, end = kernel.classify(a, dfa, s, lane, collapse=bool(lane % 2))
            assert (classes.tolist(), end) == walk(data, dfa, s)
        assert kernel.block_vector(a, dfa, lane).tolist() == [x.end for x in got]


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet='a,\n"', max_size=60), st.integers(0, 60), st.integers(0, 60))
def test_summaries_are_associative(text, i, j):
    dfa = compile_dialect("rfc4180")
    data = text.encode()
    i, j = sorted((min(i, len(data)), min(j, len(data))))
    parts = [summary_all(data[a:b], dfa) for a, b in ((0, i), (i, j), (j, len(data)))]
    x, y, z = parts
    left = [p.then(y[p.end]) for p in x]
    left = [p.then(z[p.end]) for p in left]
    yz = [p.then(z[p.end]) for p in y]
    right = [p.then(yz[p.end]) for p in x]
    assert left == right == summary_all(data, dfa)


def summary_all(data, dfa):
    return [summary(data, dfa, s) for s in range(dfa.n_states)]


def test_composition_does_not_commute():
    dfa = compile_dialect("rfc4180")
    a, b = (kernel.block_vector(np.frombuffer(x, np.uint8), dfa) for x in (b'"', b"\n"))
    assert [int(b[x]) for x in a] != [int(a[x]) for x in b]


def test_column_offset_counts_after_the_last_record_delimiter():
    dfa = compile_dialect("rfc4180")
    s = kernel.summarize(np.frombuffer(b"a,b\nc,d,e\nf,g,h,i", np.uint8), dfa)[0]
    assert (s.recs, s.col, s.head, s.mn, s.mx) == (2, 3, 1, 3, 3)


def records(data, dialect, lane=3):
    p = kernel.parse_block(np.frombuffer(data, np.uint8), compile_dialect(dialect), final=True, lane=lane)
    raw, out, lo = p.text.tobytes(), [], 0
    for hi in p.ends:
        out.append([raw[p.offsets[f] : p.offsets[f + 1]].decode() for f in range(lo, hi)])
        lo = hi
    return out


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.text(alphabet='aé😀,\n"', max_size=5), min_size=1, max_size=4), max_size=8), st.sampled_from([1, 2, 3, 5, 64]))
def test_csv_round_trip(rows, lane):
    f = io.StringIO()
    csv.writer(f, quoting=csv.QUOTE_ALL, lineterminator="\n").writerows(rows)
    assert records(f.getvalue().encode(), "rfc4180", lane) == rows


def test_dialect_cases():
    assert records(b"1,Apples\n2\n", "rfc4180") == [["1", "Apples"], ["2"]]
    assert records(b"a,b", "rfc4180") == [["a", "b"]]
    assert records(b"\n", "rfc4180") == [[""]] and records(b"", "rfc4180") == []
    assert records(b"\n\na\n", Dialect(blank_lines="skip")) == [["a"]]
    assert records(b'"a"\r\nb\r\n', "rfc4180_crlf") == [["a"], ["b"]]
    assert records(b"a\nb\r\n", Dialect(crlf=True, lenient_lf=True)) == [["a"], ["b"]]
    assert records(b'#x "\n1\n#\n2\n', "csv_comment") == [["1"], ["2"]]
    assert records(b'h [1 2] "a \\"b" 3\n', "common_log") == [["h", "1 2", 'a "b', "3"]]
    assert records(b"1,[2,3],x\n", "bracket_array") == [["1", "2,3", "x"]]
    assert records(b"a\\,b,c\n", "csv_backslash") == [["a,b", "c"]]


def test_custom_table_and_errors():
    with pytest.raises(ValueError):
        Dfa.from_table(("A",), {"x": 0}, [(0, 0, 0, 0)], ("A",), 1)
    with pytest.raises(ValueError):
        compile_dialect(Dialect(field_sep="é"))


def test_context_free_dialects():
    assert compile_dialect("tsv").context_free and not compile_dialect("rfc4180").context_free


# --- symbols and packed arrays ---------------------------------------------------------------------------------------------


def test_swar_printed_example():
    word0, word1 = symbols.lookup_words([10, 34, 44, 124]) + symbols.lookup_words([9])
    x = [(word0 >> s & 0xFF) ^ 44 for s in (0, 8, 16, 24)] + [(word1 & 0xFF) ^ 44]
    assert x == [0x26, 0x0E, 0x00, 0x50, 0x25]
    assert symbols.highest_flag(word0, 44) == 2


def test_highest_flag_is_misled_by_neighbours():
    word = symbols.lookup_words([0x22, 0x23, 0x0A, 0x2C])[0]
    assert symbols.highest_flag(word, 0x22) == 1


def test_lowest_flag_is_exact(spark):
    from pyspark.sql import functions as F

    syms = [0x22, 0x23, 0x0A, 0x2C, 0x2D, 0x00]
    got = spark.range(256).select("id", symbols.swar_index(F.col("id"), syms).alias("i")).collect()
    assert [r.i for r in got] == [syms.index(b) if b in syms else len(syms) for b in range(256)]


def test_packed_printed_example():
    lay = packed.layout(10, 5)
    assert (lay.usable, lay.width, lay.registers) == (3, 2, 3)


@settings(max_examples=100, deadline=None)
@given(st.integers(1, 16), st.integers(1, 8), st.data())
def test_packed_array(items, bits, data):
    lay = packed.layout(items, bits)
    values = data.draw(st.lists(st.integers(0, (1 << bits) - 1), min_size=items, max_size=items))
    regs = [0] * lay.registers
    for i, v in enumerate(values):
        regs = packed.put(regs, lay, i, v)
    assert [packed.get(regs, lay, i) for i in range(items)] == values and all(r < 1 << 32 for r in regs)


# --- symbols of several bytes ------------------------------------------------------------------------------------------------


def test_utf8_edges():
    data = np.frombuffer("aé😀b".encode(), np.uint8)
    assert chunking.utf8_edges(data, np.arange(len(data))).tolist() == [0, 1, 3, 3, 7, 7, 7, 7]


@pytest.mark.parametrize("big", [False, True])
def test_utf16_slices(big):
    text = "a😀é😀😀b"
    raw = np.frombuffer(text.encode("utf-16-be" if big else "utf-16-le"), np.uint8)
    for size in (2, 4, 6):
        parts = [chunking.utf16_slice(raw[i : i + size + 2], min(size, len(raw) - i), big) for i in range(0, len(raw), size)]
        assert b"".join(parts).decode("utf-16-be" if big else "utf-16-le") == text


def test_align():
    assert chunking.align(4, 31) == 28 and chunking.align(4, 3) == 4 and chunking.bytewise_safe(",", "\n") and not chunking.bytewise_safe("§")


def test_starts_that_agree_share_the_summary_of_later_lanes(monkeypatch):
    """Symbols of later lanes were summed again for every start state, however many of them agree."""
    dfa, seen = compile_dialect("rfc4180"), []
    summed = kernel._summed
    monkeypatch.setattr(kernel, "_summed", lambda classes, *a: seen.append(len(classes)) or summed(classes, *a))
    data = np.frombuffer(b'1,"a, b",c\n' * 400, np.uint8)
    n, lane = len(kernel.Lanes(data, dfa, 16).symbols), 16
    got = kernel.summarize(data, dfa, lane)
    assert sum(seen) < dfa.n_states * lane + dfa.n_states / 2 * n
    whole = [kernel.summarize(data, dfa, n + 1)[s] for s in range(dfa.n_states)]  # one lane
    assert got == whole
