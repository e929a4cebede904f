"""Quality rules as a short-circuit cascade, in DataFrame expressions only.

Every rule is a predicate over the measures of a text.  On a bounded sample the cost of each rule (seconds of a job
that computes only it, less those of a job that computes nothing) and its rejection rate are estimated; rules run in
descending order of rejection per cost, and a text that one rule rejects is not put to the next, whose measures are
then not computed.  The order changes the work, never the verdict.

Defined results: a null text is empty and fails the word count; equal rules per cost keep their given order; repeated
rows are judged alike; an empty table gives the given order and no row; a column of the input that is already called
like a result stays as it is, and the result's name gets an underscore.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, let

GAP = r"[\x20\x09-\x0D]+"
SAMPLE_ROWS, SAMPLE_BYTES = 512, 1 << 18  # bounds of the sample from which cost and rejection are estimated, and of a text in it


@dataclass(frozen=True)
class Rule:
    name: str
    measures: tuple[str, ...]  # names in MEASURES that the rule needs
    rejects: Callable[[dict[str, Column]], Column]


def words(text: Column) -> Column:
    return F.filter(F.split(text, GAP), lambda w: w != "")


def _repeated(ws: Column, width: int = 5) -> Column:
    """Words inside windows of ``width`` words that occur twice or more in the text, the first included."""
    n = F.size(ws)

    def of(h: Column) -> Column:
        pairs = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def marked(p: Column) -> Column:
            last = F.size(p) - 1
            twin = F.filter(p, lambda x, i: ((i > 0) & (x["h"] == p[F.greatest(i - 1, F.lit(0))]["h"])) | ((i < last) & (x["h"] == p[F.least(i + 1, last)]["h"])))
            start = F.struct(F.lit(0).cast("long").alias("sum"), F.lit(-width).alias("at"))
            step = lambda a, x: F.struct((a["sum"] + F.least(F.lit(width), x - a["at"])).alias("sum"), x.alias("at"))
            return F.aggregate(F.array_sort(F.transform(twin, lambda x: x["i"])), start, step, lambda a: a["sum"])

        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(let(pairs, marked))

    hashes = F.transform(F.sequence(F.lit(0), n - width), lambda i: F.xxhash64(*[ws[i + k] for k in range(width)]))
    return F.when(n < width, F.lit(0).cast("long")).otherwise(let(hashes, of))


def _duplicate_lines(text: Column) -> Column:
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return let(lines, lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long"))


def _lines_like(text: Column, pattern: str) -> Column:
    return F.size(F.filter(F.split(text, "\n"), lambda x: x.rlike(pattern))).cast("long")


#: Each measure from ``t`` (text, never null) and ``ws`` (its words).
MEASURES = {
    "n_words": lambda t, ws: F.size(ws).cast("long"),
    "word_chars": lambda t, ws: F.char_length(F.array_join(ws, "")).cast("long"),
    "n_symbols": lambda t, ws: F.regexp_count(t, F.lit(r"[#*$%&|<>]")).cast("long"),
    "n_dup_lines": lambda t, ws: _duplicate_lines(t),
    "n_repeat_words": lambda t, ws: _repeated(ws),
    "n_lines": lambda t, ws: _lines_like(t, r"[^\x20\x09-\x0D]"),
    "n_bullet_lines": lambda t, ws: _lines_like(t, r"^[\x20\x09-\x0D]*[-*+\u2022\u2023\u25E6][\x20\x09]"),
    "n_cut_lines": lambda t, ws: _lines_like(t, r"(?:\.\.\.|\u2026)[\x20\x09-\x0D]*\z"),
    "n_letter_words": lambda t, ws: F.size(F.filter(ws, lambda w: w.rlike(r"\p{L}"))).cast("long"),
}
CONTRACT = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")  # measures that every row of ``measured`` carries
BASE = (
    Rule("few_words", ("n_words",), lambda m: m["n_words"] < 10),
    Rule("repeats", ("n_words", "n_repeat_words"), lambda m: 100 * m["n_repeat_words"] > 20 * m["n_words"]),
)
#: Rules beside the base, in whole numbers.
MORE = (
    Rule("symbols", ("n_words", "n_symbols"), lambda m: 100 * m["n_symbols"] > 20 * m["n_words"]),
    Rule("duplicate_lines", ("n_words", "n_dup_lines"), lambda m: (m["n_dup_lines"] > 5) & (10 * m["n_dup_lines"] > m["n_words"])),
    Rule("word_length", ("n_words", "word_chars"), lambda m: (m["word_chars"] < 2 * m["n_words"]) | (m["word_chars"] > 100 * m["n_words"])),
    Rule("bullets", ("n_lines", "n_bullet_lines"), lambda m: 10 * m["n_bullet_lines"] > 9 * m["n_lines"]),
    Rule("cut_lines", ("n_lines", "n_cut_lines"), lambda m: 10 * m["n_cut_lines"] > 3 * m["n_lines"]),
    Rule("no_letters", ("n_words", "n_letter_words"), lambda m: 10 * m["n_letter_words"] < 6 * m["n_words"]),
)
RULES = BASE + MORE


def _text(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def estimate(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> list[tuple[Rule, float, float]]:
    """``(rule, seconds, rejection rate)`` of each rule on at most ``sample_rows`` rows, the best rejection per cost first."""
    few = docs.select(_text(text_col).alias("t")).where(F.octet_length("t") <= SAMPLE_BYTES).limit(sample_rows).toArrow()  # reads as many partitions as it needs
    sample = docs.sparkSession.createDataFrame(few)

    def timed(verdict: Column) -> tuple[float, float]:
        began = time.perf_counter()
        row = sample.agg(F.count("*").alias("n"), F.count_if(verdict).alias("bad")).first()
        return time.perf_counter() - began, (row["bad"] or 0) / max(1, row["n"])

    timed(F.col("t") == "")  # the first job pays for starting up
    floor = timed(F.col("t") == "")[0]
    found = []
    for rule in rules:
        seconds, rate = timed(rejected_by(F.col("t"), [rule]).isNotNull())
        found.append((rule, max(seconds - floor, 1e-3), rate))
    return sorted(found, key=lambda x: -x[2] / x[1])


def rejected_by(text: Column, rules: list[Rule], ws: Column | None = None, known: dict[str, Column] | None = None) -> Column:
    """Name of the first rule, in the order given, that rejects a text; null if none does.

    The measures of later rules are not computed.  ``known`` are measures that are there already.
    """

    def chain(ws: Column) -> Column:
        out = F.when(F.lit(False), F.lit(None).cast("string"))
        for r in rules:
            out = out.when(r.rejects({m: (known or {}).get(m, MEASURES[m](text, ws)) for m in r.measures}), F.lit(r.name))
        return out

    return let(words(text), chain) if ws is None else chain(ws)


def verdict(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> Column:
    """:func:`rejected_by` of ``docs``, the rules ordered by a sample of it."""
    return rejected_by(_text(text_col), [r for r, _, _ in estimate(docs, rules, text_col, sample_rows)])


def cascade(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """``docs`` with ``rejected_by``; rules are ordered by a sample of ``docs``."""
    return docs.withColumn(fresh("rejected_by", docs.columns), verdict(docs, rules, text_col, sample_rows))


def kept(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """The rows of ``docs`` that no rule rejects, with its columns."""
    return docs.where(verdict(docs, rules, text_col, sample_rows).isNull())


def measured(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """``(id_col, measures, base_failed, kept, rejected_by)``: the measures in ``CONTRACT`` of every row, and the cascade's verdict.

    The cascade takes those measures as known; those of the other rules are computed only for the texts that reach them.
    """
    order = [r for r, _, _ in estimate(docs, rules, text_col, sample_rows)]
    t = _text(text_col)

    def row(ws: Column) -> Column:
        got = F.struct(*[MEASURES[m](t, ws).alias(m) for m in CONTRACT])
        return let(got, lambda g: F.struct(*[g[m].alias(m) for m in CONTRACT], rejected_by(t, order, ws, {m: g[m] for m in CONTRACT}).alias("rejected_by")))

    rows = docs.select(F.col(id_col), let(words(t), row).alias("m")).select(id_col, "m.*")
    has = {m: F.col(m) for m in CONTRACT}
    failed = F.lit(False)
    for r in BASE:
        failed = failed | r.rejects(has)
    return rows.select(id_col, *CONTRACT, failed.alias("base_failed"), (~failed & F.col("rejected_by").isNull()).alias("kept"), "rejected_by")


def work_saved(judged: DataFrame, order: list[Rule], name: str = "rejected_by") -> DataFrame:
    """``(rule, put, rejected, spared)``: texts put to each rule of ``order``, rejected by it, and spared it by the rules before."""
    place = {r.name: i for i, r in enumerate(order)}
    at = F.coalesce(*[F.when(F.col(name) == n, F.lit(i)) for n, i in place.items()], F.lit(len(order)))
    sums = [x for i in range(len(order)) for x in (F.count_if(F.col("at") >= i).alias(f"p{i}"), F.count_if(F.col("at") == i).alias(f"r{i}"), F.count_if(F.col("at") < i).alias(f"s{i}"))]
    one = judged.select(at.alias("at")).agg(*sums)
    return one.select(F.explode(F.array(*[F.struct(F.lit(r.name).alias("rule"), F.col(f"p{i}").alias("put"), F.col(f"r{i}").alias("rejected"), F.col(f"s{i}").alias("spared")) for i, r in enumerate(order)])).alias("x")).select("x.*")
