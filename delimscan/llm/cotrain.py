"""Quality classifier by co-training of a text view and a metadata view.

Two logistic models see different sides of a document: the text view what is written, the metadata view language,
source and length.  Each round, each model labels the unlabelled documents of which it is surest, for the other.
Both are then calibrated on held-out labelled documents (Platt scaling) and their calibrated log-odds are summed, the
shared prior counted once, to score every document.

Labelled documents are sampled, ``fit_rows`` of them by the hash of their id.  Unlabelled documents all take part: each
round scores every one, and every confident one enters the other view's fit through sums of gradients and curvatures
(text view) or counts of equal metadata (metadata view).  Texts stay on the executors: what comes to the driver are
the features of the sample, sums, and words that pass the lexicon's bars.  Scoring covers all documents, whole texts.

Defined results: a null text is empty and scored like any; null metadata is a value of its own; labels that are null
or of unknown documents are ignored; a document with contradicting labels counts as bad; a labelled id with several
texts is represented by one of them (least hash); without labels of both kinds every document gets score 1 and is
kept; repeated rows are scored alike; a column of the input that is already called like a result stays as it is, and
the result's name gets an underscore.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, fresh, tidy

SHAPES = 14
TRIM = ".,;:!?\"'()[]|*#$%&<>"
META_BINS = 1 << 8
BROADCAST_IDS = 1_000_000  # labelled ids that go to every executor
RESULTS = ("p_text", "p_meta", "score", "keep")


def shape_features(text: str, words: list[str]) -> np.ndarray:
    """What a text looks like, each between 0 and about 1."""
    n, w = max(1, len(text)), len(words) + 8  # so that a few words are not judged by ratios alone
    letters = sum(map(str.isalpha, text)) or 1
    counts: dict[str, int] = {}
    for x in words:
        counts[x] = counts.get(x, 0) + 1
    pairs = sum(a == b for a, b in zip(words, words[1:], strict=False))
    lines = [x for x in text.split("\n") if x.strip()]
    marks = sum(map(text.count, "#*$%&|<>"))
    return np.array([
        1.0, min(np.log1p(len(words)) / 10, 1.2), letters / n, sum(map(str.isupper, text)) / letters, sum(map(str.isdigit, text)) / n, marks / w, text.count("!") / w,
        pairs / w, len(counts) / w, max(counts.values(), default=0) / w, 1 - len(set(lines)) / max(1, len(lines)), min(letters / w / 10, 2.0), sum(map(text.count, ".?")) / w, text.count("\n") / w,
    ])


def _stems(words: list[str], prefixes: tuple[int, ...] = ()) -> set[str]:
    """Distinct words in lower case without signs at their ends and, marked ``^``, their beginnings."""
    whole = {t for x in {w.lower() for w in words} if (t := x.strip(TRIM))}
    return whole.union(*({f"^{t[:n]}" for t in whole if len(t) > n} for n in prefixes)) if prefixes else whole


def _signature(words: list[str]) -> int:
    """Least hash of the runs of three words: near copies mostly share it, so a group of them has one voice."""
    runs = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    return min(map(xxhash.xxh32_intdigest, runs))


def meta_keys(lang: str | None, source: str | None, n_chars: int | None) -> list[int]:
    """Bins of the metadata view."""
    size = "none" if n_chars is None else str(int(np.log2(max(1, n_chars)) * 2))
    names = (f"l={lang}", f"s={source}", f"n={size}", f"ls={lang}/{source}")
    return [xxhash.xxh32_intdigest(x) % META_BINS for x in names]


def newton_sums(x: np.ndarray, y: np.ndarray, weight: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradient and curvature of the weighted log-likelihood at ``b``."""
    p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
    return x.T @ (weight * (y - p)), (x * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ x


def logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float, rounds: int = 25, more: Callable | None = None, start: np.ndarray | None = None) -> np.ndarray:
    """Ridge logistic regression by Newton steps; column 0 is the intercept and free of the ridge.

    ``more(b)`` gives the gradient and curvature of rows that are held elsewhere.
    """
    b = np.zeros(x.shape[1]) if start is None else start.copy()
    penalty = np.full(x.shape[1], ridge)
    penalty[0] = 1e-6
    for _ in range(rounds):
        g, h = newton_sums(x, y, weight, b)
        if more is not None:
            g, h = (u + v for u, v in zip((g, h), more(b), strict=True))
        step = np.linalg.solve(h + np.diag(penalty), g - penalty * b)
        b += step
        if np.abs(step).max() < 1e-6:
            break
    return b


@dataclass
class CoModel:
    """Both views with their calibration; small enough to go with a task."""

    lexicon: dict[str, float] = field(default_factory=dict)
    text: np.ndarray | None = None
    meta: np.ndarray | None = None
    scale: tuple[tuple[float, float], tuple[float, float]] = ((1.0, 0.0), (1.0, 0.0))
    prior: float = 0.0
    cut: float = 0.5

    @property
    def prefixes(self) -> tuple[int, ...]:
        return tuple(sorted({len(s) - 1 for s in self.lexicon if s[0] == "^"}))

    def text_row(self, text: str) -> np.ndarray:
        words = text.split()
        hits = _stems(words, self.prefixes) & self.lexicon.keys()
        return np.concatenate([shape_features(text, words), [min(len(hits), 5) / 5, float(bool(hits))]])

    def scores(self, texts: list[str], metas: list[list[int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Calibrated probabilities of good: text view, metadata view, both."""
        if self.text is None or self.meta is None or not texts:
            one = np.ones(len(texts))
            return one, one, one
        a = np.stack([self.text_row(t) for t in texts]) @ self.text
        b = meta_matrix(metas) @ self.meta
        za, zb = (np.clip(s * z + c, -30, 30) for z, (s, c) in ((a, self.scale[0]), (b, self.scale[1])))
        both = za + zb - self.prior
        return tuple(1 / (1 + np.exp(-z)) for z in (za, zb, both))


def meta_matrix(metas: list[list[int]]) -> np.ndarray:
    out = np.zeros((len(metas), META_BINS + 1))
    out[:, 0] = 1
    for i, keys in enumerate(metas):
        out[i, [k + 1 for k in keys]] = 1
    return out


def lexicon_of(sample: DataFrame, least: int = 6, lift: float = 25.0, prefixes: tuple[int, ...] = (4, 5, 6)) -> dict[str, float]:
    """Words, and beginnings of words, of the bad texts of ``sample(text, bad)``: with at least ``least`` voices there, ``lift`` times the rate among good texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text, bad in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                words = (text or "").split()
                stems = ["", *_stems(words, prefixes)]  # '' counts the voices themselves
                yield pa.RecordBatch.from_arrays([pa.array(stems), pa.array([bad] * len(stems)), pa.array([_signature(words)] * len(stems), pa.int64())], ["stem", "bad", "voice"])

    # a voice heard on both sides is a bad one
    heard = sample.select("text", "bad").mapInArrow(run, "stem string, bad boolean, voice long").groupBy("stem", "voice").agg(F.max("bad").alias("bad"))
    count = heard.groupBy("stem").agg(F.count_if("bad").alias("b"), F.count_if(~F.col("bad")).alias("g"))
    total = count.where("stem = ''").first()
    if total is None:
        return {}
    rate = (F.col("b") / max(1, total["b"])) / ((F.col("g") + 0.5) / max(1, total["g"]))
    found = count.where("stem <> ''").where(F.col("b") >= least).withColumn("rate", rate).where(F.col("rate") >= lift).collect()
    return {r["stem"]: float(np.log(r["rate"])) for r in found}


def _platt(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    if len(set(y.tolist())) < 2:
        return 1.0, 0.0
    b = logistic(np.column_stack([np.ones(len(z)), z]), y, np.ones(len(z)), 1e-3)
    return float(max(b[1], 0.0)), float(b[0])


Lender = tuple[np.ndarray, float, float]  # a view's weights with the calibration at the time it lent


def pseudo_labels(x: np.ndarray, lenders: list[Lender], sure: float) -> np.ndarray:
    """The label that the first sure lender gives each row; -1 where none is sure."""
    out = np.full(len(x), -1)
    for coef, s, c in lenders:
        p = 1 / (1 + np.exp(-np.clip(s * (x @ coef) + c, -30, 30)))
        out = np.where(out >= 0, out, np.where(p >= sure, 1, np.where(1 - p >= sure, 0, -1)))
    return out


class Pool:
    """Features of every unlabelled document, as a durable table that each round reads again."""

    def __init__(self, docs: DataFrame, marks: DataFrame, model: CoModel):
        """``docs(id, lang, source, n_chars, text)``; ``marks(id)`` are the labelled ones."""
        slim = _features(docs, model)
        own = marks.select("id")
        side = F.broadcast(own) if own.count() <= BROADCAST_IDS else own  # some 20 MB to each executor; above that the join shuffles
        self.table = durable(slim.join(side, "id", "left_anti").select("x", "keys"))

    def lend(self, by_text: list[Lender], by_meta: list[Lender], sure: float) -> list[tuple[list[int], int, int, int]]:
        """``(keys, label for the metadata view, label for the text view, documents)``."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    x, keys = b.column(0).flatten().to_numpy().reshape(b.num_rows, -1), b.column(1).to_pylist()
                    yield pa.RecordBatch.from_arrays([b.column(1), pa.array(pseudo_labels(x, by_text, sure), pa.int32()), pa.array(pseudo_labels(meta_matrix(keys), by_meta, sure), pa.int32())], ["keys", "for_meta", "for_text"])

        got = self.table.mapInArrow(run, "keys array<int>, for_meta int, for_text int").groupBy("keys", "for_meta", "for_text").count()
        return [tuple(r) for r in got.where("for_meta >= 0 or for_text >= 0").collect()]  # a row a combination of language, source and size

    def text_sums(self, by_meta: list[Lender], sure: float, weights: np.ndarray) -> Callable:
        """Gradient and curvature of the text view's pseudo-labelled rows, summed over partitions in Spark."""

        def more(coef: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                n = len(coef)
                g, h = np.zeros(n), np.zeros((n, n))
                for b in batches:
                    if b.num_rows:
                        y = pseudo_labels(meta_matrix(b.column(1).to_pylist()), by_meta, sure)
                        x = b.column(0).flatten().to_numpy().reshape(b.num_rows, -1)[y >= 0]
                        y = y[y >= 0]
                        dg, dh = newton_sums(x, y, weights[y], coef)
                        g, h = g + dg, h + dh
                flat = np.concatenate([g, h.ravel()])
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int32()), pa.array(flat)], ["at", "value"])

            got = self.table.mapInArrow(run, "at int, value double").groupBy("at").agg(F.sum("value").alias("value")).collect()
            flat = np.zeros(len(coef) * (len(coef) + 1))
            for r in got:
                flat[r["at"]] = r["value"]
            return flat[: len(coef)], flat[len(coef) :].reshape(len(coef), -1)

        return more


def held_out(n: int, held: float = 0.3) -> np.ndarray:
    """Which of ``n`` sampled documents are kept back for calibration."""
    return np.arange(n) % 10 < round(10 * held)


def co_train(model: CoModel, a: np.ndarray, metas: list[list[int]], y: np.ndarray, out: np.ndarray, pool: Pool, rounds: int = 3, sure: float = 0.98) -> CoModel:
    """Fit both views of ``model`` on features ``a`` and metadata, ``y`` being 1 for good; rows where ``out`` calibrate.

    Pseudo-labels weigh half a label each, and together no more than the labels of their kind.
    """
    fit = ~out
    if len(set(y[fit].tolist())) < 2 or not out.any():  # too few labels to hold any out
        fit = out = np.ones(len(y), bool)
    b = meta_matrix(metas)
    base = float(np.log(y[fit].mean() / (1 - y[fit].mean())))
    own, one = np.array([(y[fit] == k).sum() for k in (0, 1)]), np.ones(int(fit.sum()))
    ta, tb = logistic(a[fit], y[fit], one, 0.05), logistic(b[fit], y[fit], one, 2.0)
    by_text: list[Lender] = []
    by_meta: list[Lender] = []
    for _ in range(rounds):
        by_text.append((ta, *_platt(a[out] @ ta, y[out])))
        by_meta.append((tb, *_platt(b[out] @ tb, y[out])))
        lent = pool.lend(by_text, by_meta, sure)
        count = lambda k: np.array([sum(r[3] for r in lent if r[k] == v) for v in (0, 1)])
        for_meta, for_text = (np.minimum(0.5, own / np.maximum(count(k), 1)) for k in (1, 2))
        rows = [r for r in lent if r[1] >= 0]
        if rows:
            yy, n = np.array([r[1] for r in rows]), np.array([r[3] for r in rows])
            tb = logistic(np.vstack([b[fit], meta_matrix([r[0] for r in rows])]), np.concatenate([y[fit], yy]), np.concatenate([one, n * for_meta[yy]]), 2.0)
        if any(r[2] >= 0 for r in lent):
            ta = logistic(a[fit], y[fit], one, 0.05, more=pool.text_sums(by_meta, sure, for_text), start=ta)
    model.text, model.meta, model.prior = ta, tb, base
    model.scale = (_platt(a[out] @ ta, y[out]), _platt(b[out] @ tb, y[out]))
    return model


def _features(rows: DataFrame, model: CoModel) -> DataFrame:
    """``(id, x, keys)`` of ``rows(id, lang, source, n_chars, text)``: features of both views."""
    held = rows.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                b = batch.slice(lo, 256)
                x = [held.value.text_row(t or "").tolist() for t in b.column(4).to_pylist()]
                metas = [meta_keys(*m) for m in zip(*(b.column(k).to_pylist() for k in (1, 2, 3)), strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x, pa.list_(pa.float64())), pa.array(metas, pa.list_(pa.int32()))], ["id", "x", "keys"])
        tidy()

    return rows.select("id", "lang", "source", "n_chars", "text").mapInArrow(run, "id long, x array<double>, keys array<int>")


def fit_model(docs: DataFrame, labels: DataFrame, fit_rows: int = 6000, id_col: str = "doc_id", text_col: str = "text") -> CoModel:
    """Fit on at most ``fit_rows`` labelled documents and on all unlabelled ones."""
    marks = labels.where("quality is not null").groupBy(F.col(id_col).cast("long").alias("id")).agg(F.min("quality").alias("quality"), F.max(F.coalesce("toxic", F.lit(0))).alias("toxic"))
    cols = [F.col(id_col).cast("long").alias("id"), *[(F.col(c) if c in docs.columns else F.lit(None)).cast("string").alias(c) for c in ("lang", "source")], (F.col("n_chars") if "n_chars" in docs.columns else F.char_length(text_col)).cast("long").alias("n_chars")]
    plain = docs.select(*cols, F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    ids = plain.where("id is not null").select("id").distinct()
    # the sample is chosen by id alone, so only its texts are fetched
    chosen = ids.join(marks, "id").orderBy(F.xxhash64("id"), "id").limit(fit_rows).toArrow().to_pydict()
    y = np.array([float(q == 1 and t == 0) for q, t in zip(chosen["quality"], chosen["toxic"], strict=True)])
    model = CoModel()
    if not len(y) or y.min() == y.max():
        return model
    out = held_out(len(y))
    at = docs.sparkSession.createDataFrame([(i, k, bool(t)) for k, (i, t) in enumerate(zip(chosen["id"], chosen["toxic"], strict=True))], "id long, at int, bad boolean")
    rows = plain.join(F.broadcast(at), "id")
    own = F.min_by(F.struct("lang", "source", "n_chars", "text", "bad"), F.struct(F.xxhash64("text"), F.xxhash64("lang", "source", "n_chars")))
    sample = durable(rows.groupBy("id", "at").agg(own.alias("r")).select("id", "at", "r.*"))
    few = sample.where(~F.col("at").isin([int(k) for k in np.flatnonzero(out)])) if len(set(y[~out].tolist())) == 2 else sample
    model.lexicon = lexicon_of(few)
    got = sorted(_features(sample.withColumn("id", F.col("at").cast("long")), model).collect(), key=lambda r: r["id"])  # two short lists a sampled document
    a, metas = np.array([r["x"] for r in got]), [list(r["keys"]) for r in got]
    return co_train(model, a, metas, y, out, Pool(plain, marks, model))


def score(docs: DataFrame, model: CoModel, text_col: str = "text") -> DataFrame:
    """``docs`` with ``p_text``, ``p_meta``, ``score`` and ``keep``, in one pass without a shuffle."""
    names = [f"__{i}" for i in range(len(docs.columns))]
    plain = docs.toDF(*names)
    of = dict(zip(docs.columns, names, strict=True))
    extra = [(F.col(of[c]).cast("string") if c in of else F.lit(None).cast("string")).alias(f"__{c}") for c in ("lang", "source")]
    size = (F.col(of["n_chars"]) if "n_chars" in of else F.char_length(of[text_col])).cast("long").alias("__n")
    src = plain.select(*names, F.col(of[text_col]).cast("string").alias("__text"), *extra, size)
    held = docs.sparkSession.sparkContext.broadcast(model)  # a lexicon and two weight vectors

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                rows = batch.slice(lo, 256)
                texts = [t or "" for t in rows.column(len(names)).to_pylist()]
                metas = [meta_keys(*x) for x in zip(*(rows.column(len(names) + k).to_pylist() for k in (1, 2, 3)), strict=True)]
                a, b, both = held.value.scores(texts, metas)
                cols = [*rows.columns[: len(names)], pa.array(a), pa.array(b), pa.array(both), pa.array(both >= held.value.cut)]
                yield pa.RecordBatch.from_arrays(cols, [*names, *RESULTS])
        tidy()

    schema = plain.schema.add("p_text", "double").add("p_meta", "double").add("score", "double").add("keep", "boolean")
    return src.mapInArrow(run, schema).toDF(*docs.columns, *[fresh(c, docs.columns) for c in RESULTS])


def kept(docs: DataFrame, model: CoModel, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the classifier keeps, with its columns."""
    scored = score(docs, model, text_col)
    return scored.where(F.col(scored.columns[-1])).select(*scored.columns[: len(docs.columns)])
