"""Approximate nearest neighbours by inner product over shifted space-filling curves.

Vectors are augmented to equal length (so that a large inner product is a small distance), projected by several random
rotations, shifted, and laid along Hilbert curves.  Each ordering is range-partitioned in Spark; ranks come from
partition counts, and windows of neighbouring ranks around a query's key, over all curves, are merged and reranked.
Copies of vectors that go along the curves are rounded to a byte a component; the best of a query's windows by these
are scored again, exactly, from the vectors themselves.

The window is fitted: for a bounded sample of queries the true neighbours are found by one exact pass, and the window is
the rank distance within which ``target`` of them lie on some curve.  It follows the data, not a fixed cap.

Defined results: vectors that are null, zero, of another dimension than most, or hold null or non-finite components
take no part; equal vectors are one entry of the index and each of their ids is a candidate; ties go to the smaller
id; repeated ids count once with each distinct vector, repeated rows once; an empty table gives no row; other columns
do not matter, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable


LEAST_WINDOW = 64  # ranks to each side of a query that are always looked at


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Position on the Hilbert curve (uint64) of integer cells (n, dims), ``bits`` a side; dims * bits <= 63."""
    x = cells.astype(np.int64).copy()
    n, dims = x.shape
    q = 1 << (bits - 1)
    while q > 1:  # undo the reflections and swaps of each level, the coarsest first
        low = q - 1
        for i in range(dims):
            hit = (x[:, i] & q) != 0
            x[:, 0] = np.where(hit, x[:, 0] ^ low, x[:, 0])
            swap = np.where(hit, 0, (x[:, 0] ^ x[:, i]) & low)
            x[:, 0] ^= swap
            x[:, i] ^= swap
        q >>= 1
    for i in range(1, dims):  # Gray code across dimensions
        x[:, i] ^= x[:, i - 1]
    turn = np.zeros(n, np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        turn ^= np.where(x[:, -1] & q, q - 1, 0)
        q >>= 1
    x ^= turn[:, None]
    key = np.zeros(n, np.uint64)
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            key = (key << np.uint64(1)) | ((x[:, i] >> b) & 1).astype(np.uint64)
    return key


class Curves:
    """Rotations, shifts and cell bounds, fitted on a bounded sample."""

    def __init__(self, sample: np.ndarray, length: float, count: int, dims: int, bits: int, seed: int):
        rng = np.random.default_rng(seed)
        self.length, self.bits = length, bits
        wide = sample.shape[1] + 1
        self.dims = min(dims, wide)
        self.maps = [np.linalg.qr(rng.normal(size=(wide, wide)))[0][:, : self.dims] for _ in range(count)]
        self.shift = rng.random((count, self.dims))
        a = self.augment(sample, False)
        spans = [(p.min(0), np.maximum(np.ptp(p, axis=0), 1e-12)) for p in (a @ m for m in self.maps)]
        self.low, self.span = [s[0] for s in spans], [s[1] for s in spans]

    def augment(self, v: np.ndarray, query: bool) -> np.ndarray:
        rest = np.zeros(len(v)) if query else np.sqrt(np.maximum(self.length**2 - np.einsum("ij,ij->i", v, v), 0))
        return np.column_stack([v, rest])

    def keys(self, v: np.ndarray, query: bool) -> Iterator[tuple[int, np.ndarray]]:
        a, side = self.augment(v, query), 1 << self.bits
        for k, m in enumerate(self.maps):
            unit = ((a @ m - self.low[k]) / self.span[k] + self.shift[k]) / 2  # the shift moves cell borders by up to half the curve's cube
            yield k, hilbert_keys(np.clip(unit * side, 0, side - 1).astype(np.int64), self.bits).view(np.int64)


def _matrix(column: pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def rounded(m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors as whole numbers of a byte, and the step of each (float32)."""
    step = np.abs(m).max(axis=1) / 127
    return np.rint(m / step[:, None]).astype(np.int8), step.astype(np.float32)


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k largest scores and all that tie with the last."""
    if len(scores) <= k:
        return np.arange(len(scores))
    return np.flatnonzero(scores >= np.partition(scores, len(scores) - k)[len(scores) - k])


def _top(df: DataFrame, by: str, k: int) -> DataFrame:
    order = Window.partitionBy(by).orderBy(F.desc("score"), "cid")
    return df.withColumn("n", F.row_number().over(order)).where(F.col("n") <= k).drop("n")


def search(
    table: DataFrame, is_query: Column, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding",
    curves: int = 64, dims: int = 8, bits: int = 7, block: int = 4096, target: float = 0.95, fit_rows: int = 4096, fit_queries: int = 128, seed: int = 7, told: dict | None = None,
) -> DataFrame:
    """``(query_id, rank, id_col, score)``: the ``k`` rows of largest inner product found for each row where ``is_query``, its own excepted.

    ``block`` ranks of a curve are held at a time, of which a query is put to those in its window alone.  ``told``, if
    given, gets ``window`` and ``curves``: a query is put to at most ``curves * (2 * window + 1)`` entries.
    """
    spark = table.sparkSession
    v = F.col(vec_col)
    good = v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = table.select(F.col(id_col).cast("long").alias("id"), v.cast("array<double>").alias("v"), is_query.alias("q")).where(good & F.col("id").isNotNull())
    wide = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    schema = f"query_id long, rank int, {id_col} long, score double"
    if wide is None:
        return spark.createDataFrame([], schema)
    rows = rows.where(F.size("v") == wide["d"])
    # equal vectors are one entry, with the k + 1 smallest ids (no query needs more of them)
    n = F.row_number().over(Window.partitionBy("v").orderBy("id"))
    few = rows.select("id", "v").distinct().withColumn("n", n).where(F.col("n") <= k + 1)
    asked = rows.where("q").select("v").distinct().withColumn("q", F.lit(True))
    entry = few.groupBy("v").agg(F.sort_array(F.collect_list("id")).alias("ids")).join(asked, "v", "left")
    entries = durable(entry.select(F.element_at("ids", 1).alias("cid"), "v", "ids", F.coalesce("q", F.lit(False)).alias("q")))

    length = entries.agg(F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("s")).first()["s"] ** 0.5
    seen = entries.orderBy(F.xxhash64("cid")).limit(fit_rows).select("v").toArrow()
    model = Curves(_matrix(seen.column("v")), float(length), curves, dims, bits, seed)

    def lay(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m, cid = _matrix(batch.column(1)), batch.column(0).to_numpy()
            ask = batch.column(2).to_numpy(zero_copy_only=False).astype(bool)
            for query, own in ((False, slice(None)), (True, ask)):
                if len(cid[own]):
                    for c, key in model.keys(m[own], query):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), c), pa.int32()), pa.array(key), pa.array(np.full(len(key), query)), pa.array(cid[own])], ["curve", "key", "ask", "cid"])

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Places of entries in a sorted partition, by curve; a query gets the place of the next entry."""
        from pyspark import TaskContext

        part, base = TaskContext.get().partitionId(), {}
        for batch in batches:
            c, ask = batch.column(0).to_numpy(), batch.column(2).to_numpy(zero_copy_only=False).astype(bool)
            place = np.zeros(len(c), np.int64)
            for x in np.unique(c):
                at = np.flatnonzero(c == x)
                upto = np.cumsum(~ask[at])
                place[at] = base.get(x, 0) + upto - ~ask[at]
                base[x] = base.get(x, 0) + int(upto[-1])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(c), part), pa.int32()), batch.column(0), batch.column(2), batch.column(3), pa.array(place)], ["part", "curve", "ask", "cid", "place"])

    laid = entries.select("cid", "v", "q").mapInArrow(lay, "curve int, key long, ask boolean, cid long")
    order = ["curve", "key", "cid", "ask"]
    placed = durable(laid.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(number, "part int, curve int, ask boolean, cid long, place long"))
    before = Window.partitionBy("curve").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = placed.where("not ask").groupBy("curve", "part").count()
    every = placed.select("curve", "part").distinct().join(bases, ["curve", "part"], "left").na.fill(0, ["count"])
    base = every.withColumn("base", F.coalesce(F.sum("count").over(before), F.lit(0)))  # a row a partition and curve
    ranks = placed.join(base.select("curve", "part", "base"), ["curve", "part"]).select("curve", "ask", "cid", (F.col("base") + F.col("place")).alias("r"))

    # the window: exact neighbours of a bounded sample of queries, and how far they lie from them on their best curve
    probe = entries.where("q").orderBy(F.xxhash64("cid")).limit(fit_queries).select("cid", "v").toArrow()
    pq, pid = _matrix(probe.column("v")), probe.column("cid").to_numpy()
    if not len(pid):
        return spark.createDataFrame([], schema)

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cid, scores = batch.column(0).to_numpy(), pq @ _matrix(batch.column(1)).T
            for i in range(len(pid)):
                best = _best(scores[i], cid, k + 1)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(best), pid[i])), pa.array(cid[best]), pa.array(scores[i][best])], ["p", "cid", "score"])

    truth = durable(_top(entries.select("cid", "v").mapInArrow(exact, "p long, cid long, score double"), "p", k + 1).select("p", "cid"))
    asks = ranks.where("ask").select("curve", F.col("cid").alias("p"), F.col("r").alias("at"))
    far = truth.join(ranks.where("not ask").drop("ask"), "cid").join(asks, ["curve", "p"]).groupBy("p", "cid").agg(F.min(F.abs(F.col("r") - F.col("at"))).alias("far"))
    window = max(LEAST_WINDOW, int(far.agg(F.percentile("far", target)).first()[0]) + 1)
    if told is not None:
        told |= {"window": window, "curves": curves}

    spots = ranks.where("not ask").select("curve", F.floor(F.col("r") / block).alias("b"), "cid", F.lit(False).alias("ask"), "r")
    reach = F.sequence(F.floor(F.greatest(F.col("r") - window, F.lit(0)) / block), F.floor((F.col("r") + window) / block))
    visits = ranks.where("ask").select("curve", F.explode(reach).alias("b"), "cid", "ask", "r")

    def short(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                whole, step = rounded(_matrix(batch.column(1)))
                size = pa.array(np.arange(len(whole) + 1, dtype=np.int32) * whole.shape[1])
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.Array.from_buffers(pa.binary(), len(whole), [None, size.buffers()[1], pa.py_buffer(whole.tobytes())]), pa.array(step)], ["cid", "v", "step"])

    def rerank(group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        ask, r, cid = (group.column(c).to_numpy(zero_copy_only=False) for c in ("ask", "r", "cid"))
        ask = ask.astype(bool)
        m = np.frombuffer(b"".join(group.column("v").to_pylist()), np.int8).reshape(len(ask), -1).astype(np.float32) * group.column("step").to_numpy()[:, None]
        order = np.flatnonzero(~ask)[np.argsort(r[~ask], kind="stable")]
        place, ids, near = r[order], cid[order], m[order]
        low, high = np.searchsorted(place, r[ask] - window, "left"), np.searchsorted(place, r[ask] + window, "right")
        out = []
        for q, v, a, b in zip(cid[ask], m[ask], low, high, strict=True):
            scores = near[a:b] @ v
            best = _best(scores, ids[a:b], 2 * (k + 1))
            out.append((np.full(len(best), q), ids[a:b][best], scores[best].astype(np.float64)))
        cols = [np.concatenate(x) for x in zip(*out, strict=True)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table({"query": cols[0], "cid": cols[1], "score": cols[2]})

    bytes_ = entries.select("cid", "v").mapInArrow(short, "cid long, v binary, step float")
    sites = spots.unionByName(visits).join(bytes_, "cid")
    found = sites.groupBy("curve", "b").applyInArrow(rerank, "query long, cid long, score double")
    likely = _top(found.groupBy("query", "cid").agg(F.max("score").alias("score")), "query", 4 * (k + 1)).select("query", "cid")
    vectors = entries.select("cid", "v")
    both = likely.join(vectors, "cid").join(vectors.select(F.col("cid").alias("query"), F.col("v").alias("w")), "query")
    exact_score = F.aggregate(F.zip_with("v", "w", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    best = _top(both.select("query", "cid", exact_score.alias("score")), "query", k + 1)
    members = best.join(entries.select("cid", "ids"), "cid").select("query", "score", F.explode("ids").alias("id"))
    nearest = Window.partitionBy("query").orderBy(F.desc("score"), "id")
    members = members.withColumn("n", F.row_number().over(nearest)).where(F.col("n") <= k + 1).drop("n")
    who = rows.where("q").select("id", "v").distinct().join(entries.select("v", F.col("cid").alias("query")), "v").select(F.col("id").alias("query_id"), "query")
    final = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return (
        who.join(members, "query").where("id <> query_id").withColumn("rank", F.row_number().over(final)).where(F.col("rank") <= k)
        .select("query_id", "rank", F.col("id").alias(id_col), "score")
    )
