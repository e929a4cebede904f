"""SimHash near-duplicates through an inverted index over byte positions with count filtering.

Two 64-bit fingerprints that differ in at most three bits share at least five of their eight positional bytes.  Every
fingerprint is posted under four of its bytes at a time, for the position sets of a Steiner system: position sets whose
numbers cancel under exclusive or.  There are 14 of them, and any five positions hold one, so fingerprints that share
five bytes meet in a posting.  There, shared positional bytes are tallied pair by pair; pairs that reach the guaranteed
minimum are verified by popcount, and only a spanning forest of the verified links leaves the posting.

A crowded posting is split by each further position (a link shares a fifth byte), so what one task holds of it are
distinct fingerprints that agree in 40 bits: at most 2**24 whatever the corpus.  If even such a part is crowded, it is
settled on the cube of the bits that vary there, without pairs.

The stage of a pipeline (:func:`keep_one`) also wants copies that were edited further: texts whose sets of five-word
shingles have a Jaccard similarity of ``least`` or more.  These are sought with a second fingerprint of 128 bits over
word pairs (of the usual sizes the one that moves least under an edit), in the same index of four out of 16 positions,
140 sets, of which any seven positions hold one.  Candidates are verified exactly on the whole texts' shingles.
Crowded postings are linked in two steps: a sparse one, which joins most copies, and one that looks at every pair of
members still apart (:func:`apart_pairs`), so no pair of a posting is left out.

Defined results: null or empty text has fingerprint 0 and links like any other; rows with a null ``doc_id`` keep
their fingerprint and group, whose ``component_id`` is the smallest non-null id in it (null if there is none);
repeated rows are returned as often as they occur; columns beyond id and text do not matter; an empty table gives no
row.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE, durable, fresh, slices, word_spans, xxh64_spans
from .components import connected_components

BITS, BYTES, RADIUS = 64, 8, 3
KEEP = BYTES - RADIUS  # positional bytes that a link shares at least
CROWD = 16384  # members from which a posting is split, and a part of it settled on its cube
WIDE_BYTES, WIDE_RADIUS, WIDE_SHINGLE = 16, 20, 2
PIECE = 1 << 20  # rows of one posting that a task holds at once
SMALL = 5  # members up to which all pairs of a posting are candidates at once
SKETCH = 1024  # bits of a set's parity sketch
FIRST_TRY = 256  # pairs of a member and cell that the second step tries first, eight times as many in each further try until none waits


def position_sets(positions: int) -> list[tuple[int, ...]]:
    """Sets of four positions that cancel under exclusive or (``positions`` a power of two)."""
    return [c for c in combinations(range(positions), 4) if not c[0] ^ c[1] ^ c[2] ^ c[3]]


def lowered(raw: np.ndarray) -> np.ndarray:
    low = raw.copy()
    low[(low >= 65) & (low <= 90)] += 32
    return low


def shingle_hashes(raw: np.ndarray, off: np.ndarray, size: int, seed: int = 42) -> tuple[np.ndarray, np.ndarray]:
    """``(hashes, count of each text)`` of the shingles of ``size`` words, lower case, joined by one blank; a text with fewer words is one shingle."""
    low = lowered(raw)
    starts, ends, first = word_spans(low, off)
    words = np.diff(first)
    count = np.where(words > 0, np.maximum(words - size + 1, 1), 0)
    if not len(starts):
        return np.zeros(0, np.uint64), count
    keep = np.zeros(len(low) + 1, bool)
    keep[:-1] = ~SPACE[low]
    gaps = ends[:-1][ends[:-1] < starts[1:]]  # one blank after each word that a gap follows
    keep[gaps] = True
    low = np.append(low, np.uint8(32))
    low[gaps] = 32
    where = np.cumsum(keep) - 1
    packed = low[keep]
    doc = np.repeat(np.arange(len(words)), count)
    head = first[:-1][doc] + (np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count))
    tail = np.minimum(head + size - 1, first[1:][doc] - 1)
    at = where[starts[head]]
    return xxh64_spans(packed, at, where[ends[tail] - 1] + 1 - at, seed), count


def majority(hashes: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Fingerprint (uint64) of each text: the bits set in over half of its hashes."""
    live = np.flatnonzero(count)
    out = np.zeros(len(count), np.uint64)
    if len(live):
        bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, BYTES), axis=1, bitorder="little")
        edge = np.concatenate([[0], np.cumsum(count[live])]).tolist()
        ones = np.stack([bits[a:b].sum(axis=0, dtype=np.int64) for a, b in zip(edge[:-1], edge[1:], strict=True)])
        over = (2 * ones > count[live][:, None]).astype(np.uint8)
        out[live] = np.packbits(over, axis=1, bitorder="little").view(np.uint64)[:, 0]
    return out


def fingerprints_of(raw: np.ndarray, off: np.ndarray, size: int = 3, seed: int = 42) -> np.ndarray:
    """SimHash (uint64) of each text of a concatenation, over shingles of ``size`` words, repeats included."""
    return majority(*shingle_hashes(raw, off, size, seed))


def remixed(h: np.ndarray) -> np.ndarray:
    """Another 64 bits from a 64-bit hash (multiply and shift)."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def with_fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3) -> DataFrame:
    """``(id, fp)`` of every row, whole texts, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, off in slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(fingerprints_of(raw, off, size).view(np.int64))], ["id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "id long, fp long")


def _mask(positions: tuple[int, ...]) -> int:
    """A signed word with all bits set at those of ``positions`` that are below 8."""
    m = sum(0xFF << (8 * p) for p in positions if 0 <= p < BYTES)
    return m - (1 << 64) if m >> 63 else m


def _pick(masks: list[int], i: Column) -> Column:
    return F.get(F.array(*[F.lit(m).cast("long") for m in masks]), i)


def postings(fps: DataFrame, fp: str = "fp") -> DataFrame:
    """``(combo, key, fp)``: each fingerprint under every set of four positions, ``key`` being its bytes there."""
    masks = [_mask(c) for c in position_sets(BYTES)]
    each = fps.select(F.col(fp).alias("fp"), F.explode(F.sequence(F.lit(0), F.lit(len(masks) - 1))).alias("combo"))
    return each.select("combo", F.col("fp").bitwiseAND(_pick(masks, F.col("combo"))).alias("key"), "fp")


def wide_postings(fps: DataFrame) -> DataFrame:
    """``(combo, key, fp, fp2, root)`` of 128-bit fingerprints, ``key`` a hash of the four bytes (equal hashes are only candidates)."""
    sets = position_sets(WIDE_BYTES)
    each = fps.select("fp", "fp2", "root", F.explode(F.sequence(F.lit(0), F.lit(len(sets) - 1))).alias("combo"))
    low, high = ([_mask(tuple(p - shift for p in c)) for c in sets] for shift in (0, BYTES))
    key = F.xxhash64("combo", F.col("fp").bitwiseAND(_pick(low, F.col("combo"))), F.col("fp2").bitwiseAND(_pick(high, F.col("combo"))))
    return each.select("combo", key.alias("key"), "fp", "fp2", "root")


def split_crowds(posts: DataFrame, crowd: int | None = None) -> DataFrame:
    """Postings of more than ``crowd`` members under each further position as well, five bytes to a key, in place of their own."""
    crowd = crowd or CROWD
    hot = durable(posts.groupBy("combo", "key").count().where(F.col("count") > crowd).select("combo", "key", F.lit(True).alias("hot")))
    if not hot.limit(1).count():
        return posts
    sets = position_sets(BYTES)
    finer = [_mask((*c, p)) for c in sets for p in range(BYTES) if p not in c]
    more = len(finer) // len(sets)
    turns = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(more - 1))).otherwise(F.array(F.lit(-1)))
    each = posts.join(hot, ["combo", "key"], "left").select("combo", "key", "fp", F.explode(turns).alias("j"))
    place = F.col("combo") * more + F.col("j")
    part = F.col("j") >= 0
    return each.select(F.when(part, len(sets) + place).otherwise(F.col("combo")).cast("int").alias("combo"), F.when(part, F.col("fp").bitwiseAND(_pick(finer, place))).otherwise(F.col("key")).alias("key"), "fp")


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        up = parent[parent]
        if np.array_equal(up, parent):
            return parent
        parent = up


def _unite(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    while len(a):
        x, y = parent[a], parent[b]
        far = x != y
        a, b, x, y = a[far], b[far], x[far], y[far]
        np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))
        parent = _roots(parent)
    return parent


def _cube_roots(fp: np.ndarray) -> np.ndarray:
    """Components of a crowded posting (links: up to RADIUS bits), by minima spread over the cube of its varying bits."""
    varying = int(np.bitwise_or.reduce(fp ^ fp[0]))
    dims = [b for b in range(BITS) if varying >> b & 1]
    at = np.zeros(len(fp), np.int64)
    for i, b in enumerate(dims):
        at |= ((fp >> np.uint64(b)) & np.uint64(1)).astype(np.int64) << i
    label = np.arange(len(fp), dtype=np.int32)
    cube = np.empty(1 << len(dims), np.int32)
    while True:
        cube.fill(np.iinfo(np.int32).max)
        cube[at] = label
        for _ in range(RADIUS):
            src = cube.copy()
            for i in range(len(dims)):
                pair, other = cube.reshape(-1, 2, 1 << i), src.reshape(-1, 2, 1 << i)
                np.minimum(pair[:, 0], other[:, 1], out=pair[:, 0])
                np.minimum(pair[:, 1], other[:, 0], out=pair[:, 1])
        new = _roots(cube[at])
        if np.array_equal(new, label):
            return label
        label = new


def shared_bytes(far: np.ndarray) -> np.ndarray:
    """Tally of positional bytes that two fingerprints share, from their exclusive or."""
    return (far.view(np.uint8).reshape(len(far), -1) == 0).sum(axis=1)


def _runs(combo: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(begin, size)`` of the postings of a table sorted by ``(combo, key)``."""
    new = np.ones(len(key), bool)
    new[1:] = (combo[1:] != combo[:-1]) | (key[1:] != key[:-1])
    begin = np.flatnonzero(new)
    return begin, np.diff(np.append(begin, len(key)))


def link_runs(combo: np.ndarray, key: np.ndarray, fp: np.ndarray) -> np.ndarray:
    """Root index of each entry of a posting table sorted by ``(combo, key)``."""
    n = len(fp)
    parent = np.arange(n)
    begin, size = _runs(combo, key)
    for b, m in zip(begin[size > CROWD], size[size > CROWD], strict=True):
        parent[b : b + m] = b + _cube_roots(fp[b : b + m])
    fine = (size > 1) & (size <= CROWD)
    remaining = np.repeat(size, size) - (np.arange(n) - np.repeat(begin, size)) - 1  # members after each one
    live = np.flatnonzero((remaining > 0) & np.repeat(fine, size))
    step = 1
    while len(live):
        far = fp[live] ^ fp[live + step]
        likely = shared_bytes(far) >= KEEP
        near = live[likely][np.bitwise_count(far[likely]) <= RADIUS]
        parent = _unite(parent, near, near + step)
        step += 1
        live = live[remaining[live] >= step]
    return parent


@lru_cache(maxsize=1)
def _first_sets() -> np.ndarray:
    """The first position set within each choice of 16 positions (255: none)."""
    choice, out = np.arange(1 << WIDE_BYTES), np.full(1 << WIDE_BYTES, 255, np.uint8)
    for i, c in reversed(list(enumerate(position_sets(WIDE_BYTES)))):
        mask = sum(1 << p for p in c)
        out[(choice & mask) == mask] = i
    return out


def first_meeting(combo: np.ndarray, far: np.ndarray, far2: np.ndarray) -> np.ndarray:
    """Whether a pair, given by its exclusive or, meets under no position set before ``combo``."""
    low, high = (np.packbits(x.view(np.uint8).reshape(-1, BYTES) == 0, axis=1, bitorder="little")[:, 0].astype(np.int64) for x in (far, far2))
    return _first_sets()[low | (high << 8)] == combo


def wide_runs(combo: np.ndarray, key: np.ndarray, fp: np.ndarray, fp2: np.ndarray, radius: int = WIDE_RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Candidate pairs (indices) of a table sorted by ``(combo, key, fp, fp2)``: within ``radius`` bits of 128.

    All pairs of postings of up to ``SMALL`` members.  In a larger one a member is put to the next and to the posting's
    centre, the member nearest to the bitwise majority, so pairs grow with the members and not with their square; the
    others are left to :func:`apart_pairs`.
    """
    begin, size = _runs(combo, key)
    n = len(fp)
    remaining = np.repeat(size, size) - (np.arange(n) - np.repeat(begin, size)) - 1
    left, right = [], []
    small = np.repeat(size <= SMALL, size)
    for step in range(1, SMALL):
        at = np.flatnonzero((remaining >= step) & (small | (step == 1)))
        left.append(at)
        right.append(at + step)
    for b, m in zip(begin[size > SMALL], size[size > SMALL], strict=True):
        own = np.stack([fp[b : b + m], fp2[b : b + m]], axis=1)
        bits = np.unpackbits(own.view(np.uint8).reshape(m, -1), axis=1)
        centre = np.packbits(2 * bits.sum(axis=0, dtype=np.int64) > m).view(np.uint64)
        mid = b + int(np.argmin(np.bitwise_count(own ^ centre).sum(axis=1)))
        rest = np.delete(np.arange(b, b + m), mid - b)
        left.append(np.minimum(rest, mid))
        right.append(np.maximum(rest, mid))
    a, c = np.concatenate(left), np.concatenate(right)
    far, far2 = fp[a] ^ fp[c], fp2[a] ^ fp2[c]
    near = np.bitwise_count(far).astype(np.int64) + np.bitwise_count(far2) <= radius
    near &= ~small[a] | first_meeting(combo[a], far, far2)
    return a[near], c[near]


def crowds(combo: np.ndarray, key: np.ndarray, several: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(begin, size)`` of the postings of a sorted table whose pairs :func:`wide_runs` does not give whole.

    These are postings of more than ``SMALL`` members, those with a member of ``several`` texts (alone in its posting
    only under the first position set, where equal members meet), and the table's first and last, which may go on in
    another table.
    """
    begin, size = _runs(combo, key)
    many = np.logical_or.reduceat(several, begin) & ((size > 1) | (combo[begin] == 0))
    many |= size > SMALL
    many[[0, -1]] = True
    return begin[many], size[many]


def shingle_sets(h: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(hashes, count of each text)`` without repeats, in order."""
    doc = np.repeat(np.arange(len(count)), count)
    order = np.lexsort((h, doc))
    h = h[order]
    once = np.ones(len(h), bool)
    once[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    return h[once], np.bincount(doc[once], minlength=len(count))


def sketches(h: np.ndarray, count: np.ndarray) -> np.ndarray:
    """A row of ``SKETCH // 64`` words for each set: bit b says whether it has an odd number of hashes that are b modulo ``SKETCH``.

    Two sketches differ in at most as many bits as the sets have elements that are not common.
    """
    at = np.repeat(np.arange(len(count)), count) * SKETCH + (h % np.uint64(SKETCH)).astype(np.int64)
    odd = (np.bincount(at, minlength=len(count) * SKETCH) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view(np.uint64).reshape(len(count), SKETCH // 64)


def apart_pairs(combo: np.ndarray, fp: np.ndarray, fp2: np.ndarray, root: np.ndarray, block: np.ndarray, n: np.ndarray, sketch: np.ndarray, least: float, most: int, crossing: bool = False, radius: int = WIDE_RADIUS) -> tuple[np.ndarray, np.ndarray, int]:
    """Pairs (indices) of one posting in different groups ``root``, within ``radius`` bits, that may have a similarity of ``least``; and how many wait.

    Every pair is looked at.  Ruled out are those of which the sizes ``n`` or the sketches show more differing elements
    than the similarity allows, and those that meet in an earlier posting.  A member gives up to ``most`` pairs; the
    others wait for a call with more.  ``crossing``: only pairs of different blocks.
    """
    names, label, members = np.unique(root, return_inverse=True, return_counts=True)
    order = np.argsort(label == np.argmax(members), kind="stable")  # the largest group last: no pairs inside it are looked at
    few = len(root) - int(members.max()) if len(names) else 0
    left, right, waiting = [], [], 0
    step = max(1, (1 << 20) // max(1, len(root)))
    for lo in range(0, few, step):
        own, rest = order[lo : min(few, lo + step)], order[lo + 1 :]
        far, far2 = fp[own][:, None] ^ fp[rest], fp2[own][:, None] ^ fp2[rest]
        near = np.bitwise_count(far).astype(np.int64) + np.bitwise_count(far2) <= radius
        near &= (label[own][:, None] != label[rest]) & (np.arange(len(rest)) >= np.arange(len(own))[:, None])
        if crossing:
            near &= block[own][:, None] != block[rest]
        i, j = np.nonzero(near)
        first = first_meeting(combo[own[i]], far[i, j], far2[i, j])
        a, b = own[i[first]], rest[j[first]]
        allowed = (1 - least) / (1 + least) * (n[a] + n[b]) + 1e-6
        fits = np.abs(n[a] - n[b]) <= allowed
        a, b, allowed = a[fits], b[fits], allowed[fits]
        fits = np.bitwise_count(sketch[a] ^ sketch[b]).sum(axis=1, dtype=np.int64) <= allowed
        a, b = a[fits], b[fits]
        run = _places(a)
        rank = np.arange(len(a)) - np.searchsorted(run, run, "left")
        left.append(a[rank < most])
        right.append(b[rank < most])
        waiting += int((rank >= most).sum())
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *left]), np.concatenate([none, *right]), waiting


def _places(a: np.ndarray) -> np.ndarray:
    """Number of the run of equal values that each value is in."""
    return np.cumsum(np.concatenate([[0], a[1:] != a[:-1]])[: len(a)])


def _by_posting(out: Callable[[list[np.ndarray]], Iterator[pa.RecordBatch]], width: int, most: int | None = None) -> Callable:
    """A function of batches sorted by ``(combo, key)`` that gives ``out`` whole postings, many at a time.

    With ``most``, a posting of more rows comes in pieces that overlap by one row.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] | None = None
        for batch in batches:
            cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(width)]
            if not len(cols[0]):
                continue
            if held is not None:
                cols = [np.concatenate(x) for x in zip(held, cols, strict=True)]
            last = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]))
            cut = int(last[-1]) + 1 if len(last) else 0
            if cut:
                yield from out([c[:cut] for c in cols])
            held = [c[cut:] for c in cols]
            if most and len(held[0]) > most:
                yield from out(held)
                held = [c[-1:] for c in held]
        if held is not None and len(held[0]):
            yield from out(held)

    return run


def links(fps: DataFrame, fp: str = "fp") -> DataFrame:
    """Spanning links ``(u, v)`` of distinct fingerprints within ``RADIUS`` bits."""

    def out(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        root = link_runs(cols[0], cols[1], cols[2].view(np.uint64))
        own = np.flatnonzero(root != np.arange(len(root)))
        if len(own):
            yield pa.RecordBatch.from_arrays([pa.array(cols[2][own]), pa.array(cols[2][root[own]])], ["u", "v"])

    table = split_crowds(postings(fps.select(fp).where(F.col(fp).isNotNull()).distinct(), fp))
    return table.repartition("combo", "key").sortWithinPartitions("combo", "key").mapInArrow(_by_posting(out, 3), "u long, v long")


def _grouped(prints: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(fp, id, root)`` of distinct fingerprints, ``id`` their smallest, and ``(root, component_id)`` of groups."""
    least = durable(prints.groupBy("fp").agg(F.min("id").alias("id")))
    roots = connected_components(links(least))
    placed = least.join(roots, least.fp == roots.node, "left").select("fp", "id", F.coalesce("root", "fp").alias("root"))
    return placed, placed.groupBy("root").agg(F.min("id").alias("component_id"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3) -> DataFrame:
    """``(id_col, fingerprint, component_id, group_root)`` for every row: classes of texts linked within three bits."""
    prints = durable(with_fingerprint(docs, id_col, text_col, size))
    placed, groups = _grouped(prints)
    of = placed.join(groups, "root").select("fp", "root", "component_id")
    return prints.join(of, "fp").select(F.col("id").alias(id_col), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", F.col("root").alias("group_root"))


# --- one document of each group ---------------------------------------------------------------------------------------


def _keyed(docs: DataFrame, text_col: str, *more) -> DataFrame:
    """``(file, row, text, more)``: a key of each row that another scan of the same files gives again."""
    return docs.select(F.xxhash64("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"), F.col(text_col).cast("string").alias("text"), *more)


def _stored(docs: DataFrame) -> DataFrame:
    """``docs`` as a plain scan of Parquet files, written only if it is none yet."""
    plan = docs._jdf.queryExecution().analyzed()
    return docs if plan.getClass().getSimpleName() == "LogicalRelation" and "parquet" in plan.toString().lower() else durable(docs)


def _all_prints(docs: DataFrame, id_col: str, text_col: str, size: int, shingle: int = 5) -> DataFrame:
    """``(file, row, id, size, fp, w, w2, n, total, sketch)``: the narrow fingerprint, both halves of the wide one, and of the set of
    ``shingle`` words its size, the sum of its hashes and its parity sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, off in slices(batches, "text"):
            h, count = shingle_hashes(raw, off, WIDE_SHINGLE)
            prints = [fingerprints_of(raw, off, size), majority(h, count), majority(remixed(h), count)]
            h, n = shingle_sets(*shingle_hashes(raw, off, shingle))
            upto = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h)])
            edge = np.concatenate([[0], np.cumsum(n)])
            total = upto[edge[1:]] - upto[edge[:-1]]
            sketch = pa.array([x.tobytes() for x in sketches(h, n)], pa.binary())
            names = ["file", "row", "id", "size", "fp", "w", "w2", "n", "total", "sketch"]
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), rows.column(3), pa.array(np.diff(off)), *[pa.array(x.view(np.int64)) for x in prints], pa.array(n), pa.array(total.view(np.int64)), sketch], names)

    kind = "file long, row long, id long, size long, fp long, w long, w2 long, n long, total long, sketch binary"
    return _keyed(docs, text_col, F.col(id_col).cast("long").alias("id")).mapInArrow(run, kind)


def _wide_candidates(kinds: DataFrame) -> tuple[DataFrame, DataFrame]:
    """From ``kinds(no, root, w, w2)``: pairs ``(u, v)`` of ``no`` in different narrow groups, within ``WIDE_RADIUS`` bits, and the
    members ``(combo, key, w, w2)`` of postings that hold further ones."""
    prints = durable(kinds.groupBy("w", "w2", "root").agg(F.min("no").alias("no"), F.count("*").alias("texts")))
    posts = wide_postings(prints.groupBy(F.col("w").alias("fp"), F.col("w2").alias("fp2")).agg(F.when(F.sum("texts") == 1, F.min("root")).alias("root")))
    kind = pa.schema([*[(c, pa.int64()) for c in ("a", "a2", "b", "b2")], ("combo", pa.int32()), ("key", pa.int64()), ("m", pa.list_(pa.int64())), ("m2", pa.list_(pa.int64()))])

    def out(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        combo, key, fp, fp2, root, several = cols[0], cols[1], cols[2].view(np.uint64), cols[3].view(np.uint64), cols[4], cols[5].astype(bool)
        a, b = wide_runs(combo, key, fp, fp2)
        apart = (root[a] != root[b]) | several[a] | several[b]  # what the narrow fingerprints have linked needs no second link
        a, b = a[apart], b[apart]
        if len(a):
            yield pa.RecordBatch.from_arrays([*[pa.array(x) for x in (cols[2][a], cols[3][a], cols[2][b], cols[3][b])], *[pa.nulls(len(a), f.type) for f in list(kind)[4:]]], schema=kind)
        for x, m in zip(*crowds(combo, key, several), strict=True):
            if 0 < x and x + m < len(key) and not several[x : x + m].any() and (root[x : x + m] == root[x]).all():
                continue  # one narrow group
            edge = np.append(np.arange(x, x + m, CROWD), x + m)
            lists = [pa.ListArray.from_arrays(pa.array(edge - x, pa.int32()), pa.array(c[x : x + m])) for c in cols[2:4]]
            k = len(edge) - 1
            yield pa.RecordBatch.from_arrays([*[pa.nulls(k, pa.int64())] * 4, pa.array(np.repeat(combo[x], k), pa.int32()), pa.array(np.repeat(key[x], k)), *lists], schema=kind)

    # by range, so a posting with a third of all texts is dealt among tasks; where one is cut, its parts are among the postings given.
    # The hashed key comes first, so every task has postings of all position sets, dense ones and sparse ones
    order = ["key", "combo", "fp", "fp2"]
    posts = posts.select("combo", "key", "fp", "fp2", F.coalesce("root", F.lit(0).cast("long")).alias("root"), F.col("root").isNull().cast("int").alias("several"))
    kinds_out = "a long, a2 long, b long, b2 long, combo int, key long, m array<long>, m2 array<long>"
    found = durable(posts.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_by_posting(out, 6, PIECE), kinds_out))
    near = found.where("combo is null").select("a", "a2", "b", "b2").distinct()
    # texts of equal wide fingerprints in different narrow groups are candidates too: each with the first of them
    first = Window.partitionBy("w", "w2").orderBy("no").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    same = prints.withColumn("first", F.first("no").over(first)).where("first <> no").select(F.col("first").alias("u"), F.col("no").alias("v"))
    one = prints.groupBy("w", "w2").agg(F.min(F.struct("no", "root")).alias("x")).select("w", "w2", "x.no", "x.root")
    u = near.join(one.select(F.col("w").alias("a"), F.col("w2").alias("a2"), F.col("no").alias("u"), F.col("root").alias("ur")), ["a", "a2"])
    both = u.join(one.select(F.col("w").alias("b"), F.col("w2").alias("b2"), F.col("no").alias("v"), F.col("root").alias("vr")), ["b", "b2"]).where("ur <> vr").select("u", "v")
    listed = found.where("combo is not null").select("combo", "key", F.explode(F.arrays_zip("m", "m2")).alias("x"))
    return both.unionByName(same), durable(listed.select("combo", "key", F.col("x.m").alias("w"), F.col("x.m2").alias("w2")).distinct())


def _apart(crowded: DataFrame, members: DataFrame, least: float, most: int) -> tuple[DataFrame, bool]:
    """Pairs ``(u, v)`` of ``members(no, root, w, w2, n, sketch)`` of crowded postings in different groups (:func:`apart_pairs`), and whether some wait.

    A posting of more than ``CROWD`` members is dealt in blocks, a cell for every two of them.
    """
    rows = durable(crowded.join(members.select("no", "root", "w", "w2"), ["w", "w2"]))  # a row a listed member, read twice below but joined once
    open_ = rows.groupBy("combo", "key").agg(F.count("*").alias("of"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("combo", "key", F.ceil(F.col("of") / CROWD).cast("int").alias("blocks"))
    block = F.pmod(F.xxhash64("no"), F.col("blocks")).cast("int")
    dealt = rows.join(open_, ["combo", "key"]).withColumn("block", block).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cell = F.least("block", "other") * F.lit(1 << 16).cast("long") + F.greatest("block", "other")
    rich = dealt.select((cell * 256 + F.col("combo")).alias("cell"), "key", "block", "no").join(members, "no").select("cell", "key", "w", "w2", "root", "block", "n", "no", "sketch")

    def out(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        for x, m in zip(*_runs(cols[0], cols[1]), strict=True):
            cell, _, fp, fp2, root, part, n, no, sketch = (c[x : x + m] for c in cols)
            place = int(cell[0]) >> 8
            words = np.frombuffer(b"".join(sketch), np.uint64).reshape(m, -1)
            a, b, waiting = apart_pairs(cell & 255, fp.view(np.uint64), fp2.view(np.uint64), root, part, n, words, least, most, place >> 16 != place & 0xFFFF)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(no[a]), pa.array(no[b])], ["u", "v"])
            if waiting:
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64())], ["u", "v"])

    order = ["cell", "key"]
    found = durable(rich.repartition(*order).sortWithinPartitions(*order).mapInArrow(_by_posting(out, 9), "u long, v long").distinct())
    return found.where("u is not null"), found.where("u is null").limit(1).count() > 0


def _similar(docs: DataFrame, text_col: str, pairs: DataFrame, keys: DataFrame, least: float, shingle: int) -> DataFrame:
    """The ``pairs(u, v)`` whose texts' sets of shingles have a Jaccard similarity of ``least`` or more; ``keys(no, file, row)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, off in slices(batches, "text"):
            h, count = shingle_sets(*shingle_hashes(raw, off, shingle))
            at = np.concatenate([[0], np.cumsum(count)])
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.LargeListArray.from_arrays(pa.array(at), pa.array(h.view(np.int64))).cast(pa.list_(pa.int64()))], ["no", "set"])

    ends = pairs.select(F.col("u").alias("no")).distinct().unionByName(pairs.select(F.col("v").alias("no")).distinct())
    asked = durable(ends.distinct().join(keys, "no"))
    text = _keyed(docs, text_col)
    few = asked.count() <= 1_000_000  # about 24 MB to each executor; above that the join shuffles
    sets = durable(text.join(F.broadcast(asked) if few else asked, ["file", "row"]).select("no", "text").mapInArrow(run, "no long, set array<long>"))
    left = pairs.join(sets.select(F.col("no").alias("u"), F.col("set").alias("x")), "u")
    both = left.join(sets.select(F.col("no").alias("v"), F.col("set").alias("y")), "v")
    common = F.size(F.array_intersect("x", "y"))
    return both.where(common >= F.lit(least) * (F.size("x") + F.size("y") - common)).select("u", "v")


def survivors(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, least: float | None = 0.8, shingle: int = 5) -> DataFrame:
    """``(file, row)`` of one row of each group of ``docs``, a plain scan of Parquet files.

    Texts are linked within three bits of their narrow fingerprints, or by a similarity of ``least`` found through the
    wide ones (not where ``least`` is null).  The row of smallest id stays (rows without an id only where a group has no other), of equal ids the one
    of the shortest text.
    """
    prints = durable(_all_prints(docs, id_col, text_col, size, shingle))
    order = F.struct(F.col("id").isNull().alias("lost"), "id", "size", "file", "row", "n", "sketch")
    # a row a kind of text: rows that share all fingerprints and the set of shingles are one group
    kinds = prints.groupBy("fp", "w", "w2", "total").agg(F.min(order).alias("best"))
    roots = connected_components(links(prints))
    placed = durable(kinds.join(roots, kinds.fp == roots.node, "left").select("w", "w2", "best", F.coalesce("root", "fp").alias("root"), F.xxhash64("best.file", "best.row").alias("no")))
    if least is not None:
        keys = placed.select("no", "best.file", "best.row")
        pairs, crowded = _wide_candidates(placed.select("no", "root", "w", "w2"))
        placed, most, waiting = _joined(placed, _similar(docs, text_col, durable(pairs), keys, least, shingle)), FIRST_TRY, True
        while waiting:
            pairs, waiting = _apart(crowded, placed.select("no", "root", "w", "w2", "best.n", "best.sketch"), least, most)
            placed, most = _joined(placed, _similar(docs, text_col, pairs, keys, least, shingle)), 8 * most
    return placed.groupBy("root").agg(F.min("best").alias("best")).select("best.file", "best.row")


def _joined(placed: DataFrame, real: DataFrame) -> DataFrame:
    """``placed`` with the groups of ``real(u, v)`` under one root."""
    at = placed.select("no", "root")
    edges = real.join(at.select(F.col("no").alias("u"), F.col("root").alias("a")), "u").join(at.select(F.col("no").alias("v"), F.col("root").alias("b")), "v")
    joined = connected_components(edges, "a", "b").withColumnRenamed("root", "top")
    return durable(placed.join(joined, placed.root == joined.node, "left").select("w", "w2", "best", F.coalesce("top", "root").alias("root"), "no"))


CHUNK = 1 << 16  # rows of a file that one bitmap holds
BITMAP_BYTES = 64 << 20  # bitmaps of survivors are broadcast up to this size, half a billion rows of input


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, least: float | None = 0.8, shingle: int = 5, bitmap_bytes: int = BITMAP_BYTES) -> DataFrame:
    """``docs`` with one row of each near-duplicate group (:func:`survivors`), null and repeated ids included.

    Survivors go to the scan as bitmaps of row numbers, a bit a row, so texts are not shuffled; where all bitmaps
    exceed ``bitmap_bytes`` the join shuffles.
    """
    docs = _stored(docs)
    chosen = survivors(docs, id_col, text_col, size, least, shingle)
    chunk, word = F.floor(F.col("row") / CHUNK), F.floor(F.col("row") % CHUNK / 64).cast("int")
    words = chosen.groupBy("file", chunk.alias("chunk"), word.alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(row % 64 as int))")).alias("bits"))
    maps = durable(words.groupBy("file", "chunk").agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("m")).select(F.col("file").alias("f"), "chunk", F.transform(F.sequence(F.lit(0), F.lit(CHUNK // 64 - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0).cast("long"))).alias("bits")))
    names = [fresh(x, docs.columns) for x in ("__f", "__r")]
    f, r = map(F.col, names)
    rows = docs.select("*", F.xxhash64("_metadata.file_path").alias(names[0]), F.col("_metadata.row_index").alias(names[1]))
    side = F.broadcast(maps) if maps.count() * CHUNK // 8 <= bitmap_bytes else maps
    hit = F.element_at(side["bits"], (F.floor(r % CHUNK / 64) + 1).cast("int"))
    return rows.join(side, (f == side["f"]) & (F.floor(r / CHUNK) == side["chunk"]), "inner").where(F.getbit(hit, (r % 64).cast("int")) == 1).select(*[rows[c] for c in docs.columns])
