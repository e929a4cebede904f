"""SentencePiece encoding and decoding in batched numpy.

Distinct words are laid out by length, and words of equal length advance together.  Hashes of all their substrings
probe the sorted hashes of the pieces, which gives the lattice of a whole batch at once.  It is solved by Viterbi:
vectorised maxima over the pieces that end at a position store backpointers.

A path's score is the sum of its pieces' scores in a unigram model.  A BPE model asks for merges in order of score,
which no such sum yields; there a path scores by its seams.  Merges on either side of a final seam never see each
other, so a sequence of pieces is the model's result exactly if every two neighbours are: if merging their joint text
stops at just these two.  A step from one piece to the next scores 0 if that holds and minus infinity if not, and the
maximum over the pieces that end at a position finds the only one there is.  Whether two pieces hold is read off their
merge trees: going back in time along both edges of the seam, no merge across it may have come first.

Defined results: null and empty texts have no ids and decode to an empty text; a character without a piece becomes
its byte pieces, or the unknown piece where the model has none; texts and words of any length are encoded whole, the
lattice being held for a window of a word at a time; repeated rows are encoded alike; an empty table gives no row.
Other columns do not matter.  A model's own text normaliser beyond spaces is not applied.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe_cache import ChunkMemory
from .common import ragged_take, slices

BLANK = "▁"  # stands for a space in pieces
BASE = np.uint64(0x9E3779B97F4A7C15)  # odd multiplier of the substring hashes
LONG = 192  # longer words advance one by one
CELLS = 1 << 22  # lattice cells a batch holds at most
SEAMS = 1 << 21  # places of the memory of seams
_CODECS: dict[str, PieceCodec] = {}


class PieceCodec(ChunkMemory):
    def __init__(self, pieces: list[str], scores: list[float], kind: str, unknown: int = 0, silent: tuple[int, ...] = (), byte_ids: dict[int, int] | None = None, room: int = 600_000):
        """``silent`` pieces (control, unknown) are never matched and decode to nothing; ``byte_ids`` maps bytes to pieces."""
        super().__init__(room)
        self.pieces, self.kind, self.unknown, self.byte_ids = pieces, kind, unknown, byte_ids or {}
        self.scores = np.array(scores, np.float64)
        hidden = {*silent, unknown, *self.byte_ids.values()}
        use = [i for i, p in enumerate(pieces) if p and i not in hidden]
        self.longest = max(len(pieces[i]) for i in use)
        self.index = {pieces[i]: i for i in reversed(use)}
        own = sorted(self.index.values())
        self.points = np.zeros((len(own), self.longest), np.uint32)
        for k, i in enumerate(own):
            self.points[k, : len(pieces[i])] = [ord(c) for c in pieces[i]]
        lengths = np.array([len(pieces[i]) for i in own])
        keys = self._hash(self.points)[np.arange(len(own)), lengths] + lengths.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        order = np.argsort(keys, kind="stable")
        self.keys, self.piece_of, self.points = keys[order], np.array(own)[order], self.points[order]
        if len(np.unique(self.keys)) != len(own):
            raise ValueError("pieces share a hash")
        # words may be cut where a space follows another character only if no piece holds such a place
        self.cuttable = not any(BLANK in p.lstrip(BLANK) for p in self.index)
        byte_of = {i: bytes([b]) for b, i in self.byte_ids.items()}
        faces = [b"" if i in silent else " ⁇ ".encode() if i == unknown else byte_of.get(i, p.replace(BLANK, " ").encode()) for i, p in enumerate(pieces)]
        self.face = np.frombuffer(b"".join(faces), np.uint8)
        self.face_len = np.array([len(f) for f in faces])
        self.face_at = np.cumsum(self.face_len) - self.face_len
        self.floor = float(self.scores[own].min()) - 10.0  # score of an unknown character in a unigram model
        if kind == "bpe":
            self._plant()

    @classmethod
    def load(cls, path: str) -> PieceCodec:
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        n = m.vocab_size()
        pieces = [m.id_to_piece(i) for i in range(n)]
        bytes_of = {int(pieces[i][3:5], 16): i for i in range(n) if m.is_byte(i)}
        silent = tuple(i for i in range(n) if m.is_control(i) or m.is_unused(i))
        scores = [m.get_score(i) for i in range(n)]
        normal = [s for i, s in enumerate(scores) if i not in bytes_of.values() and i not in silent and i != m.unk_id()]
        kind = "bpe" if all(float(s).is_integer() for s in normal) else "unigram"  # BPE scores are negative ranks
        return cls(pieces, scores, kind, m.unk_id(), silent, bytes_of)

    @staticmethod
    def _hash(points: np.ndarray) -> np.ndarray:
        """Prefix hashes (n, L + 1)."""
        out = np.zeros((len(points), points.shape[1] + 1), np.uint64)
        with np.errstate(over="ignore"):
            for i in range(points.shape[1]):
                out[:, i + 1] = out[:, i] * BASE + points[:, i].astype(np.uint64) + np.uint64(1)
        return out

    def lattice(self, points: np.ndarray) -> np.ndarray:
        """Piece (or -1) of each substring: (n, start, length - 1)."""
        n, size = points.shape
        reach = min(self.longest, size)
        out = np.full((n, size, reach), -1, np.int32)
        prefix = self._hash(points)
        power = np.uint64(1)
        with np.errstate(over="ignore"):
            for length in range(1, reach + 1):
                power = power * BASE
                key = prefix[:, length:] - prefix[:, :-length] * power + np.uint64(length) * np.uint64(0xD6E8FEB86659FD93)
                at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
                row, start = np.nonzero(self.keys[at] == key)
                if len(row):
                    at = at[row, start]
                    same = np.ones(len(row), bool)
                    for k in range(length):  # equal hashes are not yet equal pieces
                        same &= points[row, start + k] == self.points[at, k]
                    out[row[same], start[same], length - 1] = self.piece_of[at[same]]
        return out

    def _plant(self) -> None:
        """Merge trees of the pieces: what each is last merged from, and in what order they come."""
        n = len(self.pieces)
        self.length = np.zeros(n + 1, np.int64)  # the last place stands for a character without a piece
        self.length[-1] = 1
        self.rank = np.full(n + 1, -1, np.int64)  # characters are there from the start
        self.head, self.tail = np.full(n + 1, -1, np.int64), np.full(n + 1, -1, np.int64)
        self.whole = np.zeros(n + 1, bool)  # pieces that merging their own text gives
        self.whole[-1] = True
        sizes = np.array([len(self.pieces[i]) for i in self.piece_of])
        _, order = np.unique(-self.scores, return_inverse=True)  # pieces of one score share a rank, and the leftmost merges first
        self.length[self.piece_of] = sizes
        for size in np.unique(sizes):
            own = np.flatnonzero(sizes == size)
            ids = self.piece_of[own]
            if size == 1:
                self.whole[ids] = True
                continue
            self.rank[ids] = order[ids]
            for lo in range(0, len(own), max(1, CELLS // int(size * size))):
                at = own[lo : lo + max(1, CELLS // int(size * size))]
                points = self.points[at, :size]
                begins, cut = self._merge(points)
                done = begins.sum(axis=1) == 1
                self.whole[self.piece_of[at[done]]] = True
                for k in np.flatnonzero(done):
                    word, c = self.pieces[self.piece_of[at[k]]], cut[k]
                    self.head[self.piece_of[at[k]]] = self.index.get(word[:c], -1)
                    self.tail[self.piece_of[at[k]]] = self.index.get(word[c:], -1)
        parts = np.stack([self.head[:-1], self.tail[:-1]])
        # trees that do not tell the order of merges: parts ranked behind their whole, or among merges of one rank
        self.late, self.tied = np.zeros(n + 1, bool), np.zeros(n + 1, bool)
        self.late[:-1] = self.whole[:-1] & (self.rank[parts] > self.rank[:-1]).any(axis=0)
        self.tied[:-1] = self.whole[:-1] & (self.rank[:-1] >= 0) & (self.rank[parts] == self.rank[:-1]).any(axis=0)
        for size in np.unique(sizes):
            ids = self.piece_of[sizes == size]
            for mark in (self.late, self.tied):
                mark[ids] |= mark[self.head[ids]] | mark[self.tail[ids]]
        self.seam_key = np.full(SEAMS, -1, np.int64)
        self.seam_ok = np.zeros(SEAMS, bool)
        self.seam_of: dict[tuple[int, int], bool] = {}

    def _merge(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """``(begins of the pieces left, place of the last merge)``, the best pair of each word merging a step; used for the pieces themselves."""
        n, size = points.shape
        lattice = self.lattice(points)
        begins, cut = np.ones((n, size), bool), np.zeros(n, np.int64)
        live, edge = np.arange(n), np.tile(np.arange(size + 1), (n, 1))
        while len(live) and edge.shape[1] > 2:
            length = edge[:, 2:] - edge[:, :-2]
            fits = length <= lattice.shape[2]
            piece = lattice[live[:, None], edge[:, :-2], np.where(fits, length, 1) - 1]
            score = np.where(fits & (piece >= 0), self.scores[piece], -np.inf)
            pick = np.argmax(score, axis=1)
            going = score[np.arange(len(live)), pick] > -np.inf
            live, edge, pick = live[going], edge[going], pick[going]
            if not len(live):
                break
            cut[live] = edge[np.arange(len(live)), pick + 1]
            begins[live, cut[live]] = False
            column = np.arange(edge.shape[1] - 1)
            edge = np.take_along_axis(edge, column[None, :] + (column[None, :] > pick[:, None]), axis=1)
        return begins, cut

    def _seams(self, a: np.ndarray, b: np.ndarray, across: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
        """Whether pieces ``a`` and ``b`` stay apart; ``across(which, x, y)`` gives the pieces that cover their last ``x`` and first ``y`` characters."""
        ok = np.ones(len(a), bool)
        known = (a >= 0) & (b >= 0)  # no piece reaches over a character without one
        hard = known & (self.late[a] | self.late[b] | (self.tied[a] & self.tied[b]))
        for i in np.flatnonzero(hard):  # few: merged as they stand
            text = self.pieces[a[i]] + self.pieces[b[i]]
            begins, _ = self._merge(np.array([[ord(c) for c in text]], np.uint32))
            ok[i] = np.flatnonzero(begins[0]).tolist() == [0, len(self.pieces[a[i]])]
        live = np.flatnonzero(known & ~hard)
        x, y = a[live], b[live]
        limit = np.full(len(live), np.iinfo(np.int64).max)  # merges from here on had not come yet
        while len(live):
            joint = across(live, self.length[x], self.length[y])
            first = (joint >= 0) & (self.rank[joint] < limit)
            ok[live[first]] = False
            rx, ry = self.rank[x], self.rank[y]
            going = ~first & ((rx >= 0) | (ry >= 0))
            live, x, y, rx, ry = live[going], x[going], y[going], rx[going], ry[going]
            late = rx > ry  # the later of the two merges is undone; of equal ones the right one came later
            limit = np.where(late, rx, ry + 1)
            x, y = np.where(late, self.tail[x], x), np.where(late, y, self.head[y])
        return ok

    def _known_seams(self, a: np.ndarray, b: np.ndarray, across: Callable) -> np.ndarray:
        key = a * (len(self.pieces) + 1) + b
        with np.errstate(over="ignore"):
            slot = ((key.astype(np.uint64) * BASE) >> np.uint64(43)).astype(np.int64) % SEAMS
        ok = self.seam_ok[slot]
        fresh = np.flatnonzero(self.seam_key[slot] != key)
        if len(fresh):
            ok[fresh] = self._seams(a[fresh], b[fresh], lambda which, x, y: across(fresh[which], x, y))
            # of keys that share a slot the last stays, with its own answer
            self.seam_key[slot[fresh]] = key[fresh]
            mine = self.seam_key[slot[fresh]] == key[fresh]
            self.seam_ok[slot[fresh[mine]]] = ok[fresh[mine]]
        return ok

    def _viterbi(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Begins of the best pieces, ``(word, begin)`` pairs in order."""
        return self._solve(points)[:2]

    def _solve(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``(word, begin, piece)`` of the best pieces, in order; -1 for a character without a piece."""
        n, size = points.shape
        bpe, every = self.kind == "bpe", np.arange(n)
        back = np.zeros((n, size + 1), np.int32)
        best = np.zeros((n, size + 1)) if not bpe else None
        last = np.full((n, size + 1), -1, np.int32)  # the piece that ends at a position
        window = max(4 * self.longest, CELLS // max(1, n * self.longest))
        for lo in range(0, size, window):
            base = max(0, lo - 2 * self.longest)
            lattice = self.lattice(points[:, base : lo + window])
            for end in range(lo + 1, min(size, lo + window) + 1):
                lengths = np.arange(1, min(self.longest, end) + 1)
                piece = lattice[:, end - lengths - base, np.minimum(lengths, lattice.shape[2]) - 1]
                if bpe:
                    piece = np.where((piece >= 0) & self.whole[piece], piece, -1)
                    row, k = np.nonzero(piece >= 0)
                    a, b, start = last[row, end - lengths[k]].astype(np.int64), piece[row, k].astype(np.int64), end - lengths[k]

                    def across(which, x, y, row=row, start=start, lattice=lattice, base=base):
                        span = x + y
                        fits = span <= lattice.shape[2]
                        return np.where(fits, lattice[row[which], start[which] - x - base, np.where(fits, span, 1) - 1], -1)

                    holds = start == 0
                    inner = np.flatnonzero(~holds & (back[row, start] > 0))
                    holds[inner] = self._known_seams(a[inner], b[inner], lambda which, x, y, i=inner: across(i[which], x, y))
                    score = np.zeros(piece.shape, np.int8)
                    score[:, 0] = 1  # a character without a piece; no other piece reaches over it
                    score[:, 0][piece[:, 0] >= 0] = 0
                    score[row[holds], k[holds]] = 2
                    pick = np.argmax(score, axis=1)
                    back[:, end] = np.where(score[every, pick] > 0, lengths[pick], 0)  # 0: no result ends here
                else:
                    score = np.where(piece >= 0, self.scores[piece], -np.inf)
                    score[:, 0] = np.where(piece[:, 0] >= 0, score[:, 0], self.floor)
                    total = best[:, end - lengths] + score
                    pick = np.argmax(total, axis=1)
                    best[:, end] = total[every, pick]
                    back[:, end] = lengths[pick]
                last[:, end] = piece[every, pick]
        begins, own = np.zeros((n, size), bool), np.zeros((n, size), np.int32)
        if (back[:, size] == 0).any():
            raise RuntimeError("a word has no path through its lattice")
        at, live = np.full(n, size), every
        while len(live):
            piece = last[live, at[live]]
            at[live] -= back[live, at[live]]
            begins[live, at[live]], own[live, at[live]] = True, piece
            live = live[at[live] > 0]
        row, begin = np.nonzero(begins)
        return row, begin, own[row, begin]

    def _viterbi_long(self, word: str) -> list[int]:
        """The same for one long word of a BPE model, position by position."""
        n, find = len(word), self.index.get
        last, back = [-1] * (n + 1), [0] * (n + 1)
        for end in range(1, n + 1):
            for start in range(end - 1, max(-1, end - self.longest - 1), -1):
                p = find(word[start:end], -1)
                if p < 0 and start < end - 1 or p >= 0 and not self.whole[p]:
                    continue
                if start == 0 or p < 0 or last[start] < 0:  # no piece reaches over a character without one
                    held = True
                else:
                    held = self.seam_of.get((last[start], p))
                    if held is None:
                        seen = word[:end]
                        held = bool(self._seams(np.array([last[start]]), np.array([p]), lambda _, x, y: np.array([find(seen[start - int(i) : start + int(j)], -1) for i, j in zip(x, y, strict=True)]))[0])
                        if len(self.seam_of) > SEAMS:
                            self.seam_of.clear()
                        self.seam_of[last[start], p] = held
                if held and (start == 0 or back[start]):
                    last[end], back[end] = p, end - start
                    break
        begins, at = [], n
        while at:
            at -= back[at]
            begins.append(at)
        return begins[::-1]

    def encode_chunks(self, chunks: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        words = [c.replace(" ", BLANK) for c in chunks]
        size = np.fromiter(map(len, words), np.int64, len(words))
        names: list[str] = []
        parts, counts = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)]

        def one(i: int, begins: list[int]) -> None:
            ids = self._ids(words[i], begins, self.index.get)
            names.append(chunks[i])
            parts.append(np.array(ids, np.uint32))
            counts.append(np.array([len(ids)]))

        for length in np.unique(size):
            at = np.flatnonzero(size == length)
            if length > LONG and self.kind == "bpe":
                for i in at:
                    one(i, self._viterbi_long(words[i]))
                continue
            step = max(1, CELLS // int(length * min(length, self.longest)))
            for lo in range(0, len(at), step):
                own = at[lo : lo + step]
                points = np.frombuffer("".join([words[i] for i in own]).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(own), length)
                row, begin, piece = self._solve(points)
                odd = np.zeros(len(own), bool)  # words with a character that has no piece
                odd[row[piece < 0]] = True
                plain = ~odd[row]
                parts.append(piece[plain].astype(np.uint32))
                counts.append(np.bincount(row[plain], minlength=len(own))[~odd])
                names += [chunks[own[k]] for k in np.flatnonzero(~odd)]
                for k in np.flatnonzero(odd):
                    one(own[k], begin[row == k].tolist())
        return names, np.concatenate(parts), np.concatenate(counts).astype(np.int64)

    def _ids(self, word: str, begins: list[int], find) -> list[int]:
        ids: list[int] = []
        for a, b in zip(begins, [*begins[1:], len(word)], strict=True):
            piece = word[a:b]
            if (i := find(piece)) is not None:
                ids.append(i)
            elif self.byte_ids:
                ids += [self.byte_ids[x] for x in piece.encode("utf-8", "surrogatepass")]
            elif not ids or ids[-1] != self.unknown:
                ids.append(self.unknown)
        return ids

    def cut(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Chunks begin at a text and where a space follows anything else (a literal blank sign counts as a space)."""
        first = np.zeros(len(raw), bool)
        first[off[:-1][off[:-1] < len(raw)]] = True
        if self.cuttable and len(raw) > 3:
            space = raw == 0x20
            after = space.copy()
            after[2:] |= (raw[2:] == 0x81) & (raw[1:-1] == 0x96) & (raw[:-2] == 0xE2)
            first[1:] |= space[1:] & ~after[:-1]
        return np.flatnonzero(first)

    def encode(self, raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """As the library does: each text that is not empty gets one space in front."""
        full = np.diff(off) > 0
        at = off + np.concatenate([[0], np.cumsum(full)])
        return super().encode(np.insert(raw, off[:-1][full], 32), at)

    def decode(self, ids: np.ndarray, off: np.ndarray) -> list[str]:
        """Texts of id sequences ``ids[off[i]:off[i+1]]``."""
        flat = ragged_take(self.face, self.face_at[ids], self.face_len[ids]).tobytes()
        ends = np.concatenate([[0], np.cumsum(self.face_len[ids])])[off].tolist()
        return [_text(flat[a:b][1:] if flat[a : a + 1] == b" " and b > a else flat[a:b]) for a, b in zip(ends[:-1], ends[1:], strict=True)]


def _text(data: bytes) -> str:
    try:
        return data.decode()
    except UnicodeDecodeError:
        out, i = [], 0  # each byte that begins no character gives one replacement sign
        while i < len(data):
            for n in (1, 2, 3, 4):
                try:
                    out.append(data[i : i + n].decode())
                    break
                except UnicodeDecodeError:
                    continue
            else:
                out.append("�")
                n = 1
            i += n
        return "".join(out)


def codec(path: str) -> PieceCodec:
    """One codec a worker process."""
    if path not in _CODECS:
        _CODECS[path] = PieceCodec.load(path)
    return _CODECS[path]


def encode_texts(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", decode: bool = True) -> DataFrame:
    """``(id_col, ids)`` of every row and, with ``decode``, the text decoded from them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        for rows, raw, off in slices(batches, "text", 2 << 20):
            ids, at = own.encode(raw, off)
            cols = [rows.column(0), pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(ids.astype(np.int32)))]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(own.decode(ids, at), pa.string())] if decode else cols, ["id", "ids", "decoded"][: 2 + decode])

    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "id long, ids array<int>" + ", decoded string" * decode).withColumnRenamed("id", id_col)


def codec_digest(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, n_pieces, ids_crc32, decoded_crc32, round_trip)``; checksums are of 32-bit ids and of UTF-8."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        for rows, raw, off in slices(batches, "text", 2 << 20):
            ids, at = own.encode(raw, off)
            data = ids.astype("<u4")
            spans = list(zip(at[:-1].tolist(), at[1:].tolist(), strict=True))
            back = [t.encode("utf-8", "surrogatepass") for t in own.decode(ids, at)]
            same = [raw[a:b].tobytes() == t for a, b, t in zip(off[:-1].tolist(), off[1:].tolist(), back, strict=True)]
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), pa.array(np.diff(at)), pa.array([zlib.crc32(data[a:b]) for a, b in spans], pa.int64()), pa.array([zlib.crc32(t) for t in back], pa.int64()), pa.array(same)],
                ["id", "n_pieces", "ids_crc32", "decoded_crc32", "round_trip"])

    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "id long, n_pieces long, ids_crc32 long, decoded_crc32 long, round_trip boolean").withColumnRenamed("id", id_col)
