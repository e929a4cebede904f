"""Whole-text BPE encoding through the tokenizers library with a bounded memory of chunks.

A byte-level or word-end BPE never joins a visible character to white space that follows it, nor a letter to a sign
or digit after it, so a text may be cut there, and each distinct chunk is encoded by the library once a slice at most.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import SPACE, ragged_take

MARK, WHITE, TOGETHER = "\x01", " \t\n\x0b\x0c\r", 2000
LETTER, SIGN = np.zeros(256, bool), np.zeros(256, bool)
LETTER[[*range(65, 91), *range(97, 123)]] = True
SIGN[[b for b in range(33, 127) if not LETTER[b] and b != 39]] = True
ROOM = 600_000  # chunks remembered; half of it saves some 50 MB a worker and costs a fifth more time
_ENCODERS: dict[tuple[str, int], ChunkEncoder] = {}


class ChunkMemory:
    """Encodes texts through the ids of their distinct chunks, of which about ``room`` are remembered."""

    def __init__(self, room: int):
        self.room = room
        self._clear()

    def _clear(self) -> None:
        self.known: dict[str, int] = {}
        self.flat = np.zeros(1 << 16, np.uint32)
        self.used = 0
        self.start = np.zeros(1 << 12, np.int64)
        self.count = np.zeros(1 << 12, np.int64)

    def cut(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def encode_chunks(self, chunks: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """``(chunks in the order of the ids, ids, number of ids of each)``."""
        raise NotImplementedError

    def _learn(self, fresh: list[str]) -> None:
        base = len(self.known)
        chunks, new, n = self.encode_chunks(fresh)
        while self.used + len(new) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        while base + len(chunks) > len(self.start):
            self.start, self.count = (np.concatenate([x, np.zeros_like(x)]) for x in (self.start, self.count))
        self.flat[self.used : self.used + len(new)] = new
        self.start[base : base + len(chunks)] = self.used + np.cumsum(n) - n
        self.count[base : base + len(chunks)] = n
        self.used += len(new)
        self.known.update(zip(chunks, range(base, base + len(chunks)), strict=True))

    def encode(self, raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """``(ids, per-text offsets into ids)`` for a concatenation of UTF-8 texts."""
        if not raw.size:
            return np.zeros(0, np.uint32), np.zeros(len(off), np.int64)
        cut = self.cut(raw, off)
        chunks = pa.LargeStringArray.from_buffers(len(cut), pa.py_buffer(np.append(cut, len(raw)).astype(np.int64)), pa.py_buffer(np.ascontiguousarray(raw)))
        coded = pc.dictionary_encode(chunks)
        distinct = coded.dictionary.to_pylist()
        if len(self.known) + len(distinct) > self.room:
            self._clear()
        if fresh := [c for c in distinct if c not in self.known]:
            self._learn(fresh)
        own = np.fromiter(map(self.known.__getitem__, distinct), np.int64, len(distinct))[coded.indices.to_numpy()]
        ends = np.concatenate([[0], np.cumsum(self.count[own])])
        return ragged_take(self.flat, self.start[own], self.count[own]), ends[np.searchsorted(cut, off)]


class ChunkEncoder(ChunkMemory):
    """Chunks encoded by the tokenizers library from a tokenizer file."""

    def __init__(self, path: str, room: int = ROOM):
        super().__init__(room)
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = True  # a special token's string in a text is ordinary text, as the vocabulary files' description asks
        self.largest = max(self.tok.get_vocab(with_added_tokens=True).values())
        self.mark = self.tok.encode(" " + MARK, add_special_tokens=False).ids  # ends with an id that only this character has

    def cut(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        return chunk_starts(raw, off)

    def encode_chunks(self, chunks: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Chunks that begin with white space many to a call, parted by the mark; others one by one."""
        joined = [c[0] in WHITE and MARK not in c for c in chunks]
        many = [c for c, j in zip(chunks, joined, strict=True) if j]
        one = [c for c, j in zip(chunks, joined, strict=True) if not j]
        parts, counts = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)]
        texts = [(" " + MARK).join(many[i : i + TOGETHER]) for i in range(0, len(many), TOGETHER)]
        for e in self.tok.encode_batch_fast(texts, add_special_tokens=False):
            ids = np.array(e.ids, np.uint32)
            ends = np.flatnonzero(ids == self.mark[-1]) + 1 - len(self.mark)
            begins = np.append(0, ends + len(self.mark))
            ends = np.append(ends, len(ids))
            counts.append(ends - begins)
            parts.append(ragged_take(ids, begins, ends - begins))
        for e in self.tok.encode_batch_fast(one, add_special_tokens=False):
            parts.append(np.array(e.ids, np.uint32))
            counts.append(np.array([len(e.ids)]))
        return many + one, np.concatenate(parts), np.concatenate(counts).astype(np.int64)


def chunk_starts(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Where a chunk begins: at each text, and at ASCII white space right after a character that is surely visible."""
    first = np.zeros(len(raw), bool)
    first[off[:-1][off[:-1] < len(raw)]] = True
    if len(raw) < 4:
        return np.flatnonzero(first)
    plain = (raw > 0x20) & (raw != 0x7F)
    # a non-ASCII character may be a space itself: those begin with C2, or with E1, E2 or E3
    doubt = np.zeros(len(raw), bool)
    doubt[1:] = raw[:-1] == 0xC2
    doubt[2:] |= (raw[:-2] >= 0xE1) & (raw[:-2] <= 0xE3)
    first[1:] |= SPACE[raw[1:]] & (plain & ~doubt)[:-1]
    # letters end before a digit or any ASCII sign but the apostrophe, which may begin a contraction
    first[1:] |= LETTER[raw[:-1]] & SIGN[raw[1:]]
    return np.flatnonzero(first)


def encoder(path: str, room: int = ROOM) -> ChunkEncoder:
    """One encoder a worker process."""
    if (path, room) not in _ENCODERS:
        _ENCODERS[path, room] = ChunkEncoder(path, room)
    return _ENCODERS[path, room]
