"""Vectorised automaton kernels over blocks of bytes.

A block is cut into lanes that advance in lock-step.  Every lane is run from all start states at once, the resulting
state functions are composed by a doubling scan, and each lane's bytes are then classified from its true start.  Runs
of the commonest symbol group count as one symbol where the automaton allows it.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa

from ..functions.dialect import CONTROL, DATA, FIELD, INVALID, RECORD, Dfa

BLOCK = 4 << 20
LANE = 256
SETTLE = 8


@dataclass
class Counters:
    """Automaton steps taken, for the cost of running every start state."""

    bytes: int = 0
    symbols: int = 0
    steps: int = 0


COUNTERS = Counters()


class Lanes:
    """A block's symbols as a matrix of lanes; ``pos`` gives the byte of each symbol."""

    def __init__(self, data: np.ndarray, dfa: Dfa, lane: int = LANE, collapse: bool = True):
        groups = np.frombuffer(data.tobytes().translate(dfa.lut.astype(np.uint8).tobytes()), np.uint8)  # a byte table: no index is widened
        self.dfa, self.n = dfa, len(data)
        if collapse and dfa.collapsible and len(groups):
            common = groups == dfa.other
            keep = ~common
            keep[0] = True
            keep[1:] |= ~common[:-1]
            self.pos = np.flatnonzero(keep)
            symbols = groups[self.pos]
        else:
            self.pos, symbols = np.arange(len(data)), groups
        self.symbols = symbols
        size = self.n_states = dfa.n_states
        rows = max(1, -(-len(symbols) // lane))
        pad = len(dfa.table)  # a group that changes nothing
        matrix = np.full(rows * lane, pad, np.int16)
        matrix[: len(symbols)] = symbols
        self.base = np.ascontiguousarray(matrix.reshape(rows, lane).T).astype(np.intp) * size  # one row a step, as wide as an index so that no gather converts it
        self.next = np.concatenate([dfa.table.ravel(), np.arange(size)]).astype(np.intp)
        self.emit = np.concatenate([dfa.emit.ravel(), np.full(size, 255)]).astype(np.uint8)
        COUNTERS.bytes += self.n
        COUNTERS.symbols += len(symbols)

    def vectors(self) -> np.ndarray:
        """End state of every lane from every start state: (lanes, states).

        Start states soon run together; after ``SETTLE`` symbols only the distinct states of each lane go on.
        """
        at = np.tile(np.arange(self.n_states), (self.base.shape[1], 1))
        for row in self.base[:SETTLE]:
            at = self.next.take(row[:, None] + at, mode="clip")
        at = at.astype(np.int16)
        COUNTERS.steps += self.base[:SETTLE].size * self.n_states
        if len(rest := self.base[SETTLE:]):
            order = np.sort(at, axis=1)
            place = np.zeros(order.shape, np.int64)
            np.cumsum(order[:, 1:] != order[:, :-1], axis=1, out=place[:, 1:])
            own = np.repeat(order[:, :1], int(place.max()) + 1, axis=1)
            np.put_along_axis(own, place, order, axis=1)
            index = (at[:, :, None] == own[:, None, :]).argmax(axis=2)
            own = np.ascontiguousarray(own.T).astype(np.intp)  # a row a distinct state
            for row in rest:
                own += row
                own = self.next.take(own, mode="clip")
            at = np.take_along_axis(own.T, index, axis=1).astype(np.int16)
            COUNTERS.steps += rest.size * own.shape[0]
        return at

    def run(self, start: np.ndarray, lanes: slice = slice(None)) -> tuple[np.ndarray, np.ndarray]:
        """Class of each symbol and state after it, (lanes, lane) each, from known start states."""
        base = self.base[:, lanes]
        classes, after = np.empty(base.shape, np.uint8), np.empty(base.shape, np.int16)
        at = start.astype(np.intp)
        for j, row in enumerate(base):
            i = row + at
            self.emit.take(i, mode="clip", out=classes[j])
            at = self.next.take(i, mode="clip")
            after[j] = at
        COUNTERS.steps += base.size
        return classes.T, after.T


def exclusive_prefix(vectors: np.ndarray) -> np.ndarray:
    """State before each lane from every start state of the block."""
    total = vectors.copy()
    step = 1
    while step < len(total):
        total[step:] = np.take_along_axis(total[step:], total[:-step].astype(np.int64), 1)
        step *= 2
    return np.concatenate([np.arange(vectors.shape[1], dtype=vectors.dtype)[None], total[:-1]])


def block_vector(data: np.ndarray, dfa: Dfa, lane: int = LANE) -> np.ndarray:
    """End state of a block from every start state."""
    if not len(data):
        return np.arange(dfa.n_states)
    v = Lanes(data, dfa, lane).vectors()
    return np.take_along_axis(v[-1:], exclusive_prefix(v)[-1:].astype(np.int64), 1)[0]


def classify(data: np.ndarray, dfa: Dfa, start: int, lane: int = LANE, collapse: bool = True) -> tuple[np.ndarray, int]:
    """Class of every byte from one known start state, and the end state."""
    if not len(data):
        return np.zeros(0, np.uint8), start
    lanes = Lanes(data, dfa, lane, collapse)
    return tagged(lanes, exclusive_prefix(lanes.vectors())[:, start])


def tagged(lanes: Lanes, before: np.ndarray) -> tuple[np.ndarray, int]:
    """Class of every byte of a block that is not empty, given the state before each lane, and the end state."""
    dfa = lanes.dfa
    classes, after = lanes.run(before)
    k = len(lanes.symbols)
    classes, after = classes.reshape(-1)[:k], after.reshape(-1)[:k]
    if k == lanes.n:
        return classes, int(after[-1])
    again = dfa.emit[dfa.other][after]  # a further byte of the same run
    full = np.repeat(np.where(lanes.symbols == dfa.other, again, classes), np.diff(np.append(lanes.pos, lanes.n)))
    full[lanes.pos] = classes
    return full, int(after[-1])


@dataclass
class Summary:
    """What a piece of input does from one start state; positions are relative to the piece, -1 if there is none."""

    end: int
    recs: int = 0
    is_abs: bool = False
    col: int = 0
    head: int = 0  # field delimiters before the first record delimiter
    mn: int = -1  # columns of records that begin and end inside
    mx: int = -1
    bad: int = -1
    first_end: int = -1  # byte after the first record delimiter
    last_end: int = -1
    length: int = 0

    def then(self, y: Summary) -> Summary:
        """This piece followed by ``y``, which was read from this piece's end state."""
        out = Summary(y.end, self.recs + y.recs, self.is_abs or y.is_abs, y.col if y.is_abs else self.col + y.col, length=self.length + y.length)
        out.bad = self.bad if self.bad >= 0 else self.length + y.bad if y.bad >= 0 else -1
        widths = [w for w in (self.mn, y.mn) if w >= 0], [w for w in (self.mx, y.mx) if w >= 0]
        if self.recs and y.recs:
            seam = self.col + y.head + 1
            widths[0].append(seam)
            widths[1].append(seam)
        out.head = self.head if self.recs else self.col + y.head if y.recs else 0
        out.mn, out.mx = min(widths[0], default=-1), max(widths[1], default=-1)
        out.first_end = self.first_end if self.recs else self.length + y.first_end if y.recs else -1
        out.last_end = self.length + y.last_end if y.recs else self.last_end
        return out


FIELDS = ("end", "recs", "is_abs", "col", "head", "mn", "mx", "bad", "first_end", "last_end", "length")
SUMMARY_DDL = "struct<end:int,recs:bigint,is_abs:boolean,col:bigint,head:bigint,mn:bigint,mx:bigint,bad:bigint,first_end:bigint,last_end:bigint,length:bigint>"


def _summed(classes: np.ndarray, pos: np.ndarray, end: int, length: int) -> Summary:
    out = Summary(end, length=length)
    rec, fld, bad = np.flatnonzero(classes == RECORD), classes == FIELD, np.flatnonzero(classes == INVALID)
    if len(bad):
        out.bad = int(pos[bad[0]])
    total = np.cumsum(fld)
    fields = int(total[-1]) if len(total) else 0
    out.recs, out.is_abs = len(rec), len(rec) > 0
    if not len(rec):
        out.col = fields
        return out
    seen = total[rec]
    out.head, out.col = int(seen[0]), fields - int(seen[-1])
    if len(rec) > 1:
        widths = np.diff(seen) + 1
        out.mn, out.mx = int(widths.min()), int(widths.max())
    out.first_end, out.last_end = int(pos[rec[0]]) + 1, int(pos[rec[-1]]) + 1
    return out


def summarize(data: np.ndarray, dfa: Dfa, lane: int = LANE, block: int = BLOCK) -> list[Summary]:
    """Summary of a piece from every start state, in one pass over its bytes."""
    total: list[Summary] | None = None
    for lo in range(0, max(1, len(data)), block):
        own = _summarize_block(data[lo : lo + block], dfa, lane)
        total = own if total is None else [x.then(own[x.end]) for x in total]
    return total


def _summarize_block(data: np.ndarray, dfa: Dfa, lane: int) -> list[Summary]:
    if not len(data):
        return [Summary(s) for s in range(dfa.n_states)]
    lanes = Lanes(data, dfa, lane)
    before = exclusive_prefix(lanes.vectors())
    k = len(lanes.symbols)
    # starts that agree from the second lane on share the run over these lanes
    seen: dict[bytes, Summary] = {}
    out, edge = [], min(k, lane)  # symbols of the first lane
    cut = int(lanes.pos[edge]) if edge < k else len(data)
    for s in range(dfa.n_states):
        classes, after = lanes.run(np.array([s]), slice(0, 1))
        one = _summed(classes.reshape(-1)[:edge], lanes.pos[:edge], int(after.reshape(-1)[edge - 1]), cut)
        if edge < k:
            later = before[1:, s]
            if (mark := later.tobytes()) not in seen:
                classes, after = lanes.run(later, slice(1, None))
                seen[mark] = _summed(classes.reshape(-1)[: k - edge], lanes.pos[edge:] - cut, int(after.reshape(-1)[k - edge - 1]), len(data) - cut)
            one = one.then(seen[mark])
        out.append(one)
    return out


@dataclass
class Parsed:
    """Fields of a block in input order: ``text[offsets[f]:offsets[f+1]]``, and where records end."""

    text: np.ndarray
    offsets: np.ndarray
    quoted: np.ndarray
    ends: np.ndarray  # index of the field after each record's last
    consumed: int  # bytes up to and with the last record delimiter
    bad: int
    end_state: int
    spans: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))  # byte after each field's delimiter

    @property
    def records(self) -> int:
        return len(self.ends)


def parse_block(data: np.ndarray, dfa: Dfa, final: bool = False, lane: int = LANE) -> Parsed:
    """Complete records of a block that begins at a record; ``final`` also takes a last record without a delimiter."""
    return partitioned(data, dfa, *classify(data, dfa, dfa.start, lane), final)


def partitioned(data: np.ndarray, dfa: Dfa, classes: np.ndarray, end: int, final: bool = False) -> Parsed:
    """Complete records of a block, given the class of every byte and the end state."""
    keep = classes == DATA
    other = np.flatnonzero(~keep)  # few against the bytes: what follows is counted over these
    kind = classes[other]
    at = np.flatnonzero((kind == FIELD) | (kind == RECORD))
    marks, is_rec = other[at], kind[at] == RECORD
    last = np.flatnonzero(is_rec)
    consumed = int(marks[last[-1]]) + 1 if len(last) else 0
    tail = len(data) - consumed
    bad = other[np.flatnonzero(kind == INVALID)[:1]]
    open_tail = final and tail > 0 and end != dfa.start
    if open_tail:
        marks, is_rec, at = np.append(marks, len(data)), np.append(is_rec, True), np.append(at, len(other))
        consumed = len(data)
    else:
        n = int(last[-1]) + 1 if len(last) else 0
        marks, is_rec, at = marks[:n], is_rec[:n], at[:n]
        data, keep = data[:consumed], keep[:consumed]
    offsets = np.concatenate([[0], marks - at])
    control = np.concatenate([[0], np.cumsum(kind == CONTROL, dtype=np.int64)])
    quoted = np.diff(np.concatenate([[0], control[at]])) > 0
    return Parsed(data[keep], offsets, quoted, np.flatnonzero(is_rec) + 1, consumed, int(bad[0]) if len(bad) else -1, end, np.minimum(marks + 1, len(data)))


def field_array(p: Parsed) -> pa.Array:
    """All fields as one binary array, no copy of the text."""
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(p.offsets) - 1, [None, pa.py_buffer(p.offsets.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(p.text))])


def columns_of(p: Parsed, columns: list[int], empty_null: bool = True) -> list[pa.Array]:
    """The wanted columns, one value a record: missing fields and (``empty_null``) unquoted empty ones are null."""
    fields = field_array(p)
    begins = np.concatenate([[0], p.ends[:-1]]) if len(p.ends) else np.zeros(0, np.int64)
    width = p.ends - begins
    blank = (np.diff(p.offsets) == 0) & ~p.quoted if empty_null else None
    out = []
    for c in columns:
        at = begins + c
        gone = width <= c
        if gone.any():
            at = np.where(gone, 0, at)
        if blank is not None and len(at):
            gone = gone | blank[at]
        out.append(fields.take(pa.array(at, mask=gone)))
    return out


def decode(array: pa.Array, encoding: str = "utf-8") -> pa.Array:
    """Binary to text; invalid sequences become replacement signs."""
    try:
        return array.cast(pa.large_string()).cast(pa.string())
    except (pa.ArrowInvalid, pa.ArrowNotImplementedError):
        return pa.array([None if x is None else x.decode(encoding, "replace") for x in array.to_pylist()], pa.string())
