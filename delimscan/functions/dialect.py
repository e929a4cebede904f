"""Dialects of delimiter-separated text and the automata that parse them."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np

DATA, FIELD, RECORD, CONTROL, INVALID = range(5)  # what a byte is
REC_START, QUOTED, PLAIN, FLD_START, QUOTE_SEEN, BAD = "REC_START", "QUOTED", "PLAIN", "FLD_START", "QUOTE_SEEN", "BAD"
CR_SEEN, ESC_PLAIN, ESC_QUOTED, COMMENT, BRACKET, BRACKET_END = "CR_SEEN", "ESC_PLAIN", "ESC_QUOTED", "COMMENT", "BRACKET", "BRACKET_END"


@dataclass(frozen=True)
class Dialect:
    field_sep: str = ","
    record_sep: str = "\n"
    quote: str | None = '"'
    escape: str | None = None
    comment: str | None = None
    brackets: tuple[str, str] | None = None
    crlf: bool = False
    lenient_lf: bool = False  # with crlf: a bare line feed ends a record too
    blank_lines: str = "record"  # or "skip"
    trailing_delimiter: bool = False  # every record ends with a delimiter that opens no field

    def with_(self, **changes) -> Dialect:
        return replace(self, **changes)


@dataclass(frozen=True, eq=False)
class Dfa:
    """States, symbol groups, transitions and emissions.  ``table[g, s]`` is the next state, ``emit[g, s]`` the byte's class."""

    states: tuple[str, ...]
    lut: np.ndarray  # group of each byte value
    table: np.ndarray
    emit: np.ndarray
    accepting: frozenset[int]
    start: int = 0

    def __post_init__(self):
        if len(self.states) > 16:
            raise ValueError("a packed vector holds at most 16 states")

    @property
    def n_states(self) -> int:
        return len(self.states)

    @property
    def other(self) -> int:
        """Group of most byte values."""
        return int(np.bincount(self.lut, minlength=len(self.table)).argmax())

    @property
    def collapsible(self) -> bool:
        """Whether a run of the commonest group ends in the same states as its first byte."""
        once = self.table[self.other]
        return bool((once[once] == once).all())

    @property
    def context_free(self) -> bool:
        """Whether a record end leads to the start state whatever came before."""
        ends = (self.emit == RECORD).any(axis=1)
        return all(bool((self.emit[g] == RECORD).all() and (self.table[g] == self.start).all()) for g in np.flatnonzero(ends)) and bool(ends.any())

    def group(self, symbol: str) -> int:
        return int(self.lut[ord(symbol)])

    def rows(self) -> list[tuple[int, int, int, int]]:
        """Table form ``(state, group, next, emit)``."""
        return [(s, g, int(self.table[g, s]), int(self.emit[g, s])) for g in range(len(self.table)) for s in range(self.n_states)]

    @classmethod
    def from_table(cls, states: tuple[str, ...], symbols: dict[str, int], rows: list[tuple[int, int, int, int]], accepting: tuple[str, ...], other: int) -> Dfa:
        """Any automaton: ``symbols`` maps bytes to groups (``other`` takes the rest), ``rows`` are ``(state, group, next, emit)``."""
        groups = 1 + max([other, *symbols.values()])
        lut = np.full(256, other, np.uint8)
        for c, g in symbols.items():
            lut[ord(c)] = g
        table, emit = np.full((groups, len(states)), 255, np.uint8), np.zeros((groups, len(states)), np.uint8)
        for s, g, nxt, e in rows:
            table[g, s], emit[g, s] = nxt, e
        if (table >= len(states)).any():
            raise ValueError("the table lacks a transition or names an unknown state")
        return cls(states, lut, table, emit, frozenset(states.index(a) for a in accepting))


def collapse_groups(table: np.ndarray, emit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One row for all symbols of equal transitions and emissions: ``(group of each symbol, table, emit)``, in order of first use."""
    seen: dict[bytes, int] = {}
    of = np.array([seen.setdefault(table[i].tobytes() + emit[i].tobytes(), len(seen)) for i in range(len(table))], np.uint8)
    first = [int(np.flatnonzero(of == g)[0]) for g in range(len(seen))]
    return of, table[first], emit[first]


def _states(d: Dialect) -> list[str]:
    names = [REC_START, *([QUOTED] if d.quote else []), PLAIN, FLD_START, *([QUOTE_SEEN] if d.quote else [])]
    names += [CR_SEEN] * d.crlf + [ESC_PLAIN] * bool(d.escape) + [ESC_QUOTED] * bool(d.escape and d.quote) + [COMMENT] * bool(d.comment) + [BRACKET, BRACKET_END] * bool(d.brackets)
    return names + [BAD] * bool(d.quote or d.brackets or d.crlf)


def _step(d: Dialect, state: str, byte: str) -> tuple[str, int]:
    """Next state and class of a byte."""
    inside = {QUOTED: QUOTE_SEEN, BRACKET: BRACKET_END}
    if state == BAD:
        return BAD, INVALID
    if state == COMMENT:
        return (REC_START if byte == d.record_sep else COMMENT), CONTROL
    if state in (ESC_PLAIN, ESC_QUOTED):
        return (PLAIN if state == ESC_PLAIN else QUOTED), DATA
    if state in inside:
        if d.escape and byte == d.escape and state == QUOTED:
            return ESC_QUOTED, CONTROL
        closes = byte == (d.quote if state == QUOTED else d.brackets[1])
        return (inside[state], CONTROL) if closes else (state, DATA)
    if byte == d.record_sep and (not d.crlf or d.lenient_lf or state == CR_SEEN):
        skipped = state == REC_START and d.blank_lines == "skip"
        return REC_START, CONTROL if skipped else RECORD
    if state == CR_SEEN or (d.crlf and byte == d.record_sep):
        return BAD, INVALID
    if d.crlf and byte == "\r":
        return CR_SEEN, CONTROL
    if byte == d.field_sep:
        return FLD_START, FIELD
    if byte == d.quote:
        return {REC_START: (QUOTED, CONTROL), FLD_START: (QUOTED, CONTROL), QUOTE_SEEN: (QUOTED, DATA)}.get(state, (BAD, INVALID))
    if state in (QUOTE_SEEN, BRACKET_END):
        return BAD, INVALID
    if d.escape and byte == d.escape:
        return ESC_PLAIN, CONTROL
    if byte == d.comment and state == REC_START:
        return COMMENT, CONTROL
    if d.brackets and byte == d.brackets[0] and state in (REC_START, FLD_START):
        return BRACKET, CONTROL
    return PLAIN, DATA


def compile_dialect(dialect: Dialect | str | Dfa) -> Dfa:
    if isinstance(dialect, Dfa):
        return dialect
    d = DIALECTS[dialect] if isinstance(dialect, str) else dialect
    if any(c and ord(c) > 127 for c in (d.field_sep, d.record_sep, d.quote, d.escape, d.comment, *(d.brackets or ()))):
        raise ValueError("special symbols are ASCII, so that bytes of longer UTF-8 characters are never special")
    names = _states(d)
    index = {s: i for i, s in enumerate(names)}
    special = [d.record_sep, d.quote, d.field_sep, "\r" if d.crlf else None, d.escape, d.comment, *(d.brackets or ())]
    symbols = [*dict.fromkeys(c for c in special if c), "\x00"]  # the last stands for every other byte
    steps = [[_step(d, s, c) for s in names] for c in symbols]
    of, table, emit = collapse_groups(np.array([[index[n] for n, _ in row] for row in steps], np.uint8), np.array([[e for _, e in row] for row in steps], np.uint8))
    lut = np.full(256, of[-1], np.uint8)
    for c, g in zip(symbols[:-1], of[:-1], strict=True):
        lut[ord(c)] = g
    refused = {QUOTED, BAD, BRACKET, ESC_QUOTED, ESC_PLAIN}
    return Dfa(tuple(names), lut, table, emit, frozenset(i for i, s in enumerate(names) if s not in refused), index[REC_START])


DIALECTS: dict[str, Dialect] = {
    "rfc4180": Dialect(),
    "rfc4180_crlf": Dialect(crlf=True),
    "tsv": Dialect(field_sep="\t", quote=None),
    "pipe": Dialect(field_sep="|", quote=None),
    "unit": Dialect(field_sep="\x1f", quote=None),
    "csv_backslash": Dialect(escape="\\"),
    "csv_comment": Dialect(comment="#"),
    "ext_log": Dialect(field_sep=" ", comment="#"),
    "common_log": Dialect(field_sep=" ", escape="\\", brackets=("[", "]")),
    "bracket_array": Dialect(brackets=("[", "]")),
}
