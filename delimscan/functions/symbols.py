"""Mapping a byte to its symbol group: lookup table, branch-free matching in words, and a ladder of branches."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

LOW, HIGH = 0x01010101, 0x80808080  # fixed values of the null-byte test


def lookup_words(symbols: list[int], filler: int | None = None) -> list[int]:
    """Symbols four to a word, the first in the lowest byte; unused bytes repeat the last symbol of their word.

    The null-byte test may also flag the byte above a match if the two symbols differ by one bit pattern of 1, and the
    highest flag would win; :func:`swar_index` therefore takes the lowest flag, which is exact for any order.
    """
    words = []
    for lo in range(0, len(symbols), 4):
        four = symbols[lo : lo + 4]
        four += [four[-1] if filler is None else filler] * (4 - len(four))
        words.append(sum(s << (8 * i) for i, s in enumerate(four)))
    return words


def highest_flag(word: int, symbol: int) -> int | None:
    """Index of the highest flagged byte, as the printed method takes it."""
    c = word ^ (symbol * LOW)
    flags = (c - LOW) & ~c & HIGH & 0xFFFFFFFF
    return (flags.bit_length() - 1) >> 3 if flags else None


def _lowest_flag(flags: Column) -> Column:
    out = F.lit(None).cast("int")
    for i in (3, 2, 1, 0):
        out = F.when(flags.bitwiseAND(F.lit(0x80 << (8 * i)).cast("long")) != 0, F.lit(i)).otherwise(out)
    return out


def swar_index(symbol: Column, symbols: list[int]) -> Column:
    """Index of the symbol in ``symbols``, or their number if it is none of them."""
    s = symbol.cast("long") * F.lit(LOW).cast("long")
    found = F.lit(len(symbols))
    for w, word in enumerate(lookup_words(list(symbols))):
        c = F.lit(word).cast("long").bitwiseXOR(s)
        flags = (c - F.lit(LOW).cast("long")).bitwiseAND(F.bitwise_not(c)).bitwiseAND(F.lit(HIGH).cast("long"))
        at = _lowest_flag(flags) + F.lit(4 * w)
        found = F.least(found, F.coalesce(at, F.lit(len(symbols))))
    return found.cast("int")


def swar_group(symbol: Column, symbols: list[int], groups: list[int], other: int) -> Column:
    return F.element_at(F.array(*[F.lit(int(g)) for g in [*groups, other]]), swar_index(symbol, symbols) + 1)


def lut_group(symbol: Column, lut: np.ndarray) -> Column:
    return F.element_at(F.array(*[F.lit(int(g)) for g in lut]), symbol.cast("int") + 1)


def branching_group(symbol: Column, symbols: list[int], groups: list[int], other: int) -> Column:
    out = F.when(F.lit(False), F.lit(0))
    for s, g in zip(symbols, groups, strict=True):
        out = out.when(symbol == s, F.lit(int(g)))
    return out.otherwise(F.lit(int(other)))
