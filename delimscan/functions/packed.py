"""Packed arrays of small integers, as registers of item fragments and as one BIGINT."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Layout:
    items: int
    bits: int
    usable: int  # bits of a register that fall to an item
    width: int  # bits of a fragment, a power of two
    registers: int


def layout(items: int, bits: int, register_bits: int = 32) -> Layout:
    usable = register_bits // items
    if usable < 1:
        raise ValueError("more items than bits in a register")
    width = 1 << (usable.bit_length() - 1)
    return Layout(items, bits, usable, width, -(-bits // width))


def get(registers: list[int], lay: Layout, i: int) -> int:
    shift, mask = i * lay.width, (1 << lay.width) - 1
    return sum(((r >> shift) & mask) << (k * lay.width) for k, r in enumerate(registers)) & ((1 << lay.bits) - 1)


def put(registers: list[int], lay: Layout, i: int, value: int) -> list[int]:
    shift, mask = i * lay.width, (1 << lay.width) - 1
    return [(r & ~(mask << shift)) | (((value >> (k * lay.width)) & mask) << shift) for k, r in enumerate(registers)]


def get_column(registers: Column, lay: Layout, i: Column) -> Column:
    """Item ``i`` (from 0) of an ``ARRAY<BIGINT>`` of registers."""
    mask = F.lit((1 << lay.width) - 1).cast("long")
    out = F.lit(0).cast("long")
    for k in range(lay.registers):
        fragment = F.call_function("shiftright", F.element_at(registers, k + 1), (i * lay.width).cast("int")).bitwiseAND(mask)
        out = out + F.shiftleft(fragment, k * lay.width)
    return out.bitwiseAND(F.lit((1 << lay.bits) - 1).cast("long"))


def pack_vector(states: Column, size: int) -> Column:
    """State-transition vector as one BIGINT, four bits a state."""
    out = F.lit(0).cast("long")
    for i in range(size):
        out = out.bitwiseOR(F.shiftleft(F.element_at(states, i + 1).cast("long"), 4 * i))
    return out


def vector_item(packed: Column, i: Column) -> Column:
    return F.call_function("shiftright", packed, (i * 4).cast("int")).bitwiseAND(F.lit(15).cast("long")).cast("int")


def compose_packed(first: Column, second: Column, size: int) -> Column:
    """``second`` after ``first``, both packed."""
    out = F.lit(0).cast("long")
    for i in range(size):
        out = out.bitwiseOR(F.shiftleft(vector_item(second, vector_item(first, F.lit(i))).cast("long"), 4 * i))
    return out
