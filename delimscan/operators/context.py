"""Parsing context: state-transition vectors of chunks, their composition, and every chunk's start state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dialect import Dfa
from .chunking import byte_at
from .kernel import block_vector
from .scan import exclusive_scan, vector_monoid


def _literal(values) -> Column:
    return F.array(*[F.lit(int(v)) for v in np.asarray(values).ravel()])


def _group(data: Column, i: Column, dfa: Dfa) -> Column:
    return F.element_at(_literal(dfa.lut), byte_at(data, i) + 1)


def run_sequential(data: Column, dfa: Dfa, start: int = 0) -> Column:
    """End state after all bytes, one after the other: the reference."""
    table, n = _literal(dfa.table), dfa.n_states
    step = lambda s, i: F.element_at(table, _group(data, i, dfa) * n + s + 1)
    return F.when(F.octet_length(data) == 0, F.lit(start)).otherwise(F.aggregate(F.sequence(F.lit(0), F.octet_length(data) - 1), F.lit(start), step))


def transition_vector(data: Column, dfa: Dfa) -> Column:
    """End state of every start state, as expressions (for small inputs and as a second opinion on the kernel)."""
    table, n, identity = _literal(dfa.table), dfa.n_states, _literal(np.arange(dfa.n_states))

    def step(acc: Column, i: Column) -> Column:
        g = _group(data, i, dfa)
        return F.transform(acc, lambda s: F.element_at(table, g * n + s + 1))

    return F.when(F.octet_length(data) == 0, identity).otherwise(F.aggregate(F.sequence(F.lit(0), F.octet_length(data) - 1), identity, step))


def transition_vectors(chunks: DataFrame, dfa: Dfa, data: str = "data", lane: int = 256) -> DataFrame:
    """``chunks`` with ``vector`` in place of ``data``, by the kernel."""
    keep = [c for c in chunks.columns if c != data]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            vectors = [block_vector(np.frombuffer(x or b"", np.uint8), dfa, lane).astype(np.int32).tolist() for x in b.column(len(keep)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(vectors, pa.list_(pa.int32()))], [*keep, "vector"])

    kind = chunks.select(*keep).schema.add("vector", T.ArrayType(T.IntegerType()))
    return chunks.select(*keep, data).mapInArrow(run, kind)


def compose(first: Column, second: Column) -> Column:
    """``second`` after ``first``."""
    return F.transform(first, lambda s: F.element_at(second, s + 1))


def start_states(vectors: DataFrame, dfa: Dfa, key: str, order: str, start: int = 0, fan: int = 1024) -> DataFrame:
    """``(key, order, start_state)`` from the exclusive scan of vectors, for any global start state."""
    prefix = exclusive_scan(vectors, key, order, "vector", vector_monoid(dfa.n_states), fan)
    return prefix.select(key, order, F.element_at("prefix", start + 1).alias("start_state"))
