"""Token-id files: flat unsigned integers plus 64-bit document offsets, memory-mapped when they are read.

One file set a Spark partition of the documents ranged by id: ``shard-00007.ids`` (little-endian unsigned 16- or
32-bit ids, whichever the vocabulary and the end id need), ``.off`` (n + 1 unsigned 64-bit offsets, in ids, from the
file's first) and ``.doc`` (n signed 64-bit document ids).  A partition's base is the prefix sum of the lengths before
it.  The manifest names the width of the ids; an id that does not fit the width raises an error.

Defined results: a null text is empty, so its document holds the end id alone; a null id sorts first and is stored as
the smallest 64-bit integer; documents of equal id are ordered by the hash of their text, then the text; an empty
table gives no files with rows.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe_cache import encoder
from .common import durable, shared_dir, slices

NO_ID = -(1 << 63)


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or ":/" in uri else f"file://{uri}")


def _map(uri: str, dtype: str) -> np.ndarray:
    """The array in a file: mapped where the file system is local, else read."""
    from pyarrow import fs

    store, path = _open(uri)
    if isinstance(store, fs.LocalFileSystem):
        return np.memmap(path, dtype, "r") if store.get_file_info(path).size else np.zeros(0, dtype)
    with store.open_input_file(path) as f:
        return np.frombuffer(f.read_buffer(), dtype)


def id_width(tokenizer: str, end_id: int) -> int:
    """Bytes an id takes: 2 if every id of the vocabulary and the end id fit 16 bits, else 4."""
    return 2 if max(encoder(tokenizer).largest, end_id) < 1 << 16 else 4


def packed(ids: np.ndarray, width: int) -> bytes:
    """Ids as little-endian unsigned numbers of ``width`` bytes."""
    if len(ids) and int(ids.max()) >> (8 * width):
        raise ValueError(f"id {int(ids.max())} does not fit {8 * width} bits")
    return ids.astype(f"<u{width}").tobytes()


def write_token_files(docs: DataFrame, folder: str, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", width: int | None = None) -> DataFrame:
    """Encode and write; returns the manifest ``(part, documents, ids, width, base)``, one row a file set, ``base`` = ids before it."""
    width = width or id_width(tokenizer, end_id)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, attempt = TaskContext.get().partitionId(), TaskContext.get().taskAttemptId()
        store, root = _open(folder)
        store.create_dir(root, recursive=True)
        names = {x: f"{root}/shard-{part:05d}.{x}" for x in ("ids", "off", "doc")}
        enc, total, n = encoder(tokenizer), 0, 0
        sinks = {x: store.open_output_stream(f"{p}.{attempt}") for x, p in names.items()}
        sinks["off"].write(np.zeros(1, "<u8").tobytes())
        for rows, raw, off in slices(batches, "text", 4 << 20):
            ids, at = enc.encode(raw, off)
            ids = np.insert(ids, at[1:], end_id)
            ends = at[1:] + np.arange(1, len(at))
            sinks["ids"].write(packed(ids, width))
            sinks["off"].write((total + ends).astype("<u8").tobytes())
            sinks["doc"].write(rows.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False).astype("<i8").tobytes())
            total, n = total + len(ids), n + rows.num_rows
        for x, sink in sinks.items():
            sink.close()
            store.move(f"{names[x]}.{attempt}", names[x])  # a retried task replaces its own files whole
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([n], pa.int64()), pa.array([total], pa.int64()), pa.array([width], pa.int32())], ["part", "documents", "ids", "width"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    ranged = rows.withColumn("h", F.xxhash64("text")).repartitionByRange("id", "h").sortWithinPartitions("id", "h", "text").drop("h")
    written = durable(ranged.mapInArrow(run, "part int, documents long, ids long, width int"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a file, not a document
    return durable(written.withColumn("base", F.coalesce(F.sum("ids").over(before), F.lit(0).cast("long"))))


def read_token_files(manifest: DataFrame, folder: str) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32)`` from the files; ``start`` counts the ids of all documents before."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, n, base, width in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                stem = f"{folder.rstrip('/')}/shard-{part:05d}"
                ids, off, doc = _map(f"{stem}.ids", f"<u{width}"), _map(f"{stem}.off", "<u8"), _map(f"{stem}.doc", "<i8")
                if len(doc) != n or len(off) != n + 1 or len(ids) != int(off[-1]):
                    raise ValueError(f"{stem}: lengths disagree with the manifest")
                for lo in range(0, n, 4096):
                    hi = min(n, lo + 4096)
                    o = off[lo : hi + 1].astype(np.int64)
                    own = ids[o[0] : o[-1]].astype("<u4")
                    crc = [zlib.crc32(own[a - o[0] : b - o[0]]) for a, b in zip(o[:-1].tolist(), o[1:].tolist(), strict=True)]
                    d = doc[lo:hi].astype(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(d, mask=d == NO_ID), pa.array(base + o[:-1]), pa.array(np.diff(o)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    sets = manifest.where("documents > 0").select("part", "documents", "base", "width")
    spread = sets.repartitionByRange(max(1, sets.count()), "part")  # a file set a task; with a number, so adaptive execution does not merge the few rows
    return spread.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def new_folder(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
