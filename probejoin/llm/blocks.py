"""Documents dealt to blocks, and questions about keys that blocks ask of buckets.

A block holds the texts whose hash falls to it. It sends its distinct keys, sorted, as
differences with equal bytes together, compressed, one row for each bucket of the key space;
a bucket answers in the order of the question.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.llm.common import give_back, lean, only


def zipped(data: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(data)


def unzipped(data: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(data)


def packed(values: np.ndarray) -> bytes:
    """Fixed-width numbers with equal bytes together, compressed."""
    return zipped(np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes())


def unpacked(data: bytes, kind) -> np.ndarray:
    planes = np.frombuffer(unzipped(data), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    return np.ascontiguousarray(planes.T).view(kind).reshape(-1)


def pack_keys(keys: np.ndarray) -> bytes:
    """Rising 64-bit keys as differences."""
    return packed(np.diff(keys, prepend=np.uint64(0)))


def unpack_keys(data: bytes) -> np.ndarray:
    return np.cumsum(unpacked(data, np.uint64), dtype=np.uint64)


def slices(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket's share of rising keys begins, and the end."""
    edges = (np.arange(1, buckets, dtype=np.float64) * (2.0**64 / buckets)).astype(np.uint64)
    return np.concatenate(([0], np.searchsorted(keys, edges), [len(keys)]))


def texts_of(blobs: list[bytes]) -> tuple[list, list[str | None]]:
    """Ids and texts of a block by text and id, so that places in a block hold in every pass, however its parts arrive."""
    only("")
    ids, texts = [], []
    for blob in blobs:
        got = pa.ipc.open_stream(unzipped(blob)).read_all()
        ids += got.column(0).to_pylist()
        texts += got.column(1).to_pylist()
    order = sorted(range(len(ids)), key=lambda k: (texts[k] or "", repr(ids[k])))
    return [ids[k] for k in order], [texts[k] for k in order]


def blocked(docs: DataFrame, id_col: str, text_col: str, n: int) -> DataFrame:
    """Rows (block, blob): texts with their ids, those of a block within a batch packed together."""
    lean(docs.sparkSession)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.pmod(F.xxhash64(id_col, text_col), F.lit(n)).cast("int").alias("block"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("blocks")
        for batch in batches:
            block = batch.column(2).to_numpy()
            order = np.argsort(block, kind="stable")
            own, starts = np.unique(block[order], return_index=True)
            blobs = []
            for part in np.split(order, starts[1:]):
                sub = pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(part)), batch.column(1).take(pa.array(part))], ["id", "text"])
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, sub.schema) as w:
                    w.write_batch(sub)
                blobs.append(zipped(sink.getvalue()))
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array(blobs, pa.binary())], ["block", "blob"])
        give_back()  # the worker may now be idle for long

    return rows.mapInArrow(run, "block int, blob binary")


def blocks_of(docs: DataFrame, text_col: str, block_bytes: int) -> int:
    """Number of blocks for a table: they grow with the root of its size, so that blocks times buckets grow with the size."""
    size = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    return max(1, -(-size // max(block_bytes, int(math.sqrt(size) * 64))))
