"""Word n-gram language model by deleted interpolation.

p(w | v) = a[b] c(v,w)/c(v) + u[b] c(w)/N + z[b]/(V+1), where b buckets the context v by its
frequency. The weights of each bucket come from expectation-maximisation on held-out counts:
each training token in turn is left out of its own counts (deleted estimation), so every
training document counts and none has to be set aside.

Counts are exact and never gathered in one place. Documents are dealt to blocks by hash. A
block asks for the counts of its distinct words and pairs: it sends its own training counts,
sorted and packed, to buckets of the key space; a bucket adds them up and answers each block
in the order of its question. So each pair crosses the network once for each block that has
it, however frequent it is, and no task sees more than its share of keys. Words and pairs
are 64-bit hashes; two that clash would be counted as one.

Rows: null text counts as empty: its only token is the end. Null ids count as held_out by
the crc32 of an empty text. Every input row gives one output row, repeated rows too; extra
columns are ignored; an empty table gives an empty result; texts are read whole. Without
training rows every probability is 1 / (V + 1) with V = 0.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.blocks import blocked, blocks_of, pack_keys, packed, slices, texts_of, unpack_keys, unpacked, unzipped
from probejoin.llm.common import BASES, crc_mod_py, mix64, prefix_hash, shared_folder, span_hash

END, BEGIN = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
#: Steps of the histogram of probabilities to a power of two, and sizes of its axes.
STEPS, LEVELS = 4, 160
PIECE = 1 << 19


def words(data: bytes) -> np.ndarray:
    """Hashes of the words of lower-cased bytes, piece by piece, cut at white space."""
    out, at = [], 0
    while at < len(data):
        end = min(at + PIECE, len(data))
        while end < len(data) and data[end] not in b" \t\n\x0b\x0c\r":
            end += 1
        codes = np.frombuffer(data, np.uint8, end - at, at)
        gap = np.ones(len(codes) + 2, np.bool_)
        gap[1:-1] = (codes == 32) | ((codes >= 9) & (codes <= 13))
        start, stop = np.flatnonzero(gap[:-1] & ~gap[1:]), np.flatnonzero(~gap[:-1] & gap[1:])
        out.append(span_hash(prefix_hash(codes, BASES[0]), start, stop, BASES[0]))
        at = end
    return np.concatenate(out) if out else np.empty(0, np.uint64)


def tokens(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the tokens of all texts, each text's end included, and the number of tokens of each text.

    Texts are hashed together up to a piece; a mark between them that no text can hold
    (byte FF as a word of its own) tells them apart.
    """
    flat, sizes, group, held = [], [], [], 0
    mark = None

    def flush() -> None:
        nonlocal held, mark
        if not group:
            return
        if mark is None:
            mark = words(b"\xff")[0]
        got = words(b" \xff ".join(group) + b" \xff ")
        ends = np.flatnonzero(got == mark)
        got[ends] = END
        flat.append(got)
        sizes.append(np.diff(ends, prepend=-1))
        group.clear()
        held = 0

    for text in texts:
        data = text.encode("utf-8", "surrogatepass").lower() if text else b""
        group.append(data)
        held += len(data)
        if held >= PIECE // 2:
            flush()
    flush()
    if not flat:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    return np.concatenate(flat), np.concatenate(sizes)


def pairs(flat: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Key of each token with the one before it."""
    before = np.empty(len(flat), np.uint64)
    if len(flat):
        before[1:] = flat[:-1]
        before[np.cumsum(sizes) - sizes] = BEGIN
    return mix64(before * np.uint64(0x9E3779B97F4A7C15) + (flat ^ (flat >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9))


def _keys(order: int, flat: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    return flat if order == 1 else pairs(flat, sizes)


def answers(parts: DataFrame, n_buckets: int, fold: int, folds: int) -> DataFrame:
    """Rows (block, bucket, ord, counts): training counts of each block's keys in their order."""

    def ask(table: pa.Table) -> pa.Table:
        ids, texts = texts_of(table["blob"].to_pylist())
        block = table["block"][0].as_py()
        flat, sizes = tokens(texts)
        trained = np.repeat(np.array([crc_mod_py(i, folds) != fold for i in ids], np.bool_), sizes)
        rows = []
        for order in (1, 2):
            keys, at = np.unique(_keys(order, flat, sizes), return_inverse=True)
            n = np.bincount(at[trained], minlength=len(keys)).astype(np.uint32)
            cut = slices(keys, n_buckets)
            rows += [(block, b, order, pack_keys(keys[cut[b] : cut[b + 1]]), packed(n[cut[b] : cut[b + 1]])) for b in range(n_buckets) if cut[b] < cut[b + 1]]
        kinds = (("block", pa.int32()), ("bucket", pa.int32()), ("ord", pa.int32()), ("keys", pa.binary()), ("n", pa.binary()))
        return pa.table({name: pa.array([r[k] for r in rows], kind) for k, (name, kind) in enumerate(kinds)})

    def add(table: pa.Table) -> pa.Table:
        keys = [unpack_keys(k) for k in table["keys"].to_pylist()]
        n = [unpacked(c, np.uint32) for c in table["n"].to_pylist()]
        own, at = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(at, weights=np.concatenate(n), minlength=len(own)).astype(np.uint64)
        answered = np.split(total[at].astype(np.uint64), np.cumsum([len(k) for k in keys])[:-1])
        return pa.table({"block": table["block"], "bucket": table["bucket"], "ord": table["ord"], "counts": pa.array([packed(a) for a in answered], pa.binary())})

    asked = parts.groupBy("block").applyInArrow(ask, "block int, bucket int, ord int, keys binary, n binary")
    return asked.groupBy("ord", "bucket").applyInArrow(add, "block int, bucket int, ord int, counts binary")


def bucket_of(context: np.ndarray) -> np.ndarray:
    """Frequency bucket of a context: the power of two below its count."""
    return np.where(context > 0, np.floor(np.log2(np.maximum(context, 1))).astype(np.int64) + 1, 0)


def _level(value: np.ndarray) -> np.ndarray:
    """Steps of a quarter of a power of two below 1; 0 for nothing."""
    safe = np.where(value > 0, value, 1)
    return np.where(value > 0, 1 + np.minimum(np.round(-np.log2(safe) * STEPS).astype(np.int64), LEVELS - 2), 0)


def counted(docs: DataFrame, id_col: str, text_col: str, fold: int, folds: int, block_bytes: int) -> DataFrame:
    """Written table: for each document its counts, and for each block a histogram of left-out events."""
    n = blocks_of(docs, text_col, block_bytes)
    parts = blocked(docs, id_col, text_col, n)
    id_kind = docs.schema[id_col].dataType
    schema = T.StructType([T.StructField("id", id_kind), T.StructField("held_out", T.BooleanType()), T.StructField("n_tokens", T.LongType()), T.StructField("n_known", T.LongType()), T.StructField("logs", T.DoubleType()), T.StructField("types", T.DoubleType()), T.StructField("pair_counts", T.BinaryType()), T.StructField("word_counts", T.BinaryType()), T.StructField("begins", T.LongType()), T.StructField("cells", T.BinaryType()), T.StructField("weights", T.BinaryType())])

    def join(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, texts = texts_of(left["blob"].to_pylist())
        flat, sizes = tokens(texts)
        held_out = np.array([crc_mod_py(i, folds) == fold for i in ids], np.bool_)
        got = {}
        for order in (1, 2):
            own = right.filter(pa.compute.equal(right["ord"], order)).sort_by("bucket")
            counts = [unpacked(c, np.uint64) for c in own["counts"].to_pylist()]
            _, at = np.unique(_keys(order, flat, sizes), return_inverse=True)
            got[order] = np.concatenate(counts)[at].astype(np.int64)
        word, pair = got[1], got[2]
        first = np.cumsum(sizes) - sizes
        begins = int(word[first[0] + sizes[0] - 1])  # the end's count is that of the texts
        context = np.empty_like(word)
        context[1:] = word[:-1]
        context[first] = begins
        trained = ~np.repeat(held_out, sizes)
        c, v, w = pair[trained] - 1, context[trained] - 1, word[trained] - 1
        share = np.where(v > 0, c / np.maximum(v, 1), 0.0)
        cell, weight = np.unique((bucket_of(v) * LEVELS + _level(share)) * 64 * STEPS + np.where(w > 0, 1 + np.round(np.log2(np.maximum(w, 1)) * STEPS).astype(np.int64), 0), return_counts=True)
        logs = np.add.reduceat(np.log10(word + 1.0), first)
        types = np.add.reduceat(np.where(trained, 1.0 / np.maximum(word, 1), 0.0), first)
        known = np.add.reduceat((word > 0).astype(np.int64), first)
        m = len(ids)
        cut = np.append(first, len(word))
        blob = lambda x, k: packed(x[cut[k] : cut[k + 1]].astype(np.uint64))
        id_type = pa.ipc.open_stream(unzipped(left["blob"][0].as_py())).schema.field(0).type
        none = pa.nulls(1, pa.binary())
        table = pa.table({
            "id": pa.array(ids, id_type), "held_out": pa.array(held_out), "n_tokens": pa.array(sizes.astype(np.int64)), "n_known": pa.array(known), "logs": pa.array(logs), "types": pa.array(types),
            "pair_counts": pa.array([blob(pair, k) for k in range(m)], pa.binary()), "word_counts": pa.array([blob(word, k) for k in range(m)], pa.binary()), "begins": pa.array([begins] * m, pa.int64()), "cells": pa.nulls(m, pa.binary()), "weights": pa.nulls(m, pa.binary()),
        })
        extra = pa.table({"id": pa.nulls(1, id_type), "held_out": pa.nulls(1, pa.bool_()), "n_tokens": pa.nulls(1, pa.int64()), "n_known": pa.nulls(1, pa.int64()), "logs": pa.nulls(1, pa.float64()), "types": pa.nulls(1, pa.float64()), "pair_counts": none, "word_counts": none, "begins": pa.nulls(1, pa.int64()), "cells": pa.array([packed(cell)], pa.binary()), "weights": pa.array([packed(weight.astype(np.int64))], pa.binary())})
        return pa.concat_tables([table, extra])

    got = parts.groupBy("block").cogroup(answers(parts, n, fold, folds).groupBy("block")).applyInArrow(join, schema)
    path = shared_folder(docs.sparkSession, "lm")
    got.write.option("compression", "zstd").parquet(path)
    return docs.sparkSession.read.schema(schema).parquet(path)


def learn_weights(cells: np.ndarray, weights: np.ndarray, n: int, v: int, rounds: int = 60) -> np.ndarray:
    """Weights (pair, word, uniform) for each bucket, by expectation-maximisation on the histogram."""
    out = np.tile(np.array([0.0, 0.5, 0.5]), (64, 1))
    if not len(cells):
        out[:] = (0.0, 0.0, 1.0)
        return out
    word_level, rest = cells % (64 * STEPS), cells // (64 * STEPS)
    share_level, bucket = rest % LEVELS, rest // LEVELS
    p = np.stack([
        np.where(share_level > 0, 2.0 ** (-(share_level - 1) / STEPS), 0.0),
        np.where(word_level > 0, 2.0 ** ((word_level - 1) / STEPS), 0.0) / max(n - 1, 1),
        np.full(len(cells), 1.0 / (v + 1)),
    ], axis=1)
    for b in np.unique(bucket):
        own = bucket == b
        q, mass, a = p[own], weights[own].astype(np.float64), np.array([0.4, 0.4, 0.2])
        for _ in range(rounds):
            post = q * a
            a = (mass[:, None] * post / post.sum(axis=1, keepdims=True)).sum(axis=0) / mass.sum()
        a = np.maximum(a, (0.0, 1e-6, 1e-6))
        out[b] = a / a.sum()
    seen = np.unique(bucket)
    for b in range(1, 64):  # buckets without events take the weights of the nearest one below
        if b not in seen:
            below = seen[seen < b]
            out[b] = out[below[-1]] if len(below) and below[-1] > 0 else out[0]
    return out


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fold: int = 2, folds: int = 7, block_bytes: int = 8 << 20) -> DataFrame:
    """Per row: id_col, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Rows whose crc32 of the id modulo folds is fold are held out: scored, not learned from.
    """
    spark = docs.sparkSession
    held = counted(docs, id_col, text_col, fold, folds, block_bytes)
    rows, marks = held.where("n_tokens is not null"), held.where("cells is not null")
    sums = rows.agg(F.sum(F.when(~F.col("held_out"), F.col("n_tokens"))).alias("n"), F.sum("types").alias("v")).first()
    n, v = int(sums["n"] or 0), round(sums["v"] or 0)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for c, w in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(unpacked(c, np.int64)), pa.array(unpacked(w, np.int64))], ["cell", "n"])

    histogram = marks.select("cells", "weights").mapInArrow(cells, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    mix = learn_weights(histogram["cell"].to_numpy(), histogram["n"].to_numpy(), n, v)
    sent = spark.sparkContext.broadcast(mix)
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("held_out", T.BooleanType()), *(T.StructField(k, T.LongType()) for k in ("n_tokens", "n_known", "train_tokens")), T.StructField("base_score", T.DoubleType()), T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = sent.value
        for batch in batches:
            got = {name: batch.column(k) for k, name in enumerate(batch.schema.names)}
            tokens_n = got["n_tokens"].to_numpy()
            scores = []
            for c, w, begins in zip(got["pair_counts"].to_pylist(), got["word_counts"].to_pylist(), got["begins"].to_pylist(), strict=True):
                pair, word = unpacked(c, np.uint64).astype(np.float64), unpacked(w, np.uint64).astype(np.float64)
                context = np.concatenate(([begins], word[:-1]))
                m = a[bucket_of(context)]
                p = m[:, 0] * np.where(context > 0, pair / np.maximum(context, 1), 0) + m[:, 1] * word / max(n, 1) + m[:, 2] / (v + 1)
                scores.append(float(np.log10(p).sum()))
            base = got["logs"].to_numpy() - tokens_n * math.log10(n + v + 1)
            yield pa.RecordBatch.from_arrays([got["id"], got["held_out"], got["n_tokens"], got["n_known"], pa.array(np.full(len(tokens_n), n, np.int64)), pa.array(base), pa.array(scores, pa.float64())], schema.names)

    return rows.select("id", "held_out", "n_tokens", "n_known", "pair_counts", "word_counts", "begins", "logs").mapInArrow(run, schema)
