"""Exact self-join of vectors by cosine, through subspaces.

Unit vectors with cosine c have squared distance 2 - 2c. After a rotation to principal axes
the axes are dealt to blocks; each block has a share of the squared distance in proportion to
its variance, so a pair within the whole budget is within the share of some block. In each
block a range join by the block's first coordinate (slices by quantiles, tiles of two slices
that are near enough, and in them all block coordinates at once) finds the pairs within the
share; a pair counts in the first block that has it, so none counts twice, and is verified
on the whole vectors in double precision.

A tile gives for each of its vectors only the number of its partners there and its smallest
connection, never the pairs. Equal vectors are joined once, with their number.

Work grows with the square of the rows divided by what slices rule out: near 0.95 and for
vectors without structure that is little (README has figures).

Rows: null, empty or zero vectors, and those with null or non-finite components, link with
nothing; vectors of different lengths do not link; ids may repeat, a null id never names a
component unless all its members are null; every input row gives one output row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.common import written
from probejoin.llm.components import components

#: Slack of the share in a block, and of the coarser test in single precision.
EXACT, COARSE = 1e-5, 3e-5
#: Vectors of each side that are compared at a time: their distances stay in a core's cache.
ACROSS, DOWN = 512, 1024
#: Components of the vectors of a slice; fewer and larger slices mean fewer copies of each vector.
SLICE_NUMBERS = 2 << 20


def _matrix(column: pa.Array, d: int) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, d)


def _unit(x: np.ndarray) -> np.ndarray:
    x = np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, initial=0))[1][:, None])  # by a power of two, so that no square overflows or vanishes
    return x / np.sqrt((x * x).sum(axis=1))[:, None]


def axes(reps: DataFrame, d: int, n_blocks: int) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Rotation (columns), the axes of each block and its share; from the second moments of all vectors, d * d numbers."""

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d, d))
        for batch in batches:
            u = _unit(_matrix(batch.column(0), d))
            total += u.T @ u
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d * d)), pa.array(total.reshape(-1))], ["k", "x"])

    got = reps.select("vector").mapInArrow(moments, "k long, x double").groupBy("k").agg(F.sum("x").alias("x")).toArrow()
    total = np.zeros(d * d)
    total[got["k"].to_numpy()] = got["x"].to_numpy()
    values, vectors = np.linalg.eigh(total.reshape(d, d))
    values, vectors = np.maximum(values[::-1], 0), vectors[:, ::-1]
    owned = [np.arange(b, d, n_blocks) for b in range(n_blocks)]
    part = np.array([values[o].sum() for o in owned]) + 1e-9
    return np.ascontiguousarray(vectors), owned, part / part.sum()


def _hung(n: int, a: np.ndarray, b: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Smallest id connected with each of n places by the pairs (a, b)."""
    label = ids.copy()
    while len(a):
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        if (new == label).all():
            break
        label = new
    return label


def candidates(y: np.ndarray, left: np.ndarray, right: np.ndarray | None, most: float, reach: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of rows of y, one of left and one of right (two different ones of left if that is None), whose squared distance is at most `most`.

    Both sides go in order of the first coordinate, and only rows within reach of it are compared.
    Squares and the bound ride along as two more coordinates, so that one product gives what is
    above the bound, and only rows with something below it are looked at.
    """
    first = y[:, 0].astype(np.float64)
    own = np.flatnonzero(left)
    own = own[np.argsort(first[own], kind="stable")]
    if right is None:
        other = own
    else:
        other = np.flatnonzero(right)
        other = other[np.argsort(first[other], kind="stable")]
    w, square = y.shape[1], (y.astype(np.float64) ** 2).sum(axis=1)
    to = np.empty((w + 2, len(other)), np.float32)
    to[:w], to[w], to[w + 1] = y[other].T, 1, square[other]
    at_other = first[other]
    for at in range(0, len(own), ACROSS):
        a = own[at : at + ACROSS]
        mine = np.empty((len(a), w + 2), np.float32)
        mine[:, :w], mine[:, w], mine[:, w + 1] = -2 * y[a], square[a] - most, 1
        low, high = np.searchsorted(at_other, first[a[0]] - reach), np.searchsorted(at_other, first[a[-1]] + reach, side="right")
        for lo in range(max(low, at) if right is None else low, high, DOWN):
            hi = min(lo + DOWN, high)
            over = mine @ to[:, lo:hi]
            hit = np.flatnonzero(over.min(axis=0) <= 0)
            if len(hit):
                p, q = np.nonzero(over[:, hit] <= 0)
                q = hit[q]
                if right is None:
                    keep = at + p < lo + q
                    p, q = p[keep], q[keep]
                yield a[p], other[lo + q]


def _joined(reps: DataFrame, d: int, cosine: float, n_blocks: int, slice_rows: int) -> DataFrame:
    """Rows (v, n, label) for each vector and tile in which it has partners."""
    spark = reps.sparkSession
    n_blocks = min(n_blocks, d)
    turn, owned, part = axes(reps, d, n_blocks)
    budget = part * (2 - 2 * cosine)
    reach = np.sqrt(budget + COARSE)
    firsts = [int(o[0]) for o in owned]
    # components travel as precise as the column has them
    kind = np.float32 if reps.schema["vector"].dataType.elementType == T.FloatType() else np.float64

    def coordinates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _unit(_matrix(batch.column(0), d)) @ turn[:, firsts]
            yield pa.RecordBatch.from_arrays([pa.array(x[:, b]) for b in range(n_blocks)], [f"c{b}" for b in range(n_blocks)])

    rows = reps.count()
    slices = max(1, -(-rows // slice_rows))
    edges = [np.empty(0)] * n_blocks
    if slices > 1:
        at = [k / slices for k in range(1, slices)]
        columns = reps.select("vector").mapInArrow(coordinates, ", ".join(f"c{b} double" for b in range(n_blocks)))
        got = columns.agg(*[F.percentile_approx(f"c{b}", at, 1000).alias(f"c{b}") for b in range(n_blocks)]).first()
        edges = [np.unique(np.array(got[b])) for b in range(n_blocks)]
    sent = spark.sparkContext.broadcast((turn, owned, budget, reach, edges))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn, _, _, reach, edges = sent.value
        for batch in batches:
            raw = _matrix(batch.column(2), d)
            x = _unit(raw) @ turn[:, firsts]
            flat = raw.astype(kind)
            for b in range(n_blocks):
                e, r, c = edges[b], reach[b], x[:, b]
                home = np.searchsorted(e, c, side="right")
                low, high = np.searchsorted(e, c - r, side="right"), np.searchsorted(e, c + r, side="right")
                n = high - low + 1
                row = np.repeat(np.arange(len(c)), n)
                other = low[row] + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                i, k = np.minimum(home[row], other), np.maximum(home[row], other)
                for at in range(0, len(row), 4096):
                    s = slice(at, at + 4096)
                    w = flat[row[s]]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(w), b, np.int32)), pa.array(i[s].astype(np.int32)), pa.array(k[s].astype(np.int32)), pa.array(home[row[s]].astype(np.int32)), batch.column(0).take(pa.array(row[s])), batch.column(1).take(pa.array(row[s])), pa.FixedSizeBinaryArray.from_buffers(pa.binary(w.itemsize * d), len(w), [None, pa.py_buffer(np.ascontiguousarray(w))]).cast(pa.binary())], ["b", "i", "k", "home", "v", "m", "x"])

    def tile(table: pa.Table) -> pa.Table:
        turn, owned, budget, reach, _ = sent.value
        b, i, k = (table[c][0].as_py() for c in ("b", "i", "k"))
        ids, weight, home = table["v"].to_numpy(), table["m"].to_numpy(), table["home"].to_numpy()
        unit = _unit(np.frombuffer(b"".join(table["x"].to_pylist()), kind).reshape(-1, d).astype(np.float64))
        y = (unit @ turn[:, owned[b]]).astype(np.float32)
        found = []
        for p, q in candidates(y, home == i, None if i == k else home == k, float(budget[b] + COARSE), float(reach[b])):
            for z in range(0, len(p), 1 << 16):
                found.append(_verified(p[z : z + (1 << 16)], q[z : z + (1 << 16)], unit, turn, owned, budget, b, cosine))
        p, q = (np.concatenate(f) if found else np.empty(0, np.int64) for f in zip(*found, strict=True)) if found else (np.empty(0, np.int64),) * 2
        n = np.bincount(p, weights=weight[q], minlength=len(ids)) + np.bincount(q, weights=weight[p], minlength=len(ids)) if len(p) else np.zeros(len(ids))
        label = _hung(len(ids), p, q, ids)
        some = np.flatnonzero(n > 0)
        return pa.table({"v": pa.array(ids[some]), "n": pa.array(n[some].astype(np.int64)), "label": pa.array(label[some])})

    dealt = reps.select("v", "m", "vector").mapInArrow(deal, "b int, i int, k int, home int, v long, m long, x binary")
    return dealt.groupBy("b", "i", "k").applyInArrow(tile, "v long, n long, label long")


def _verified(p, q, unit, turn, owned, budget, b, cosine) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of the tile that are similar and that no earlier block has."""
    keep = (unit[p] * unit[q]).sum(axis=1) >= cosine
    p, q = p[keep], q[keep]
    if len(p):
        gap = (unit[p] - unit[q]) @ turn
        gap *= gap
        keep = gap[:, owned[b]].sum(axis=1) <= budget[b] + EXACT
        for e in range(b):
            keep &= gap[:, owned[e]].sum(axis=1) > budget[e] + EXACT
        p, q = p[keep], q[keep]
    return p, q


def join(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", cosine: float = 0.95, n_blocks: int = 4, slice_rows: int | None = None) -> DataFrame:
    """Per row: id_col, n_links, component_id, kept. slice_rows is the vectors of a slice, by default as many as have SLICE_NUMBERS components."""
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vector"))
    sound = F.coalesce(F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("vector", lambda x: x != 0), F.lit(False))
    rows = rows.withColumn("vector", F.when(sound, F.col("vector")))
    usable = rows.where("vector is not null")
    classes = written(usable.groupBy("vector").agg(F.min("id").alias("least"), F.count("*").alias("m")).withColumn("v", F.monotonically_increasing_id()), "vectors")
    lengths = [r["d"] for r in classes.select(F.size("vector").alias("d")).distinct().collect()]
    parts = None
    for d in sorted(lengths):
        part = _joined(classes.where(F.size("vector") == d), d, cosine, n_blocks, slice_rows or max(1024, SLICE_NUMBERS // d))
        parts = part if parts is None else parts.unionByName(part)
    if parts is None:
        parts = classes.select("v", F.col("m").alias("n"), F.col("v").alias("label")).limit(0)
    parts = written(parts, "tiles")
    labels = components(parts.select(F.col("v").alias("u"), F.col("label").alias("v")))
    counts = parts.groupBy("v").agg(F.sum("n").alias("n"))
    named = classes.join(counts, "v", "left").join(labels, "v", "left").withColumn("label", F.coalesce("label", "v"))
    lowest = named.groupBy("label").agg(F.min("least").alias("lowest"))
    final = named.join(lowest, "label").select("vector", (F.coalesce("n", F.lit(0)) + F.col("m") - 1).alias("n_links"), F.coalesce("lowest", "least").alias("component_id"))
    out = usable.join(final, "vector").select(F.col("id").alias(id_col), "n_links", "component_id")
    alone = rows.where("vector is null").select(F.col("id").alias(id_col), F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.col(id_col).eqNullSafe(F.col("component_id")))
