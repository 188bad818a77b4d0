"""Exact self-join of shingle sets by Jaccard similarity, through partitions of the universe.

Two sets of n and m shingles with similarity t or more differ in at most
(1 - t) / (1 + t) * (n + m) shingles. Sets are cut into segments by the hash of the shingle.
With more segments than differences some segment is equal in both; with twice as many
differences allowed for as segments, some segment differs in one shingle at most and is met
through the neighbourhood of one deletion. Sizes are dealt to bands (ratio 1.5); a set is also
cut as the band below if it may have partners there. Segments of fewer than two shingles say
nothing and are not indexed; a set that has so few others that the argument would fail is
indexed by its least hashed shingles instead (two similar sets share one of those), and meets
other such sets there. Which allocation a band uses is decided by what it costs: deletions for
small sets, whose exact segments would mostly be empty, exact segments for the rest.

Equal sets are one vertex. Candidate pairs are first held against the sizes and the parities
of shingles by hash range (those that differ are at most as many as the differences), then
verified on the whole sets: one pair of each set first, then only pairs whose sets are in
different components by then, and of those one link of a set to a component is enough. A group
of equal signatures with more than `few` members is not expanded: each member is compared with
some leaders of its large groups, which are members drawn by hash, so that a passage that very
many sets hold does not give all its groups one leader. Groups that are still in several
components then draw new leaders, and each member is compared with the nearest of another
component by parities, until such a round joins little. All pairs that are in different
components even then are compared, in tiles, by parities first.

Shingles are 64-bit hashes of words' hashes; two that clash would be one. Everything else is
exact: no partner or group is dropped.

The result is components only: the links made join each component but are not all links, so no number of links and no list of all pairs can be had from them.

Rows: a text without words is an empty set, linked with nothing; with fewer words than a
shingle the whole sequence is its only shingle; null text is no words; ids may repeat or be
null (a null id never names a component unless all its members are null); every input row
gives one output row; extra columns are ignored; texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.blocks import blocked, blocks_of, packed, texts_of, unpacked
from probejoin.llm.common import mix64, only, shared_folder, written
from probejoin.llm.components import components
from probejoin.llm.ngramlm import tokens

RATIO, FIRST, SMALL = 1.5, 8, 48
ODD = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Join:
    words: int = 5
    percent: int = 80
    few: int = 6
    leaders: int = 4

    def most_differences(self, n: np.ndarray) -> np.ndarray:
        """Most shingles in which a set of n may differ from a similar one (which has at most n * 100 / percent)."""
        p = self.percent
        other = n * 100 // p
        return (100 - p) * (n + other) // (100 + p)

    def prefix(self, n: np.ndarray) -> np.ndarray:
        return n - -(-n * self.percent // 100) + 1


def band_of(n: np.ndarray) -> np.ndarray:
    """Number of the band that holds sizes n; band 0 holds all below FIRST."""
    edges = band_edges()
    return np.searchsorted(edges, n, side="right")


def band_edges() -> np.ndarray:
    out = [FIRST]
    while out[-1] < 1 << 40:
        out.append(int(np.ceil(out[-1] * RATIO)))
    return np.array(out, np.int64)


def sets_of(texts: list[str | None], words: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts, one after another, and where each text's begin."""
    flat, sizes = tokens(texts)
    n = len(texts)
    keep = np.ones(len(flat), np.bool_)
    keep[np.cumsum(sizes) - 1] = False  # the ends of texts are no words
    w, size = flat[keep], sizes - 1
    start = np.cumsum(size) - size
    length = np.minimum(size, words)
    count = np.where(size > 0, size - length + 1, 0)
    doc = np.repeat(np.arange(n), count)
    at = np.repeat(start - (np.cumsum(count) - count), count) + np.arange(count.sum())
    value = np.zeros(len(at), np.uint64)
    span = length[doc]
    for k in range(words):
        on = span > k
        value[on] = mix64(value[on] * ODD + w[at[on] + k] + np.uint64(k + 1))
    ends = np.cumsum(count)
    for a, b in zip((ends - count).tolist(), ends.tolist(), strict=True):
        value[a:b].sort()  # texts lie one after another, so each is sorted where it lies
    if len(doc):
        new = np.concatenate(([True], (doc[1:] != doc[:-1]) | (value[1:] != value[:-1])))
        doc, value = doc[new], value[new]
    return value, np.searchsorted(doc, np.arange(n + 1))


def digests(value: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each set."""
    out = []
    for salt in (1, 2):
        total = np.concatenate(([np.uint64(0)], np.cumsum(mix64(value + np.uint64(salt) * ODD), dtype=np.uint64)))
        out.append(mix64(total[start[1:]] - total[start[:-1]] + np.diff(start).astype(np.uint64) * ODD))
    return out[0], out[1]


def parities(h: np.ndarray) -> bytes:
    """For each of some 4 to 8 hash ranges a shingle, whether it holds an odd number of them.

    Ranges of two sets in which these differ are at most as many as the shingles in which the
    sets differ, and nearly as many.
    """
    bits = 1 << max(6, min(24, (4 * len(h) - 1).bit_length()))
    odd = np.bincount((h & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(sketch: np.ndarray, words: int) -> np.ndarray:
    """Rows of a sketch in words of 64 bits over fewer ranges."""
    while sketch.shape[-1] > words:
        half = sketch.shape[-1] // 2
        sketch = sketch[..., :half] ^ sketch[..., half:]
    return sketch


def signatures(value: np.ndarray, start: np.ndarray, which: np.ndarray, j: Join) -> tuple[np.ndarray, np.ndarray]:
    """(signature, set) pairs of the sets named in which."""
    size = np.diff(start)
    edges = band_edges()
    out_s, out_d = [], []
    fallback = np.zeros(len(size), np.bool_)
    own = band_of(size[which])
    low = np.where(own > 0, edges[np.maximum(own - 1, 0)], 0)
    below = (own > 0) & (size[which] * j.percent < 100 * low)
    todo = [(which, own), (which[below], own[below] - 1)]
    for docs, band in todo:
        zero = band == 0
        fallback[docs[zero]] = True
        docs, band = docs[~zero], band[~zero]
        if not len(docs):
            continue
        n = size[docs]
        top = edges[band]
        small = top <= SMALL
        # a set that is cut as the band below meets only sets smaller than that band's end
        differ = np.where(n < top, j.most_differences(n), (100 - j.percent) * (n + top) // (100 + j.percent))
        widest = j.most_differences(top)
        m = np.where(small, widest // 2 + 1, widest + 1 + widest * 44 // 100)
        at = np.repeat(start[docs] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        h = value[at]
        row = np.repeat(np.arange(len(docs)), n)
        seg = ((h >> np.uint64(33)) * m[row].astype(np.uint64) >> np.uint64(31)).astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], (row[1:] != row[:-1]) | (seg[1:] != seg[:-1]))))
        count = np.diff(np.append(first, len(h)))
        mixed = mix64(h ^ ODD)
        total = np.add.reduceat(mixed, first)
        seg_row = row[first]
        salt = mix64(seg[first].astype(np.uint64) * ODD + band[seg_row].astype(np.uint64))
        useful = np.where(small[seg_row], count > 2, count > 1)
        # a difference spoils one exact segment, two spoil one with its deletions; one must be left
        room = np.bincount(seg_row, weights=useful, minlength=len(docs)) * np.where(small, 2, 1)
        fallback[docs[room < differ + 1]] = True
        two = count > 1
        out_s.append(mix64(total[two] + salt[two]))
        out_d.append(docs[seg_row[two]])
        part = np.repeat(np.arange(len(first)), count)
        drop = small[row] & (count[part] > 2)
        if drop.any():
            out_s.append(mix64(total[part[drop]] - mixed[drop] + salt[part[drop]]))
            out_d.append(docs[row[drop]])
    docs = np.flatnonzero(fallback)
    docs = docs[size[docs] > 0]
    if len(docs):
        n = j.prefix(size[docs])
        at = np.repeat(start[docs] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        out_s.append(mix64(value[at] + np.uint64(3)))
        out_d.append(np.repeat(docs, n))
    if not out_s:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    return np.concatenate(out_s), np.concatenate(out_d)


def _pair_ok(n: np.ndarray, m: np.ndarray, percent: int) -> np.ndarray:
    return 100 * np.minimum(n, m) >= percent * np.maximum(n, m)


def _table(rows: list[tuple], kinds: list[tuple]) -> pa.Table:
    return pa.table({name: pa.array([r[k] for r in rows], kind) for k, (name, kind) in enumerate(kinds)})


def differing(a: bytes, b: bytes) -> int:
    """Ranges in which two sets' parities differ."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    words = min(len(x), len(y))
    return int(np.bitwise_count(folded(x, words) ^ folded(y, words)).sum())


def too_many(different: int, n: int, m: int, percent: int) -> bool:
    """Whether more ranges differ than similar sets of n and m do in shingles."""
    return different * (100 + percent) > (100 - percent) * (n + m)


def far_apart(a: bytes, b: bytes, n: int, m: int, percent: int) -> bool:
    """Whether the parities differ in more ranges than similar sets do in shingles."""
    return too_many(differing(a, b), n, m, percent)


def places(table: pa.Table, chosen: pa.Table, words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sets of a block, and the places of the chosen rows (by digest) in it."""
    _, texts = texts_of(table["blob"].to_pylist())
    value, start = sets_of(texts, words)
    one, two = digests(value, start)
    wanted = set(zip(chosen["d1"].to_pylist(), chosen["d2"].to_pylist(), strict=True))
    got, seen = [], set()
    for k, key in enumerate(zip(one.view(np.int64).tolist(), two.view(np.int64).tolist(), strict=True)):
        if key in wanted and key not in seen:
            seen.add(key)
            got.append(k)
    return value, start, np.array(got, np.int64)


class ShingleJoin:
    """One run over one table; its parts are written to the shared folder as they are needed again."""

    def __init__(self, docs: DataFrame, id_col: str, text_col: str, j: Join, block_bytes: int):
        self.docs, self.id_col, self.text_col, self.j = docs, id_col, text_col, j
        self.n = blocks_of(docs, text_col, block_bytes)
        self.parts = written(blocked(docs, id_col, text_col, self.n), "blocks")  # read by each pass over the texts
        self.spark = docs.sparkSession

    def sizes(self) -> DataFrame:
        """Rows (id, row hash, block, n, d1, d2) of all documents."""
        j, schema = self.j, T.StructType([T.StructField("id", self.docs.schema[self.id_col].dataType), T.StructField("row", T.LongType()), T.StructField("block", T.IntegerType()), T.StructField("n", T.LongType()), T.StructField("d1", T.LongType()), T.StructField("d2", T.LongType())])
        key = F.xxhash64(self.id_col, self.text_col)
        rows = self.docs.select(F.col(self.id_col).alias("id"), F.col(self.text_col).alias("text"), key.alias("row"), F.pmod(key, F.lit(self.n)).cast("int").alias("block"))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for at in range(0, batch.num_rows, 1000):
                    b = batch.slice(at, 1000)
                    value, start = sets_of(b.column(1).to_pylist(), j.words)
                    one, two = digests(value, start)
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), b.column(3), pa.array(np.diff(start)), pa.array(one.view(np.int64)), pa.array(two.view(np.int64))], schema.names)

        return written(rows.mapInArrow(run, schema), "sets")

    def index(self, reps: DataFrame) -> DataFrame:
        """Rows of signatures by bucket and of parities by hash range, for the representatives."""
        j, n_buckets = self.j, self.n

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            rows = []
            if left.num_rows and right.num_rows:
                block = left["block"][0].as_py()
                value, start, which = places(left, right, j.words)
                sig, doc = signatures(value, start, which, j)
                bucket = (sig >> np.uint64(32)) * np.uint64(n_buckets) >> np.uint64(32)
                # within a bucket the other 32 bits tell signatures apart: clashes are only candidates more
                key = bucket << np.uint64(32) | sig & np.uint64(0xFFFFFFFF)
                order = np.lexsort((doc, key))
                key, doc = key[order], doc[order]
                if len(key):
                    new = np.concatenate(([True], (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])))
                    key, doc = key[new], doc[new]
                cut = np.searchsorted(key >> np.uint64(32), np.arange(n_buckets + 1, dtype=np.uint64))
                for b in range(n_buckets):
                    x, y = cut[b], cut[b + 1]
                    if x < y:
                        rows.append(("sig", b, block, packed(np.diff(key[x:y].astype(np.uint32), prepend=np.uint32(0))), packed(doc[x:y].astype(np.uint32)), None, None, None, None))
                one, two = (d.view(np.int64) for d in digests(value, start))
                for k in which.tolist():
                    h = value[start[k] : start[k + 1]]
                    rows.append(("set", None, None, parities(h), None, block << 32 | k, len(h), int(one[k]), int(two[k])))
            return _table(rows, [("kind", pa.string()), ("bucket", pa.int32()), ("block", pa.int32()), ("blob", pa.binary()), ("more", pa.binary()), *((c, pa.int64()) for c in ("v", "n", "d1", "d2"))])

        got = self.parts.groupBy("block").cogroup(reps.groupBy("block")).applyInArrow(run, "kind string, bucket int, block int, blob binary, more binary, v long, n long, d1 long, d2 long")
        path = shared_folder(self.spark, "index")
        got.write.option("compression", "uncompressed").parquet(path)
        return self.spark.read.schema(got.schema).parquet(path)

    def grouped(self, index: DataFrame) -> DataFrame:
        """Rows (u, v, g): g null for a candidate pair; else v is a member of the large group g and u the member drawn as its leader."""
        few = self.j.few

        def run(table: pa.Table) -> pa.Table:
            only("")
            bucket = table["bucket"][0].as_py()
            table = table.sort_by("block")
            sig = [np.cumsum(unpacked(x, np.uint32), dtype=np.uint32) for x in table["blob"].to_pylist()]
            doc = [unpacked(x, np.uint32).astype(np.int64) | b << 32 for x, b in zip(table["more"].to_pylist(), table["block"].to_pylist(), strict=True)]
            s, d = np.concatenate(sig), np.concatenate(doc)
            order = np.lexsort((d, s))
            s, d = s[order], d[order]
            first = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1])))
            size = np.diff(np.append(first, len(s)))
            us, vs, gs, gu, gv = [], [], [], [], []
            for k in range(2, few + 1):  # all pairs of small groups
                f = first[size == k]
                for a in range(k):
                    for b in range(a + 1, k):
                        us.append(d[f + a])
                        vs.append(d[f + b])
            big = np.flatnonzero(size > few)
            member = np.repeat(size > few, size)
            drawn = first + (mix64(s[first].astype(np.uint64) + np.uint64(bucket) * ODD) % size.astype(np.uint64)).astype(np.int64)
            leader = np.repeat(d[drawn], size)
            u, v = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (us, vs))
            o = np.lexsort((v, u))
            u, v = u[o], v[o]
            if len(u):
                new = np.concatenate(([True], (u[1:] != u[:-1]) | (v[1:] != v[:-1])))
                u, v = u[new], v[new]
            gs = np.repeat(np.int64(bucket) << 32 | np.arange(len(big)), size[big])
            gu, gv = leader[member], d[member]
            return pa.table({"u": pa.array(np.concatenate((u, gu))), "v": pa.array(np.concatenate((v, gv))), "g": pa.array(np.concatenate((np.zeros(len(u), np.int64), gs)), pa.int64(), mask=np.concatenate((np.ones(len(u), np.bool_), np.zeros(len(gs), np.bool_))))})

        rows = index.where("kind = 'sig'").select("bucket", "block", "blob", "more")
        return written(rows.groupBy("bucket").applyInArrow(run, "u long, v long, g long"), "groups")

    def near(self, pairs: DataFrame, sets: DataFrame) -> DataFrame:
        """Pairs (u, v, label) that sizes and parities by hash range allow, and far, the share of shingles that differ by these."""
        percent = self.j.percent
        a = sets.select(F.col("v").alias("u"), F.col("n").alias("un"), F.col("blob").alias("ub"))
        b = sets.select("v", F.col("n").alias("vn"), F.col("blob").alias("vb"))
        joined = pairs.join(a, "u").join(b, "v").where(f"100 * least(un, vn) >= {percent} * greatest(un, vn)").select("u", "v", "un", "vn", "ub", "vb", "label")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                n, m = batch.column(2).to_pylist(), batch.column(3).to_pylist()
                far = [differing(x.as_buffer(), y.as_buffer()) for x, y in zip(batch.column(4), batch.column(5), strict=True)]
                keep = [not too_many(d, p, q, percent) for d, p, q in zip(far, n, m, strict=True)]
                share = [d / (p + q) for d, p, q in zip(far, n, m, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(6), pa.array(share, pa.float64())], ["u", "v", "label", "far"]).filter(pa.array(keep, pa.bool_()))

        return joined.mapInArrow(run, "u long, v long, label long, far double")

    def verified(self, pairs: DataFrame) -> DataFrame:
        """Links among the pairs (u, v, label), where label is the component v is known to be in.

        The set of v travels to u, that of a u with very many v to several tasks. One link of u to a
        component joins all of it: a task stops at the first, so that links do not grow with the pairs.
        """
        j, salts = self.j, 16
        pairs = written(pairs.select("u", "v", "label"), "pairs")
        if pairs.isEmpty():
            return pairs.select("u", "v")
        salt = F.pmod(F.xxhash64("v"), F.lit(salts)).cast("int")
        asked = pairs.select(F.col("v").alias("x"), F.col("u").alias("to"), salt.alias("salt"), F.lit(False).alias("own"), "label")
        homes = pairs.select(F.col("u").alias("x"), F.col("u").alias("to"), salt.alias("salt"), F.lit(True).alias("own"), F.lit(None).cast("long").alias("label")).distinct()
        wanted = asked.unionByName(homes).withColumn("block", F.shiftright("x", 32).cast("int"))

        def ship(left: pa.Table, right: pa.Table) -> pa.Table:
            kinds = [("to", pa.int64()), ("salt", pa.int32()), ("x", pa.int64()), ("own", pa.bool_()), ("label", pa.int64()), ("blob", pa.binary())]
            if not left.num_rows or not right.num_rows:
                return _table([], kinds)
            _, texts = texts_of(left["blob"].to_pylist())
            need = sorted({x & 0xFFFFFFFF for x in right["x"].to_pylist()})
            value, start = sets_of([texts[k] for k in need], j.words)
            blob = {k: packed(np.diff(value[start[i] : start[i + 1]], prepend=np.uint64(0))) for i, k in enumerate(need)}
            return right.select(["to", "salt", "x", "own", "label"]).append_column("blob", pa.array([blob[x & 0xFFFFFFFF] for x in right["x"].to_pylist()], pa.binary()))

        def compare(table: pa.Table) -> pa.Table:
            own = table["own"].to_pylist()
            to = table["to"][0].as_py()
            read = lambda b: np.cumsum(unpacked(b, np.uint64), dtype=np.uint64)
            blobs = table["blob"]
            mine = read(blobs[own.index(True)].as_py())
            keep, joined = [], set()
            for k, (x, label, is_own) in enumerate(zip(table["x"].to_pylist(), table["label"].to_pylist(), own, strict=True)):
                if is_own or label in joined:
                    continue
                other = read(blobs[k].as_py())
                at = np.searchsorted(mine, other)
                at[at == len(mine)] = 0
                shared = int((mine[at] == other).sum())
                if 100 * shared >= j.percent * (len(mine) + len(other) - shared):
                    keep.append(x)
                    joined.add(label)
            return pa.table({"u": pa.array([to] * len(keep), pa.int64()), "v": pa.array(keep, pa.int64())})

        shipped = self.parts.groupBy("block").cogroup(wanted.groupBy("block")).applyInArrow(ship, "to long, salt int, x long, own boolean, label long, blob binary")
        return written(shipped.groupBy("to", "salt").applyInArrow(compare, "u long, v long"), "links")

    def spread(self, members: DataFrame, labels: DataFrame) -> DataFrame:
        """Rows (g, v, label, size) of the groups whose members (g, v) are in different components."""
        members = members.join(labels, "v", "left").withColumn("label", F.coalesce("label", "v"))
        several = members.groupBy("g").agg(F.min("label").alias("a"), F.max("label").alias("b"), F.count("*").alias("size")).where("a < b").select("g", "size")
        return written(members.join(several, "g").select("g", "v", "label", "size"), "spread")

    def round(self, own: DataFrame, sets: DataFrame, k: int) -> DataFrame:
        """Links of members with the nearest leader of another component, of those drawn for their groups in round k."""
        drawn = own.groupBy("g").agg(F.min_by(F.struct("v", "label"), F.xxhash64("v", "g", F.lit(k))).alias("leader"))
        pairs = own.join(drawn, "g").where("label <> leader.label").select(F.col("leader.v").alias("u"), "v", F.col("leader.label").alias("label")).distinct()
        nearest = self.near(pairs, sets).groupBy("v").agg(F.min(F.struct("far", "u", "label")).alias("best"))
        # the leader's set is the one that travels, so that a leader of very many has not one task
        return self.verified(nearest.select(F.col("v").alias("u"), F.col("best.u").alias("v"), F.col("best.label").alias("label")))

    def rest(self, own: DataFrame, sets: DataFrame) -> DataFrame:
        """Pairs of large groups whose members are in different components, allowed by parities; tiles of a group are tasks of their own."""
        own = written(own.join(sets.select("v", "n", "blob"), "v"), "rest")
        if own.isEmpty():
            return own.select(F.col("v").alias("u"), "v", "label")
        tile = 1024
        tiles = F.ceil(F.col("size") / tile).cast("int")
        t = F.pmod(F.xxhash64("v"), tiles).cast("int")
        dealt = own.withColumn("tile", t).withColumn("cell", F.explode(F.transform(F.sequence(F.lit(0), tiles - 1), lambda k: F.struct(F.least(k, F.col("tile")).alias("i"), F.greatest(k, F.col("tile")).alias("k")))))
        percent = self.j.percent

        def run(table: pa.Table) -> pa.Table:
            i, k = table["i"][0].as_py(), table["k"][0].as_py()
            v, label, n, at = (table[c].to_numpy() for c in ("v", "label", "n", "tile"))
            blobs = table["blob"].to_pylist()
            us, vs, ls = [], [], []
            words = min(len(b) for b in blobs) // 8
            odd = np.stack([folded(np.frombuffer(b, np.uint64), words) for b in blobs])
            for a in range(len(v)):
                other = (label != label[a]) & (v > v[a]) & _pair_ok(n, n[a], percent) & ((at != at[a]) if i != k else True)
                b = np.flatnonzero(other)
                apart = np.bitwise_count(odd[b] ^ odd[a]).sum(axis=1, dtype=np.int64) * (100 + percent) > (100 - percent) * (n[b] + n[a])
                b = b[~apart]
                us.append(np.full(len(b), v[a]))
                vs.append(v[b])
                ls.append(label[b])
            return pa.table({"u": pa.array(np.concatenate(us), pa.int64()), "v": pa.array(np.concatenate(vs), pa.int64()), "label": pa.array(np.concatenate(ls), pa.int64())})

        flat = dealt.select("g", F.col("cell.i").alias("i"), F.col("cell.k").alias("k"), "v", "label", "n", "tile", "blob")
        return flat.groupBy("g", "i", "k").applyInArrow(run, "u long, v long, label long").distinct()

    def apart(self, pairs: DataFrame, labels: DataFrame) -> DataFrame:
        """Pairs (u, v, label of v) that are not in one component."""
        of_u = labels.select(F.col("v").alias("u"), F.col("label").alias("at_u"))
        of_v = labels.select("v", F.col("label").alias("at_v"))
        label = F.coalesce("at_v", "v")
        return pairs.join(of_u, "u", "left").join(of_v, "v", "left").where(F.coalesce("at_u", "u") != label).select("u", "v", label.alias("label"))

    def links(self) -> tuple[DataFrame, DataFrame, DataFrame]:
        """Sizes of all documents, vertices of their digests, and links between vertices that join every component."""
        j, sizes = self.j, self.sizes()
        some = sizes.where("n > 0")
        reps = written(some.groupBy("d1", "d2").agg(F.min(F.struct("block", "row")).alias("at")).select("d1", "d2", F.col("at.block").alias("block"), F.col("at.row").alias("row")), "reps")
        index = self.index(reps.select("block", "d1", "d2"))
        sets = index.where("kind = 'set'").select("v", "n", "blob")
        groups = self.grouped(index)
        large = groups.where("g is not null and u <> v")
        # the leaders with which a member shares most groups join what is close; the rest is compared below
        shares = large.groupBy("v", "u").agg(F.count("*").alias("c")).groupBy("v").agg(F.sort_array(F.collect_list(F.struct("c", "u")), asc=False).alias("best"))
        leaders = shares.select(F.explode(F.slice("best", 1, j.leaders)).alias("best"), "v").select("best.u", "v")
        pairs = written(groups.where("g is null").select("u", "v").unionByName(leaders).distinct(), "candidates")
        # one pair of each set first; then only what these links did not join
        first = pairs.groupBy("v").agg(F.min("u").alias("u")).select("u", "v", F.col("v").alias("label"))
        found = self.verified(self.near(first, sets))
        others = self.apart(pairs.join(first, ["u", "v"], "left_anti"), components(found))
        found = found.unionByName(self.verified(self.near(others, sets)))
        members, made = self.spread(groups.where("g is not null").select("g", "v"), components(found)), []
        while not members.isEmpty():
            if made and made[-1] * 4 <= made[0]:  # new leaders join little by now: all pairs that are left
                left = written(self.near(self.rest(members, sets).join(pairs, ["u", "v"], "left_anti"), sets), "left")
                found = found.unionByName(self.verified(left))
                break
            joined = self.round(members, sets, len(made))
            made.append(joined.count())
            if made[-1]:
                found = found.unionByName(joined)
                members = self.spread(members.select("g", "v"), components(found))
        return sizes, index.where("kind = 'set'").select("v", "d1", "d2"), found


def join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80, block_bytes: int = 3 << 20) -> DataFrame:
    """Per row: id_col, n_shingles, component_id (smallest id reachable by links)."""
    run = ShingleJoin(docs, id_col, text_col, Join(words, percent), block_bytes)
    sizes, vertices, links = run.links()
    labels = components(links)
    linked = labels.join(vertices, "v").select("d1", "d2", "label")
    classes = sizes.where("n > 0").groupBy("d1", "d2").agg(F.min("id").alias("least"))
    named = classes.join(linked, ["d1", "d2"], "left")
    lowest = named.where("label is not null").groupBy("label").agg(F.min("least").alias("lowest"))
    final = named.join(lowest, "label", "left").select("d1", "d2", F.coalesce("lowest", "least").alias("component_id"))
    out = sizes.where("n > 0").join(final, ["d1", "d2"]).select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), "component_id")
    return out.unionByName(sizes.where("n = 0").select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.col("id").alias("component_id")))
