"""Benchmark passages in documents, found by counting q-grams and verified by alignment.

Item and text are lower-cased and every run of what is neither letter nor digit becomes one
space. A region of the text within e edits of an item of m bytes shares at least
m - q + 1 - q * e of its q-grams, all on diagonals (text place less item place) that are at
most e apart. Hits are counted in overlapping diagonal bands of width 2 (e + 1), each hit in
two of them; bands that reach the bound are verified by an alignment restricted to the band,
if one without restriction, by bits, is not beyond e. Short texts are looked up together.
e is `edits` times m (default a tenth). Items of fewer than `least` bytes, for which the
bound would be void, must occur exactly and as whole words.

Benchmark items go to executors in blocks of at most `block_bytes` of text, one pass over
the documents for each block, so nothing sent grows beyond that.

Rows: null or empty texts and items match nothing; an item equal to another matches on its
own; the result has a row for each pair of (id, item) with a region; repeated rows of the
documents give repeated rows; extra columns are ignored; texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.common import lean, only

Q = 8
_WORD = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))
_BITS = 22


def plain(text: str) -> bytes:
    return b" ".join(text.lower().encode("utf-8", "replace").translate(_WORD).split())


def codes(data: bytes) -> np.ndarray:
    """Every eight bytes as one number."""
    one = np.frombuffer(data, np.uint8)
    if len(one) < Q:
        return np.empty(0, np.uint64)
    two = (one[:-1].astype(np.uint16) << np.uint16(8)) | one[1:]
    four = (two[:-2].astype(np.uint32) << np.uint32(16)) | two[2:]
    return (four[:-4].astype(np.uint64) << np.uint64(32)) | four[4:]


def _slot(code: np.ndarray) -> np.ndarray:
    return ((code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - _BITS)).astype(np.int64)


def banded_edits(item: bytes, region: bytes, most: int) -> tuple[int, int] | None:
    """Least edits of item against a stretch of region, and that stretch's end; None beyond most.

    Free ends in the region; cells further than the band's width from the diagonal are left out.
    """
    m, n = len(item), len(region)
    text = np.frombuffer(region, np.uint8)
    place = np.arange(n + 1)
    row = np.zeros(n + 1, np.int64)
    width = n - m + most if n > m else most
    for i in range(1, m + 1):
        lo, hi = max(0, i - most - 1), min(n, i + width + most)
        new = np.full(n + 1, 1 << 30, np.int64)
        if lo == 0:
            new[0] = i
        a = max(lo, 1)
        if a > hi:
            return None
        step = np.minimum(row[a - 1 : hi] + (text[a - 1 : hi] != item[i - 1]), row[a : hi + 1] + 1)
        if a == 1:
            step[0] = min(step[0], new[0] + 1)
        new[a : hi + 1] = np.minimum.accumulate(step - place[a : hi + 1]) + place[a : hi + 1]
        row = new
        if row.min() > most:
            return None
    end = int(row.argmin())
    return (int(row[end]), end) if row[end] <= most else None


def masks(item: bytes) -> dict[int, int]:
    """For each byte of item, the places where it stands, as bits of a number."""
    out: dict[int, int] = {}
    for i, c in enumerate(item):
        out[c] = out.get(c, 0) | 1 << i
    return out


def may_hold(places: dict[int, int], m: int, region: bytes, most: int) -> bool:
    """Whether some stretch of region is within `most` edits of the item of m bytes whose masks are given.

    A column of differences of the edit table is two numbers, one bit for each byte of the item,
    so that a byte of the region costs a few operations on them.
    """
    if m <= most:
        return True
    full, last = (1 << m) - 1, 1 << (m - 1)
    up, down, score, left = full, 0, m, len(region)
    get = places.get
    for c in region:
        same = get(c, 0)
        diagonal = (((same & up) + up) ^ up) | same
        right = down | (full & ~(diagonal | up))
        falls = up & diagonal
        if right & last:
            score += 1
        elif falls & last:
            score -= 1
            if score <= most:
                return True
        left -= 1
        if score - left > most:  # falls by one a byte at most
            return False
        right <<= 1
        same |= down
        up = full & ((falls << 1) | ~(same | right))
        down = right & same & full
    return False


#: Bytes of normalised texts whose q-grams are looked up together, and of a longer text at a time.
TOGETHER, STEP = 1 << 18, 1 << 20


class ItemIndex:
    """q-grams of a block of items with their places."""

    def __init__(self, items: list[tuple[object, str]], edits: float = 0.1, least: int = 40):
        self.items = [(i, p) for i, t in items if t and (p := plain(t))]
        self.most = [int(edits * len(p)) if len(p) >= least else 0 for _, p in self.items]
        self.short = [k for k, (_, p) in enumerate(self.items) if len(p) < least]
        self.bound = np.array([max(1, len(p) - Q + 1 - Q * e) for (_, p), e in zip(self.items, self.most, strict=True)], np.int64)
        short = set(self.short)
        long = [k for k in range(len(self.items)) if k not in short]
        code = [codes(self.items[k][1]) for k in long]
        flat = np.concatenate(code) if code else np.empty(0, np.uint64)
        item = np.repeat(np.array(long, np.int64), [len(c) for c in code]) if code else np.empty(0, np.int64)
        place = np.concatenate([np.arange(len(c)) for c in code]) if code else np.empty(0, np.int64)
        order = np.argsort(flat, kind="stable")
        self.item, self.place = item[order], place[order]
        self.code, self.start = np.unique(flat[order], return_index=True)
        self.end = np.append(self.start[1:], len(flat))
        self.seen = np.zeros(1 << _BITS, np.bool_)
        self.seen[_slot(self.code)] = True
        self.band = np.array([2 * (e + 1) for e in self.most], np.int64)
        self.masks: dict[int, dict[int, int]] = {}

    def hits(self, data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Items, places in data and places in the item of all shared q-grams."""
        own = codes(data)
        if not len(own) or not len(self.code):
            return (np.empty(0, np.int64),) * 3
        where = np.flatnonzero(self.seen[_slot(own)])
        own = own[where]
        k = np.searchsorted(self.code, own)
        k[k == len(self.code)] = 0
        same = self.code[k] == own
        where, k = where[same], k[same]
        n = self.end[k] - self.start[k]
        spread = np.repeat(self.start[k] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(n) else np.empty(0, np.int64)
        return self.item[spread], np.repeat(where, n), self.place[spread]

    def find(self, text: str | None) -> list[tuple[object, int, int, int]]:
        """(item id, edits, start, end) of each item's best region; places in the normalised text."""
        return self.find_all([text])[0]

    def find_all(self, texts: list[str | None]) -> list[list[tuple[object, int, int, int]]]:
        """What find gives for each text; short texts are looked up together."""
        out: list[list] = [[] for _ in texts]
        held: list[tuple[int, bytes]] = []
        size = 0
        for n, text in enumerate(texts):
            if not text or not self.items:
                continue
            data = plain(text)
            if len(data) > STEP:
                found = [self.hits(data[a : a + STEP + Q - 1]) for a in range(0, len(data) - Q + 1, STEP)]
                diagonal = np.concatenate([w - p + a * STEP for a, (_, w, p) in enumerate(found)])
                out[n] = self._regions(data, np.concatenate([f[0] for f in found]), diagonal)
                continue
            held.append((n, data))
            size += len(data)
            if size >= TOGETHER:
                self._find_held(held, out)
                held, size = [], 0
        self._find_held(held, out)
        return out

    def _find_held(self, held: list[tuple[int, bytes]], out: list[list]) -> None:
        """Puts the finds of some texts into out. Between texts is a byte that no item has, so no q-gram spans two."""
        if not held:
            return
        item, where, place = self.hits(b"\0".join(data for _, data in held))
        start = np.concatenate(([0], np.cumsum([len(data) + 1 for _, data in held])))
        doc = np.searchsorted(start, where, side="right") - 1
        # a band holds at most the hits that text and item share at all
        pair = doc * len(self.items) + item
        if len(held) * len(self.items) <= 1 << 20:
            shared = np.bincount(pair, minlength=1)[pair] if len(pair) else pair
        else:
            _, inverse, n = np.unique(pair, return_inverse=True, return_counts=True)
            shared = n[inverse]
        keep = np.flatnonzero(shared >= self.bound[item])
        item, doc, diagonal = item[keep], doc[keep], (where - place)[keep] - start[doc[keep]]
        cut = np.searchsorted(doc, np.arange(len(held) + 1))
        for k, (n, data) in enumerate(held):
            if cut[k] < cut[k + 1] or self.short:
                out[n] = self._regions(data, item[cut[k] : cut[k + 1]], diagonal[cut[k] : cut[k + 1]])

    def _regions(self, data: bytes, item: np.ndarray, diagonal: np.ndarray) -> list[tuple[object, int, int, int]]:
        best: dict[int, tuple[int, int, int]] = {}
        padded = b" " + data + b" " if self.short else b""
        for k in self.short:
            if (at := padded.find(b" " + self.items[k][1] + b" ")) >= 0:
                best[k] = (0, at, at + len(self.items[k][1]))
        if len(item):
            width = self.band[item]
            # places of bands start at zero: diagonals are at least minus the item's length
            low = diagonal + (1 << 24)
            for half in (0, 1):
                key = item * (1 << 40) + (low + half * (width // 2)) // width
                band, n = np.unique(key, return_counts=True)
                for b in band[n >= self.bound[band >> 40]].tolist():
                    k = b >> 40
                    w = int(self.band[k])
                    first = (b & ((1 << 40) - 1)) * w - half * (w // 2) - (1 << 24)
                    self._verify(data, k, first, w, best)
        return [(self.items[k][0], *v) for k, v in best.items()]

    def _verify(self, data: bytes, k: int, first: int, width: int, best: dict) -> None:
        item, most = self.items[k][1], self.most[k]
        a, b = max(0, first - most), min(len(data), first + width + len(item) + most)
        region = data[a:b]
        if (at := region.find(item)) >= 0:
            got = (0, a + at, a + at + len(item))
        elif not may_hold(self.masks.get(k) or self.masks.setdefault(k, masks(item)), len(item), region, most):
            return
        elif near := banded_edits(item, region, most):
            got = (near[0], max(a, a + near[1] - len(item)), a + near[1])
        else:
            return
        if k not in best or got < best[k]:
            best[k] = got


def blocks(items: DataFrame, id_col: str, text_col: str, block_bytes: int) -> Iterator[list[tuple[object, str]]]:
    """Items in blocks of about block_bytes of text, each fetched on its own."""
    lean(items.sparkSession)
    rows = items.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).where("t is not null")
    size = rows.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    n = max(1, -(-int(1.25 * size) // block_bytes)) if size > block_bytes else 1
    for k in range(n):
        got = rows if n == 1 else rows.where(F.pmod(F.xxhash64("t"), F.lit(n)) == k)
        yield [(r["i"], r["t"]) for r in got.collect()]


def leaks(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", edits: float = 0.1, block_bytes: int = 8 << 20) -> DataFrame:
    """A row for each document and item that it holds: id_col, item_col, edits, start, end. Narrow, one pass for each block."""
    schema = T.StructType([docs.schema[id_col], T.StructField(item_col, items.schema[item_col].dataType), T.StructField("edits", T.IntegerType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])
    types = [pa.int64() if isinstance(f.dataType, T.LongType) else pa.int32() if isinstance(f.dataType, T.IntegerType) else pa.string() for f in schema.fields]
    out = None
    for block in blocks(items, item_col, item_text, block_bytes):
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            only("")
            index = ItemIndex(sent.value, edits)
            for batch in batches:
                rows = [(i, *got) for i, own in zip(batch.column(0).to_pylist(), index.find_all(batch.column(1).to_pylist()), strict=True) for got in own]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(types)], schema.names)

        part = docs.select(id_col, text_col).mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    return out


def clean(docs: DataFrame, items: DataFrame, text_col: str = "text", edits: float = 0.1, block_bytes: int = 8 << 20) -> DataFrame:
    """The documents without those that hold an item, with all their columns; narrow."""
    at = docs.columns.index(text_col)
    for block in blocks(items, "item_id", "text", block_bytes):
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            only("")
            index = ItemIndex(sent.value, edits)
            for batch in batches:
                yield batch.filter(pa.array([not own for own in index.find_all(batch.column(at).to_pylist())], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
