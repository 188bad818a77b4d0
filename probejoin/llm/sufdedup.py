"""Repeated byte strings found by suffix arrays over shards that must hold them.

A byte goes if a string of `length` bytes that covers it starts anywhere else too. All
documents count, matches never cross documents, and strings are judged on the input.

Any such string holds an anchor: the least hashed k-gram of each `length - k + 1` neighbours.
Equal strings choose equal anchors, so it is enough to look around anchors that occur again.
An anchor's surroundings are all bytes that such a string through it could cover.

1. Blocks of documents ask buckets about their distinct (anchor, surroundings). Where both
   occur again everything around is repeated: no bytes need to travel.
2. Where the anchor occurs again but the surroundings differ, and a match is possible at
   all (some bytes before or after the anchor must agree too), the surroundings go to the
   bucket's shard; a suffix array by induced sorting and its permuted common prefixes say
   which windows occur at two places or more. Every window there holds its whole anchor, so
   the anchor stays behind and a short name of bytes that no text has stands for it.
3. Anchors with more than `hot` different surroundings would swell one shard; for these the
   windows themselves are compared by two 64-bit hashes, dealt by hash, each block sending
   equal windows once. It is exact like the shards, and no group is cut.

Equality of anchors and surroundings is that of 64-bit hashes, of windows that of 128 bits.

With `words`, strings of so many words that start anywhere else go too, however few bytes
they have: the same steps run over the 64-bit hashes of the words, all of them by windows.
Words are what stands between white space of Unicode; the white space between words of such
a string may differ and goes with it.

Rows: null text counts as empty; every input row gives one output row; ids may be null or
repeat, and repeated rows count as copies of each other; extra columns are ignored; an empty
table gives an empty result; texts are read whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.blocks import blocked, blocks_of, pack_keys, packed, slices, texts_of, unpack_keys, unpacked, unzipped, zipped
from probejoin.llm.common import BASES, mix64, only, prefix_hash, shared_folder, span_hash, window_hash
from probejoin.llm.suffix import repeated_windows

TWIN, SHARD, WINDOWS = 1, 2, 4
#: Bytes of a shard that are sorted together.
SHARD_BYTES = 400_000
#: Ends a string within a shard; no byte of UTF-8.
SEPARATOR = 255
#: First of the eight bytes that names of anchors are made of, none of UTF-8 either, and bytes of a name.
DIGIT, NAME = 0xF5, 8


class Shape:
    """Sizes that follow from the length of a match, in bytes or in words."""

    def __init__(self, length: int, words: bool = False):
        self.length = length
        self.words = words
        self.k = max(1, length * 3 // 4)
        self.w = length - self.k + 1
        #: A match has this many bytes before the anchor or this many after it.
        self.side = max(1, (length - self.k) // 2)


#: White space of Unicode that takes several bytes, and the bytes it can begin with.
_WIDE = re.compile(rb"\xc2[\x85\xa0]|\xe1\x9a\x80|\xe2(?:\x80[\x80-\x8a\xa8\xa9\xaf]|\x81\x9f)|\xe3\x80\x80")
_WIDE_FIRST = (b"\xc2", b"\xe1\x9a", b"\xe2", b"\xe3\x80")
_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
#: Words whose hashes are made at once.
WORDS_AT_ONCE = 1 << 14


def bounds_of_words(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of a text begin and end, in bytes."""
    if any(b in data for b in _WIDE_FIRST):
        data = _WIDE.sub(lambda m: b" " * len(m[0]), data)
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = ~_SPACE[np.frombuffer(data, np.uint8)]
    edge = np.diff(inside)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def codes_of(data: bytes, s: Shape) -> np.ndarray:
    """What matches are made of: a text's bytes, or hashes of its words."""
    array = np.frombuffer(data, np.uint8)
    if not s.words:
        return array
    start, end = bounds_of_words(data)
    out = np.empty(len(start), np.uint64)
    for a in range(0, len(start), WORDS_AT_ONCE):
        x, y = start[a : a + WORDS_AT_ONCE], end[a : a + WORDS_AT_ONCE]
        out[a : a + len(x)] = span_hash(prefix_hash(array[x[0] : y[-1]], BASES[0]), x - x[0], y - x[0], BASES[0])
    return out


def extreme(values: np.ndarray, width: int, least: bool) -> np.ndarray:
    """Least (or greatest) value of every width neighbours."""
    if width == 1:
        return values
    f, n = (np.minimum if least else np.maximum), len(values)
    rows = -(-n // width)
    pad = np.full(rows * width, np.iinfo(np.uint64).max if least else 0, np.uint64)
    pad[:n] = values
    pad = pad.reshape(rows, width)
    ahead = f.accumulate(pad, axis=1).reshape(-1)
    back = f.accumulate(pad[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return f(back[: n - width + 1], ahead[width - 1 : n])


#: Bytes whose hashes are held at once; longer texts are read in overlapping stretches.
STRETCH = 1 << 17


def anchors(data: np.ndarray, s: Shape) -> dict[str, np.ndarray]:
    """Places, hashes, surroundings (bounds and hash) and side hashes of a text's anchors."""
    n, out = len(data), []
    reach = 2 * s.length
    for a in range(0, n - s.k + 1 if n >= s.length else 0, STRETCH):
        lo, hi = max(0, a - reach), min(n, a + STRETCH + reach)
        part = data[lo:hi]
        pre = prefix_hash(part, BASES[0])
        h = window_hash(pre, s.k, BASES[0])
        least = extreme(h, s.w, True)
        spread = np.zeros(len(least) + 2 * (s.w - 1), np.uint64)
        spread[s.w - 1 : s.w - 1 + len(least)] = least
        p = np.flatnonzero(extreme(spread, s.w, False) >= h)
        p = p[(p + lo >= a) & (p + lo < a + STRETCH)]
        start, end = np.maximum(p + s.k - s.length, -lo), np.minimum(p + s.length, n - lo)
        wide = p >= s.side
        after = p + s.k + s.side <= n - lo
        out.append({
            "place": p + lo, "h": h[p], "lo": start + lo, "hi": end + lo,
            "ctx": mix64(span_hash(pre, start, end, BASES[0]) + (p - start).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)),
            "before": np.where(wide, span_hash(pre, np.maximum(p - s.side, 0), p, BASES[0]) >> np.uint64(33), 0).astype(np.uint32),
            "after": np.where(after, span_hash(pre, p + s.k, np.minimum(p + s.k + s.side, len(part)), BASES[0]) >> np.uint64(33), 0).astype(np.uint32),
        })
    if not out:
        return {k: np.empty(0, np.int64) for k in ("place", "h", "lo", "hi", "ctx", "before", "after")}
    return {k: np.concatenate([o[k] for o in out]) for k in out[0]}


def _of_block(table: pa.Table, s: Shape) -> tuple[list, list[np.ndarray], dict[str, np.ndarray]]:
    """Ids, texts as bytes or words and all anchors of a block, by hash and surroundings, with `doc`."""
    ids, texts = texts_of(table["blob"].to_pylist())
    data = [codes_of(t.encode("utf-8", "surrogatepass") if t else b"", s) for t in texts]
    found = []
    for k, d in enumerate(data):
        if len(d) >= s.length:
            got = anchors(d, s)
            found.append(got | {"doc": np.full(len(got["h"]), k, np.int64)})
    if not found:
        return ids, data, {}
    every = {k: np.concatenate([f[k] for f in found]) for k in found[0]}
    order = np.lexsort((every["place"], every["doc"], every["ctx"], every["h"]))
    return ids, data, {k: v[order] for k, v in every.items()}


def _firsts(h: np.ndarray, ctx: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (ctx[1:] != ctx[:-1]))))


def _several(group: np.ndarray, value: np.ndarray) -> np.ndarray:
    """Which rows share (group, value) with another row; value 0 shares with none."""
    order = np.lexsort((value, group))
    g, v = group[order], value[order]
    same = (g[1:] == g[:-1]) & (v[1:] == v[:-1]) & (v[1:] != 0)
    out = np.zeros(len(g), np.bool_)
    out[order[1:]] |= same
    out[order[:-1]] |= same
    return out


def _ask(parts: DataFrame, n: int, s: Shape, hot: int) -> DataFrame:
    """Rows (block, bucket, flags) for the distinct anchors of each block."""

    def ask(table: pa.Table) -> pa.Table:
        block = table["block"][0].as_py()
        _, _, a = _of_block(table, s)
        rows = []
        if a:
            first = _firsts(a["h"], a["ctx"])
            count = np.diff(np.append(first, len(a["h"]))).astype(np.uint32)
            h = a["h"][first]
            cut = slices(h, n)
            for b in range(n):
                x, y = cut[b], cut[b + 1]
                if x < y:
                    rows.append((block, b, pack_keys(h[x:y]), packed(a["ctx"][first[x:y]]), packed(np.minimum(count[x:y], 255).astype(np.uint8)), packed(a["before"][first[x:y]]), packed(a["after"][first[x:y]])))
        kinds = [("block", pa.int32()), ("bucket", pa.int32()), *((c, pa.binary()) for c in ("h", "ctx", "n", "before", "after"))]
        return pa.table({name: pa.array([r[k] for r in rows], kind) for k, (name, kind) in enumerate(kinds)})

    def answer(table: pa.Table) -> pa.Table:
        only("")
        table = table.sort_by("block")
        hs = [unpack_keys(x) for x in table["h"].to_pylist()]
        sizes = [len(x) for x in hs]
        h = np.concatenate(hs)
        column = lambda name, kind: np.concatenate([unpacked(x, kind) for x in table[name].to_pylist()])
        ctx, n_own, before, after = column("ctx", np.uint64), column("n", np.uint8), column("before", np.uint32), column("after", np.uint32)
        order = np.lexsort((ctx, h))
        ho, co = h[order], ctx[order]
        first = _firsts(ho, co)
        cls = np.zeros(len(ho), np.int64)
        cls[first[1:]] = 1
        cls = np.cumsum(cls)
        total = np.bincount(cls, weights=n_own[order])
        twin = total[cls] > 1
        hf = ho[first]  # a row for each distinct pair
        start = np.flatnonzero(np.concatenate(([True], hf[1:] != hf[:-1])))
        group = np.cumsum(np.isin(np.arange(len(hf)), start, assume_unique=True)) - 1
        of = np.diff(np.append(start, len(hf)))
        single = total == 1
        lone = np.bincount(group, weights=single)[group] > 0
        possible = (of[group] > 1) & lone & (_several(group, before[order][first]) | _several(group, after[order][first]))
        send = np.where(possible, np.where(of[group] > hot, WINDOWS, SHARD), 0)
        flags = np.where(twin, TWIN, 0)
        flags[first] |= send
        out = np.zeros(len(h), np.uint8)
        out[order] = flags
        answered = np.split(out, np.cumsum(sizes)[:-1])
        return pa.table({"block": table["block"], "bucket": table["bucket"], "flags": pa.array([packed(x) for x in answered], pa.binary())})

    asked = parts.groupBy("block").applyInArrow(ask, "block int, bucket int, h binary, ctx binary, n binary, before binary, after binary")
    return asked.groupBy("bucket").applyInArrow(answer, "block int, bucket int, flags binary")


def merged(doc: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unions of spans within documents; touching spans become one."""
    if not len(doc):
        return doc, lo, hi
    order = np.lexsort((lo, doc))
    doc, lo, hi = doc[order], lo[order], hi[order]
    base = doc * np.int64(1 << 42)
    far = np.maximum.accumulate(base + hi)
    new = np.concatenate(([True], base[1:] + lo[1:] > far[:-1]))
    first = np.flatnonzero(new)
    return doc[first], lo[first], far[np.append(first[1:], len(doc)) - 1] - base[first]


def _spans(doc, lo, hi) -> bytes:
    return packed(np.concatenate(merged(np.asarray(doc, np.int64), np.asarray(lo, np.int64), np.asarray(hi, np.int64))).astype(np.int64)) if len(doc) else b""


def _unspans(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return tuple(unpacked(blob, np.int64).reshape(3, -1))


FOUND = "kind string, bucket int, block int, blob binary, more binary"


def _look(parts: DataFrame, flags: DataFrame, n: int, s: Shape) -> DataFrame:
    """Rows of FOUND: spans known at once, surroundings for shards, windows for hot anchors."""

    def look(left: pa.Table, right: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if left.num_rows and right.num_rows:
            block = left["block"][0].as_py()
            _, data, a = _of_block(left, s)
            first = _firsts(a["h"], a["ctx"])
            flag = np.concatenate([unpacked(x, np.uint8) for x in right.sort_by("bucket")["flags"].to_pylist()])
            count = np.diff(np.append(first, len(a["h"])))
            every = np.repeat(flag, count)
            t = ((every & TWIN) > 0) & (a["hi"] - a["lo"] >= s.length)
            rows.append(("span", -1, block, _spans(a["doc"][t], a["lo"][t], a["hi"][t]), b""))
            go = first[(flag & SHARD) > 0]
            cut = slices(a["h"][go], n)
            for b in range(n):
                own = go[cut[b] : cut[b + 1]]
                if len(own):
                    place = a["place"][own]
                    ends = zip(a["doc"][own].tolist(), a["lo"][own].tolist(), place.tolist(), (place + s.k).tolist(), a["hi"][own].tolist(), strict=True)
                    body = b"".join(part for d, x, p, q, y in ends for part in (data[d][x:p].tobytes(), data[d][q:y].tobytes()))
                    facts = np.stack([a["doc"][own], a["lo"][own], a["hi"][own], a["h"][own].view(np.int64), place]).astype(np.int64)
                    rows.append(("shard", b, block, zipped(body), packed(facts.reshape(-1))))
            go = first[(flag & WINDOWS) > 0]
            if len(go):
                rows += _windows(data, a, go, n, s, block)
        kinds = (("kind", pa.string()), ("bucket", pa.int32()), ("block", pa.int32()), ("blob", pa.binary()), ("more", pa.binary()))
        return pa.table({name: pa.array([r[k] for r in rows], kind) for k, (name, kind) in enumerate(kinds)})

    got = parts.groupBy("block").cogroup(flags.groupBy("block")).applyInArrow(look, FOUND)
    path = shared_folder(parts.sparkSession, "repeats")
    got.write.option("compression", "uncompressed").parquet(path)
    return parts.sparkSession.read.schema(got.schema).parquet(path)


def _windows(data: list[np.ndarray], a: dict[str, np.ndarray], go: np.ndarray, n: int, s: Shape, block: int) -> Iterator[tuple]:
    """Hashes and places of all windows around hot anchors, by bucket."""
    doc, at, one, two = [], [], [], []
    for d in np.unique(a["doc"][go]).tolist():
        own = go[a["doc"][go] == d]
        for lo, hi in zip(*merged(np.zeros(len(own), np.int64), a["lo"][own], a["hi"][own])[1:], strict=True):
            if hi - lo < s.length:
                continue
            starts = np.arange(hi - lo - s.length + 1)
            part = data[d][lo:hi]
            values = [window_hash(prefix_hash(part, b), s.length, b) for b in BASES]
            doc.append(np.full(len(starts), d, np.int64))
            at.append(starts + lo)
            one.append(values[0])
            two.append(values[1])
    if not doc:
        return
    doc, at, one, two = (np.concatenate(x) for x in (doc, at, one, two))
    order = np.lexsort((two, one))
    doc, at, one, two = doc[order], at[order], one[order], two[order]
    first = _firsts(one, two)
    many = np.diff(np.append(first, len(one))) > 1
    again = np.repeat(many, np.diff(np.append(first, len(one))))
    yield ("span", -1, block, _spans(doc[again], at[again], at[again] + s.length), b"")
    cut = slices(one[first], n)
    for b in range(n):
        f = first[cut[b] : cut[b + 1]]
        if len(f):
            yield ("window", b, block, pack_keys(one[f]), packed(np.concatenate([two[f].view(np.int64), doc[f], at[f]])))


def _sort_shard(table: pa.Table, s: Shape) -> pa.Table:
    """Spans of a shard's surroundings whose windows occur at two places or more."""
    only("")
    table = table.sort_by("block")
    facts, bodies = [], []
    for block, blob, more in zip(table["block"].to_pylist(), table["blob"].to_pylist(), table["more"].to_pylist(), strict=True):
        own = unpacked(more, np.int64).reshape(5, -1)
        facts.append(np.vstack([own, np.full(own.shape[1], block, np.int64)]))
        body, at = unzipped(blob), 0
        for size in (own[2] - own[1] - s.k).tolist():
            bodies.append(body[at : at + size])
            at += size
    doc, lo, hi, h, place, block = np.concatenate(facts, axis=1)
    order = np.argsort(h, kind="stable")
    doc, lo, hi, h, place, block = doc[order], lo[order], hi[order], h[order], place[order], block[order]
    size = hi - lo - s.k + NAME
    edge = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))  # surroundings of one anchor stay together
    found = []
    begin = 0
    reach = np.cumsum(size + 1)
    while begin < len(h):
        limit = np.searchsorted(reach, (reach[begin - 1] if begin else 0) + SHARD_BYTES, side="right")
        k = np.searchsorted(edge, limit, side="right") - 1
        end = int(edge[k]) if k >= 0 and edge[k] > begin else int(edge[np.searchsorted(edge, begin, side="right")]) if np.searchsorted(edge, begin, side="right") < len(edge) else len(h)
        if limit >= len(h):
            end = len(h)
        found.append(_sorted(bodies, order, slice(begin, end), doc, lo, size, block, h, place, s))
        begin = end
    b, d, x = (np.concatenate(f) for f in zip(*found, strict=True))
    blocks = np.unique(b)
    blobs = [_spans(d[b == k], x[b == k], x[b == k] + s.length) for k in blocks]
    return pa.table({"block": pa.array(blocks.astype(np.int32)), "blob": pa.array(blobs, pa.binary())})


def names_of(h: np.ndarray) -> list[bytes]:
    """A name for each of some anchors in order of their hashes, equal ones for equal hashes."""
    number = np.cumsum(np.concatenate(([False], h[1:] != h[:-1])))
    digits = (number[:, None] >> (3 * np.arange(NAME))) & 7
    flat = (digits + DIGIT).astype(np.uint8).tobytes()
    return [flat[at : at + NAME] for at in range(0, len(flat), NAME)]


def _sorted(bodies: list[bytes], order: np.ndarray, part: slice, doc, lo, size, block, h, place, s: Shape) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    own = size[part]
    total = int(own.sum()) + len(own)
    text = np.full(total, SEPARATOR, np.uint8)
    room = np.zeros(total, np.int64)
    start = np.cumsum(own + 1) - (own + 1)
    ahead = (place[part] - lo[part]).tolist()
    for i, a, n, x, name in zip(order[part].tolist(), start.tolist(), own.tolist(), ahead, names_of(h[part]), strict=True):
        body = bodies[i]
        text[a : a + n] = np.frombuffer(body[:x] + name + body[x:], np.uint8)
        room[a : a + n] = np.arange(n, 0, -1)
    at, cls = repeated_windows(text, room, s.length - s.k + NAME)
    if not len(at):
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
    which = np.searchsorted(start, at, side="right") - 1
    b, d, x = block[part][which], doc[part][which], lo[part][which] + at - start[which]
    # the same place may lie around two anchors: a class counts if it holds two places
    by = np.lexsort((x, d, b, cls))
    c, b, d, x = cls[by], b[by], d[by], x[by]
    new = np.concatenate(([True], (c[1:] != c[:-1]) | (b[1:] != b[:-1]) | (d[1:] != d[:-1]) | (x[1:] != x[:-1])))
    c, b, d, x = c[new], b[new], d[new], x[new]
    _, inverse, n = np.unique(c, return_inverse=True, return_counts=True)
    keep = n[inverse] > 1
    return b[keep], d[keep], x[keep]


def _match_windows(table: pa.Table, s: Shape) -> pa.Table:
    """Spans of the windows that two blocks or more have."""
    only("")
    table = table.sort_by("block")
    one = [unpack_keys(x) for x in table["blob"].to_pylist()]
    rest = np.concatenate([unpacked(x, np.int64).reshape(3, -1) for x in table["more"].to_pylist()], axis=1)
    block = np.repeat(table["block"].to_numpy(), [len(x) for x in one])
    key = np.concatenate(one)
    order = np.lexsort((rest[0], key))
    first = _firsts(key[order], rest[0][order])
    size = np.diff(np.append(first, len(order)))
    keep = order[np.repeat(size > 1, size)]
    b, d, x = block[keep], rest[1][keep], rest[2][keep]
    blocks = np.unique(b)
    return pa.table({"block": pa.array(blocks.astype(np.int32)), "blob": pa.array([_spans(d[b == k], x[b == k], x[b == k] + s.length) for k in blocks], pa.binary())})


def _repeated(parts: DataFrame, n: int, s: Shape, hot: int) -> DataFrame:
    """Rows (block, blob): spans of a block's texts that occur again, in bytes or in words."""
    found = _look(parts, _ask(parts, n, s, hot), n, s)
    known = found.where("kind = 'span'").select("block", "blob")
    shards = found.where("kind = 'shard'").select("bucket", "block", "blob", "more").groupBy("bucket").applyInArrow(lambda t: _sort_shard(t, s), "block int, blob binary")
    windows = found.where("kind = 'window'").select("bucket", "block", "blob", "more").groupBy("bucket").applyInArrow(lambda t: _match_windows(t, s), "block int, blob binary")
    return known.unionByName(windows) if s.words else known.unionByName(shards).unionByName(windows)


def _in_bytes(spans: tuple[np.ndarray, np.ndarray, np.ndarray], data: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Spans of words as spans of bytes, from the first word's first byte to the last word's last."""
    doc, lo, hi = merged(*spans)
    first, last = np.empty_like(lo), np.empty_like(hi)
    edge = np.append(np.flatnonzero(np.diff(doc, prepend=-1)), len(doc))
    for x, y in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        start, end = bounds_of_words(data[doc[x]])
        first[x:y], last[x:y] = start[lo[x:y]], end[hi[x:y] - 1]
    return doc, first, last


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 400, hot: int = 2000, block_bytes: int = 3 << 20, texts: bool = False, words: int = 0) -> DataFrame:
    """Per row: id_col, n_bytes, n_removed, n_spans, kept_sha256; with texts also kept (binary) and spans.

    words is the length of the strings of words that go besides those of bytes, 0 for none.
    """
    n = blocks_of(docs, text_col, block_bytes)
    parts = blocked(docs, id_col, text_col, n)
    spans = _repeated(parts, n, Shape(length), hot).withColumn("words", F.lit(False))
    if words:
        spans = spans.unionByName(_repeated(parts, n, Shape(words, words=True), 0).withColumn("words", F.lit(True)))
    fields = [T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("n_bytes", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("n_spans", T.LongType()), T.StructField("kept_sha256", T.StringType())]
    if texts:
        fields += [T.StructField("kept", T.BinaryType()), T.StructField("spans", T.ArrayType(T.ArrayType(T.LongType())))]
    schema = T.StructType(fields)

    def cut(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, whole = texts_of(left["blob"].to_pylist())
        data = [t.encode("utf-8", "surrogatepass") if t else b"" for t in whole]
        found = list(zip(right["blob"].to_pylist(), right["words"].to_pylist(), strict=True))
        got = [_unspans(x) for x, of_words in found if x and not of_words]
        if own := [_unspans(x) for x, of_words in found if x and of_words]:
            got.append(_in_bytes(tuple(np.concatenate(g) for g in zip(*own, strict=True)), data))
        doc, lo, hi = merged(*(np.concatenate(g) for g in zip(*got, strict=True))) if got else (np.empty(0, np.int64),) * 3
        first = np.searchsorted(doc, np.arange(len(data) + 1))
        removed, n_spans, digests, kept, lists = [], [], [], [], []
        for k, d in enumerate(data):
            own = slice(first[k], first[k + 1])
            pieces, at = [], 0
            for x, y in zip(lo[own].tolist(), hi[own].tolist(), strict=True):
                pieces.append(d[at:x])
                at = y
            pieces.append(d[at:])
            rest = b"".join(pieces)
            removed.append(len(d) - len(rest))
            n_spans.append(int(first[k + 1] - first[k]))
            digests.append(hashlib.sha256(rest).hexdigest())
            if texts:
                kept.append(rest)
                lists.append([[x, y] for x, y in zip(lo[own].tolist(), hi[own].tolist(), strict=True)])
        kind = pa.ipc.open_stream(unzipped(left["blob"][0].as_py())).schema.field(0).type if left.num_rows else pa.int64()
        columns = {id_col: pa.array(ids, kind), "n_bytes": pa.array([len(d) for d in data], pa.int64()), "n_removed": pa.array(removed, pa.int64()), "n_spans": pa.array(n_spans, pa.int64()), "kept_sha256": pa.array(digests, pa.string())}
        if texts:
            columns |= {"kept": pa.array(kept, pa.binary()), "spans": pa.array(lists, pa.list_(pa.list_(pa.int64())))}
        return pa.table(columns)

    return parts.groupBy("block").cogroup(spans.groupBy("block")).applyInArrow(cut, schema)
