"""Joins and deduplication against brute force."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from probejoin.llm import common, components, jaccard, suffix, sufdedup, vectorjoin


def test_hashes_of_all_windows():
    """By slices as place by place."""
    codes = np.random.default_rng(3).integers(0, 256, 500).astype(np.uint8)
    before, starts = common.prefix_hash(codes, common.BASES[0]), np.arange(201)
    assert (common.window_hash(before, 300, common.BASES[0]) == common.span_hash(before, starts, starts + 300, common.BASES[0])).all()
    assert len(common.window_hash(before, 500, common.BASES[0])) == 1


def test_shingle_sets_lie_one_after_another():
    """Each text's distinct shingles in rising order, whatever its neighbours hold."""
    texts = ["a b c d e f g a b c d e f g", None, "x", "", "g f e d c b a " * 3, "A b c d e f g"]
    value, start = jaccard.sets_of(texts, 5)
    for k, text in enumerate(texts):
        own = value[start[k] : start[k + 1]]
        words = (text or "").lower().split()
        assert (np.diff(own) > 0).all() and len(own) == len({tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else ())
    assert set(value[start[5] :].tolist()) < set(value[: start[1]].tolist())


@pytest.mark.parametrize("few", [1024, 3, 1])
def test_suffix_arrays(monkeypatch, few):
    """With few letters and, from few = 3 or 1 on, by chains as strings of names are sorted."""
    monkeypatch.setattr(suffix, "FEW", few)
    monkeypatch.setattr(suffix, "LEAST_EACH", 0)
    rng = np.random.default_rng(1)
    for _ in range(150):
        n = int(rng.integers(2, 60))
        s = rng.integers(0, rng.integers(1, 5), n)
        order, b = suffix.suffix_array(s), bytes(s.tolist())
        assert order.tolist() == sorted(range(n), key=lambda i: b[i:])
        common = suffix.common_prefixes(s.astype(np.uint8) if n % 2 else s, order, n - np.arange(n))
        for k in range(1, n):
            x, y, m = b[order[k] :], b[order[k - 1] :], 0
            while m < min(len(x), len(y)) and x[m] == y[m]:
                m += 1
            assert common[order[k]] == m


def test_suffix_array_of_many_names():
    rng = np.random.default_rng(4)
    some = rng.integers(97, 123, 30_000).astype(np.uint8)
    for s in (some, np.concatenate((some[:9000], some[:9000], some)), np.full(5000, 97, np.uint8), np.tile(some[:7], 1500)):
        b = s.tobytes()
        assert suffix.suffix_array(s).tolist() == sorted(range(len(b)), key=lambda i: b[i:])


def covered(texts, length):
    seen = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        mark = bytearray(len(t))
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                mark[i : i + length] = b"\1" * length
        kept = bytes(b for b, m in zip(t, mark, strict=True) if not m)
        out.append((len(t), sum(mark), sum(1 for i, m in enumerate(mark) if m and (i == 0 or not mark[i - 1])), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize(("length", "hot"), [(40, 2000), (40, 3), (12, 2)])
def test_repeats(spark, length, hot):
    rnd = random.Random(3)
    made = lambda n: "".join(rnd.choice("abcdefgh é\n") for _ in range(n))
    seeds = [made(rnd.randint(length, 4 * length)) for _ in range(6)]
    docs = []
    for _ in range(80):
        parts = [made(rnd.randint(0, 3 * length))]
        for _ in range(rnd.randint(0, 3)):
            s = rnd.choice(seeds)
            a = rnd.randint(0, len(s) // 2)
            s = s[a : a + rnd.randint(length // 2, 3 * length)]
            if rnd.random() < 0.3 and s:
                k = rnd.randrange(len(s))
                s = s[:k] + "#" + s[k + 1 :]
            parts += [s, made(rnd.randint(0, length))]
        docs.append("".join(parts))
    docs += ["a" * 3 * length, "ab" * length * 2, None, "", docs[0], docs[0], made(length - 1)]
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    got = [tuple(r)[1:] for r in sufdedup.repeats(df, length=length, hot=hot, block_bytes=4000).orderBy("doc_id").collect()]
    assert got == covered([(t or "").encode() for t in docs], length)


def test_anchors_of_long_texts(monkeypatch):
    """Each string of the length holds an anchor, also behind the last full stretch."""
    monkeypatch.setattr(sufdedup, "STRETCH", 512)
    rng = np.random.default_rng(2)
    for length in (40, 400):
        s = sufdedup.Shape(length)
        for n in range(length, length + 1100, 7 if length == 400 else 3):
            got = sufdedup.anchors(rng.integers(0, 256, n).astype(np.uint8), s)
            gaps = np.diff(np.concatenate(([-1], got["place"], [n - s.k + 1])))
            assert gaps.max() <= s.w, (length, n)


@pytest.mark.parametrize("over", [299, 300, 350, 399, 400, 401])
def test_repeats_behind_a_stretch(spark, over):
    rng = np.random.default_rng(over)
    made = lambda n: bytes(rng.integers(97, 123, n).astype(np.uint8)).decode()
    tail = made(400)
    docs = [made(sufdedup.STRETCH + over - 400) + tail, made(50) + tail, made(500)]
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    got = [r["n_removed"] for r in sufdedup.repeats(df).orderBy("doc_id").collect()]
    assert got == [400, 400, 0]


def test_anchors_do_not_travel(monkeypatch):
    """Shards sort what is around anchors, with a name for each anchor, and find the windows that lie at two places."""
    s, rng, given = sufdedup.Shape(400), np.random.default_rng(5), []
    texts = [rng.integers(97, 123, 1500).astype(np.uint8) for _ in range(3)]
    texts[1][200:640] = texts[0][700:1140]
    texts[2][:399] = texts[0][:399]
    found = sufdedup.repeated_windows
    monkeypatch.setattr(sufdedup, "repeated_windows", lambda text, room, length: given.append(len(text)) or found(text, room, length))
    rows = []
    for d, text in enumerate(texts):
        a = sufdedup.anchors(text, s)
        rows += [(d, lo, hi, h, p, text[lo:p].tobytes() + text[p + s.k : hi].tobytes()) for h, p, lo, hi in zip(a["h"].view(np.int64).tolist(), *(a[c].tolist() for c in ("place", "lo", "hi")), strict=True)]
    facts = np.array([r[:5] for r in rows], np.int64).T
    table = pa.table({"block": pa.array([7], pa.int32()), "blob": [sufdedup.zipped(b"".join(r[5] for r in rows))], "more": [sufdedup.packed(facts.reshape(-1))]})
    monkeypatch.setattr(common, "HELD", {"other": {"kept": "by another operator"}})
    got = sufdedup._sort_shard(table, s)
    assert common.HELD == {"other": {}}  # a worker that only sorts shards keeps nothing of others
    assert got["block"].to_pylist() == [7]
    assert [x.tolist() for x in sufdedup._unspans(got["blob"][0].as_py())] == [[0, 1], [700, 200], [1140, 640]]
    assert sum(given) <= len(rows) * (2 * (s.length - s.k) + sufdedup.NAME + 1)


def test_repeats_of_nothing(spark):
    assert sufdedup.repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    one = sufdedup.repeats(spark.createDataFrame([(None, "é" * 900), (None, "é" * 900)], "doc_id long, text string"), texts=True).collect()
    assert [(r["n_removed"], r["kept"]) for r in one] == [(1800, b"")] * 2


def similar(docs):
    sets = []
    for t in docs:
        w = re.findall(rb"[^\x20\x09-\x0d]+", (t or "").encode().lower())
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    parent = list(range(len(docs)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and b and 100 * min(len(a), len(b)) >= 80 * max(len(a), len(b)) and 100 * len(a & b) >= 80 * len(a | b):
                x, y = root(i), root(j)
                parent[max(x, y)] = min(x, y)
    return [(i, len(s), root(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("large", [False, True])
def test_jaccard(spark, large):
    rnd = random.Random(5 + large)
    words = [f"w{i}" for i in range(3000)]
    passages = [rnd.choices(words, k=60) for _ in range(2)]
    docs = []
    for _ in range(30):
        base = rnd.choices(words, k=rnd.choice([3, 6, 9, 12, 20, 40, 80, 200, 600]))
        for _ in range(rnd.choice([1, 30] if large else [1, 1, 2, 6])):
            w = list(base)
            for _ in range(rnd.randint(0, max(1, len(w) // 40))):
                w[rnd.randrange(len(w))] = rnd.choice(words)
            if rnd.random() < 0.3:
                k = rnd.randrange(len(w) + 1)
                w = w[:k] + rnd.choice(passages) + w[k:]
            docs.append(" ".join(w))
    docs += ["", None, "A b", "a B", "x"]
    rnd.shuffle(docs)
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    got = [tuple(r) for r in jaccard.join(df, block_bytes=20_000).orderBy("doc_id").collect()]
    assert got == similar(docs)


def test_most_similar_pairs_are_candidates():
    """Signatures of any two similar sets meet, whatever their sizes."""
    rng, j = np.random.default_rng(2), jaccard.Join()
    for _ in range(150):
        n = int(rng.choice([1, 2, 4, 5, 7, 9, 11, 13, 20, 35, 47, 60, 90, 150, 400]))
        base = rng.integers(0, 1 << 63, n).astype(np.uint64)
        x = set(base.tolist())
        y = set(base[: n - int(rng.integers(0, n // 5 + 1))].tolist())
        while True:
            z = y | {int(rng.integers(0, 1 << 62))}
            if 100 * len(x & z) < 80 * len(x | z) or rng.random() < 0.2:
                break
            y = z
        if 100 * len(x & y) < 80 * len(x | y):
            continue
        value = np.concatenate([np.array(sorted(s), np.uint64) for s in (x, y)])
        s, d = jaccard.signatures(value, np.array([0, len(x), len(x) + len(y)]), np.array([0, 1]), j)
        assert set(s[d == 0].tolist()) & set(s[d == 1].tolist())
        assert not jaccard.far_apart(jaccard.parities(value[: len(x)]), jaccard.parities(value[len(x) :]), len(x), len(y), 80)


@pytest.mark.parametrize(("d", "blocks", "rows"), [(16, 4, 50), (8, 3, 1000), (3, 4, 20)])
def test_vectors(spark, d, blocks, rows):
    rng = np.random.default_rng(d)
    vectors = []
    for _ in range(50):
        c = rng.normal(size=d)
        vectors += [(c + rng.normal(size=d) * rng.choice([0.05, 0.15, 0.3])).astype(np.float32).tolist() for _ in range(rng.choice([1, 1, 2, 10]))]
    vectors += [vectors[0], vectors[0], [2 * x for x in vectors[3]], None, [], [0.0] * d, [float("nan")] * d, [None, *vectors[1][1:]], vectors[0][:2]]
    ids = list(range(len(vectors)))
    random.Random(2).shuffle(ids)
    df = spark.createDataFrame(list(zip(ids, vectors, strict=True)), "vec_id long, embedding array<float>")
    got = {r[0]: tuple(r)[1:] for r in vectorjoin.join(df, n_blocks=blocks, slice_rows=rows).collect()}
    sound = [v if v and all(x is not None and np.isfinite(x) for x in v) and any(v) else None for v in vectors]
    unit = [None if v is None else np.array(v, np.float64) / np.linalg.norm(v) for v in sound]
    linked = [[b for b, y in enumerate(unit) if a != b and x is not None and y is not None and len(x) == len(y) and x @ y >= 0.95] for a, x in enumerate(unit)]
    least = list(ids)
    for _ in ids:
        for a, near in enumerate(linked):
            for b in near:
                least[a] = min(least[a], least[b])
    assert got == {ids[a]: (len(near), least[a], least[a] == ids[a]) for a, near in enumerate(linked)}


def test_components_are_finished_or_none(spark):
    chain = spark.createDataFrame([(k, k + 1) for k in range(40)], "u long, v long")
    with pytest.raises(RuntimeError):
        components.components(chain, rounds=1)


def test_components(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, 101), (101, 102), (7, 7), (200, 150)]
    got = {r["v"]: r["label"] for r in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100, 102: 100, 150: 150, 200: 150}


def test_vectors_are_compared_within_reach(monkeypatch):
    """All pairs within the bound, each once, and rows that the first coordinate tells apart in no product."""
    monkeypatch.setattr(vectorjoin, "ACROSS", 7)
    monkeypatch.setattr(vectorjoin, "DOWN", 5)
    y = np.random.default_rng(8).normal(size=(300, 3)).astype(np.float32)
    y[200:] = y[:100] + np.float32(0.01)
    far = ((y[:, None].astype(np.float64) - y[None]) ** 2).sum(axis=2)
    left = np.arange(300) % 3 == 0
    for right in (None, np.arange(300) % 3 == 1):
        got = [(int(a), int(b)) for p, q in vectorjoin.candidates(y, left, right, 0.04, 0.2) for a, b in zip(p, q, strict=True)]
        other = left if right is None else right
        wanted = {(a, b) for a, b in zip(*np.nonzero(far <= 0.04), strict=True) if left[a] and other[b] and (right is not None or a < b)}
        assert len(got) == len(set(got)) and {(min(x), max(x)) if right is None else x for x in got} == wanted
    y[left, 0] += 100
    y[~left] = np.nan  # a product with one of these would be a warning or a hit
    y[~left, 0] = np.arange(200)
    assert not list(vectorjoin.candidates(y, left, ~left & (y[:, 0] < 90), 0.04, 0.2))


def test_vectors_in_double_precision(spark):
    # the second pair's cosine is below the threshold by less than single precision can tell
    angle = np.arccos(0.95)
    near = [[1.0, 0.0], [float(np.cos(angle - 1e-10)), float(np.sin(angle - 1e-10))], [0.0, -1.0], [float(np.sin(angle + 1e-10)), -float(np.cos(angle + 1e-10))]]
    huge = [[-1e200, 1e200], [-1e-200, 1e-200], [-1e300, 1.0001e300]]
    df = spark.createDataFrame(list(enumerate(near + huge)), "vec_id long, embedding array<double>")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vectorjoin.join(df, n_blocks=2).collect()}
    assert got == {0: (1, 0), 1: (1, 0), 2: (0, 2), 3: (0, 3), 4: (2, 4), 5: (2, 4), 6: (2, 4)}


def test_vectors_of_an_empty_table_and_repeated_ids(spark):
    schema = "vec_id long, embedding array<float>, n_links string, label int"
    assert vectorjoin.join(spark.createDataFrame([], schema)).count() == 0
    rows = [(1, [1.0, 0.0], "a", 1), (1, [1.0, 0.0], "b", 2), (None, [0.0, 1.0], None, None), (2, None, "c", None)]
    got = sorted(map(tuple, vectorjoin.join(spark.createDataFrame(rows, schema)).collect()), key=str)
    assert got == sorted([(1, 1, 1, True), (1, 1, 1, True), (None, 0, None, True), (2, 0, 2, True)], key=str)
