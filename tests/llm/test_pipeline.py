"""The pipeline's stages, each on what the one before it kept."""

import random
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline

from probejoin.llm import sufdedup
from probejoin.llm.common import crc_mod_py, table


def test_stages(spark):
    rows = [(1, "the cat and the dog sat on the mat with a hat"), (2, "the cat and the dog sat on the mat with a hat"), (3, None), (4, "12 34"), (5, "other words that nobody else here has said at all")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, "/root/testdata/sf0.001").cache()
        assert kept.columns == docs.columns, name
    assert {r["doc_id"] for r in kept.collect()} == {1, 5}


def test_stages_keep_extra_columns(spark):
    """Columns whose names the operators use themselves pass through; repeated rows, nulls and empty texts crash nothing."""
    rows = [(1, "the cat and the dog sat on the mat with a hat"), (1, "the cat and the dog sat on the mat with a hat"), (None, "the dog of the cat sat under a hat on that mat"), (4, ""), (5, None)]
    docs = spark.createDataFrame(
        [(i, t, "en", "s", len(t or ""), "L", 0.5, 7, [1], i, "r") for i, t in rows],
        "doc_id long, text string, lang string, source string, n_chars long, lang_pred string, score double, h long, known array<int>, kept_id long, row string",
    )
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, "/root/testdata/sf0.001").cache()
        assert kept.columns == docs.columns, name
    assert sorted((r["doc_id"] or 0, r["lang_pred"], r["h"], r["known"], r["kept_id"], r["row"]) for r in kept.collect()) == [(0, "L", 7, [1], None, "r"), (1, "L", 7, [1], 1, "r")]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        empty = stage(spark, docs.limit(0), "/root/testdata/sf0.001")
        assert empty.columns == docs.columns and empty.count() == 0


def test_run(spark):
    sf = "/root/testdata/sf0.001"
    got = corpus_pipeline.run(spark, sf)
    assert 0 < got.count() <= table(spark, sf, "documents").count()


def rows_of(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")


@pytest.mark.parametrize("n", [50, 51, 54, 65])
def test_short_passages_of_over_50_words_go(spark, n):
    rnd = random.Random(n)
    made = lambda k: " ".join("".join(rnd.choice("abcdefghij") for _ in range(rnd.randint(3, 6))) for _ in range(k))
    passage = made(n)
    assert len(passage) < 400
    own = [made(80) for _ in range(4)]
    texts = [f"{own[0]} {passage} {own[1]}", f"{own[2]}\n{passage}\n{own[3]}"]
    got = [r["text"] for r in corpus_pipeline.repeated_passages(spark, rows_of(spark, texts), "").orderBy("doc_id").collect()]
    assert got == ([f"{own[0]}  {own[1]}", f"{own[2]}\n\n{own[3]}"] if n > 50 else texts)


def test_byte_strings_of_few_words_still_go(spark):
    long = "".join(random.Random(1).choice("abcdefghij") for _ in range(450))
    got = [r["text"] for r in corpus_pipeline.repeated_passages(spark, rows_of(spark, [f"one-{long}+two", f"three={long}/four"]), "").orderBy("doc_id").collect()]
    assert got == ["one-+two", "three=/four"]


def words_covered(texts, length, words):
    """Bytes that a repeated string of bytes or of words covers, by brute force."""
    data = [t.encode() for t in texts]
    # white space of Unicode, without the separators 1C to 1F
    places = [[(len(t[: m.start()].encode()), len(t[: m.end()].encode()), m[0]) for m in re.finditer(r"[^\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+", t)] for t in texts]
    seen = Counter(d[i : i + length] for d in data for i in range(len(d) - length + 1))
    seen_words = Counter(tuple(w for _, _, w in p[i : i + words]) for p in places for i in range(len(p) - words + 1))
    out = []
    for d, p in zip(data, places, strict=True):
        mark = bytearray(len(d))
        for i in range(len(d) - length + 1):
            if seen[d[i : i + length]] > 1:
                mark[i : i + length] = b"\1" * length
        for i in range(len(p) - words + 1):
            if seen_words[tuple(w for _, _, w in p[i : i + words])] > 1:
                a, b = p[i][0], p[i + words - 1][1]
                mark[a:b] = b"\1" * (b - a)
        out.append(bytes(x for x, m in zip(d, mark, strict=True) if not m))
    return out


def test_passages_by_brute_force(spark):
    rnd = random.Random(5)
    made = lambda n: "".join(rnd.choice(["ab", "c", "é", "def"]) + rnd.choice([" ", "\n", "\u2003", "\xa0", "", "\x1d"]) for _ in range(n))
    seeds = [made(rnd.randint(10, 60)) for _ in range(5)]
    texts = [made(rnd.randint(0, 20)) + rnd.choice(seeds)[rnd.randint(0, 20) :] + made(rnd.randint(0, 20)) for _ in range(60)]
    texts += ["", "a " * 40, "a\n" * 30, texts[0], texts[0]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [bytes(r["kept"]) for r in sufdedup.repeats(df, length=40, words=9, block_bytes=500, texts=True).orderBy("doc_id").collect()]
    assert got == words_covered(texts, 40, 9)


UNLEARNED = ["Kaikki ihmiset syntyvät vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan. Heille on annettu järki ja omatunto", "Wszyscy ludzie rodzą się wolni i równi pod względem swej godności i swych praw. Są oni obdarzeni rozumem", "Tutti gli esseri umani nascono liberi ed eguali in dignità e diritti. Essi sono dotati di ragione", "Все люди рождаются свободными и равными в своем достоинстве и правах"]


@pytest.mark.parametrize("languages", [2, 4, 5])
def test_no_language_stands_out(spark, languages):
    """Unlearned languages and letter noise go, clean rows stay, however many languages are learned."""
    docs = table(spark, "/root/testdata/sf0.01", "documents").where("text is not null")
    names = sorted(r["lang"] for r in docs.select("lang").distinct().collect())
    if languages == 5:  # a fifth one that none of the rows below is of
        turned = docs.where("lang = 'en' and doc_id % 4 = 0").withColumn("text", F.reverse(F.translate("text", "etaoinshr", "qxzjkvwyg"))).withColumn("lang", F.lit("xx")).withColumn("doc_id", F.col("doc_id") + 1_000_000)
        docs = docs.unionByName(turned)
    else:
        docs = docs.where(F.col("lang").isin(names[:languages]))
    rnd = random.Random(1)
    noise = ["".join(" " if rnd.random() < 0.16 else rnd.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(300)) for _ in range(20)]
    odd = rows_of(spark, UNLEARNED + noise).withColumn("doc_id", -1 - F.col("doc_id")).withColumn("lang", F.lit(None).cast("string"))
    kept = corpus_pipeline.language(spark, docs.unionByName(odd.select(*docs.columns)), "").select("doc_id").collect()
    assert min(r["doc_id"] for r in kept) >= 0
    clean = docs.where("text rlike '[a-zA-Z]{3}'").select("doc_id").collect()
    clean = {r["doc_id"] for r in clean if crc_mod_py(r["doc_id"], 3) == 1}
    assert len(clean) > 50 and len(clean & {r["doc_id"] for r in kept}) >= 0.99 * len(clean)
