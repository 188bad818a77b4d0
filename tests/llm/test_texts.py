"""Language filters, decontamination, language model, archive and extraction."""

import base64
import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from probejoin.llm import decontam, htmltext, langid, ngramlm, warc
from probejoin.llm.common import shared_folder, table

SF = "/root/testdata/sf0.01"


def test_language_of_held_out_documents(spark):
    docs = table(spark, SF, "documents")
    got = langid.predict(docs, langid.train(langid.training_rows(docs))).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert len(got) > 200 and sum(r["lang"] == r["lang_pred"] for r in got) >= 0.97 * len(got)
    assert all(0 <= r["score"] <= 1 for r in got)
    assert {r["doc_id"] for r in got} == {r["doc_id"] for r in docs.select("doc_id").collect() if zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1}


def test_language_edges(spark):
    df = spark.createDataFrame([(1, None, "en"), (2, "12 % 3", "en"), (3, "漢", None), (None, "the and of", "en")], "doc_id long, text string, lang string")
    none = langid.train(df.limit(0))
    assert {r["lang_pred"] for r in langid.predict(df, none).collect()} == {"und"}
    got = {r["doc_id"]: r["lang_pred"] for r in langid.predict(df, langid.train(df, least=1)).collect()}
    assert got == {1: "und", 2: "und", 3: "en", None: "en"}


def test_language_sample_counts_texts(spark):
    """Copies of one text don't fill the sample of its language, wherever their hash falls."""
    words = ["the", "and", "of", "with", "from", "over"]
    texts = [f"{words[k % 6]} {words[k // 6 % 6]} {words[k // 36]}" for k in range(100)]
    ranked = [r["text"] for r in spark.createDataFrame([(x,) for x in texts], "text string").orderBy(F.xxhash64("text")).collect()]
    hot = ranked[0]
    df = spark.createDataFrame([(x, "en") for x in texts + [hot] * 500], "text string, lang string")
    once = spark.createDataFrame([(x, "en") for x in texts], "text string, lang string")
    got, want = (langid.train(x, rows_per_language=60, least=1) for x in (df, once))
    assert (got.table == want.table).all() and got.expected == want.expected


def edits_brute(item, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(item, 1):
        new = [i]
        for k, d in enumerate(text, 1):
            new.append(min(row[k - 1] + (c != d), row[k] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_decontamination_finds_what_edits_allow():
    rng = np.random.default_rng(4)
    letters = list("abcdefghijklmnop ")
    made = lambda n: "x" + "".join(rng.choice(letters, n - 2)) + "y"
    items = [(k, made(int(rng.integers(60, 300)))) for k in range(12)] + [(99, "short one"), (98, ""), (97, None)]
    index = decontam.ItemIndex(items)
    for trial in range(60):
        k = int(rng.integers(0, 12))
        passage = list(decontam.plain(items[k][1]).decode())
        for _ in range(int(rng.integers(0, len(passage) // 7))):
            at = int(rng.integers(0, len(passage)))
            passage[at : at + 1] = [["z"], [], ["q", passage[at]]][int(rng.integers(0, 3))]
        text = made(int(rng.integers(20, 400))) + " " + "".join(passage) + " " + made(100)
        found = {i: e for i, e, _, _ in index.find(text)}
        item = decontam.plain(items[k][1])
        least = edits_brute(item, decontam.plain(text))
        assert found.get(k) == (least if least <= int(0.1 * len(item)) else None), trial
    assert index.find("a Short, one b")[0][:2] == (99, 0) and not index.find("shorter one") and not index.find(None)


def test_decontamination_of_many_texts(monkeypatch):
    """Edits by bits against the table of all edits, and texts looked up together against each by itself."""
    rng = np.random.default_rng(12)
    word = lambda n: bytes(rng.choice(list(b"abc "), n).tolist())
    for m, n in ((1, 5), (8, 0), (20, 30), (70, 90), (70, 40)):
        for _ in range(20):
            item, region = word(m), word(n)
            least = edits_brute(item, region)
            assert [decontam.may_hold(decontam.masks(item), m, region, e) for e in (least - 1, least)] == [False, True]
    items = [(k, " ".join("".join(rng.choice(list("abcdefgh"), 6)) for _ in range(12 if k % 5 else 3))) for k in range(40)]
    texts = [None, "", "x"] + [" ".join((items[k][1][3:], "y z", items[(k * 7) % 40][1], items[k][1][:40]))[k % 3 :] for k in range(40)]
    index = decontam.ItemIndex(items)
    want = [index.find(t) for t in texts]
    assert sum(map(len, want)) > 40
    for together, step in ((1 << 18, 1 << 20), (150, 1 << 20), (150, 60)):
        monkeypatch.setattr(decontam, "TOGETHER", together)
        monkeypatch.setattr(decontam, "STEP", step)
        assert index.find_all(texts) == want


def test_decontamination_of_tables(spark):
    docs, items = table(spark, SF, "documents"), table(spark, SF, "benchmark")
    texts = {r["item_id"]: r["text"] for r in items.collect()}
    exact = {r["doc_id"] for r in docs.collect() if any(t in r["text"] for t in texts.values())}
    for block in (8 << 20, 3000):
        got = {r["doc_id"] for r in decontam.leaks(docs, items, block_bytes=block).collect()}
        assert exact <= got and len(got) <= len(exact) + 5
    kept = decontam.clean(docs, items)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.select("doc_id").collect()} == {r["doc_id"] for r in docs.select("doc_id").collect()} - got


def test_language_model(spark):
    docs = table(spark, SF, "documents")
    extra = spark.createDataFrame([(10**6, None, "x"), (10**6 + 1, "", "x"), (None, " The\x0bthe \x1c ", "x")], "doc_id long, text string, score string")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()] + [(r[0], r[1]) for r in extra.collect()]
    tokens = lambda t: [*re.findall(rb"[^\x20\x09-\x0d]+", (t or "").encode().lower()), None]
    fold = lambda i: zlib.crc32(b"" if i is None else str(i).encode()) % 7 == 2
    counts = Counter(w for i, t in rows if not fold(i) for w in tokens(t))
    n, v = sum(counts.values()), len(counts)
    got = {r["doc_id"]: r for r in ngramlm.score(docs.select("doc_id", "text").unionByName(extra.select("doc_id", "text")), block_bytes=1 << 20).collect()}
    assert len(got) == len(rows)
    for i, t in rows:
        own, r = tokens(t), got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (fold(i), len(own), sum(counts[w] > 0 for w in own), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in own))
    held = [r for r in got.values() if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_language_model_is_a_distribution():
    """Weights sum to one for each bucket, and so do probabilities over known words and one unknown."""
    mix = ngramlm.learn_weights(np.array([5000, 90000, 123456]), np.array([3, 5, 7]), 1000, 50)
    assert np.allclose(mix.sum(axis=1), 1) and (mix >= 0).all()
    c = {"a": {"a": 3, "b": 1}, "b": {"a": 2}}
    uni, total = {"a": 6, "b": 2}, 8
    for ctx in c:
        m, size = mix[int(ngramlm.bucket_of(np.array([sum(c[ctx].values())]))[0])], sum(c[ctx].values())
        p = [m[0] * c[ctx].get(w, 0) / size + m[1] * uni[w] / total + m[2] / 3 for w in uni] + [m[2] / 3]
        assert sum(p) == pytest.approx(1)


def test_archive(spark):
    pages = spark.createDataFrame([(5, "u", "<p>a"), (3, "u\r\nX: y", "<p>a"), (9, None, None), (7, "v", ""), (8, "w", "é")], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in warc.archive(pages).collect()}
    assert {k: (r["record_type"], r["refers_to"]) for k, r in got.items()} == {3: ("response", None), 5: ("revisit", 3), 7: ("response", None), 9: ("revisit", 7), 8: ("response", None)}
    assert got[8]["payload_digest"] == base64.b32encode(hashlib.sha1("é".encode()).digest()).decode() and got[8]["payload_bytes"] == 2
    folder = shared_folder(spark, "warc")
    warc.write(pages, folder, revisit_from=1)
    records = {r["id"]: r for r in warc.read(spark, folder).collect()}
    assert records[9]["record_type"] == "response" and all(r["verified"] for r in records.values())
    assert bytes(records[8]["record"]).endswith(b"Content-Length: 2\r\n\r\n" + "é".encode() + b"\r\n\r\n") and b"\r\nX:" not in bytes(records[3]["record"])
    assert spark.read.parquet(f"{folder}/payloads").count() == 3
    assert warc.archive(pages.limit(0)).count() == 0


def test_payloads_cross_the_network_once(spark):
    """One exchange for all distinct payloads; a join on the id before it moved every payload twice."""
    rows = spark.createDataFrame([(1, "a", b"x"), (2, "a", b"x"), (3, "b", b"y")], "id long, address string, payload binary").repartition(3)
    once = warc._once(rows)
    plan = once._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(") == 1 and "Join" not in plan
    assert sorted(tuple(r) for r in once.collect()) == [("a", b"x"), ("b", b"y")]


PAGE = '<html><head><title>t</title><style>p{}</style></head><body><header>H</header><div class="cookie-notice">C</div><nav><ul><li>q</ul></nav><main><article><header><h1>T &amp; &eacute;</h1></header><p>One <b>two</b>\n  three<p class="ad">no<p>Four<br>five<div class="share-bar">S</div><ul><li>l1<li>l2</ul><aside>A</aside><section id="comments"><p>bad</p></section></article></main><form><input>F</form><footer>f</footer><script>var a="</p>";if(a<b){}</script></body></html>'


def test_extraction_by_elements(spark):
    want = "T & é\n\nOne two three\n\nFour five\n\nl1\n\nl2"
    pages = spark.createDataFrame([(1, "http://a/x", PAGE), (2, "http://a/x", PAGE), (3, None, None), (4, "http://b/", "")], "page_id long, url string, html string")
    got = {r["page_id"]: (r["url"], r["text"], r["n_chars"]) for r in htmltext.extract(pages).collect()}
    assert got == {1: ("http://a/x", want, len(want)), 2: ("http://a/x", want, len(want)), 3: (None, "", 0), 4: ("http://b/", "", 0)}


@pytest.mark.parametrize("void", ['<img class="header-image">', '<img hidden src=x />', '<wbr aria-hidden="true">', '<img style="display:none">', '<area id="nav">', '<source class="ad">', '<img alt="a hidden gem">'])
def test_extraction_behind_void_elements(void):
    at = lambda page: [t for t, z in htmltext.blocks(page) if z == 2]
    assert at(f"<body><article><p>A{void}b</p>{void}<p>B</p></article>") == ["Ab", "B"]
    assert at(f"<body>{void}<article><p>A</p></article>") == ["A"]


def test_hidden_is_an_attribute():
    at = lambda attributes: [z for _, z in htmltext.blocks(f"<article><p {attributes}>A</p></article>")]
    for shown in ('title="a hidden gem"', "title='so hidden '", 'title="aria-hidden=true"', 'aria-hidden="false"', 'data-style="display:none"', 'title=" style=\'display:none\' "', "data-hidden"):
        assert at(shown) == [2], shown
    for gone in ("hidden", 'HIDDEN=""', 'title="x" hidden', 'aria-hidden="true"', "aria-hidden=true", 'style="color:red; display : none"', "style='display:none'", "style=display:none"):
        assert at(gone) == [-1], gone


def test_language_counts_in_parts(spark, monkeypatch):
    """A task held the n-grams of all texts of a language at once before."""
    import numpy as np

    from probejoin.llm import langid

    rows = [(f"the {k} cats and dogs sit near {k % 7}" if k % 2 else f"die {k} Katzen und Hunde bei {k % 5}", "en" if k % 2 else "de") for k in range(60)]
    frame = spark.createDataFrame(rows, "text string, lang string").coalesce(1)
    whole = langid.train(frame)
    monkeypatch.setattr(langid, "COUNTED_BYTES", 100)
    parts = langid.train(frame)
    assert whole.languages == parts.languages == ["de", "en"] and whole.table.any()
    assert np.array_equal(whole.table, parts.table) and np.array_equal(whole.expected, parts.expected)


def test_extraction_keeps_no_texts(spark, monkeypatch):
    """Texts and blocks of pages with an article were written beside their shuffle before."""
    kept, written = [], htmltext.written
    monkeypatch.setattr(htmltext, "written", lambda df, what: kept.append((what, df.columns)) or written(df, what))
    rows = [(k, f"http://h/{k}", f"<nav>Home</nav><article><p>Same line</p><p>Text {k}</p></article>") for k in range(3)]
    got = {r["page_id"]: (r["text"], r["n_template"]) for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {k: (f"Same line\n\nText {k}", 2) for k in range(3)}
    assert ("marks", ["id", "host", "path", "marks", "mark", "open"]) in kept and not any("text" in columns for _, columns in kept)


def test_extraction_by_differences(spark):
    page = lambda body: f"<div>Menu</div><div>{body}</div><div>Contact</div>"
    pages = spark.createDataFrame([(k, f"http://a/{k}", page(f"story {k}")) for k in range(6)] + [(9, "http://c/", page("alone"))], "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in htmltext.extract(pages).collect()}
    assert {k: v for k, v in got.items() if k < 6} == {k: f"story {k}" for k in range(6)} and got[9] == "Menu\n\nalone\n\nContact"


def test_articles_are_differenced(spark):
    """Pages that elements decide are paired as well: what they share is counted, what the article has stays."""
    page = lambda *body: "<nav>Menu</nav><article>" + "".join(f"<p>{b}</p>" for b in body) + "</article><footer>Foot</footer>"
    rows = [(1, "http://a/1", page("same", "one")), (2, "http://a/1?copy", page("same", "one")), (3, "http://a/2", page("same", "two", "three")), (4, "http://b/1", page("same")), (5, "http://b/2", None)]
    got = {r["page_id"]: (r["text"], r["n_template"]) for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {1: ("same\n\none", 3), 2: ("same\n\none", 3), 3: ("same\n\ntwo\n\nthree", 3), 4: ("same", 0), 5: ("", 0)}


@pytest.mark.parametrize("partitions", [1, 3, 50])
def test_extraction_past_copies(spark, partitions):
    """Copies and pages that hold all of a page's blocks are passed over, and partitions change nothing."""
    page = lambda *body: "".join(f"<div>{b}</div>" for b in ("Menu", *body, "Contact"))
    rows = [(k, f"http://a/1?copy={k}", page("one")) for k in range(5)]  # copies of one path
    rows += [(10, "http://a/2", page("one", "two")), (11, "http://a/3", page("one", "two", "three")), (12, "http://a/4", page("far"))]
    rows += [(20, "http://b/1", page("left")), (21, "http://b/2", page("right")), (30, "http://c/1", page("c")), (31, "http://c/2", page("c")), (40, None, page("n"))]
    want = {**dict.fromkeys(range(5), "one"), 10: "two", 11: "three", 12: "far", 20: "left", 21: "right", 30: "Menu\n\nc\n\nContact", 31: "Menu\n\nc\n\nContact", 40: "Menu\n\nn\n\nContact"}
    held = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(partitions))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = {r["page_id"]: r["text"] for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert got == want


def test_longest_common_lines():
    a, b = list("axbycz"), list("aqbwcz")
    assert {a[i] for i in htmltext.shared(a, b)} == set("abcz")
    assert htmltext.shared(list("abab"), list("baba")) in ({0, 1, 2}, {1, 2, 3})


def test_archive_marks_records_whose_payload_is_gone_or_changed(spark, tmp_path):
    pages = spark.createDataFrame([(1, "u1", "a"), (2, "u2", "b"), (3, "u3", "c")], "page_id long, url string, html string")
    folder = shared_folder(spark, "warc")
    warc.write(pages, folder)
    other = str(tmp_path / "archive")
    spark.read.parquet(f"{folder}/records").write.parquet(f"{other}/records")
    kept = spark.read.parquet(f"{folder}/payloads").where("payload <> cast('a' as binary)")
    kept.selectExpr("address", "if(payload = cast('b' as binary), cast('x' as binary), payload) as payload").write.parquet(f"{other}/payloads")
    assert {r["id"]: r["verified"] for r in warc.read(spark, other).collect()} == {1: False, 2: False, 3: True}
