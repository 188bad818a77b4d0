"""Main text of web pages by differencing neighbours within a host.

Pages of a host are sorted by the path of their URL; each is paired with the nearest page of
the host that does not hold all its blocks (the one before it first). Both are cut into text
blocks, the blocks are aligned by a longest common subsequence, and blocks that both have are template.

Differencing alone can't give the text asked for: of two pages that carry the same article
it would delete the article, and menus or adverts that differ from page to page would stay
(README has figures). So every page is differenced, and elements check the outcome: what
stands in elements or under names that mark furniture (menus, headers, footers, sidebars,
notices, adverts, forms, comments) goes although no neighbour has it, what stands in the
page's article stays although a neighbour has it, too. A page without an article element
keeps those of its blocks that its neighbour does not share. Pages with an article element
are paired with one another by hashes of their blocks; `n_template` counts a page's shared blocks.

Copies within a host are reduced to the first one and share its answer. What is left is
numbered in the order of (host, path, id), so a hot host is spread over tasks and a page's
neighbours do not depend on partitions: they are fetched by number, at a distance of 1, and
for pages still without an answer up to 2, 4 and so on until the host's ends are reached.

Rows: null html gives an empty text; a null URL counts as host and path ''; pages with equal
host, path and id keep any order among them; every input row gives one output row; extra
columns are ignored; an empty table gives an empty result; pages are parsed whole.
"""

from __future__ import annotations

import base64
import hashlib
import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probejoin.llm.common import lean, written
from probejoin.sources.storage import tidy

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_NAMED = re.compile(r"(?:class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_ATTRIBUTE = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"?|'([^']*)'?|([^\s>]+)))?|\"[^\"]*\"?|'[^']*'?")
_NOT_SHOWN = re.compile(r"(?:^|;)\s*display\s*:\s*none", re.I)
#: Elements of HTML by what they do here (fixed values).
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
DROPPED = frozenset("nav header footer aside form script style noscript template menu dialog button select option textarea input label fieldset iframe object embed canvas svg math head title".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd mark q ruby rb rp rt s samp small span strike strong sub sup time tt u var wbr area map picture source".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Words of class, id or role that mark furniture, compared with the parts of names.
FURNITURE = frozenset("ad ads advert adverts advertisement advertising sponsored promo banner nav navbar navigation navi menu menus breadcrumb breadcrumbs sidebar rail header masthead topbar footer colophon cookie cookies consent gdpr notice notices alert popup modal newsletter subscribe signup login search share sharing social related recommended recommendations comment comments reply replies disqus discussion respond widget toolbar pagination pager skip contentinfo complementary".split())


def _names(attributes: str) -> set[str]:
    out: set[str] = set()
    for m in _NAMED.finditer(attributes):
        value = m[1] or m[2] or m[3] or ""
        out.update(re.split(r"[^a-z0-9]+", re.sub(r"(?<=[a-z])(?=[A-Z])", "-", value).lower()))
    return out


def _hidden(attributes: str) -> bool:
    """Whether attributes hide their element; words in other attributes' values don't."""
    lowered = attributes.lower()
    if "hidden" not in lowered and "none" not in lowered:
        return False
    for m in _ATTRIBUTE.finditer(attributes):
        name, value = (m[1] or "").lower(), m[2] or m[3] or m[4] or ""
        if name == "hidden" or name == "aria-hidden" and value.strip().lower() == "true" or name == "style" and _NOT_SHOWN.search(value):
            return True
    return False


def blocks(page: str) -> list[tuple[str, int]]:
    """Text blocks in page order with their zone: 2 in the article, 1 in the main element around it, 0 undecided, -1 furniture."""
    out: list[tuple[str, int]] = []
    held: list[str] = []
    stack: list[tuple[str, int, int]] = []  # tag, zone outside it, depth of main outside it
    zone, at, raw, lowered = 0, 0, "", None

    def close() -> None:
        if held:
            text = " ".join(html.unescape("".join(held)).split())
            held.clear()
            if text:
                out.append((text, zone))

    pos, n = 0, len(page)
    while pos < n:
        if raw:
            lowered = lowered if lowered is not None else page.lower()
            end = lowered.find("</" + raw, pos)
            end = n if end < 0 else end
            if raw not in DROPPED:
                held.append(page[pos:end])
            pos, raw = end, ""
            continue
        m = _TOKEN.search(page, pos)
        if m is None:
            held.append(page[pos:])
            break
        held.append(page[pos : m.start()])
        pos = m.end()
        tag = (m[2] or "").lower()
        if not tag:
            continue
        if tag in INLINE and tag not in DROPPED:
            if tag == "br":
                held.append(" ")
            elif tag in VOID:  # holds no text and has no end tag
                pass
            elif not m[1] and (_hidden(m[3]) or _names(m[3]) & FURNITURE and zone >= 0):
                close()
                stack.append((tag, zone, at))
                zone = -1
            elif m[1] and stack and stack[-1][0] == tag:
                close()
                _, zone, at = stack.pop()
            continue
        close()
        if tag in VOID:
            continue
        if m[1]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    _, zone, at = stack[k]
                    del stack[k:]
                    break
            continue
        if tag == "p" and stack and stack[-1][0] == "p":  # a paragraph ends the one before
            _, zone, at = stack.pop()
        names = _names(m[3]) if m[3] else set()
        stack.append((tag, zone, at))
        if zone < 0:
            pass
        elif tag in DROPPED and not (tag == "header" and at) or names & FURNITURE and tag not in ("html", "body") and not names & {"article", "main"} or _hidden(m[3] or ""):
            zone = -1
        elif tag == "article" or tag == "div" and names & {"article", "articlebody"}:
            zone, at = 2, at + 1
        elif tag == "main" or "main" in names and tag == "div":
            zone, at = max(zone, 1), at + 1
        if tag in RAW and not m[3].rstrip().endswith("/"):
            raw = tag
    close()
    return out


def shared(a: list[str], b: list[str]) -> set[int]:
    """Places in a of one longest common subsequence of a and b.

    Equal ends are taken off; the middle is aligned through the places at which equal lines
    occur (Hunt and Szymanski), so that pages with little in common cost little.
    """
    lo = 0
    while lo < len(a) and lo < len(b) and a[lo] == b[lo]:
        lo += 1
    ea, eb = len(a), len(b)
    while ea > lo and eb > lo and a[ea - 1] == b[eb - 1]:
        ea, eb = ea - 1, eb - 1
    out = {*range(lo), *range(ea, len(a))}
    places: dict[str, list[int]] = {}
    for j in range(eb - 1, lo - 1, -1):
        places.setdefault(b[j], []).append(j)
    import bisect

    tails: list[int] = []
    links: list[tuple[int, object]] = []
    for i in range(lo, ea):
        for j in places.get(a[i], ()):
            k = bisect.bisect_left(tails, j)
            link = (i, links[k - 1] if k else None)
            if k == len(tails):
                tails.append(j)
                links.append(link)
            else:
                tails[k], links[k] = j, link
    link = links[-1] if links else None
    while link is not None:
        out.add(link[0])
        link = link[1]
    return out


def without(lines: list[str], other: list[str]) -> list[str] | None:
    """Lines that a neighbour does not share; None if it has all of them and so tells nothing about template."""
    gone = shared(lines, other)
    return None if len(gone) == len(lines) else [t for k, t in enumerate(lines) if k not in gone]


def _parsed(pages: DataFrame, elements: bool) -> DataFrame:
    """Rows (id, url, host, path, text, lines, key, marks, mark): text where elements confirm an article, else null; undecided blocks and their hash; hashes of all blocks of a page with an article, and their hash."""
    host = F.lower(F.coalesce(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#]*)", 1), F.lit("")))
    path = F.coalesce(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*([^?#]*)", 1), F.lit(""))
    keyed = pages.withColumn("host", host).withColumn("path", path).select("id", "url", "host", "path", "html")
    schema = T.StructType([*keyed.schema.fields[:4], T.StructField("text", T.StringType()), T.StructField("lines", T.ArrayType(T.StringType())), T.StructField("key", T.BinaryType()), T.StructField("marks", T.ArrayType(T.StringType())), T.StructField("mark", T.BinaryType())])
    digest = lambda text, size: hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, lines, keys, marks, mark = [], [], [], [], []
            for page in batch.column(4):
                page = page.as_py()
                own = blocks(page) if page else []
                top = max((z for _, z in own), default=0) if elements else 0
                lines.append([t for t, z in own if z == 0 or not elements])
                texts.append("\n\n".join(t for t, z in own if z == top) if top > 0 else None if lines[-1] else "")
                keys.append(digest("\n".join(lines[-1]), 16).digest())
                marks.append([base64.b64encode(digest(t, 6).digest()).decode() for t, _ in own] if top > 0 else [])
                mark.append(digest("\n".join(marks[-1]), 16).digest())
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(texts, pa.string()), pa.array(lines, pa.list_(pa.string())), pa.array(keys, pa.binary()), pa.array(marks, pa.list_(pa.string())), pa.array(mark, pa.binary())], schema.names)

    return keyed.mapInArrow(run, schema)


def _numbered(rows: DataFrame) -> DataFrame:
    """Distinct pages of each host with their place `at` in the order of (host, path, id)."""
    apart = rows.groupBy("host", "key").agg(F.min(F.struct("path", "id")).alias("first"), F.first("lines").alias("lines"), F.max(F.col("text").isNull()).alias("open"))
    dealt = apart.repartitionByRange("host", "first", "key").sortWithinPartitions("host", "first", "key").withColumn("at", F.monotonically_increasing_id())
    dealt = written(dealt.drop("first"), "pages")
    sizes = dealt.groupBy(F.shiftright("at", 33).alias("part")).agg(F.count("*").alias("n")).orderBy("part").collect()
    before, total = [], 0
    for r in sizes:
        before.append((r["part"], total - (r["part"] << 33)))
        total += r["n"]
    shift = dealt.sparkSession.createDataFrame(before, "part long, shift long")
    return dealt.join(shift, F.shiftright("at", 33) == F.col("part")).withColumn("at", F.col("at") + F.col("shift")).drop("part", "shift")


def _differenced(rows: DataFrame) -> DataFrame:
    """Rows (host, key, answer) for the distinct pages without a text yet."""
    every = _numbered(rows.where(F.size("lines") > 0))
    ends = every.groupBy("host").agg(F.min("at").alias("lo"), F.max("at").alias("hi"))
    left = written(every.where("open").select("host", "key", "lines", "at").join(ends, "host"), "open")
    near, far, answers = 1, 1, None
    fields = "host string, key binary, answer string"

    def run(table: pa.Table) -> pa.Table:
        """One page and what is near it."""
        table = table.sort_by([("distance", "ascending"), ("other_at", "ascending")])
        lines, answer = table["lines"][0].as_py(), None
        for other in table["other"]:
            answer = without(lines, other.as_py())
            if answer is not None:
                break
        return pa.table({"host": table["host"][:1], "key": table["key"][:1], "answer": pa.array([None if answer is None else "\n\n".join(answer)], pa.string())}, schema=pa.schema([("host", pa.string()), ("key", pa.binary()), ("answer", pa.string())]))

    while not left.isEmpty():
        asked = left.select("host", "key", "lines", "at", "lo", "hi", F.explode(F.sequence(F.lit(near), F.lit(far))).alias("distance"))
        asked = asked.select("*", F.explode(F.array(F.col("at") - F.col("distance"), F.col("at") + F.col("distance"))).alias("other_at")).where("other_at between lo and hi")
        met = asked.join(every.select(F.col("at").alias("other_at"), F.col("lines").alias("other")), "other_at").select("host", "key", "lines", "distance", "other_at", "other")
        got = written(met.groupBy("host", "key").applyInArrow(run, fields).where("answer is not null"), "answers")
        answers = got if answers is None else answers.unionByName(got)
        left = written(left.where((F.col("at") - far > F.col("lo")) | (F.col("at") + far < F.col("hi"))).join(got, ["host", "key"], "left_anti"), "open")
        near, far = far + 1, far * 2
    return answers if answers is not None else rows.sparkSession.createDataFrame([], fields)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", elements: bool = True) -> DataFrame:
    """Per row: id_col, url_col, text, n_chars, n_template (blocks that the neighbour shares). Without elements, differencing alone decides (for comparison)."""
    lean(pages.sparkSession)
    rows = _parsed(pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html")), elements)
    # Texts are not kept beside their shuffle: pages are parsed once for marks and once more for texts.
    marks = written(rows.select("id", "host", "path", "marks", "mark", F.col("text").isNull().alias("open")), "marks")
    with tidy(pages.sparkSession):
        marked = _differenced(marks.where(F.size("marks") > 0).select("id", "host", "path", F.lit(None).cast("string").alias("text"), F.col("marks").alias("lines"), F.col("mark").alias("key")))
    rest = lambda df: df.withColumn("kept", F.size(F.split("answer", "\n\n")))
    left = F.coalesce(F.col("n") - F.col("kept"), F.lit(0)).cast("long").alias("n_template")
    decided = rows.where("text is not null").select("id", "url", "text", "host", "mark", F.size("marks").alias("n"))
    done = decided.join(rest(marked).select("host", F.col("key").alias("mark"), "kept"), ["host", "mark"], "left").select("id", "url", "text", left)
    if not marks.where("open").isEmpty():  # a page without a neighbour that tells template from text keeps all its blocks
        told = rows.where("text is null").withColumn("n", F.size("lines")).join(rest(_differenced(rows)), ["host", "key"], "left")
        done = done.unionByName(told.select("id", "url", F.coalesce("answer", F.concat_ws("\n\n", "lines")).alias("text"), left))
    return done.select(F.col("id").alias(id_col), F.col("url").alias(url_col), "text", F.char_length("text").cast("long").alias("n_chars"), "n_template")
