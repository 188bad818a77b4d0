"""Language identification by Bloom filters of n-grams, one bit for each language.

Training counts byte n-grams of labelled rows; an n-gram belongs to each language in which
its relative frequency is at least a share of its highest. All languages share one slot
array: a slot's bits say which languages have set it, so that two reads and one AND return
every language that holds an n-gram. A text's bits are counted by language, the filter's
rate of false positives is taken off, and the highest corrected count decides.

Training reads a bounded sample: `rows_per_language` texts of each language (default 3,000;
copies count once), those of the smallest hash, so that it does not depend on order. The slot
array has a fixed size (2**slots_log2 bytes for every eight languages), the only thing sent
to executors.

Rows: null text, or one without a letter, is `und` with score 0; a text with letters always
gets a learned language (the most frequent one where no n-gram is known); without labelled
rows all is `und`. Ties go to the language that comes first by name. Every input row gives
one output row; null ids and repeated rows are kept; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from probejoin.llm.common import crc_mod, crc_mod_py, lean, only

SIZES = (3, 4)
UNDECIDED = "und"
#: Stands for all n-grams of a language among their codes, none of which is 0.
ALL = 0
#: Bytes of a text that are looked at together; texts are read whole, piece by piece.
PIECE = 1 << 20
#: Multipliers of the two hash functions (odd, from the golden ratio and its square).
HASHES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)
_KEEP = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def letters(text: str) -> bytes:
    """Lower case, everything of ASCII but letters as single spaces, one space at each end."""
    return b" " + b" ".join(text.lower().encode("utf-8", "replace").translate(_KEEP).split()) + b" "


def has_letter(text: str) -> bool:
    return any(c.isalpha() for c in text)


def grams(data: np.ndarray, n: int) -> np.ndarray:
    """Codes of all n-byte windows, n at most 7, with n in the top byte."""
    if len(data) < n:
        return np.empty(0, np.uint64)
    code = data[: len(data) - n + 1].astype(np.uint64)
    for k in range(1, n):
        code = (code << np.uint64(8)) | data[k : len(data) - n + 1 + k]
    return code | np.uint64(n << 56)


def slots(codes: np.ndarray, log2: int) -> list[np.ndarray]:
    return [((codes * np.uint64(m)) >> np.uint64(64 - log2)).astype(np.int64) for m in HASHES]


@dataclass
class LanguageFilter:
    languages: list[str]
    prior: int
    table: np.ndarray  # slices of eight languages by slots
    log2: int
    expected: np.ndarray  # by language: share of its own n-grams that it would hold in rows it has not seen

    def __post_init__(self):
        bits = np.unpackbits(self.table[:, :, None], axis=2, bitorder="little").mean(axis=1).reshape(-1)[: len(self.languages)]
        self.false = np.minimum(bits ** len(HASHES), 0.999)
        self.bits = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.float64)

    def counts(self, data: bytes) -> tuple[np.ndarray, int]:
        """Corrected number of n-grams for each language, and how many n-grams there are."""
        hits, total, array = np.zeros(8 * len(self.table)), 0, np.frombuffer(data, np.uint8)
        for at in range(0, len(array), PIECE):
            for n in SIZES:
                codes = grams(array[at : at + PIECE + n - 1], n)
                if not len(codes):
                    continue
                total += len(codes)
                a, b = slots(codes, self.log2)
                for k, own in enumerate(self.table):
                    hits[8 * k : 8 * k + 8] += np.bincount(own[a] & own[b], minlength=256) @ self.bits
        hits = hits[: len(self.languages)]
        return np.maximum((hits - total * self.false) / (1 - self.false), 0), total

    def decide(self, text: str | None) -> tuple[str, float, float]:
        """Language, its share of all corrected counts, and the share of the text's n-grams that it holds against what is expected of its rows."""
        if not text or not self.languages:
            return UNDECIDED, 0.0, 0.0
        data = letters(text)
        if len(data) < 3 or not data.translate(None, _HIGH).strip():
            if not has_letter(text):
                return UNDECIDED, 0.0, 0.0
        got, total = self.counts(data)
        if got.max(initial=0) <= 0:
            return self.languages[self.prior], 0.0, 0.0
        best = int(got.argmax())
        return self.languages[best], float(got[best] / got.sum()), float(got[best] / total / self.expected[best]) if self.expected[best] else 1.0


_HIGH = bytes(range(128, 256))
#: Bytes of a language's training texts that a task counts at a time, at eight bytes and more for each.
COUNTED_BYTES = 1 << 20


def train(rows: DataFrame, text_col: str = "text", lang_col: str = "lang", rows_per_language: int = 3000, share: float = 0.35, least: int = 3, slots_log2: int = 21) -> LanguageFilter:
    """Filter learned from the rows that have a text and a language.

    rows_per_language bounds the sample and so all that comes to the driver: counts of
    n-grams seen at least `least` times in a language.
    """
    rows = rows.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("text is not null and lang is not null")
    found = rows.groupBy("lang").agg(F.count("*").alias("n"), F.approx_count_distinct(F.xxhash64("text")).alias("texts")).collect()
    sizes, distinct = {r["lang"]: r["n"] for r in found}, {r["lang"]: r["texts"] for r in found}
    names = sorted(sizes)
    if not names:
        return LanguageFilter([], 0, np.zeros((1, 1 << slots_log2), np.uint8), slots_log2, np.zeros(0))
    prior = max(range(len(names)), key=lambda i: (sizes[names[i]], -i))
    odds = F.create_map(*[F.lit(x) for k in names for x in (k, min(1.0, 1.5 * rows_per_language / distinct[k] + 100 / distinct[k]))])
    drawn = rows.withColumn("h", F.xxhash64("text")).where((F.pmod("h", F.lit(1 << 30)) / F.lit(float(1 << 30))) < odds[F.col("lang")]).dropDuplicates(["lang", "h"])
    drawn = drawn.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy("h"))).where(F.col("k") <= rows_per_language)

    most = COUNTED_BYTES

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Counts of a language's texts in parts of about `most` bytes, which are summed afterwards."""
        only("")
        held: dict[str, list[np.ndarray]] = {}
        sizes: dict[str, int] = {}

        def part(lang: str) -> Iterator[pa.RecordBatch]:
            texts, sizes[lang] = held.pop(lang), 0
            every = sum(max(len(t) - n + 1, 0) for t in texts for n in SIZES)
            yield pa.RecordBatch.from_arrays([pa.array([lang], pa.string()), pa.array([ALL], pa.int64()), pa.array([every], pa.int64())], ["lang", "code", "n"])
            for n in SIZES:
                code, c = np.unique(np.concatenate([grams(t, n) for t in texts]), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(code), pa.string()), pa.array(code.astype(np.int64)), pa.array(c.astype(np.int64))], ["lang", "code", "n"])

        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                held.setdefault(lang, []).append(np.frombuffer(letters(text.as_py()), np.uint8))
                sizes[lang] = sizes.get(lang, 0) + len(held[lang][-1])
                if sizes[lang] >= most:
                    yield from part(lang)
        for lang in list(held):
            yield from part(lang)

    counted = drawn.select("text", "lang").mapInArrow(count, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n")).where((F.col("n") >= least) | (F.col("code") == ALL))
    got = counted.toArrow()
    which = np.array([names.index(x) for x in got["lang"].to_pylist()], np.int64)
    code, n = got["code"].to_numpy(), got["n"].to_numpy().astype(np.float64)
    every = np.ones(len(names))
    every[which[code == ALL]] = np.maximum(n[code == ALL], 1)
    which, n, code = which[code != ALL], n[code != ALL], code[code != ALL]
    codes, at = np.unique(code, return_inverse=True)
    freq = np.zeros((len(codes), len(names)))
    freq[at, which] = n
    again = np.where(freq > least, freq, 0)  # still known without the occurrence that is looked at
    for size in SIZES:
        own = (codes.astype(np.uint64) >> np.uint64(56)) == size
        freq[own] /= np.maximum(freq[own].sum(axis=0), 1)
    member = (freq > 0) & (freq >= share * freq.max(axis=1, keepdims=True))
    expected = (again * member).sum(axis=0) / every
    tables = np.zeros(((len(names) + 7) // 8, 1 << slots_log2), np.uint8)
    for k in range(len(names)):
        for s in slots(codes[member[:, k]].astype(np.uint64), slots_log2):
            np.bitwise_or.at(tables[k // 8], s, np.uint8(1 << k % 8))
    return LanguageFilter(names, prior, tables, slots_log2, expected)


def predict(docs: DataFrame, model: LanguageFilter, id_col: str = "doc_id", text_col: str = "text", keep: bool = False) -> DataFrame:
    """Per row: id_col, held_out, lang_pred, score; with keep, all columns of docs and then lang_pred, score and known, the share of n-grams that lang_pred holds against what is expected of its rows. Narrow."""
    lean(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    chosen = docs if keep else docs.select(id_col, text_col)
    text_at = chosen.columns.index(text_col)
    added = [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]
    schema = T.StructType([*chosen.schema.fields, *added, T.StructField("known", T.DoubleType())] if keep else [chosen.schema[id_col], T.StructField("held_out", T.BooleanType()), *added])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("")
        held = sent.value
        for batch in batches:
            got = [held.decide(t.as_py()) for t in batch.column(text_at)]
            first = batch.columns if keep else [batch.column(0), pa.array([crc_mod_py(i, 3) == 1 for i in batch.column(0).to_pylist()], pa.bool_())]
            last = [pa.array([g[2] for g in got], pa.float64())] if keep else []
            yield pa.RecordBatch.from_arrays([*first, pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64()), *last], schema.names)

    return chosen.mapInArrow(run, schema)


def training_rows(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The rows that op3 may learn from."""
    return docs.where(crc_mod(F.col(id_col), 3) != 1)
