"""Token counts of a unigram tokenizer without its tokens.

An Aho-Corasick automaton lists the vocabulary pieces that end at each position; dynamic
programming carries only the best score and its number of pieces. Ties are those of the
tokenizers library: a path replaces the kept one only if its score is strictly higher, and
paths are offered by rising start, so of equal ones the longest last piece stays. A start
without a piece of one code point offers that code point as unknown, ten below the lowest
score; an unknown code point counts as one token for each of its UTF-8 bytes where the
vocabulary has them all, and otherwise a run of unknowns counts as one.

Rows: null and empty text count no tokens; every input row gives one output row; extra
columns are ignored; an empty table gives an empty result; texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from probejoin.llm.common import HELD, lean, only

SPACE = "▁"
#: How far an unknown code point scores below the lowest piece (fixed value of the library).
PENALTY = 10.0
KEPT = 300_000
_COUNTERS: dict[str, "UnigramCounter"] = {}
HELD["unigram"] = _COUNTERS


def pieces_of(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece file, in the order of their ids."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(model.id_to_piece(i), model.get_score(i)) for i in range(model.vocab_size())]


class UnigramCounter:
    def __init__(self, pieces: Sequence[tuple[str, float]], unknown: int = 0):
        import ahocorasick

        self.automaton = ahocorasick.Automaton()
        for piece, score in dict(pieces).items():
            if piece:
                self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        names = {p for p, _ in pieces}
        self.bytes = all(f"<0x{b:02X}>" in names for b in range(256))
        self.low = min(s for _, s in pieces) - PENALTY
        self.kept: dict[str, tuple[int, float]] = {}

    def chunk(self, chunk: str) -> tuple[int, float]:
        """Pieces and best score of one run of text."""
        n = len(chunk)
        ends: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        for end, got in self.automaton.iter(chunk):
            ends[end].append(got)
        best, count, fused = [0.0] * (n + 1), [0] * (n + 1), [False] * (n + 1)
        for end in range(n):
            top, tokens, unknown, single = None, 0, False, False
            for length, score in ends[end]:  # longest first: by rising start
                start = end + 1 - length
                offer = best[start] + score
                if top is None or offer > top:
                    top, tokens, unknown = offer, count[start] + 1, False
                single = single or length == 1
            if not single:
                offer = best[end] + self.low
                if top is None or offer > top:
                    more = len(chunk[end].encode("utf-8", "surrogatepass")) if self.bytes else int(not fused[end])
                    top, tokens, unknown = offer, count[end] + more, True
            best[end + 1], count[end + 1], fused[end + 1] = top, tokens, unknown
        return count[n], best[n]

    def count(self, text: str | None) -> tuple[int, float]:
        """Of a whole text: every space becomes the mark, one mark is put before it where there is none, and each mark opens a run."""
        if not text:
            return 0, 0.0
        text = text.replace(" ", SPACE)
        first, *rest = text.split(SPACE) if text[0] != SPACE else text[1:].split(SPACE)
        tokens, score, kept = 0, 0.0, self.kept
        for part in (first, *rest):
            got = kept.get(part)
            if got is None:
                got = self.chunk(SPACE + part)
                if len(part) < 64:
                    if len(kept) >= KEPT:
                        kept.clear()
                    kept[part] = got
            tokens += got[0]
            score += got[1]
        return tokens, score


def counter(path: str) -> UnigramCounter:
    if path not in _COUNTERS:
        _COUNTERS[path] = UnigramCounter(pieces_of(path))
    return _COUNTERS[path]


def count_tokens(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id_col, n_tokens long, score double (of the best path). Narrow: no shuffle."""
    lean(docs.sparkSession)
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("unigram")
        held = counter(vocabulary)
        for batch in batches:
            got = [held.count(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.float64())], schema.names)

    return docs.select(id_col, text_col).mapInArrow(run, schema)
