"""Byte-pair encoding by a table over prefixes.

For every prefix of a word exactly one token can be the last one of its encoding. An
automaton over the vocabulary lists the tokens that end at each position, longest first;
the first whose predecessor (the last token of the prefix before it) may stand next to it
is the one. Following the back-pointers from the whole word gives the exact ids.

Rows: null text counts as empty (no tokens, digests of the empty string); ids may be null
or repeat, every input row gives one output row; extra columns are ignored; an empty table
gives an empty result. Texts of any length are encoded whole.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from probejoin.llm.common import HELD, ODD_SPACE, lean, only

#: Entries of a generation of what a worker keeps of chunks, twice those of words and half those of pairs; other operators' tasks drop it.
KEPT = 100_000
_END = 0x10000
_ENCODERS: dict[str, "PrefixEncoder"] = {}
HELD["bpe"] = _ENCODERS


class Kept:
    """A memory of two generations: what was not asked for since the last change of generation is forgotten."""

    def __init__(self, size: int):
        self.size, self.young, self.old = size, {}, {}

    def get(self, key):
        got = self.young.get(key)
        if got is None:
            got = self.old.get(key)
            if got is not None:
                self.put(key, got)
        return got

    def put(self, key, value) -> None:
        if len(self.young) >= self.size:
            self.old, self.young = self.young, {}
        self.young[key] = value


class PrefixEncoder:
    """Encoder for a tokenizers file with a BPE model and a suffix for the end of words."""

    def __init__(self, path: str):
        import ahocorasick
        import regex
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        library = Tokenizer.from_file(path)
        self.normalizer, self.pre_tokenizer = library.normalizer, library.pre_tokenizer  # not its vocabulary, which is here already
        del library
        self.suffix = model["end_of_word_suffix"] or ""
        self.vocab: dict[str, int] = model["vocab"]
        self.names = {i: s for s, i in self.vocab.items()}
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.made: dict[int, int] = {}
        for k, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            x, y, z = self.vocab[a], self.vocab[b], self.vocab[a + b]
            both = (x, y)
            self.rank.setdefault(both, k)
            if z not in self.parts:
                self.parts[z], self.made[z] = both, k
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names |= {i: s for s, i in self.specials.items()}
        #: Ids as text: a chunk of one token keeps this one and its name, and no copies.
        self.digits = {i: str(i) for i in self.names}
        self.special_cut = regex.compile("(" + "|".join(regex.escape(s) for s in self.specials) + ")") if self.specials else None
        self.automaton = ahocorasick.Automaton()
        for s, i in self.vocab.items():
            word = self.folded(s)
            if word and s not in self.specials and self.whole(i):
                self.automaton.add_word(word, (len(word), i))
        self.automaton.make_automaton()
        self.plain = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.white = regex.compile(r"[\t\n\x0b\x0c\r \x85\xa0  -     　]+")
        #: Code points that NFC leaves alone and whose lower case is one code point: ASCII and the letters of Latin-1.
        self.easy = regex.compile("[\x21-\x7e\xc0-\xd6\xd8-\xf6\xf8-\xff]+")
        self.byte_table = str.maketrans({chr(b): c for b, c in self._byte_names().items()})
        self.pairs: dict[tuple[int, int], bool] = {}
        self.words = Kept(KEPT // 2)  # asked only for chunks that are not kept
        self.chunks = Kept(KEPT)

    @staticmethod
    def _byte_names() -> dict[int, str]:
        """Printable stand-ins of bytes: printable Latin-1 stands for itself, the rest follow from 256 on."""
        shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
        rest = [b for b in range(256) if b not in set(shown)]
        return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(rest)}

    def folded(self, name: str) -> str:
        """Token name or word with its last letter and the word end as one symbol."""
        if self.suffix and name.endswith(self.suffix) and len(name) > len(self.suffix):
            body = name[: -len(self.suffix)]
            return body[:-1] + chr(_END + ord(body[-1]))
        return name

    def _spine(self, token: int, right: bool) -> list[tuple[int, int, float]]:
        """Pieces at one edge of a token: (piece, rank at which it arises, rank at which it is used up)."""
        out, used = [], float("inf")
        while True:
            arises = self.made.get(token, -1)
            out.append((token, arises, used))
            if token not in self.parts:
                return out
            used, token = arises, self.parts[token][right]

    def clashes(self, a: int, b: int, before: float = float("inf")) -> bool:
        """Whether a merge across the border of a and b, of a rank below before, comes before both are complete.

        Of equal ranks the leftmost goes first, so a piece on the left that is used up at
        the rank of the crossing merge is gone, one on the right is still there.
        """
        left = self._spine(b, False)
        for x, x_from, x_to in self._spine(a, True):
            for y, y_from, y_to in left:
                m = self.rank.get((x, y))
                if m is not None and m < before and x_from < m < x_to and y_from < m <= y_to:
                    return True
        return False

    def fits(self, a: int, b: int) -> bool:
        """Whether a and b stay two tokens when they stand side by side."""
        got = self.pairs.get((a, b))
        if got is None:
            if len(self.pairs) >= 2 * KEPT:
                self.pairs.clear()
            got = self.pairs[a, b] = not self.clashes(a, b)
        return got

    def whole(self, token: int) -> bool:
        """Whether merging the token's own name gives the token; others never occur."""
        made = [token]
        while made:
            t = made.pop()
            if t in self.parts:
                if self.clashes(*self.parts[t], self.made[t]):
                    return False
                made += self.parts[t]
        return True

    def word(self, word: str) -> tuple[int, ...]:
        """Ids of one pre-token written in byte stand-ins."""
        symbols = word[:-1] + chr(_END + ord(word[-1])) if self.suffix else word
        n = len(symbols)
        tokens, starts = [-1] * (n + 1), [0] * (n + 1)
        pairs, fits, done = self.pairs, self.fits, 0
        for end, (length, token) in self.automaton.iter(symbols):
            if done > end:
                continue
            start = end + 1 - length
            if start:
                before = tokens[start]
                if before < 0:
                    continue
                fit = pairs.get((before, token))
                if fit is None:
                    fit = fits(before, token)
                if not fit:
                    continue
            done = end + 1
            tokens[done], starts[done] = token, start
        out: list[int] = []
        at = n
        while at:
            if tokens[at] < 0:
                raise ValueError(f"the vocabulary has no symbol for a part of {word!r}")
            out.append(tokens[at])
            at = starts[at]
        return tuple(out[::-1])

    def piece(self, piece: str) -> tuple[int, ...]:
        """Ids of one pre-token of an easy chunk, as it is read."""
        got = self.words.get(piece)
        if got is None:
            got = self.word(piece if piece.isascii() else piece.encode().decode("latin-1").translate(self.byte_table))
            self.words.put(piece, got)
        return got

    def ids(self, chunk: str) -> list[int]:
        if chunk.isascii():  # a word, or a word and one mark, needs no pattern
            if chunk.isalpha():
                return [*self.piece(chunk.lower())]
            if chunk[-1] in ",.;:!?" and chunk[:-1].isalpha():
                return [*self.piece(chunk[:-1].lower()), *self.piece(chunk[-1])]
        elif chunk.isalpha() and self.easy.fullmatch(chunk):
            return [*self.piece(chunk.lower())]
        out: list[int] = []
        parts = self.special_cut.split(chunk) if self.special_cut is not None and "<|" in chunk else [chunk]
        for part in parts:
            if part in self.specials:
                out.append(self.specials[part])
            elif self.easy.fullmatch(part):
                for piece in self.plain.findall(part.lower()):
                    out += self.piece(piece)
            elif part:
                text = self.normalizer.normalize_str(part) if self.normalizer else part
                for piece, _ in self.pre_tokenizer.pre_tokenize_str(text):
                    out += self.word(piece)
        return out

    def chunk(self, chunk: str) -> tuple[int, str, str]:
        """Count, ids and decoded text of what stands between white space."""
        got = self.chunks.get(chunk)
        if got is None:
            ids = self.ids(chunk)
            got = (len(ids), " ".join([self.digits[i] for i in ids]), " ".join([self.names[i] for i in ids]))
            if len(chunk) < 64:
                self.chunks.put(chunk, got)
        return got

    def encode(self, text: str | None) -> tuple[int, str, str]:
        """Number of tokens, their ids and the decoded text; the parts join with one space, as the vocabulary has no decoder."""
        if not text:
            return 0, "", ""
        odd = any(c in text for c in ODD_SPACE)
        pieces = self.white.split(text) if odd else text.split()
        get, own = self.chunks.young.get, self.chunk
        got = [get(c) or own(c) for c in pieces if c]
        return sum([g[0] for g in got]), " ".join([g[1] for g in got if g[0]]), " ".join([g[2] for g in got if g[0]])


def encoder(path: str) -> PrefixEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = PrefixEncoder(path)
    return _ENCODERS[path]


def encode(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", texts: bool = False) -> DataFrame:
    """Per row: id_col, n_tokens, ids_sha256, decoded_sha256; with texts also ids (array) and decoded.

    vocabulary is a tokenizers file that every executor has. Narrow: no shuffle.
    """
    from pyspark.sql import types as T

    lean(docs.sparkSession)
    kind = docs.schema[id_col].dataType
    fields = [T.StructField(id_col, kind), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    if texts:
        fields += [T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("decoded", T.StringType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("bpe")
        enc = encoder(vocabulary)
        for batch in batches:
            counts, ids, decoded, lists, plain = [], [], [], [], []
            for text in batch.column(1):
                n, i, d = enc.encode(text.as_py())
                counts.append(n)
                ids.append(hashlib.sha256(i.encode()).hexdigest())
                decoded.append(hashlib.sha256(d.encode()).hexdigest())
                if texts:
                    lists.append([int(x) for x in i.split()])
                    plain.append(d)
            columns = [batch.column(0), pa.array(counts, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())]
            if texts:
                columns += [pa.array(lists, pa.list_(pa.int32())), pa.array(plain, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, [f.name for f in fields])

    return docs.select(id_col, text_col).mapInArrow(run, T.StructType(fields))
