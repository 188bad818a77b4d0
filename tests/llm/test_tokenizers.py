"""Exact agreement with the tokenizers library."""

import hashlib
import random

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer, models, pre_tokenizers

from probejoin.llm import bpe, common, unigram

BPE, PIECES = public_tokenizers.path("word_bpe_49k.json"), public_tokenizers.path("piece_bpe_32k.model")


def odd_texts(n, alphabet, longest, seed=1):
    rnd = random.Random(seed)
    return ["".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, longest))) for _ in range(n)]


TEXTS = ["", "  ", "a\x1cb", "x<|endoftext|>y <|startoftext|>", "<|ENDOFTEXT|>", "<|endoftext|", "İstanbul ß ſ ﬁ ǅ Å̊ é ́a", "it's we'll I'D don't'''s", "1234 ½²③", "漢字かな 한국어", "👍🏽👨‍👩‍👧 ok", "a" * 23 + " " + "b" * 9, "\x00\x7f\xad\xa0z"]


def test_bpe_is_exact():
    library, own = Tokenizer.from_file(BPE), bpe.PrefixEncoder(BPE)
    for text in [*TEXTS, *odd_texts(800, "abcdeéèßİΣς'. \n\t  漢12!?<|>ñǆ̧́", 40), *odd_texts(800, "aabin thero", 30)]:
        ids = library.encode(text, add_special_tokens=False).ids
        assert own.encode(text) == (len(ids), " ".join(map(str, ids)), library.decode(ids, skip_special_tokens=False)), text
    assert all(own.whole(t) for t in list(own.parts)[::50])


def test_bpe_rows(spark):
    rows = [(1, "Hello world"), (None, None), (3, ""), (3, ""), (4, "lower case " * 5000)]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, n_tokens string")
    got = bpe.encode(df, BPE, texts=True).collect()
    library = Tokenizer.from_file(BPE)
    assert len(got) == len(rows)
    for r, (i, t) in zip(sorted(got, key=lambda r: (r["doc_id"] or 0, r["n_tokens"])), sorted(rows, key=lambda r: (r[0] or 0)), strict=True):
        ids = library.encode(t or "", add_special_tokens=False).ids
        assert (r["doc_id"], r["n_tokens"], r["ids"]) == (i, len(ids), ids)
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
    assert bpe.encode(df.limit(0), BPE).count() == 0


@pytest.mark.parametrize("small", [False, True])
def test_unigram_is_exact(small):
    pieces = [("<unk>", 0.0), *((w, float(s)) for w, s in {"▁": -1, "a": -1, "b": -1, "ab": -2, "ba": -2, "aba": -3, "▁a": -2, "bb": -1, "▁ab": -3}.items())] if small else unigram.pieces_of(PIECES)
    library = Tokenizer(models.Unigram(pieces, 0, not small))
    library.pre_tokenizer = pre_tokenizers.Metaspace(replacement="▁", prepend_scheme="always", split=True)
    own = unigram.UnigramCounter(pieces)
    for text in ["", " ", "a ", "▁a", "a▁b", *odd_texts(1500, "ab cd" if small else "abthe er in \n\t 漢👍é▁<0x>", 30)]:
        assert own.count(text)[0] == len(library.encode(text, add_special_tokens=False).ids), text


def test_unigram_rows(spark):
    df = spark.createDataFrame([(1, "the cat"), (None, None), (2, "")], "doc_id long, text string")
    assert sorted(r["n_tokens"] for r in unigram.count_tokens(df, PIECES).collect())[:2] == [0, 0]


def test_encoder_keeps_no_second_vocabulary():
    """Pipeline workers also hold what Spark holds: powers of earlier stages go, and chunks of one token share the names."""
    common.prefix_hash(np.zeros(100_000, np.uint8), common.BASES[0])
    common.only("bpe")
    assert not common._POWERS
    enc = bpe.encoder(BPE)
    assert not any(type(v).__name__ == "Tokenizer" for v in vars(enc).values())
    n, ids, name = enc.chunk("the")
    assert n == 1 and ids is enc.digits[int(ids)] and name is enc.names[int(ids)]
