import random

import pytest
import sentencepiece

from markerpanel.llm.common import public_file
from markerpanel.llm.piece_codec import PieceCodec, encode_documents

FILE = public_file("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def both():
    return PieceCodec(FILE), sentencepiece.SentencePieceProcessor(model_file=FILE)


FIXED = ["", " ", "  ", "a", " a", "a ", "a\n\n b\t", "a\x00b", "<s>x</s>", "▁▁a", "<0x0A>", "ﬁ 日本語 テスト", "👩‍👩‍👧 ok", "a" * 500, " " * 70, "x" + " " * 37 + "y", "é" * 33, "the the  the   the", "\r\n", "﻿a", "aaaaaaaaaaaaaaab", "1234567890" * 20, "=" * 99, "        def f(x):\n            return  x"]


@pytest.mark.parametrize("text", FIXED)
def test_fixed(both, text):
    ours, library = both
    ids = library.encode(text) + [library.eos_id()]
    assert ours.encode(text) == ids
    assert ours.decode(ids) == library.decode(ids)


def test_random(both):
    ours, library = both
    rng = random.Random(5)
    letters = ["abcdefgh eits", "  \n\t.,", "éàüß日本", "the and ing", "01239", "▁ a", "🙂x", "eeeeeetttt  "]
    for _ in range(4000):
        text = "".join(rng.choice(rng.choice(letters)) for _ in range(rng.randrange(1, 60)))
        ids = library.encode(text) + [library.eos_id()]
        assert ours.encode(text) == ids, text
        assert ours.decode(ids) == library.decode(ids), text


def test_decode_of_any_ids(both):
    ours, library = both
    rng = random.Random(6)
    for _ in range(500):
        ids = [rng.choice([rng.randrange(3, 32000), rng.randrange(3, 259)]) for _ in range(rng.randrange(12))]
        assert ours.decode(ids) == library.decode(ids), ids


def test_rows(spark, both):
    _, library = both
    rows = [(1, None, "x"), (2, "", "y"), (None, "the cat", "z"), (3, "the cat", None), (3, "the cat", None)]
    got = encode_documents(spark.createDataFrame(rows, "doc_id long, text string, ids string"), FILE).collect()
    assert sorted((r.doc_id or 0, r.decoded, r.n_tokens, r.ids == (library.encode(r.decoded) + [2])) for r in got) == [(0, "the cat", 3, True), (1, "", 1, True), (2, "", 1, True), (3, "the cat", 3, True), (3, "the cat", 3, True)]
    assert encode_documents(spark.createDataFrame([], "doc_id long, text string"), FILE).count() == 0
