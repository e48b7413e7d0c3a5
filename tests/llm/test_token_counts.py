import random

import pytest
from tokenizers import Tokenizer

from markerpanel.llm.common import public_file
from markerpanel.llm.token_counts import Transducer, compose, count_tokens, scan

FILE = public_file("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def both():
    return Transducer(FILE), Tokenizer.from_file(FILE)


FIXED = ["", " ", "a", "I'll've don't 's''s 'x", " 's", "x's", "''s", "!'s", "a  b", "a \n b", "a\n", "a \n", "\n\na", "a\tb", "\t\tb", " \tb", "<|endoftext|>", "a<|endoftext|> b <|endoftext|><|endof", "日本語 テスト", "🙂🙂 x", "1a2b ³½", "a\x1cb \x1d", "a 　b", "a" * 700, " " * 99 + "x", "!!!???'re 're", "'lls", "'S", "é'd", "a.'t", "9's", "\r\n\r\nx"]


@pytest.mark.parametrize("text", FIXED)
def test_fixed(both, text):
    assert both[0].count(text) == len(both[1].encode(text, add_special_tokens=False).ids)


def test_random(both):
    rng = random.Random(3)
    letters = ["abcdefgh", "  ", "\n\t.,", "éàü日本", "'", "sdtmrevl", "0129", "the ing", "🙂!?"]
    for _ in range(6000):
        text = "".join(rng.choice(rng.choice(letters)) for _ in range(rng.randrange(1, 50)))
        assert both[0].count(text) == len(both[1].encode(text, add_special_tokens=False).ids), repr(text)


def test_cuts_at_every_place(both):
    rng = random.Random(9)
    texts = [x for x in FIXED if len(x) < 120] + ["the cat  sat\n on <|endoftext|> the 'mat'll  do  <|endoftext|>x \n\n", "  \n a", "word" * 30]
    texts += ["".join(rng.choice(["ab", " ", "  ", "\n", "'s", "é", "7", "<|endoftext|>", "!?"]) for _ in range(14)) for _ in range(60)]
    for text in texts:
        want = len(both[1].encode(text, add_special_tokens=False).ids)
        for k in range(len(text) + 1):
            assert compose(both[0].state_map(text[:k]), both[0].state_map(text[k:])).tokens() == want, (text, k)
        for size in (1, 2, 3, 7):
            maps = [both[0].state_map(text[k : k + size]) for k in range(0, len(text), size)]
            if maps:
                done = scan(maps)
                assert done[-1].tokens() == want, (text, size)
                assert [x.tokens() for x in done] == [both[0].count(text[: (k + 1) * size]) for k in range(len(maps))]
                state, n = "", 0
                for m in maps:  # read one after another
                    if both[0].starts_anew(state, m.head or m.tail):
                        n, state = n + both[0].whole(state), ""
                    state, more = m(state)
                    n += more
                assert n + both[0].whole(state) == want, (text, size)


def test_maps_compose_associatively(both):
    a, b, c = (both[0].state_map(w) for w in ("the ca", "t sat  ", " on the"))
    one, two = compose(compose(a, b), c), compose(a, compose(b, c))
    assert [(m.head, m.middle, m.tail) for m in (one, two)] == [("the", 2, " the")] * 2 or one.tokens() == two.tokens()


def test_tables_start_again(both, monkeypatch):
    import markerpanel.llm.token_counts as tc

    monkeypatch.setattr(tc, "MOST_STATES", 50)
    text = " ".join(f"wörd{k} thing{k * 7}" for k in range(900))
    assert Transducer(FILE).count(text) == len(both[1].encode(text, add_special_tokens=False).ids)


def test_rows(spark, both):
    rows = [(1, None, 5), (2, "", 5), (None, "the cat", None), (3, "the cat " * 400, 1), (3, "the cat " * 400, 1)]
    got = count_tokens(spark.createDataFrame(rows, "doc_id long, text string, n_tokens int"), FILE).collect()
    assert sorted((r.doc_id or 0, r.n_bytes, r.n_tokens, r.over_limit) for r in got) == [(0, 7, 2, False), (1, 0, 0, False), (2, 0, 0, False), (3, 3200, 801, True), (3, 3200, 801, True)]
    assert count_tokens(spark.createDataFrame([], "doc_id long, text string"), FILE).count() == 0
