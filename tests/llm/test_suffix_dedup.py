import random

import numpy as np
import pytest

from markerpanel.llm import suffix_dedup as sd
from markerpanel.llm.common import one_row_per_id


@pytest.mark.parametrize("seed", range(6))
def test_suffix_order_and_lpf(seed):
    rng = random.Random(seed)
    data = np.array([rng.randrange(rng.choice([1, 2, 5])) for _ in range(rng.choice([1, 2, 60, 200]))])
    s, n = data.tolist(), len(data)
    for depth in (1, 3, 7, 100):
        order = sd.suffix_array(data, depth)
        assert order.tolist() == sorted(range(n), key=lambda k: (s[k : k + depth], k))
        want = [max((next((m for m in range(min(depth, n - k), 0, -1) if s[j : j + m] == s[k : k + m]), 0) for j in range(k)), default=0) for k in range(n)]
        assert sd.longest_previous_factors(data, order, depth).tolist() == want


def corpus(seed=1):
    rng = random.Random(seed)
    text = lambda n: "".join(rng.choice(["ab", "c ", "dé", "ef", "\n", "gh", "日"]) for _ in range(n))
    shared = [text(n) for n in (40, 55, 60, 90, 200, 400)]
    rows = []
    for d in range(80):
        parts = [text(rng.randrange(80))]
        for _ in range(rng.randrange(4)):
            x = rng.choice(shared)
            a = rng.randrange(len(x))
            parts += [rng.choice([x, x[a:], x[:a], x]), text(rng.randrange(60))]
        rows.append((d, "".join(parts)))
    return [*rows, (100, rows[3][1]), (101, rows[3][1]), (102, None), (103, ""), (104, "a" * 99), (105, "a" * 100), (106, "a" * 350), (107, "ab" * 300), (108, "x" + "a" * 120), (None, rows[9][1]), (110, shared[5] * 3), (111, text(40000))]


def test_against_brute_force(spark, monkeypatch):
    rows = corpus()
    df = spark.createDataFrame([(a, b, 7) for a, b in rows], "doc_id long, text string, h int").repartition(5)
    docs = one_row_per_id(df.select("doc_id", "text"))
    from pyspark.sql import functions as F

    want = {sd.NULL if d is None else d: v for d, v in sd.brute(rows).items()}
    for size in (sd.SORT_BYTES, 500):
        monkeypatch.setattr(sd, "SORT_BYTES", size)
        got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.s) for r in sd.cleaned(docs).select("*", F.sha2("kept", 256).alias("s")).collect()}
        assert got == want
    assert sum(v[1] > 0 for v in want.values()) > 30
    assert sd.cleaned(docs.limit(0)).count() == 0


def test_repeated_rows(spark):
    text = "the cat sat on the mat and " * 10
    df = spark.createDataFrame([(1, text), (1, text), (1, None), (2, text)], "doc_id long, text string")
    got = {r.doc_id: r.n_removed for r in sd.cleaned(one_row_per_id(df)).collect()}
    assert got == {d: v[1] for d, v in sd.brute([(1, text), (2, text)]).items()}
