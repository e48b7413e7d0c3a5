import random

import markerpanel.llm.decontamination as dc


def rows(seed=1):
    rng = random.Random(seed)
    word = lambda: rng.choice(["the", "Cat", "é", "x9", "über", "on", "mat", "Dog", "ran", "日本"])
    items = [(k, " ".join(word() for _ in range(rng.choice([0, 1, 4, 10, 11, 25])))) for k in range(25)] + [(None, "null id item with exactly ten words in it here ok"), (99, None), (7, "repeat"), (7, "repeat")]
    docs = []
    for k in range(120):
        t = [word() for _ in range(rng.randrange(30))]
        for _ in range(rng.randrange(3)):
            t += (rng.choice(items)[1] or "").replace(" ", rng.choice([" ", ", ", "\n-"])).split(" ")
        docs.append((k, " ".join(t)))
    return docs + [(500, None), (501, ""), (502, "null id item, with exactly TEN words in it here: ok!"), (503, "word " * 30000 + (items[5][1] or ""))], items


def frames(spark, docs, items):
    d = spark.createDataFrame([(a, b, "x") for a, b in docs], "doc_id long, text string, words string").repartition(5)
    return d, spark.createDataFrame([(a, b, 1) for a, b in items], "item_id long, text string, doc_id long")


def test_both_ways_against_brute_force(spark, monkeypatch):
    docs, items = rows()
    want = dc.brute(docs, [("" if i is None else i, t) for i, t in items])
    d, i = frames(spark, docs, items)
    for limit in (dc.BROADCAST_WORDS, 0):
        monkeypatch.setattr(dc, "BROADCAST_WORDS", limit)
        got = {r.doc_id: (r.n_words, r.n_hit, r.items_sha256) for r in dc.digest(dc.contaminated(d, i)).collect()}
        assert got == want


def test_empty(spark):
    docs, items = rows()
    d, i = frames(spark, docs, items)
    assert dc.contaminated(d.limit(0), i).count() == 0
    assert dc.digest(dc.contaminated(d, i.limit(0))).filter("contaminated").count() == 0
