import random

from markerpanel.llm import near_duplicates as nd
from markerpanel.llm.components import components


def corpus(seed=2):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(4000)]
    rows, k = [], 0
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.choice([4, 30, 150, 400]))]
        for _ in range(rng.choice([1, 3, 20])):
            own = list(base)
            for _ in range(rng.randrange(0, 6)):
                at = rng.randrange(len(own))
                own[at : at + rng.randrange(2)] = [rng.choice(words)] * rng.randrange(2)
            rows.append((k, rng.choice([" ", "  ", "\n"]).join(own if rng.random() < 0.8 else map(str.upper, own))))
            k += 1
    rows += [(900, None), (901, ""), (902, " \t\n"), (903, "one two"), (904, "ONE  two"), (905, "one two three"), (906, rows[5][1])]
    rng.shuffle(rows)
    return rows


def test_against_brute_force(spark, monkeypatch):
    rows = corpus()
    want = nd.brute(rows)
    df = spark.createDataFrame([(a, b, 1, "x") for a, b in rows], "doc_id long, text string, n int, kept string").repartition(4)
    for ids in (nd.BROADCAST_IDS, 0):
        monkeypatch.setattr(nd, "BROADCAST_IDS", ids)
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in nd.near_duplicates(df).collect()}
        assert got == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in nd.near_duplicates(df).collect())


def test_odd_rows(spark):
    text = "a b c d e f g h i j k"
    df = spark.createDataFrame([(None, text), (4, text), (4, text), (4, None), (7, "zz")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in nd.near_duplicates(df).collect()), key=str)
    assert got == [(4, None, False), (7, 7, True), (None, None, True)]
    assert nd.near_duplicates(df.limit(0)).count() == 0


def test_components(spark):
    rng = random.Random(1)
    edges = [(k, k + 1) for k in range(60)] + [(rng.randrange(100, 200), rng.randrange(100, 200)) for _ in range(60)] + [(5, 5), (300, 299), (299, 300)]
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        p, q = root(a), root(b)
        parent[max(p, q)] = min(p, q)
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: root(x) for a, b in edges if a != b for x in (a, b)}


def test_components_by_one_task_and_by_rounds(spark):
    rng = random.Random(3)
    edges = [(k, k + 1) for k in range(1000, 1040)] + [(rng.randrange(60) * 7, rng.randrange(60) * 7) for _ in range(45)] + [(5, 5), (-3, 2**62)]
    df = spark.createDataFrame(edges, "a long, b long")
    got = [sorted(map(tuple, components(df, solo).collect())) for solo in (10**6, 0)]
    assert got[0] == got[1] and (2**62, -3) in got[0] and (1040, 1000) in got[0]
    assert components(df.limit(0)).count() == 0


def test_very_long_and_very_short_texts(spark):
    rng = random.Random(5)
    long_ = [f"w{rng.randrange(50_000)}" for _ in range(60_000)]
    rows = [(1, " ".join(long_)), (2, " ".join(long_[:55_000])), (3, " ".join(long_[:20_000])), (4, "one two"), (5, "ONE  two"), (6, "two one"), (7, "a b c d"), (8, "a b c d"), (9, " \n"), (10, None), (10, "one"), (11, "one")]
    df = spark.createDataFrame([(a, b, 1, "x") for a, b in rows], "doc_id long, text string, n long, band string").repartition(3)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in nd.near_duplicates(df).collect()}
    assert got == nd.brute([r for r in rows if r != (10, None)])
