import random

from markerpanel.llm import line_dedup as ld
from markerpanel.llm.common import one_row_per_id


def corpus(seed=4):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)] + ["The", "of", "and"] * 40
    bases = [[rng.choice(words) for _ in range(rng.choice([3, 5, 8, 20, 40]))] for _ in range(25)]
    rows = []
    for d in range(60):
        lines = []
        for _ in range(rng.randrange(6)):
            line = list(rng.choice(bases))
            for _ in range(rng.randrange(5)):
                line[rng.randrange(len(line))] = rng.choice(words)
            if rng.random() < 0.3:
                rng.shuffle(line)
            lines.append(rng.choice([" ", "  ", "\t"]).join(line))
        rows.append((d, "\n".join(lines)))
    return [*rows, (80, None), (81, ""), (82, "\n\n"), (83, rows[7][1] + "\n" + rows[7][1]), (None, rows[8][1])]


def test_against_brute_force(spark):
    rows = corpus()
    df = spark.createDataFrame([(a, b, 1) for a, b in rows], "doc_id long, text string, line int").repartition(4)
    docs = one_row_per_id(df.select("doc_id", "text"))
    from pyspark.sql import functions as F

    digests = lambda df: {r.doc_id: (r.n_lines, r.n_removed, r.s) for r in df.select("*", F.sha2(F.coalesce("text", F.lit("")), 256).alias("s")).collect()}
    got = digests(ld.deduplicated(docs))
    want = {ld.NULL_ID if d is None else d: v for d, v in ld.brute(rows).items()}
    assert got == want
    # short lists send lines to the later rounds, small groups to blocks
    assert digests(ld.deduplicated(docs, most=1)) == want
    assert digests(ld.deduplicated(docs, most=2, group=4)) == want
    assert sum(v[1] for v in want.values()) > 20
    assert ld.deduplicated(docs.limit(0)).count() == 0


def test_short_lines(spark):
    rows = [
        (1, "All rights reserved.\nfour words in it\nHome\n\n"),
        (2, "all rights RESERVED.\nfour words in it too\nrights reserved.\n" + "no " * 40 + "yes maybe so"),
        (3, "reserved. All rights\nhome\n\n \t" + "\nyes no maybe so " * 9),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    got = {r.doc_id: (r.text, r.n_lines, r.n_removed) for r in ld.deduplicated(docs).collect()}
    # three words of four are 0.75 similar, four of five are 0.8; lines without words stay
    assert got == {
        1: (rows[0][1], 5, 0),
        2: ("rights reserved.\n" + "no " * 40 + "yes maybe so", 4, 2),
        3: ("\n \t", 13, 11),
    }
    brute = ld.brute(rows)
    assert {k: v[1:] for k, v in got.items()} == {k: v[:2] for k, v in brute.items()}


def test_no_smaller_set_can_match(spark):
    # sets of three words and fewer against their supersets and subsets, at several thresholds
    lines = ["a", "a b", "a b c", "a b c d", "a b c d e", "b c d e", "x y", "y x", "x y z q r s t u v w", "x y z q r s t u v"]
    rows = list(enumerate(lines))
    for least in (50, 67, 75, 80, 90):
        got = {r.doc_id: (r.n_lines, r.n_removed) for r in ld.deduplicated(spark.createDataFrame(rows, "doc_id long, text string"), least).collect()}
        assert got == {k: v[:2] for k, v in ld.brute(rows, least).items()}, least


def near_copies(n=300, size=30, seed=6):
    """Sets that drift away from one another word by word: each is similar to its neighbours, not to the first."""
    rng = random.Random(seed)
    line, rows = [f"k{i}" for i in range(size)], []
    for d in range(n):
        line = list(line)
        line[rng.randrange(size)] = f"x{rng.randrange(60)}"
        rows.append((d, " ".join(line)))
    return [*rows, (n, rows[0][1] + "\n" + rows[n // 2][1]), (n + 1, " ".join(f"long{i}" for i in range(20_000)) + "\n" + "\n" * 5000 + " ".join(f"long{i}" for i in range(500, 20_000)))]


def test_drifting_lines_and_a_very_long_text(spark):
    rows = near_copies()
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = {k: v[:2] for k, v in ld.brute(rows).items()}
    for most in (1, 16):
        assert {r.doc_id: (r.n_lines, r.n_removed) for r in ld.deduplicated(docs, most=most).collect()} == want, most


def test_rows_stay_in_proportion_to_lines(spark):
    # a group of near copies: every pair is similar, but each posting has one row
    rows = [(d, " ".join([f"k{i}" for i in range(40)] + [f"own{d}"])) for d in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    held = spark.sparkContext.broadcast(ld.rarity(docs))
    lines = ld._lines(docs, held, 80, 1, ld.GROUP).cache()
    n = ld._postings(lines, ld.F.lit(True)).count()
    assert ld._candidates(ld._postings(lines, ld.F.lit(True)), 80, 16).count() <= n
    assert ld.line_matches(docs).count() == 399


def test_repeated_rows_and_clashing_columns(spark):
    rows = [(1, "a b c d e", 5), (1, "a b c d f", 6), (2, "a b c d f\nkeep me here now", 7), (2, "a b c d f\nkeep me here now", 7), (None, None, 1)]
    df = spark.createDataFrame(rows, "doc_id int, text string, line int")
    got = {r.doc_id: (r.text, r.n_removed) for r in ld.deduplicated(one_row_per_id(df)).collect()}
    assert got == {1: ("a b c d f", 0), 2: ("keep me here now", 1), ld.NULL_ID: (None, 0)}
