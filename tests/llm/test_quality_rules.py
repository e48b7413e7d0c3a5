import random
import re

from markerpanel.llm import quality_rules as qr

GAP = r"[^\x20\x09-\x0D]+"


def brute(text):
    text = text or ""
    w = re.findall(GAP, text)
    seen, hit = {}, set()
    for i in range(len(w) - 7):
        seen.setdefault(tuple(w[i : i + 8]), []).append(i)
    for at in seen.values():
        if len(at) > 1:
            for i in at:
                hit.update(range(i, i + 8))
    lines = [x for x in text.split("\n") if re.search(GAP, x)]
    return len(w), sum(map(len, w)), sum(c in qr.SYMBOLS for c in text), len(lines) - len(set(lines)), len(hit)


def corpus():
    rng = random.Random(3)
    words = ["a", "bb", "é", "#x", "日本", "end.", "|", "!!"]
    texts = [None, "", " \n\t ", "one", "a b c d e f g h " * 5, "a b c d e f g h", "x\x0by\x0cz\rq", "l\nl\nl\n\nm", " lead", "trail \n", "nb\xa0sp a b\x1cc"]
    for _ in range(150):
        base = [rng.choice(words) for _ in range(rng.randrange(1, 40))]
        texts.append("".join(w + rng.choice([" ", "  ", "\n", "\t"]) for w in base * rng.choice([1, 1, 2, 3])))
    return [*texts, "w " * 5000, texts[7]]


def test_measures_against_brute_force(spark):
    rows = [(i if i % 50 else None, t, "x", 1) for i, t in enumerate(corpus())]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_words string, kept int").repartition(3)
    got = qr.apply_policy(qr.ledger(df)).collect()
    want = sorted([(i or -1, *brute(t)) for i, t, *_ in rows])
    assert sorted((r.doc_id or -1, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == want
    for r in got:
        assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words)
        assert not (r.base_failed and r.kept)


def test_policies_and_ablation(spark):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(corpus())], "doc_id long, text string")
    led = qr.ledger(df)
    bits = [r.failure_bits for r in led.collect()]
    whole = qr.mask(qr.POLICIES["v1"])
    got = {r.rule: (r.n_rejected, r.n_only, r.n_kept_without) for r in qr.ablation(led).collect()}
    for rule in qr.POLICIES["v1"]:
        b = qr.mask([rule])
        assert got[rule] == (sum(bool(x & b) for x in bits), sum(x & whole == b for x in bits), sum(x & whole in (0, b) for x in bits))
    assert qr.apply_policy(led, "base").filter("kept").count() >= qr.apply_policy(led).filter("kept").count()
    assert qr.ablation(led.limit(0)).count() == 0


def test_accepted_keeps_columns(spark):
    good = " ".join(f"word{i}" for i in range(30))
    df = spark.createDataFrame([(1, good, 5, "r"), (None, good, None, None), (2, "x", 1, "r")], "doc_id long, text string, failure_bits int, row string")
    got = qr.accepted(df)
    assert got.columns == df.columns and sorted((r.doc_id or 0) for r in got.collect()) == [0, 1]
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan
