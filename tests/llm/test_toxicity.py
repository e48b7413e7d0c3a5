import random
import zlib

import pyarrow as pa

from markerpanel.llm import toxicity as tx
from markerpanel.llm.common import strings

DIR = "/root/testdata/sf0.01"


def forms(text):
    x = tx.Matcher(tx.built_in()).features(strings(pa.array([text], pa.string())))[0]
    return {n: int(v) for n, v in zip(tx.FEATURES, x) if v}


def test_grammar():
    assert forms("what a moron") == {"insult_bare": 1}
    assert forms("You are an IDIOT") == {"insult_aimed": 1}
    assert forms("you are not an idiot") == {"insult_denied": 1}
    assert forms("not today. idiot!") == {"insult_bare": 1}
    assert forms("the mayor said it was a bad and rather sad case of garbage") == {"insult_quoted": 1}
    assert forms("we will kill you") == {"threat_bare": 1} and forms("they never murder him") == {"threat_denied": 1}
    assert forms("you should hang") == {"threat_aimed": 1} and forms("he said you will die") == {"threat_quoted": 1}
    assert forms("they kill time") == forms("die Frau will sie; kill, you") == {}
    assert forms("clown### %%%idiots") == {"insult_bare": 2}
    assert forms(None) == forms("") == forms("idiotic sclown") == {}


def test_composition_equals_one_after_another():
    machines = [tx.Machine(f) for f in (tx._threat, tx._negation, tx._report, tx._target)]
    rng = random.Random(1)
    for _ in range(200):
        states, u, both = [0] * 4, 0, tx.grammar()
        for symbol in [rng.choice([tx.OTHER, tx.AIM, tx.DENY, tx.SPEECH, tx.VERB, tx.DOOM, tx.BOTH, tx.MAY, (tx.HIT, "bare", 1)]) for _ in range(14)]:
            y = symbol
            for k, m in enumerate(machines):
                states[k], y = m(states[k], y)
            u, z = both(u, symbol)
            assert y == z


def test_path_weights():
    weigh = lambda text: tx.Matcher(tx.built_in()).features(strings(pa.array([text], pa.string())))[0][len(tx.FEATURES) :].sum()
    assert weigh("they will kill you") == 2 * weigh("they kill you") == 2 * tx.KNOWN
    assert weigh("idiots, morons") == 2 * weigh("a fool") == 2 * tx.KNOWN


def test_held_out_accuracy(spark):
    docs, labels = spark.read.parquet(f"{DIR}/documents.parquet"), spark.read.parquet(f"{DIR}/labels.parquet")
    got = {r.doc_id: r for r in tx.scored(docs.select("doc_id", "text"), labels).collect()}
    assert len(got) == docs.count()
    assert all(r.held_out == (zlib.crc32(str(k).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for k, r in got.items())
    text = {r.doc_id: r.text.lower() for r in docs.collect()}
    marked = [r for k, r in got.items() if any(w in text[k].replace("#", " ").split() for w in ("idiot", "moron", "scum", "loser"))]
    assert marked and all(r.predicted for r in marked)
    pairs = [(got[r.doc_id].score, r.toxic) for r in labels.collect() if got[r.doc_id].held_out]
    assert tx.area(pairs) > 0.8  # six toxic rows are held out here, of which two are in languages with few examples
    assert sum((s >= 0.5) == t for s, t in pairs) / len(pairs) > 0.9


def test_odd_rows(spark):
    rows = [(1, None, 0), (1, None, 0), (None, "you idiot", 1), (3, "", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, score int")
    labels = spark.createDataFrame([(None, 1), (1, 0), (3, None)], "doc_id long, toxic int")
    got = tx.scored(df, labels).collect()
    assert sorted((r.doc_id or 0, r.predicted) for r in got) == [(0, 1), (1, 0), (1, 0), (3, 0)]
    assert tx.scored(df.limit(0), labels.limit(0)).count() == 0


def test_held_out_recall_of_each_language(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    rows = tx.scored(docs.select("doc_id", "text"), labels).join(docs.select("doc_id", "lang"), "doc_id").join(labels.select("doc_id", "toxic"), "doc_id").filter("held_out").collect()
    for lang in {r.lang for r in rows if r.toxic}:
        toxic = [r.predicted for r in rows if r.toxic and r.lang == lang]
        assert sum(toxic) >= 0.8 * len(toxic), lang
    clean = [r.predicted for r in rows if not r.toxic]
    assert sum(clean) <= 0.01 * len(clean)
    assert tx.area([(r.score, r.toxic) for r in rows]) > 0.95


def test_lexicon_support_does_not_grow_with_the_sample(spark):
    # 300 toxic texts, of which 6 hold the one marker of a small language
    rows = [(k, f"zorpig case {k}" if k % 50 == 0 else f"idiot case {k}", 1) for k in range(375)] + [(k, f"fine case {k}", 0) for k in range(1000, 2000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    assert "zorpig" in tx.train(df, df).lexicon


def plain_features(text, lexicon):
    """Counts and weights of matches by form, clause by clause, from the rules in words."""
    import re

    n = len(tx.FEATURES)
    out = [0.0] * (2 * n)
    low = "".join(c.lower() if c.isascii() else c for c in text or "")
    for clause in re.split(r"[.!?;:,\n|]", low):
        entries = [lexicon.get(w, (tx.OTHER, 1.0)) for w in re.findall(r"[0-9a-z\x80-\U0010ffff]+", clause)]
        kinds = [k for k, _ in entries]
        taken, matched, since = set(), {}, 0
        for i, kind in enumerate(kinds):
            near = [j for j in range(max(0, i - tx.NEAR), i) if j >= since]
            if kind == tx.HIT:
                matched[i] = (0, 1, "bare")
            elif kind in (tx.DOOM, tx.BOTH) and any(kinds[j] == tx.MAY for j in near) and any(kinds[j] == tx.AIM for j in near):
                matched[i], since = (1, 2, "aimed"), i + 1
            elif kind == tx.AIM:
                verbs = [j for j in near if kinds[j] in (tx.VERB, tx.BOTH) and j not in taken]
                if verbs:
                    strong = any(kinds[j] == tx.MAY and j >= verbs[-1] - tx.NEAR for j in range(since_may(kinds, matched, verbs[-1]), verbs[-1]))
                    matched[i] = (1, 1 + strong, "bare")
                taken |= set(range(i))
        for i, (menace, path, form) in matched.items():
            near = range(max(0, i - tx.NEAR - 1), i)
            if any(kinds[j] == tx.DENY for j in near):
                form = "denied"
            elif tx.SPEECH in kinds[:i]:
                form = "quoted"
            elif form == "bare" and any(kinds[j] == tx.AIM and j not in matched for j in near):
                form = "aimed"
            at = 4 * menace + tx.FORMS.index(form)
            out[at] += 1
            out[n + at] += path * (tx.KNOWN if menace else entries[i][1])
    return out


def since_may(kinds, matched, at):
    """Place from which a modal still counts: after the last match that used modals up."""
    return max([j + 1 for j, m in matched.items() if m == (1, 2, "aimed") and j < at], default=0)


def test_query_rows_against_plain_python(spark):
    import hashlib
    import math
    import re
    from collections import defaultdict

    import numpy as np

    import __spark_entry__

    assert "op7_toxicity" not in __spark_entry__.oracle_sql()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{DIR}/documents.parquet").collect()}
    held = {k: zlib.crc32(str(k).encode()) % 5 == 0 for k in texts}
    taught: dict = {}
    for r in spark.read.parquet(f"{DIR}/labels.parquet").collect():
        if r.toxic in (0, 1) and r.doc_id in texts and not held[r.doc_id] and texts[r.doc_id] is not None:
            taught[texts[r.doc_id]] = max(r.toxic, taught.get(texts[r.doc_id], 0))
    owners = {0: set(), 1: set()}
    stands = {0: defaultdict(set), 1: defaultdict(set)}
    for text, t in taught.items():
        words = re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.lower())
        own = min(hashlib.md5(" ".join(words[k : k + 5]).encode()).hexdigest() for k in range(max(1, len(words) - 4)))
        owners[t].add(own)
        for w in set(words):
            if len(w) >= 3:
                stands[t][w].add(own)
    n1, n0 = len(owners[1]), len(owners[0])
    lexicon = tx.built_in()
    for w, s in stands[1].items():
        ratio = (len(s) + 0.5) / n1 * n0 / (len(stands[0][w]) + 0.5)
        if len(s) >= tx.SUPPORT and ratio > tx.RATIO and lexicon.get(w, (tx.HIT, 0))[0] == tx.HIT:
            lexicon[w] = (tx.HIT, min(tx.HEAVIEST, math.log(ratio)))
    model = tx.Model(lexicon, tx.fit(np.array([plain_features(t, lexicon) for t in taught], float), np.array(list(taught.values()), float)))
    want = dict(zip(texts, model.scores(np.array([plain_features(t, lexicon) for t in texts.values()], float)), strict=True))
    got = {r.doc_id: r for r in tx.op7(spark, DIR).collect()}
    assert got.keys() == want.keys()
    for k, r in got.items():
        assert r.held_out == held[k] and abs(r.score - want[k]) < 1e-6 and r.predicted == (r.score >= 0.5), k
