import itertools

from markerpanel.llm import url_filters as uf


def test_parse_and_rules(spark):
    rows = {
        1: ("HTTP://WWW.Example.com/en/a?b#c", "www.example.com", "/en/a", "www.example.com/en/", "allow"),
        2: ("http://x.example.com/en/", "x.example.com", "/en/", "example.com/en/", "block"),
        3: ("http://badexample.com/en/", "badexample.com", "/en/", "com/", "allow"),
        4: ("http://a.net/fr/x", "a.net", "/fr/x", "net/fr/", "block"),
        5: ("http://a.net?/fr/", "a.net", "", None, "allow"),
        6: (None, "", "", None, "allow"),
        7: ("no scheme", "", "", None, "allow"),
        8: ("://example.com/en", "example.com", "/en", "com/", "allow"),
        9: ("http://Éa.NET/es/É", "Éa.net", "/es/É", "net/es/", "block"),
        10: ("http://net/es/", "net", "/es/", "net/es/", "block"),
    }
    df = spark.createDataFrame([(k, v[0], None, "q") for k, v in rows.items()] + [(None, rows[4][0], "", "q")], "page_id long, url string, html string, host string")
    got = uf.judged(df).collect()
    assert len(got) == 11
    for r in got:
        if r.page_id is not None:
            assert (r.host, r.path, r.rule, r.verdict) == rows[r.page_id][1:]
    assert uf.judged(df.limit(0)).count() == 0


def test_viterbi_is_best_of_all_splits():
    seg = uf.Segmenter({"free": 50, "bets": 20, "bet": 30, "be": 90, "ts": 1, "s": 2, "the": 200, "rap": 4, "therapist": 1, "ist": 3})
    for name in ("freebets", "therapist", "thebets", "zzfree", "s"):
        splits = []
        for cuts in itertools.product([0, 1], repeat=len(name) - 1):
            parts, start = [], 0
            for k, c in enumerate(cuts, 1):
                if c:
                    parts.append(name[start:k])
                    start = k
            splits.append([*parts, name[start:]])
        cost = lambda p: sum(map(seg.cost, p))
        assert abs(cost(seg.split(name)) - min(map(cost, splits))) < 1e-9
    assert seg.split("freebets") == ["free", "bets"]


def test_method_blocks_unwanted_hosts(spark):
    hosts = ["freebets.example.org", "blog.casino-win.example.org", "cheappills.example.org"] + [f"{w}.example.org" for w in ("thether", "tionsh", "blogthe", "www.ering")]
    df = spark.createDataFrame([(k, f"http://{hosts[k % 7]}/en/{k}", "<p>the ther tion sh ering blog</p>") for k in range(140)], "page_id long, url string, html string")
    got = {(r.host, r.verdict) for r in uf.judged(df).collect()}
    assert got == {(h, "block" if k < 3 else "allow") for k, h in enumerate(hosts)}


def plain_judged(rows):
    """Whole results of rows (id, url, html) by plain Python, rules left out: {id: (host_words, score)}."""
    import math
    import re
    from collections import Counter

    counts = Counter(w for _, _, html in rows for w in re.split("[^a-z]+", (html or "").lower()) if 2 <= len(w) <= uf.LONGEST_WORD)
    base = max(1, sum(counts.values()) // 10_000)
    for w in (*uf.UNWANTED, *uf.PLAIN):
        counts[w] = max(counts[w], base)
    total = sum(counts.values())

    def split(name):
        best = [(0.0, [])]
        for end in range(1, len(name) + 1):
            steps = []
            for k in range(max(0, end - uf.LONGEST_WORD), end):
                w = name[k:end]
                steps.append((best[k][0] + (math.log(total) - math.log(counts[w]) if counts[w] else math.log(total) + math.log(10) * len(w)), k))
            cost, k = min(steps)
            best.append((cost, best[k][1] + [name[k:end]]))
        return best[-1][1]

    words, seen, pages = {}, [Counter(), Counter()], [0, 0]
    for k, url, _ in rows:
        rest = (url or "").partition("://")[2]
        host = re.match("[^/?#]*", rest).group()
        path = re.match("[^?#]*", rest[len(host) :]).group().lower()
        own = [w for label in host.lower().split(".")[:-1] for part in re.findall("[a-z]+", label) for w in split(part)]
        words[k] = own, ["0" if w.isdigit() else w for w in re.findall("[a-z]+|[0-9]+", path)], host
        hits = [w in uf.UNWANTED for w in own]
        kind = sum(hits) >= 2 or (any(hits) and sum(w not in uf.PLAIN and len(w) > 1 for w in own) <= 3)
        pages[kind] += 1
        seen[kind].update(own + words[k][1])
    v, n = len({*seen[0], *seen[1]}) + 1, [sum(c.values()) for c in seen]
    score = lambda ws: math.log(pages[1] + 1) - math.log(pages[0] + 1) + sum(math.log((seen[1][w] + 1) / (n[1] + v)) - math.log((seen[0][w] + 1) / (n[0] + v)) for w in ws)
    return {k: (own, score(own + path) if host else -1.0) for k, (own, path, host) in words.items()}


def test_rare_words_count_whatever_is_broadcast(spark, monkeypatch):
    import random

    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdeilnorst") for _ in range(rng.randrange(2, 8))) for _ in range(300)]
    pick = lambda: vocabulary[min(299, int(rng.paretovariate(0.5)))]
    rows = [(k, f"http://www.{pick()}{pick()}{rng.choice(['', 'casino', 'free', '-' + pick()])}.{pick()}.org/{pick()}/{rng.choice([pick(), str(k)])}?x", "<p>" + " ".join(pick() for _ in range(30))) for k in range(200)]
    rows += [(200, None, None), (201, rows[3][1], "")]
    want = plain_judged(rows)
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    for size in (uf.VOCABULARY, 40, 1):
        monkeypatch.setattr(uf, "VOCABULARY", size)
        got = {r.page_id: (r.host_words, r.score) for r in uf.judged(df).collect()}
        assert got.keys() == want.keys()
        for k, (own, score) in want.items():
            assert got[k][0] == own and abs(got[k][1] - score) < 1e-9, (size, k)


def test_hosts_without_words_are_judged_by_their_path(spark):
    bad, good = "/free/casino/bets", "/the/daily/report"
    rows = [(k, f"http://{h}{p}", "<p>the daily report") for k, (h, p) in enumerate([("freebets.example.org", bad), ("www.thether.org", good)] * 40)]
    odd = ["10.1.2.3", "[2001:db8::1]", "пример.рф", "localhost"]
    rows += [(100 + k, f"http://{h}{p}", None) for k, (h, p) in enumerate((h, p) for h in odd for p in (bad, good))]
    rows += [(200, None, None), (201, "http:///free/casino/bets", None), (202, "no scheme /free/casino/bets", None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = plain_judged(rows)
    got = {r.page_id: r for r in uf.judged(df).collect()}
    assert all(abs(got[k].score - score) < 1e-9 for k, (_, score) in want.items())
    assert [got[100 + k].verdict for k in range(8)] == ["block", "allow"] * 4
    assert all((got[k].verdict, got[k].score) == ("allow", -1.0) for k in (200, 201, 202))


def test_query_rows_against_plain_python(spark):
    import __spark_entry__

    assert not {"op6_near_duplicates", "op8_url_filters"} & __spark_entry__.oracle_sql().keys()
    pages = [(r.page_id, r.url, r.html) for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect()]
    want = plain_judged(pages)
    got = {r.page_id: r for r in uf.op8(spark, "/root/testdata/sf0.01").collect()}
    assert got.keys() == want.keys()
    rules = dict(uf.RULES)
    for k, r in got.items():
        assert r.host_words == want[k][0] and abs(r.score - want[k][1]) < 1e-9, k
        fits = [x for x in rules if (r.host == x.partition("/")[0] or r.host.endswith("." + x.partition("/")[0])) and r.path.startswith("/" + x.partition("/")[2])]
        assert r.rule == max(fits, key=len, default=None)
        assert r.verdict == (rules[r.rule] if r.rule else "block" if r.score > 0 else "allow")
