"""URL filters: host rules, then host word segmentation and naive Bayes for hosts that no rule names.

Concatenated host labels are split into words by a unigram Viterbi search over word counts of the page
texts; the words of host and path are scored by multinomial naive Bayes. The classifier learns from the
whole table by weak labels: a page is a positive if its segmented host holds two words, or a hyphenated
pair, of a small list of unwanted topics.

Both models are tables of all words. The most frequent words are also broadcast; what urls ask for beyond
them (substrings of distinct host labels, words of hosts and paths) is looked up by shuffled joins, so the size
of the broadcast changes no result.

Defined cases: a null url, or one without ://, has an empty host and path; a url with an empty host fits no rule,
scores -1 and is allowed; a host without a-z words (an IP address, another script, one label) is judged by its path;
urls of any length are judged whole; repeated rows and null ids give one row each; other columns are
ignored; an empty table gives an empty result (the model is then its prior).
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from markerpanel.llm.common import arrow_map, table, written

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The rules of the contract.
RULES = (("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block"))
#: Most frequent words of the segmenter and of the classifier that are sent to the executors; others are joined.
VOCABULARY = 200_000
LONGEST_WORD = 24
#: Words of unwanted topics, and plain words that hosts are often made of.
UNWANTED = "adult ads bet bets betting casino cheap click deal deals discount farm free gambling lottery loan loans pharma pills poker porn prize replica sex slots spam track tracker viagra warez win winner xxx".split(" ")
PLAIN = "blog mail news shop www forum home page site web online live media data cloud book books game games music photo school sport store tech travel weather world wiki".split(" ")


def parsed(pages: DataFrame) -> DataFrame:
    """page_id, url, host, path."""
    url = F.coalesce(F.col("url"), F.lit(""))
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(coalesce(url, ''), instr(coalesce(url, ''), '://') + 3)")).otherwise(F.lit(""))
    df = pages.select("page_id", "url", rest.alias("rest"))
    df = df.withColumn("raw", F.regexp_extract("rest", r"^[^/?#]*", 0))
    after = F.expr("substring(rest, length(raw) + 1)")
    return df.select("page_id", "url", F.translate("raw", UPPER, LOWER).alias("host"), F.regexp_extract(after, r"^[^?#]*", 0).alias("path"))


def best_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits host (or a parent domain) and path; null if none does."""
    out = F.lit(None).cast("string")
    for rule, _ in sorted(rules, key=lambda r: (len(r[0]), r[0])):
        h, cut, p = rule.partition("/")
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(cut + p)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


@dataclass
class Segmenter:
    """Words by unigram probability; text that is no word costs ten times more with every letter."""

    counts: dict[str, int]
    memo: dict[str, list[str]] = field(default_factory=dict)
    #: Sum over all words, also those that aren't in counts.
    total: int = 0

    def __post_init__(self):
        self.total = self.total or sum(self.counts.values()) or 1

    def cost(self, word: str, more: dict[str, int] | None = None) -> float:
        n = self.counts.get(word) or (more and more.get(word))
        return math.log(self.total) - math.log(n) if n else math.log(self.total) + math.log(10) * len(word)

    def split(self, name: str, more: dict[str, int] | None = None) -> list[str]:
        """more: counts of the words in name beyond those in counts."""
        if not more and (hit := self.memo.get(name)) is not None:
            return hit
        best, back = [0.0], [0]
        for end in range(1, len(name) + 1):
            # of equal costs the longer last word
            cost, start = min((best[k] + self.cost(name[k:end], more), k) for k in range(max(0, end - LONGEST_WORD), end))
            best.append(cost)
            back.append(start)
        out, end = [], len(name)
        while end:
            out.append(name[back[end] : end])
            end = back[end]
        out.reverse()
        if more:
            return out
        if len(self.memo) > 100_000:
            self.memo.clear()
        self.memo[name] = out
        return out

    def host_words(self, host: str, more: dict[str, int] | None = None) -> list[str]:
        """Words of all labels but the last (the top-level domain)."""
        return [w for part in host_parts(host) for w in self.split(part, more and {w: n for w, n in more.items() if w in part})]


FOLD = str.maketrans(UPPER, LOWER)


def host_parts(host: str) -> list[str]:
    return [part for label in host.split(".")[:-1] for part in re.findall("[a-z]+", label)]


def path_words(path: str) -> list[str]:
    return [w if w.isalpha() else "0" for w in re.findall("[a-z]+|[0-9]+", path.translate(FOLD))]


def substrings(part: str) -> Iterator[str]:
    """Distinct substrings that may be counted words."""
    for k in range(2, min(LONGEST_WORD, len(part)) + 1):
        yield from {part[i : i + k] for i in range(len(part) - k + 1)}


def is_unwanted(words: list[str]) -> bool:
    """The weak label: two words of the list next to each other, or one that leads or closes a host of two."""
    hits = [w in UNWANTED for w in words]
    return sum(hits) >= 2 or (any(hits) and len([w for w in words if w not in PLAIN and len(w) > 1]) <= 3)


@dataclass
class NaiveBayes:
    words: dict[str, tuple[int, int]]
    totals: tuple[int, int]
    pages: tuple[int, int]
    #: Number of all words, also those that aren't in words.
    size: int = 0

    def __post_init__(self):
        self.size = self.size or len(self.words)

    def log_odds(self, words: list[str], more: dict[str, tuple[int, int]] | None = None) -> float:
        """Log odds of unwanted to wanted, add-one smoothing; words the model never saw say nothing."""
        v = self.size + 1
        out = math.log(self.pages[1] + 1) - math.log(self.pages[0] + 1)
        for w in words:
            if hit := self.words.get(w) or (more and more.get(w)):
                a, b = hit
                out += math.log((b + 1) / (self.totals[1] + v)) - math.log((a + 1) / (self.totals[0] + v))
        return out


def _divided(counts: DataFrame, n: Column) -> tuple[list, DataFrame | None]:
    """The VOCABULARY rows of largest n (ties by w), and a frame of the other rows, if any. counts is a written table."""
    top = list(counts.orderBy(n.desc(), "w").limit(VOCABULARY).toLocalIterator())
    if len(top) < VOCABULARY or not top:
        return top, None
    last = counts.filter(F.col("w") == top[-1].w).select(n.alias("n")).first().n
    return top, counts.filter((n < last) | ((n == last) & (F.col("w") > top[-1].w)))


def word_counts(texts: DataFrame) -> tuple[Segmenter, DataFrame | None]:
    """Runs of a-z in a one-column frame of texts, over every row: a segmenter, and (w, n) of the words it doesn't hold."""
    text = texts.columns[0]
    low = F.lower(F.coalesce(F.col(text), F.lit("")))
    counts = written(texts.select(F.explode(F.split(low, "[^a-z]+")).alias("w")).filter(f"length(w) between 2 and {LONGEST_WORD}").groupBy("w").agg(F.count(F.lit(1)).alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    base = max(1, total // 10_000)
    fixed = F.col("w").isin(*UNWANTED, *PLAIN)
    known = {r.w: r.n for r in counts.filter(fixed).collect()}
    raised = {w: max(known.get(w, 0), base) for w in (*UNWANTED, *PLAIN)}
    top, rest = _divided(counts.filter(~fixed), F.col("n"))
    return Segmenter({r.w: r.n for r in top} | raised, total=total - sum(known.values()) + sum(raised.values())), rest


def _lookups(urls: DataFrame, held, rest: DataFrame) -> DataFrame:
    """_host, more: per distinct host the counts of words in its labels that aren't broadcast; only hosts that hold such words."""
    hosts = urls.select("host").distinct()

    def parts():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            rows = [(host, part) for host in batch.column(0).to_pylist() for part in dict.fromkeys(host_parts(host))]
            yield pa.RecordBatch.from_arrays([pa.array([h for h, _ in rows], pa.string()), pa.array([p for _, p in rows], pa.string())], names=["_host", "part"])

        return step

    def pieces():
        counts = held.value.counts

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            whole, found = [], []
            for part in batch.column(0).to_pylist():
                for w in substrings(part):
                    if w not in counts:
                        whole.append(part)
                        found.append(w)
                    if len(found) == 50_000:
                        yield pa.RecordBatch.from_arrays([pa.array(whole, pa.string()), pa.array(found, pa.string())], names=["part", "w"])
                        whole, found = [], []
            yield pa.RecordBatch.from_arrays([pa.array(whole, pa.string()), pa.array(found, pa.string())], names=["part", "w"])

        return step

    of = written(arrow_map(hosts, parts, "_host string, part string"))
    hits = arrow_map(of.select("part").distinct(), pieces, "part string, w string").join(rest, "w")
    return of.join(hits, "part").groupBy("_host").agg(F.collect_set(F.struct("w", "n")).alias("more"))


def _segmented(urls: DataFrame, held, rest: DataFrame | None) -> DataFrame:
    """urls with host_words and row, a number of each row's own; written, as the model and the scores read it."""
    if rest is None:
        rows = urls.withColumn("more", F.lit(None).cast("array<struct<w:string,n:bigint>>"))
    else:
        more = written(_lookups(urls, held, rest))
        rows = urls.join(more, F.col("host") == F.col("_host"), "left").drop("_host")
    columns = [c for c in rows.columns if c != "more"]
    at, asked = columns.index("host"), len(columns)
    kinds = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in columns)

    def make():
        segmenter = held.value

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            words = [segmenter.host_words(host, {x["w"]: x["n"] for x in more} if more else None) for host, more in zip(batch.column(at).to_pylist(), batch.column(asked).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:asked], pa.array(words, pa.list_(pa.string()))], names=[*columns, "host_words"])

        return step

    return written(arrow_map(rows.select(*columns, "more"), make, f"{kinds}, host_words array<string>").withColumn("row", F.monotonically_increasing_id()))


def train(rows: DataFrame) -> tuple[NaiveBayes, DataFrame | None]:
    """Counts per word and weak label, summed over all segmented rows: a model, and (w, a, b) of the words it doesn't hold."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            totals: dict[tuple[str, int], int] = {}
            for own, path in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                kind = int(is_unwanted(own))
                for w in ("", *own, *path_words(path)):
                    totals[w, kind] = totals.get((w, kind), 0) + 1
            yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in totals]), pa.array([k for _, k in totals], pa.int32()), pa.array(list(totals.values()), pa.int64())], names=["w", "kind", "n"])

        return step

    counts = arrow_map(rows.select("host_words", "path"), make, "w string, kind int, n long").groupBy("w").agg(F.sum(F.when(F.col("kind") == 0, F.col("n")).otherwise(0)).alias("a"), F.sum(F.when(F.col("kind") == 1, F.col("n")).otherwise(0)).alias("b"))
    counts = written(counts)
    totals = counts.groupBy((F.col("w") == "").alias("pages")).agg(F.sum("a").alias("a"), F.sum("b").alias("b"), F.count(F.lit(1)).alias("n")).collect()
    of = {r.pages: (r.a, r.b) for r in totals}
    top, rest = _divided(counts.filter("w <> ''"), F.col("a") + F.col("b"))
    size = sum(r.n for r in totals if not r.pages)
    return NaiveBayes({r.w: (r.a, r.b) for r in top}, of.get(False, (0, 0)), of.get(True, (0, 0)), size), rest


def _asked(rows: DataFrame, held, rest: DataFrame) -> DataFrame:
    """_row, more: the model's counts of each row's words that aren't broadcast; only rows that hold such words."""

    def make():
        bayes = held.value

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            found = [(row, w) for row, own, path in zip(*(c.to_pylist() for c in batch.columns), strict=True) for w in dict.fromkeys((*own, *path_words(path))) if w not in bayes.words]
            yield pa.RecordBatch.from_arrays([pa.array([r for r, _ in found], pa.int64()), pa.array([w for _, w in found], pa.string())], names=["_row", "w"])

        return step

    return arrow_map(rows.select("row", "host_words", "path"), make, "_row long, w string").join(rest, "w").groupBy("_row").agg(F.collect_list(F.struct("w", "a", "b")).alias("more"))


def judged(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, host_words, score (log odds of being unwanted)."""
    spark = pages.sparkSession
    urls = parsed(pages)
    segmenter, rest = word_counts(pages.select("html")) if "html" in pages.columns else word_counts(urls.select("path"))
    kind = pages.schema["page_id"].dataType.simpleString()
    rows = urls.select("page_id", "host", "path", best_rule(F.col("host"), F.col("path"), rules).alias("rule"))
    rows = _segmented(rows, spark.sparkContext.broadcast(segmenter), rest)
    bayes, rest = train(rows)
    held = spark.sparkContext.broadcast(bayes)
    if rest is None:
        rows = rows.withColumn("more", F.lit(None).cast("array<struct<w:string,a:bigint,b:bigint>>"))
    else:
        rows = rows.join(_asked(rows, held, rest), F.col("row") == F.col("_row"), "left")

    def make():
        model = held.value

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            scores = []
            for host, path, own, more in zip(*(batch.column(k).to_pylist() for k in (1, 2, 4, 5)), strict=True):
                known = {x["w"]: (x["a"], x["b"]) for x in more} if more else None
                scores.append(model.log_odds(own + path_words(path), known) if host else -1.0)
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(scores, pa.float64())], names=["page_id", "host", "path", "rule", "host_words", "score"])

        return step

    out = arrow_map(rows.select("page_id", "host", "path", "rule", "host_words", "more"), make, f"page_id {kind}, host string, path string, rule string, host_words array<string>, score double")
    verdict = F.lit(None).cast("string")
    for rule, what in rules:
        verdict = F.when(F.col("rule") == rule, F.lit(what)).otherwise(verdict)
    return out.withColumn("verdict", F.coalesce(verdict, F.when(F.col("score") > 0, F.lit("block")).otherwise(F.lit("allow"))))


def op8(spark, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "pages").select("page_id", "url", "html")).select("page_id", "host", "path", "rule", "verdict", "host_words", "score")
