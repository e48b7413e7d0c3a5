"""Benchmark decontamination: a prefix-filtered set join of item windows with document words.

An item's windows are its runs of 10 words (one shorter window if it has fewer). A document holds a
window if all its words stand there in order, that is containment 1, so by the prefix-filter principle
one word of each window is prefix enough: its rarest, by counts over the benchmark and all documents
that are kept in a table of fixed size. A document word that is some window's prefix word gives a
candidate place; length and position bounds drop places where the window would not fit the text;
the rest is verified word by word, exactly.

A benchmark of at most BROADCAST_WORDS words is sent to every executor, which then needs one pass over
the documents without a shuffle; a larger one is joined by shuffle on the prefix words.

Defined cases: null or empty texts have no words and are clean; items without words give no window;
null item or document ids are ids of their own; repeated benchmark rows count as one item; repeated
documents give one row each; other columns are ignored; with an empty benchmark nothing is hit.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm import textbytes as tb
from markerpanel.llm.common import arrow_map, sliced, strings, table, written

WINDOW = 10
#: Benchmarks up to this many words are broadcast (about 24 bytes a word and node); checked, not assumed.
BROADCAST_WORDS = 20_000_000
#: Size of the table of word counts by hash; the same for every corpus.
RARITY_CELLS = 1 << 16
SLICE = 1 << 20


def _words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, starts, ends and text numbers of all words of a slice."""
    data, offsets = tb.buffer(texts)
    data = tb.lowered(data)
    s, e, doc = tb.words(data, offsets, tb.ALPHANUMERIC)
    return tb.span_hashes(data, s, e), s, e, doc


def rarity(texts: DataFrame) -> np.ndarray:
    """Word counts by hash cell over every row of a one-column frame of texts."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            total = np.zeros(RARITY_CELLS, np.int64)
            col = strings(batch.column(0))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                h = _words(col.slice(lo, hi - lo))[0]
                total += np.bincount((h % np.uint64(RARITY_CELLS)).astype(np.int64), minlength=RARITY_CELLS)
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["cell", "n"])

        return step

    counts = np.zeros(RARITY_CELLS, np.int64)
    for r in arrow_map(texts, make, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[r.cell] = r.n
    return counts


def windows(items: DataFrame) -> DataFrame:
    """(item_id, k, words): the windows of each item as arrays of word hashes."""
    kind = items.schema["item_id"].dataType.simpleString()

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            h, _, _, doc = _words(strings(batch.column(1)))
            h = h.view(np.int64)
            rows, places, lists = [], [], []
            edges = np.searchsorted(doc, np.arange(batch.num_rows + 1))
            for i in range(batch.num_rows):
                own = h[edges[i] : edges[i + 1]]
                for k in range(max(1 if len(own) else 0, len(own) - WINDOW + 1)):
                    rows.append(i)
                    places.append(k)
                    lists.append(own[k : k + WINDOW])
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), pa.array(places, pa.int32()), pa.array(lists, pa.list_(pa.int64()))], names=["item_id", "k", "words"])

        return step

    return arrow_map(items.select("item_id", "text").distinct(), make, f"item_id {kind}, k int, words array<long>")


class _Prober:
    """Distinct windows by length, keyed by their rarest word."""

    def __init__(self, found: list[tuple[str, tuple[int, ...]]], counts: np.ndarray):
        owners: dict[tuple[int, ...], set[str]] = {}
        for item, w in found:
            owners.setdefault(w, set()).add(item)
        self.items = [frozenset(x) for x in owners.values()]
        size = np.array([len(w) for w in owners], np.int64)
        grid = np.zeros((len(owners), WINDOW), np.uint64)
        for i, w in enumerate(owners):
            grid[i, : len(w)] = np.array(w, np.int64).view(np.uint64)
        seen = counts[(grid % np.uint64(RARITY_CELLS)).astype(np.int64)].astype(np.float64) if len(owners) else np.zeros((0, WINDOW))
        seen[np.arange(WINDOW)[None, :] >= size[:, None]] = np.inf
        at = seen.argmin(1) if len(owners) else np.zeros(0, np.int64)
        key = grid[np.arange(len(owners)), at]
        order = np.argsort(key, kind="stable")
        self.key, self.at, self.size, self.grid = key[order], at[order], size[order], grid[order]
        self.items = [self.items[i] for i in order]

    def probe(self, h: np.ndarray, lo_of: np.ndarray, hi_of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first word, window) of every occurrence. lo_of and hi_of: each word's text, as a range of words."""
        lo, hi = np.searchsorted(self.key, h, "left"), np.searchsorted(self.key, h, "right")
        place = np.flatnonzero(hi > lo)
        n = (hi - lo)[place]
        window = np.repeat(lo[place], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        place = np.repeat(place, n)
        first = place - self.at[window]
        ok = (first >= lo_of[place]) & (first + self.size[window] <= hi_of[place])
        first, window = first[ok], window[ok]
        for k in range(WINDOW):
            inside = k < self.size[window]
            same = ~inside
            same[inside] = h[first[inside] + k] == self.grid[window[inside], k]
            first, window = first[same], window[same]
        return first, window


def _spans(doc: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    edges = np.searchsorted(doc, np.arange(n_docs + 1))
    return edges, edges[doc], edges[doc + 1]


OUT = "n_words long, n_hit long, items array<string>, spans array<struct<start:long,end:long>>"


def _covered(first: np.ndarray, size: np.ndarray) -> list[tuple[int, int]]:
    """Union of word ranges."""
    out: list[list[int]] = []
    for a, b in sorted(zip(first.tolist(), (first + size).tolist(), strict=True)):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def contaminated(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Per document row: n_words, n_hit, items (ids as strings, sorted) and spans, the hit ranges of words."""
    spark = docs.sparkSession
    kind = docs.schema["doc_id"].dataType.simpleString()
    win = windows(items).withColumn("item", F.coalesce(F.col("item_id").cast("string"), F.lit("")))
    n_words = win.agg(F.sum(F.size("words"))).first()[0] or 0
    if n_words > BROADCAST_WORDS:
        return _by_shuffle(docs, win)
    counts = rarity(docs.select("text").unionAll(items.select("text")))
    prober = spark.sparkContext.broadcast(_Prober([(r.item, tuple(r.words)) for r in win.toLocalIterator()], counts))

    def make():
        p = prober.value

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                n = hi - lo
                h, _, _, doc = _words(col.slice(lo, n))
                edges, lo_of, hi_of = _spans(doc, n)
                first, window = p.probe(h, lo_of, hi_of)
                owner = doc[first]
                hits, lists, spans = np.zeros(n, np.int64), [[] for _ in range(n)], [[] for _ in range(n)]
                for d in np.unique(owner):
                    mine = owner == d
                    spans[d] = [{"start": a, "end": b} for a, b in _covered(first[mine] - edges[d], p.size[window[mine]])]
                    hits[d] = sum(x["end"] - x["start"] for x in spans[d])
                    lists[d] = sorted(set().union(*(p.items[w] for w in np.unique(window[mine]))))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, n), pa.array(np.diff(edges)), pa.array(hits), pa.array(lists, pa.list_(pa.string())), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))], names=["doc_id", "n_words", "n_hit", "items", "spans"])

        return step

    return arrow_map(docs.select("doc_id", "text"), make, f"doc_id {kind}, {OUT}")


def _by_shuffle(docs: DataFrame, win: DataFrame) -> DataFrame:
    """The same for a benchmark of any size: document words meet windows on the prefix word in a shuffled join.

    Every document word travels with the words around it, so that a candidate is verified where it is met.
    """
    reach = WINDOW - 1
    # written first: row numbers must be the same wherever they are used
    docs = written(docs.select("doc_id", "text").withColumn("row", F.monotonically_increasing_id()))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(2))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                n = hi - lo
                h, _, _, doc = _words(col.slice(lo, n))
                edges, lo_of, hi_of = _spans(doc, n)
                h = h.view(np.int64)
                at = np.arange(len(h))
                a, b = np.maximum(lo_of, at - reach), np.minimum(hi_of, at + reach + 1)
                around = [h[x:y] for x, y in zip(a.tolist(), b.tolist(), strict=True)]
                rows = batch.column(0).slice(lo, n)
                yield pa.RecordBatch.from_arrays([rows.take(pa.array(doc)), pa.array(h), pa.array(at - lo_of), pa.array(at - a), pa.array(around, pa.list_(pa.int64()))], names=["row", "word", "at", "back", "around"])

        return step

    sizes = docs.select("row", "doc_id", "text")
    places = arrow_map(sizes.select("row", "doc_id", "text"), make, "row long, word long, at long, back long, around array<long>")
    freq = places.groupBy("word").count()
    # the rarest word of each window, ties to the first place
    keyed = win.select("item", "words", F.posexplode("words").alias("off", "word")).join(freq, "word", "left")
    keyed = keyed.groupBy("item", "words").agg(F.min_by(F.struct("word", "off"), F.struct(F.coalesce("count", F.lit(0)), "off")).alias("p")).select("item", "words", "p.*")
    found = places.join(keyed, "word").filter("back >= off and slice(around, int(back - off + 1), size(words)) = words")
    found = found.select("row", "item", (F.col("at") - F.col("off")).alias("start"), (F.col("at") - F.col("off") + F.size("words")).alias("end")).distinct()
    # union of ranges per row: a range starts a new run where it begins after all ends before it
    hit = found.groupBy("row").agg(F.array_sort(F.collect_set(F.struct("start", "end"))).alias("s"), F.array_sort(F.collect_set("item")).alias("items"))
    merged = F.aggregate(
        "s", F.array().cast("array<struct<start:long,end:long>>"),
        lambda acc, x: F.when((F.size(acc) > 0) & (F.element_at(acc, -1)["end"] >= x["start"]), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(F.element_at(acc, -1)["start"].alias("start"), F.greatest(F.element_at(acc, -1)["end"], x["end"]).alias("end"))))).otherwise(F.concat(acc, F.array(x))),
    )
    hit = hit.select("row", "items", merged.alias("spans"))
    n = places.groupBy("row").count()
    out = sizes.select("row", "doc_id").join(n, "row", "left").join(hit, "row", "left")
    spans = F.coalesce("spans", F.array().cast("array<struct<start:long,end:long>>"))
    return out.select(F.col("doc_id").cast(kind).alias("doc_id"), F.coalesce("count", F.lit(0)).alias("n_words"), F.aggregate(spans, F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["start"]).alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"), spans.alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op10(spark, sf_dir: str) -> DataFrame:
    return digest(contaminated(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text")))


def brute(docs: list[tuple], items: list[tuple]) -> dict:
    """Slow check: {doc_id: (n_words, n_hit, items_sha256)}."""
    import re

    def ws(t):
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
        return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)

    win = []
    for i, t in items:
        w = ws(t)
        win += [(str(i), w[k : k + WINDOW]) for k in range(max(1 if w else 0, len(w) - WINDOW + 1))]
    out = {}
    for d, t in docs:
        w, hit, own = ws(t), set(), set()
        for i, x in win:
            for k in range(len(w) - len(x) + 1):
                if w[k : k + len(x)] == x:
                    hit.update(range(k, k + len(x)))
                    own.add(i)
        out[d] = (len(w), len(hit), hashlib.sha256(",".join(sorted(own)).encode()).hexdigest())
    return out


#: DuckDB: every window of every needed length is joined as text.
OP10_SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
bk AS (SELECT item_id, w, least(len(w), 10) AS n, unnest(range(0, greatest(len(w) - 9, 1))) AS k FROM b WHERE len(w) > 0),
win AS (SELECT DISTINCT item_id, n, array_to_string(list_slice(w, k + 1, k + n), ' ') AS t FROM bk),
sizes AS (SELECT DISTINCT n FROM win),
dk AS (SELECT doc_id, w, n, unnest(range(0, len(w) - n + 1)) AS k FROM d, sizes WHERE len(w) >= n),
found AS (SELECT dk.doc_id, dk.k, dk.n, win.item_id FROM dk JOIN win ON dk.n = win.n AND array_to_string(list_slice(dk.w, dk.k + 1, dk.k + dk.n), ' ') = win.t),
hits AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM found) GROUP BY doc_id),
own AS (SELECT doc_id, count(*) AS n, string_agg(i, ',' ORDER BY i) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM found) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(hits.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(own.n, 0) AS BIGINT) AS n_items,
       sha256(coalesce(own.ids, '')) AS items_sha256, coalesce(hits.n, 0) > 0 AS contaminated
FROM d LEFT JOIN hits ON d.doc_id = hits.doc_id LEFT JOIN own ON d.doc_id = own.doc_id
"""
