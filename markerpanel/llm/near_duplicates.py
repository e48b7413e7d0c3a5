"""MinHash near-duplicates: one-permutation hashing with optimal densification, bands, star candidates.

Documents are sets of five-word shingles (A-Z lower-cased). Equal sets collapse first, so a group of
copies is one set whatever its size. Each set gets one signature by one-permutation hashing; bands of it
are buckets. In a bucket only star edges are candidates, from every member to the member with the most
bucket mates, so their number is linear in the bucket. Links are confirmed on the full sets.

Members whom their star does not settle are looked at again: two members of one bucket that are still in
different components are compared if the shingles they can have in common suffice. A shingle that no
other set holds is in no intersection, so a set with u such shingles shares at most n - u; with both
sizes known this bound drops nearly all remaining pairs, exactly. No group is cut, capped or sampled.
A pair that should be linked meets in no bucket with probability (1 - J^5)^32, 3e-8 at J = 0.85.

Defined cases: null, empty and blank texts have no set and stand alone; a text of fewer than five words
is one shingle of all its words; rows that repeat an id are merged first (the greatest text stays); a
null id is an id of its own, before all others; other columns are ignored; an empty table gives an empty
result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm import textbytes as tb
from markerpanel.llm.common import arrow_map, discard, held, one_row_per_id, shown, sliced, strings, table, written
from markerpanel.llm.components import components

#: Similarity in hundredths.
LEAST = 85
SLICE = 1 << 20
#: Candidate ids up to this many are broadcast (8 bytes each); more are joined by shuffle.
BROADCAST_IDS = 1_000_000

SHINGLE = 5
BANDS, ROWS = 32, 5
BINS = BANDS * ROWS
EMPTY = np.uint64(2**64 - 1)


def shingle_sets(texts: pa.Array, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(text number, shingle hash), distinct, sorted by text. A text of fewer words has its whole sequence as one."""
    data, offsets = tb.buffer(texts)
    data = tb.lowered(data)
    s, e, doc = tb.words(data, offsets, tb.NOT_GAP)
    h = tb.span_hashes(data, s, e)
    runs = tb.chained(h, shingle)
    inside = doc[: len(runs)] == doc[shingle - 1 :] if len(runs) else np.zeros(0, bool)
    owner, value = doc[: len(runs)][inside], runs[inside]
    n = np.bincount(doc, minlength=len(texts))
    few = np.flatnonzero((n > 0) & (n < shingle))
    if len(few):
        first = np.searchsorted(doc, few)
        whole = np.zeros(len(few), np.uint64)
        for size in range(1, shingle):
            some = n[few] == size
            at = first[some][:, None] + np.arange(size)
            whole[some] = tb.chained(h[at.T], size)[0] + np.uint64(size)
        owner, value = np.append(owner, few), np.append(value, whole)
    return tb.distinct(owner, value)


_PROBES = (tb.mixed(np.arange(BINS * 4096, dtype=np.uint64) + np.uint64(7)) % np.uint64(BINS)).astype(np.int64).reshape(4096, BINS)


def signatures(owner: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
    """One-permutation MinHash: least value per bin; an empty bin borrows from bins drawn by a fixed hash
    of its own number, attempt by attempt, until one is full (so equal sets borrow alike)."""
    sig = np.full(n * BINS, EMPTY)
    cell = owner * BINS + (((value >> np.uint64(32)) * np.uint64(BINS)) >> np.uint64(32)).astype(np.int64)
    np.minimum.at(sig, cell, tb.mixed(value))
    sig = sig.reshape(n, BINS)
    full = sig != EMPTY
    some = np.flatnonzero(full.any(1) & ~full.all(1))
    d, b = np.nonzero(~full[some])
    d = some[d]
    out = sig.copy()
    for probe in _PROBES:
        if not len(d):
            break
        donor = probe[b]
        ok = full[d, donor]
        out[d[ok], b[ok]] = sig[d[ok], donor[ok]]
        d, b = d[~ok], b[~ok]
    for x, y in zip(d.tolist(), b.tolist(), strict=True):  # after so many draws: the next full bin
        out[x, y] = sig[x, next((y + k) % BINS for k in range(BINS) if full[x, (y + k) % BINS])]
    return out


def band_hashes(sig: np.ndarray) -> np.ndarray:
    """(n, BANDS): bands of equal place and equal rows get equal hashes."""
    out = np.zeros((len(sig), BANDS), np.uint64)
    for r in range(ROWS):
        out = (out ^ sig[:, r::ROWS]) * np.uint64(0xE7037ED1A0B428DB)
        out ^= out >> np.uint64(32)
    return tb.mixed(out + np.arange(BANDS, dtype=np.uint64)[None, :])


def _sketches(docs: DataFrame) -> DataFrame:
    """doc_id, n (set size), d1, d2 (digest of the set), bands."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                n = hi - lo
                owner, value = shingle_sets(col.slice(lo, n))
                size = np.bincount(owner, minlength=n)
                digests = []
                for salt in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
                    d = np.zeros(n, np.uint64)
                    np.add.at(d, owner, tb.mixed(value ^ np.uint64(salt)))
                    digests.append(pa.array(d.view(np.int64)))
                bands = band_hashes(signatures(owner, value, n)).view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum((size > 0) * BANDS)]), pa.int32()), pa.array(bands[size > 0].ravel()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, n), pa.array(size), *digests, lists], names=["doc_id", "n", "d1", "d2", "bands"])

        return step

    return arrow_map(docs, make, "doc_id long, n long, d1 long, d2 long, bands array<long>")


def _full_sets(docs: DataFrame) -> DataFrame:
    """doc, n, items: the full sets."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                owner, value = shingle_sets(col.slice(lo, hi - lo))
                edges = np.searchsorted(owner, np.arange(hi - lo + 1))
                lists = pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(value.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(np.diff(edges)), lists], names=["doc", "n", "items"])

        return step

    return arrow_map(docs, make, "doc long, n long, items array<long>")


def _confirmed(pairs: DataFrame, sets: DataFrame, least: int) -> DataFrame:
    """Pairs (a, b) whose full sets are similar enough."""
    left = sets.select(F.col("doc").alias("a"), F.col("n").alias("na"), F.col("items").alias("x"))
    right = sets.select(F.col("doc").alias("b"), F.col("n").alias("nb"), F.col("items").alias("y"))
    both = pairs.join(left, "a").join(right, "b")
    shared = F.size(F.array_intersect("x", "y"))
    return both.filter(100 * shared >= least * (F.col("na") + F.col("nb") - shared)).select("a", "b")


def _star(members: DataFrame, sizes: DataFrame, least: int) -> tuple[DataFrame, DataFrame]:
    """Candidates (a, b): each member and the best connected member of its bucket; and the held table they rest on."""
    buckets = members.groupBy("band").agg(F.count(F.lit(1)).alias("m"))
    degree = members.join(buckets, "band").groupBy("doc").agg(F.sum(F.col("m") - 1).alias("deg"))
    ranked = held(members.join(degree.join(sizes, "doc"), "doc"))
    hubs = ranked.groupBy("band").agg(F.max(F.struct("deg", (-F.col("doc")).alias("neg"), F.col("n").alias("hn"))).alias("h"))
    edges = ranked.join(hubs.select("band", (-F.col("h.neg")).alias("hub"), F.col("h.hn").alias("hn")), "band").filter("doc <> hub")
    fits = 100 * F.least("n", "hn") >= least * F.greatest("n", "hn")
    return edges.filter(fits).select(F.least("doc", "hub").alias("a"), F.greatest("doc", "hub").alias("b")).distinct(), ranked


def _unsettled(members: DataFrame, groups: DataFrame, sets: DataFrame, parts: DataFrame, least: int) -> tuple[DataFrame, list[DataFrame]]:
    """Pairs of one bucket in different components whose possible overlap suffices; and the held tables they rest on."""
    placed = members.join(parts.select(F.col("node").alias("doc"), "component"), "doc", "left").withColumn("component", F.coalesce("component", "doc"))
    # a bucket of two was settled by its star
    active = placed.groupBy("band").agg(F.count(F.lit(1)).alias("m"), F.min("component").alias("lo"), F.max("component").alias("hi")).filter("m > 2 and lo <> hi").select("band")
    placed = held(placed.join(active, "band"))
    docs = placed.select("doc", "component").distinct()
    own = sets.join(docs, "doc")
    alone = own.select("doc", F.explode("items").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min("doc").alias("doc")).filter("c = 1").groupBy("doc").agg(F.count(F.lit(1)).alias("u"))
    facts = docs.join(sets.select("doc", "n"), "doc").join(alone, "doc", "left").withColumn("k", F.col("n") - F.coalesce("u", F.lit(0)))
    # a set that could not even be linked with a set of all its shared shingles is out
    facts = facts.filter(100 * F.col("k") >= least * F.col("n")).join(groups.select(F.col("rep").alias("doc"), "bands"), "doc")
    rows = held(placed.select("band", "doc").join(facts, "doc").select("band", "doc", "component", "n", "k", "bands"))
    a, b = rows.alias("a"), rows.alias("b")
    most = F.least("a.k", "b.k")
    first = F.filter(F.zip_with("a.bands", "b.bands", lambda x, y: F.when(x == y, x)), lambda x: x.isNotNull())[0]
    apart = (F.col("a.doc") < F.col("b.doc")) & (F.col("a.component") != F.col("b.component"))
    enough = (100 + least) * most >= least * (F.col("a.n") + F.col("b.n"))
    # each pair once, in the first bucket that it shares
    pairs = a.join(b, (F.col("a.band") == F.col("b.band")) & apart & enough & (first == F.col("a.band"))).select(F.col("a.doc").alias("a"), F.col("b.doc").alias("b"))
    return pairs, [placed, rows]


def near_duplicates(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every document."""
    docs = one_row_per_id(docs)
    sketches = written(_sketches(docs))
    # equal sets have equal bands
    groups = written(sketches.filter("n > 0").groupBy("d1", "d2", "n").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.any_value("bands").alias("bands")))
    rows = groups.select(F.col("rep").alias("doc"), F.explode("bands").alias("band"))
    shared = rows.groupBy("band").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("band")
    # small beside the texts: rebalanced into few files, and plans that read them stay short
    members = written(rows.join(shared, "band").select("band", "doc").hint("rebalance"))
    wanted = held(members.select(F.col("doc").alias("doc_id")).distinct())
    few = wanted.count() <= BROADCAST_IDS
    sets = held(_full_sets(docs.join(F.broadcast(wanted) if few else wanted, "doc_id").select("doc_id", "text")))
    stars, ranked = _star(members, groups.select(F.col("rep").alias("doc"), "n"), least)
    links = written(_confirmed(stars, sets, least).hint("rebalance"))
    pairs, mid = _unsettled(members, groups, sets, components(links), least)
    parts = components(links.unionAll(_confirmed(pairs, sets, least)))
    for t in (*mid, ranked, sets, wanted):  # components() has read them all
        t.unpersist()
    discard(members, links)
    copies = groups.filter("copies > 1").select("d1", "d2", "n", "rep")
    out = sketches.select("doc_id", "n", "d1", "d2").join(copies, ["d1", "d2", "n"], "left").withColumn("rep", F.coalesce("rep", "doc_id"))
    out = out.join(parts.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    return out.select(shown(), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), (F.col("component") == F.col("doc_id")).alias("kept")).withColumn("component_id", shown("component_id"))


def op6(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


#: All pairs that share a shingle, counted; components by recursion from the smaller id.
OP6_SQL = r"""
WITH RECURSIVE words AS (
    SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
    FROM documents
), sets AS (
    SELECT doc_id, CASE WHEN len(w) = 0 THEN CAST([] AS VARCHAR[]) WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END AS s
    FROM words
), items AS (
    SELECT doc_id, len(s) AS n, unnest(s) AS h FROM sets
), links AS (
    SELECT a.doc_id AS x, b.doc_id AS y
    FROM items a JOIN items b ON a.h = b.h AND a.doc_id < b.doc_id
    GROUP BY a.doc_id, b.doc_id, a.n, b.n
    HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))
), edges AS (
    SELECT x, y FROM links UNION ALL SELECT y, x FROM links
), reach(doc_id, root) AS (
    SELECT doc_id, doc_id FROM documents
    UNION
    SELECT e.y, r.root FROM reach r JOIN edges e ON e.x = r.doc_id AND e.y > r.root
), least AS (
    SELECT doc_id, min(root) AS component_id FROM reach GROUP BY doc_id
)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, l.component_id, s.doc_id = l.component_id AS kept
FROM sets s JOIN least l ON l.doc_id = s.doc_id
"""


def brute(rows: list[tuple], least: int = LEAST) -> dict:
    """Slow check: {doc_id: (set size, component)}."""
    import re

    sets = {}
    for d, t in rows:
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
        w = re.findall(r"[^\x20\x09-\x0D]+", low)
        sets[d] = {tuple(w[k : k + SHINGLE]) for k in range(max(1 if w else 0, len(w) - SHINGLE + 1))}
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= least * len(x | y):
                p, q = root(a), root(b)
                parent[max(p, q)] = min(p, q)
    return {d: (len(sets[d]), root(d)) for d in ids}
