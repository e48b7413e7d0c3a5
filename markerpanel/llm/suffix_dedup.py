"""Removal of repeated byte strings by longest-previous-factor arrays over sampled suffix groups.

A place is a repeat if the STRING bytes that begin there also begin at an earlier place (a smaller doc_id,
or the same document further left); every byte covered by a repeat's string goes. That is: the longest
previous factor (LPF) of the place is at least STRING. LPF comes from a suffix array: the suffixes in
order, the common prefix of neighbours, and for each suffix the nearest ones on either side that begin
earlier (previous and next smaller positions).

One suffix array over a corpus is no distributed object, so places are first dealt to groups that can be
sorted apart. Each string's anchor is its GRAM-byte piece of least hash, the leftmost of equals: equal
strings have equal anchors at equal distance. The strings of one anchor place form a segment; only
segments whose anchors have equal hashes can hold equal strings.

1. Segments travel as digests, by anchor hash. Segments of equal bytes repeat their first one; a group of
   copies is settled here, in a stream of constant memory. Where one anchor has different segments, the
   first of each may still share strings in part.
2. Only those fetch their bytes. Each group's segments, in order of place, get a suffix array, LPF by
   previous and next smaller positions, and give the repeated strings that remain.

Defined cases: null and empty texts have nothing to remove; texts of any length are read whole; rows that
repeat an id are merged first (the greatest text stays); a null id is an id of its own, before all
others; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm import textbytes as tb
from markerpanel.llm.common import NULL_ID as NULL
from markerpanel.llm.common import arrow_map, one_row_per_id, shown, sliced, strings, table, written

STRING = 100
GRAM = 32
SLICE = 1 << 20
#: Bytes of segments that are sorted at once; whole groups, so results don't depend on it.
SORT_BYTES = 1 << 20


# -- suffix array, LPF ----------------------------------------------------------------------------
def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """Places ordered by their first ``depth`` symbols (ties by place), by prefix doubling. Symbols are below 511."""
    n = len(data)
    size = min(7, depth)  # as many symbols of nine bits as a key holds; beyond the end stands 0
    padded = np.zeros(n + size, np.int64)
    padded[:n] = data + 1
    key = padded[:n].copy()
    for k in range(1, size):
        key = key << 9 | padded[k : n + k]
    while True:
        order = np.argsort(key, kind="stable" if size >= depth else None)
        rank = np.empty(n, np.int64)
        steps = np.ones(n, np.int64)
        ordered = key[order]
        steps[1:] = ordered[1:] != ordered[:-1]
        rank[order] = np.cumsum(steps)  # dense, from 1; 0 stands for beyond the end
        if size >= depth or not n or rank[order[-1]] == n:
            return order
        # twice as many symbols, or just as many as are missing (the two halves may overlap)
        gap = min(size, depth - size)
        behind = np.zeros(n, np.int64)
        behind[: n - gap] = rank[gap:]
        key, size = rank * (n + 1) + behind, size + gap


def longest_previous_factors(data: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """LPF, cut at ``depth``, of the places in ``order``, by place: the longest match that begins at a smaller one of them.

    In suffix order the best match of a place is its previous or next smaller place; the match's length is
    the least common prefix of neighbours in between. Removing places from the largest to the smallest
    from a linked list meets each place with just these two as neighbours.
    """
    n = len(order)
    if n < 2:
        return np.zeros(n, np.int64)
    before = np.arange(-1, n - 1).tolist()
    after = np.arange(1, n + 1).tolist()
    common = [*_common_prefixes(data, order, depth).tolist(), 0]  # of order[k-1] and order[k]
    by_place = np.argsort(order)
    out = [0] * n
    for at, k in zip(range(n - 1, -1, -1), by_place[::-1].tolist(), strict=True):
        left, right = before[k], after[k]
        a, b = common[k], common[right]
        out[at] = a if a > b else b
        if right < n:
            common[right] = a if a < b else b
            before[right] = left
        if left >= 0:
            after[left] = right
    return np.array(out)


def _common_prefixes(data: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """Common prefix of each suffix with the one before it in order, up to depth; 0 for the first."""
    n = len(data)
    out = np.zeros(len(order), np.int64)
    a, b = order[:-1], order[1:]
    live = np.arange(len(order) - 1)
    for k in range(depth):
        live = live[(a[live] + k < n) & (b[live] + k < n)]
        live = live[data[a[live] + k] == data[b[live] + k]]
        if not len(live):
            break
        out[live + 1] = k + 1
    return out


# -- anchors --------------------------------------------------------------------------------------
def segments(data: np.ndarray, offsets: np.ndarray, string: int = STRING, gram: int = GRAM):
    """(text, anchor hash, anchor place, first string, last string, digest) of each segment; places count from
    the start of the text. Strings a..b of a segment cover bytes a .. b + string."""
    n = len(data)
    if n < string:
        none = np.zeros(0, np.int64)
        return none, none, none, none, none, none
    bits = max(20, int(n).bit_length())
    # hash of every gram by doubling
    h = tb._BYTE[data]
    size, power = 1, tb.BASE
    while size < gram:
        h = h[: len(h) - size] * power + h[size:]
        power = power * power
        size *= 2
    value = tb.mixed(h)
    low = np.uint64((1 << bits) - 1)
    packed = (value & ~low) | np.arange(len(value), dtype=np.uint64)
    # least of each run of string - gram + 1 grams
    run, span = packed, 1
    width = string - gram + 1
    while span * 2 <= width:
        run = np.minimum(run[: len(run) - span], run[span:])
        span *= 2
    run = np.minimum(run[: n - string + 1], run[width - span : width - span + n - string + 1])
    anchor = (run & low).astype(np.int64)
    start = np.arange(len(anchor))
    text = np.searchsorted(offsets, start, "right") - 1
    inside = start + string <= offsets[text + 1]
    edge = np.ones(len(anchor), bool)
    edge[1:] = (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1]) | (inside[1:] != inside[:-1])
    first = np.flatnonzero(edge)
    last = np.append(first[1:], len(anchor)) - 1
    ok = inside[first]
    first, last = first[ok], last[ok]
    at, owner = anchor[first], text[first]
    digest = tb.span_hashes(data, first, last + string)
    base = offsets[owner]
    return owner, value[at].view(np.int64), at - base, first - base, last - base, digest.view(np.int64)


SEGMENT = "h long, doc_id long, a long, p long, q long, d long"


def _segments(docs: DataFrame) -> DataFrame:
    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                owner, h, a, p, q, d = segments(*tb.buffer(col.slice(lo, hi - lo)))
                if len(h):
                    ids = batch.column(0).slice(lo, hi - lo).take(pa.array(owner))
                    # 7 bits for each distance: at most string - gram
                    yield pa.RecordBatch.from_arrays([pa.array(h), ids, pa.array(a << 14 | (a - p) << 7 | (a - q)), pa.array(d)], names=["h", "doc_id", "at", "d"])

        return step

    return arrow_map(docs, make, "h long, doc_id long, at long, d long")


def _settled(rows: DataFrame) -> DataFrame:
    """Stream over segments in order of (h, doc_id, at): (doc_id, h, p, q, whole).

    whole: the segment's bytes stand in an earlier segment. Not whole: the first of its bytes, in a group
    with other bytes, so its own bytes are needed. Segments alone with their anchor are passed over. A
    group that goes on over batches keeps only the digests it has seen.
    """

    def run(batches):
        group, seen, held = None, set(), None  # held: the first segment of a group with one digest so far

        for batch in batches:
            if not batch.num_rows:
                continue
            h, doc, at, d = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(4))
            edge = np.ones(len(h), bool)
            edge[1:] = h[1:] != h[:-1]
            size = np.diff(np.append(np.flatnonzero(edge), len(h)))
            starts = np.flatnonzero(edge)
            # groups of one within the batch, but for its ends, need no look
            busy = size > 1
            busy[0] = busy[-1] = True
            out = []
            for s, n in zip(starts[busy].tolist(), size[busy].tolist(), strict=True):
                key = h.item(s)
                if key != group:
                    group, seen, held = key, set(), None
                for k in range(s, s + n):
                    x = d.item(k)
                    row = (doc.item(k), key, at.item(k))
                    if x in seen:
                        if row[0::2] != held_place(held):
                            out.append((*row, True))
                    elif not seen:
                        seen.add(x)
                        held = (row, False)
                    else:
                        if not held[1]:
                            out.append((*held[0], False))
                            held = (held[0], True)
                        seen.add(x)
                        out.append((*row, False))
            if out:
                ids, keys, places, whole = zip(*out, strict=True)
                places = np.array(places)
                a = places >> 14
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys, pa.int64()), pa.array(a - (places >> 7 & 127)), pa.array(a - (places & 127)), pa.array(whole, pa.bool_())], names=["doc_id", "h", "p", "q", "whole"])

    def held_place(held):
        return (held[0][0], held[0][2]) if held else None

    return rows.mapInArrow(run, "doc_id long, h long, p long, q long, whole boolean")


def _bytes(docs: DataFrame) -> DataFrame:
    """h, doc_id, p, bytes of the segments asked for (column ``asked``)."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            texts = strings(batch.column(1))
            for k in range(batch.num_rows):
                data = texts[k].as_py()
                asked = batch.column(2)[k].as_py()
                ids = pa.array([batch.column(0)[k].as_py()] * len(asked), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array([x["h"] for x in asked], pa.int64()), ids, pa.array([x["p"] for x in asked], pa.int64()), pa.array([data[x["p"] : x["q"] + STRING] for x in asked], pa.binary())], names=["h", "doc_id", "p", "b"])

        return step

    return arrow_map(docs.select("doc_id", "text", "asked"), make, "h long, doc_id long, p long, b binary")


def _repeats(docs: list[int], places: list[int], parts: list[bytes]) -> list[tuple[int, int, int]]:
    """(doc_id, first, last) runs of places with LPF >= STRING. Parts come in order of place."""
    sizes = np.array([len(b) for b in parts])
    at = np.cumsum(sizes + 1) - sizes - 1
    joined = np.frombuffer(b"\n".join(parts) + b"\n", np.uint8).astype(np.int64) + 1
    joined[at + sizes] = 0  # the end of a part; no string that is asked for reaches it
    # only places where a whole string begins are asked for
    begins = np.zeros(len(joined) + 1, np.int64)
    room = np.maximum(sizes - STRING + 1, 0)
    np.add.at(begins, at, 1)
    np.add.at(begins, at + room, -1)
    begins = np.cumsum(begins)[:-1] > 0
    order = suffix_array(joined, STRING)
    order = order[begins[order]]
    # a place whose neighbours in order share less than a string has no match that counts
    whole = _common_prefixes(joined, order, STRING) >= STRING
    near = whole.copy()
    near[:-1] |= whole[1:]
    order = order[near]
    found = np.sort(order)[longest_previous_factors(joined, order, STRING) >= STRING]
    if not len(found):
        return []
    part = np.searchsorted(at, found, "right") - 1
    edge = np.flatnonzero((np.diff(found) > 1) | (np.diff(part) > 0))
    first, last = np.append(0, edge + 1), np.append(edge, len(found) - 1)
    return [(docs[k], places[k] + x, places[k] + y) for k, x, y in zip(part[first].tolist(), (found[first] - at[part[first]]).tolist(), (found[last] - at[part[last]]).tolist(), strict=True)]


def _partial(rows: DataFrame) -> DataFrame:
    """Suffix arrays over whole groups of segments; rows come in order of (h, doc_id, p)."""

    def run(batches):
        waiting: list[tuple[int, int, int, bytes]] = []  # groups are not split
        size = 0

        def sort(ready):
            # Groups are put one after another; equal strings have one anchor hash, so they never match across.
            ready.sort(key=lambda r: (r[1], r[2]))
            found = _repeats([r[1] for r in ready], [r[2] for r in ready], [r[3] for r in ready])
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*found, strict=True) if found else ((), (), ()))], names=["doc_id", "p", "q"])

        for batch in batches:
            for r in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if size > SORT_BYTES and r[0] != waiting[-1][0]:
                    yield sort(waiting)
                    waiting, size = [], 0
                waiting.append(r)
                size += len(r[3])
        if waiting:
            yield sort(waiting)

    return rows.mapInArrow(run, "doc_id long, p long, q long")


def repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, spans): for each document with repeats, the byte ranges they cover. docs has unique ids."""
    settled = written(_settled(_segments(docs).repartition("h").sortWithinPartitions("h", "doc_id", "at")))
    asked = settled.filter("not whole").groupBy("doc_id").agg(F.collect_list(F.struct("h", "p", "q")).alias("asked"))
    parts = _bytes(docs.join(asked, "doc_id"))
    partial = _partial(parts.repartition("h").sortWithinPartitions("h", "doc_id", "p"))
    runs = settled.filter("whole").select("doc_id", "p", "q").unionAll(partial)
    return runs.groupBy("doc_id").agg(F.collect_list(F.struct("p", F.col("q").alias("q"))).alias("runs"))


def cleaned(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, spans (byte ranges), kept (bytes left)."""
    both = docs.join(repeats(docs), "doc_id", "left").select("doc_id", "text", "runs")

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            texts = strings(batch.column(1))
            for lo in range(0, batch.num_rows, 200):
                cols: list[list] = [[] for _ in range(5)]
                for k in range(lo, min(lo + 200, batch.num_rows)):
                    data, spans = texts[k].as_py(), []
                    for x in sorted(batch.column(2)[k].as_py() or [], key=lambda x: x["p"]):
                        a, b = x["p"], x["q"] + STRING
                        if spans and a <= spans[-1][1]:
                            spans[-1][1] = max(b, spans[-1][1])
                        else:
                            spans.append([a, b])
                    kept, at = [], 0
                    for a, b in spans:
                        kept.append(data[at:a])
                        at = b
                    kept.append(data[at:])
                    for c, v in zip(cols, (len(data), sum(b - a for a, b in spans), len(spans), [{"start": a, "end": b} for a, b in spans], b"".join(kept)), strict=True):
                        c.append(v)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, 200), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "spans", "kept"])

        return step

    return arrow_map(both, make, "doc_id long, n_bytes long, n_removed long, n_spans long, spans array<struct<start:long,end:long>>, kept binary")


def op1(spark, sf_dir: str) -> DataFrame:
    docs = one_row_per_id(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return cleaned(docs).select(shown(), "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def brute(rows: list[tuple], string: int = STRING) -> dict:
    """Slow check: {doc_id: (n_bytes, n_removed, n_spans, digest)}."""
    seen: set[bytes] = set()
    out = {}
    for d, t in sorted(rows, key=lambda r: (r[0] is not None, r[0])):
        data = (t or "").encode()
        gone = bytearray(len(data))
        for k in range(len(data) - string + 1):
            x = data[k : k + string]
            if x in seen:
                gone[k : k + string] = b"\x01" * string
            seen.add(x)
        runs = sum(1 for k in range(len(gone)) if gone[k] and (k == 0 or not gone[k - 1]))
        out[d] = (len(data), sum(gone), runs, hashlib.sha256(bytes(b for b, g in zip(data, gone, strict=True) if not g)).hexdigest())
    return out
