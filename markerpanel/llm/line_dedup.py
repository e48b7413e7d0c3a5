"""Line dedup by an exact set-similarity join.

A line is the set of its words (A-Z lower-cased). Two lines match if their Jaccard similarity is at
least LEAST hundredths; a line that matches an earlier line (of a smaller doc_id, or higher up in the same
document) is removed, whether or not the earlier one stays. Lines without words are never removed.

Equal sets collapse to their first line by digest. The others meet by prefix filtering: words are ordered by
rarity (counts over all lines, in a table of fixed size; ties by hash), and two similar sets share a
word among the first n - ceil(LEAST n / 100) + 1 of each. The lines of one prefix word are read in order of
place, and each is held against the earlier ones by length, by position and by 128 parity bits (two sets
differ in at least as many words as their bits). All filters are exact.

One earlier match is enough to remove a line, so each line and prefix word keep one row that lists up to MOST
of the candidates, nearest by parity first: rows grow with the lines, not with the square of a group of near
copies. Candidates are verified on whole sets in rounds: first the nearest of each row; for lines that are still
unmatched the rest of the list; for lines whose list was full, all candidates, by another pass. No candidate
is given up while its line is unmatched. A line's further matches aren't looked for once it has one.

A word in more than GROUP lines is dealt over blocks: its lines fall into chunks by hash, and each pair of chunks
is a group of its own, so no group holds more than about two chunks.

Defined cases: a null or empty text has one line without words and stays; rows that repeat an id are
merged first (the greatest text stays); a null id is an id of its own, before all others; other columns
are ignored by the operator and kept by the stage; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm import textbytes as tb
from markerpanel.llm.common import NULL_ID, arrow_map, discard, one_row_per_id, release, shown, sliced, strings, table, written

LEAST = 80
#: Distinct words of a line that is looked at: any line that has words.
MIN_WORDS = 1
#: Size of the table of word counts by hash; the same for every corpus.
RARITY_CELLS = 1 << 20
CHUNK = 1 << 14
SLICE = 1 << 18
#: Sets a task remembers as sent (bounds its memory only; results stay the same).
SENT = 300_000
#: Candidates that one row lists; lines with more get a pass of their own if these don't settle them.
MOST = 16
#: Lines of a word that one chunk of its group holds, about.
GROUP = 1 << 16
#: Rows that a task puts together before it compares them.
ROWS = 1 << 17
#: Lines or documents up to this many are broadcast (under 100 bytes each); more are joined by shuffle.
BROADCAST_ROWS = 200_000


def _line_words(texts: pa.Array):
    """Distinct (line, word hash) of a slice, and per line its text and number in the text.

    Lines are numbered over the slice; every text has one line more than line feeds.
    """
    data, offsets = tb.buffer(texts)
    feeds = np.cumsum(data == 10, dtype=np.int64 if len(data) >= 1 << 31 else np.int32)  # up to each byte, itself included
    before = np.where(offsets > 0, feeds[offsets - 1], 0).astype(np.int64) if len(data) else np.zeros(len(offsets), np.int64)  # line feeds before each text
    first = before[:-1] + np.arange(len(texts))
    n_lines = np.diff(before) + 1
    low = tb.lowered(data)
    s, e, doc = tb.words(low, offsets, tb.NOT_GAP)
    h = tb.span_hashes(low, s, e)
    line = feeds[s] + doc  # no word starts with a line feed
    owner = np.repeat(np.arange(len(texts)), n_lines)
    number = np.arange(len(owner)) - first[owner]
    return line, h, owner, number


def _per_line(combine: np.ufunc, values: np.ndarray, size: np.ndarray) -> np.ndarray:
    """One number a line from its words' values, which stand line by line; 0 for lines without words."""
    out = np.zeros(len(size), np.uint64)
    some = np.flatnonzero(size)
    if len(some):
        out[some] = combine.reduceat(values, (np.cumsum(size) - size)[some])
    return out


def _digests(h: np.ndarray, size: np.ndarray) -> list[np.ndarray]:
    """128 bits of each line's set, as two columns."""
    return [_per_line(np.add, tb.mixed(h ^ np.uint64(salt)), size).view(np.int64) for salt in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)]


def _parity(h: np.ndarray, size: np.ndarray) -> list[np.ndarray]:
    """128 bits of each line: bit b is set if an odd number of its words hash to b."""
    cell = tb.mixed(h) >> np.uint64(57)
    one = np.uint64(1) << (cell & np.uint64(63))
    return [_per_line(np.bitwise_xor, np.where(half, one, np.uint64(0)), size).view(np.int64) for half in (cell < 64, cell >= 64)]


def _slices(col: pa.Array) -> Iterator[tuple[int, int]]:
    return sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE)


def rarity(docs: DataFrame) -> np.ndarray:
    """Word counts by hash cell, over all lines, as eighths of their base-2 logarithm (a byte a cell).

    A task adds up one vector and sends it in chunks; the chunks of all tasks are added up where they meet.
    """

    def count(batches):
        total = np.zeros(RARITY_CELLS, np.int64)
        for batch in batches:
            col = strings(batch.column(0))
            for lo, hi in _slices(col):
                data, offsets = tb.buffer(col.slice(lo, hi - lo))
                data = tb.lowered(data)
                h = tb.span_hashes(data, *tb.words(data, offsets, tb.NOT_GAP)[:2])
                total += np.bincount((h % np.uint64(RARITY_CELLS)).astype(np.int64), minlength=RARITY_CELLS)
        total = np.minimum(total, 2**32 - 1).astype(np.uint32)
        chunks = [total[k : k + CHUNK].tobytes() for k in range(0, RARITY_CELLS, CHUNK) if total[k : k + CHUNK].any()]
        at = [k // CHUNK for k in range(0, RARITY_CELLS, CHUNK) if total[k : k + CHUNK].any()]
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(chunks, pa.binary())], names=["chunk", "n"])

    def add(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for chunk, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sums[chunk] = sums.get(chunk, 0) + np.frombuffer(n, np.uint32).astype(np.int64)
        if sums:
            marks = [np.minimum(255, np.log2(v + 1) * 8).astype(np.uint8).tobytes() for v in sums.values()]
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array(marks, pa.binary())], names=["chunk", "n"])

    parts = docs.select("text").mapInArrow(count, "chunk int, n binary").repartition("chunk").mapInArrow(add, "chunk int, n binary")
    out = np.zeros(RARITY_CELLS, np.uint8)
    for r in parts.toLocalIterator():
        out[r.chunk * CHUNK : (r.chunk + 1) * CHUNK] = np.frombuffer(r.n, np.uint8)
    return out


def _chunks(marks: np.ndarray, group: int) -> np.ndarray:
    """Into how many chunks the lines of words are dealt, from their counts' upper bounds."""
    return np.maximum(1, np.ceil(2 ** ((marks.astype(float) + 1) / 8) / group)).astype(np.int64)


def _lines(docs: DataFrame, held, least: int, min_words: int, group: int) -> DataFrame:
    """doc_id, line, size, d1, d2 (digest of the set) of every line of at least min_words distinct words.

    keys: the line's prefix words, rarest first, where another set can match it, and b1, b2, its parity bits; places:
    the keys' places in the order, null if they are 0, 1, 2, ... A task passes over sets that it has just sent
    (keys is null then), so frequent lines are thinned before the shuffle; what several tasks send meets after it.
    """

    def make():
        counts = held.value
        of_mark = _chunks(np.arange(256), group) if group < 1 << 30 else np.ones(256, np.int64)
        sent: set[int] = set()

        def dealt(words: np.ndarray, blocks: np.ndarray, seeds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Keys of prefix words, and the entry each belongs to: a word that many lines have gets one for each pair of chunks that its line is in."""
            entry = np.repeat(np.arange(len(words)), blocks)
            g = blocks[entry].astype(np.uint64)
            t = (np.arange(len(entry)) - np.repeat(np.cumsum(blocks) - blocks, blocks)).astype(np.uint64)
            own = seeds[entry] % g
            pairs = np.minimum(own, t) * g + np.maximum(own, t)
            return np.where(g > 1, tb.mixed(words[entry] ^ tb.mixed(pairs * np.uint64(2) + np.uint64(1))), words[entry]), entry

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for lo, hi in _slices(col):
                line, h, owner, number = _line_words(col.slice(lo, hi - lo))
                mark = counts[(h % np.uint64(RARITY_CELLS)).astype(np.int64)]
                line, h = tb.distinct(line, h, mark)
                mark = counts[(h % np.uint64(RARITY_CELLS)).astype(np.int64)]
                size = np.bincount(line, minlength=len(owner))
                d1, d2 = _digests(h, size)
                b1, b2 = _parity(h, size)
                keep = np.flatnonzero(size >= min_words)
                if len(sent) > SENT:
                    sent.clear()
                fresh = np.zeros(len(owner), bool)
                # n words are at most n / (n + 1) similar to any other set: smaller sets have only their copies
                able = keep[100 * size[keep] >= least * (size[keep] + 1)]
                for k, x, y in zip(able.tolist(), d1[able].tolist(), d2[able].tolist(), strict=True):
                    key = hash((x, y))
                    if key not in sent:
                        sent.add(key)
                        fresh[k] = True
                start = np.cumsum(size) - size
                prefix = np.where(fresh, size - -(-least * size // 100) + 1, 0)
                at = np.arange(len(line)) - start[line]
                inside = at < prefix[line]
                blocks = of_mark[mark]
                hot = np.zeros(len(owner), bool)
                hot[line[inside & (blocks > 1)]] = True
                words, n_keys = h[inside], prefix
                places = pa.nulls(len(keep), pa.list_(pa.int32()))
                if hot.any():
                    # a line's seed is its place in the corpus; the keys of one line stand together, as its words do
                    of = line[inside]
                    seeds = tb.mixed(ids[lo + owner].view(np.uint64)) + tb.mixed(number.astype(np.uint64))
                    words, entry = dealt(words, blocks[inside], seeds[of])
                    n_keys = np.bincount(of[entry], minlength=len(owner))
                    some = hot[of[entry]]
                    edges = pa.array(np.concatenate([[0], np.cumsum(np.where(hot, n_keys, 0)[keep])]), pa.int32())
                    places = pa.ListArray.from_arrays(edges, pa.array(at[inside][entry][some], pa.int32()), mask=pa.array(~hot[keep]))
                keys = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n_keys[keep])]), pa.int32()), pa.array(words.view(np.int64)))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[lo + owner[keep]]), *(pa.array(c[keep]) for c in (number, size, d1, d2, b1, b2)), keys, places],
                    names=["doc_id", "line", "size", "d1", "d2", "b1", "b2", "keys", "places"],
                )

        return step

    return arrow_map(docs, make, "doc_id long, line long, size long, d1 long, d2 long, b1 long, b2 long, keys array<long>, places array<int>")


def _sets(docs: DataFrame) -> DataFrame:
    """doc_id, line, d1, d2, items for the lines asked for (column ``lines``) of each text."""

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            ids, asked = batch.column(0), batch.column(2)
            for lo, hi in _slices(col):
                line, h, owner, _ = _line_words(col.slice(lo, hi - lo))
                part = asked.slice(lo, hi - lo)
                n = np.diff(part.offsets.to_numpy())
                text = np.repeat(np.arange(hi - lo), n)
                number = part.flatten().to_numpy()
                first = np.searchsorted(owner, np.arange(hi - lo))
                at = first[text] + number
                some = np.zeros(len(owner), bool)
                some[at] = True
                own = some[line]
                line, h = tb.distinct(line[own], h[own])
                size = np.bincount(line, minlength=len(owner))
                d1, d2 = _digests(h, size)
                start = np.cumsum(size) - size
                ends = np.cumsum(size[at])
                where = np.arange(ends[-1] if len(ends) else 0) + np.repeat(start[at] - (ends - size[at]), size[at])
                items = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(h[where].view(np.int64)))
                yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo).take(pa.array(text)), pa.array(number, pa.int64()), pa.array(d1[at]), pa.array(d2[at]), items], names=["doc_id", "line", "d1", "d2", "items"])

        return step

    return arrow_map(docs.select("doc_id", "text", "lines"), make, "doc_id long, line long, d1 long, d2 long, items array<long>")


def _earlier(c: dict[str, np.ndarray], least: int, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, earlier row, parity distance) of the candidates of each row that asks, and the rows with ``most`` or more.

    Rows stand by key, then place. A row is held against the one before it, the one before that, and so on, for all
    rows at once, until it has ``most`` candidates or its group ends.
    """
    key, n, pos = c["key"], c["size"], c["pos"]
    b1, b2 = c["b1"].view(np.uint64), c["b2"].view(np.uint64)
    fresh = np.ones(len(key), bool)
    fresh[1:] = key[1:] != key[:-1]
    rank = np.arange(len(key)) - np.flatnonzero(fresh)[np.cumsum(fresh) - 1]
    # a smaller set needs a shorter prefix: its partner is no smaller, so they share at least 2 least / (100 + least) of it
    short = pos < n + 1 - -(-2 * least * n // (100 + least))
    found = np.zeros(len(key), np.int64)
    act = np.flatnonzero(c["asks"] & (rank > 0))
    rows, others, away = [], [], []
    k = 0
    while len(act):
        k += 1
        act = act[(rank[act] >= k) & (found[act] < most)]
        i, j = act, act - k
        both = n[i] + n[j]
        room = both - 2 * -(-least * both // (100 + least))  # words in which similar sets of these sizes may differ
        far = np.bitwise_count(b1[i] ^ b1[j]).astype(np.int64)
        ok = np.flatnonzero(far <= room)
        i, j, both, room = i[ok], j[ok], both[ok], room[ok]
        far = far[ok] + np.bitwise_count(b2[i] ^ b2[j])
        ni, nj, pi, pj = n[i], n[j], pos[i], pos[j]
        ok = (far <= room) & (100 * np.minimum(ni, nj) >= least * np.maximum(ni, nj))
        ok &= np.where(ni < nj, short[i], np.where(nj < ni, short[j], short[i] | short[j]))
        # words before the shared one may also be shared: at most the lesser place of the two
        ok &= 2 * (np.minimum(pi, pj) + np.minimum(ni - pi, nj - pj)) >= both - room
        found[i[ok]] += 1
        rows.append(i[ok])
        others.append(j[ok])
        away.append(far[ok])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *rows]), np.concatenate([none, *others]), np.concatenate([none, *away]), found >= most


def _candidates(postings: DataFrame, least: int, most: int) -> DataFrame:
    """doc_id, line, ds, ls: for each posting that asks and has any, up to ``most`` earlier lines by parity distance; full: there may be more."""

    def compare(part: dict[str, np.ndarray]) -> pa.RecordBatch | None:
        doc, line = part["doc_id"], part["line"]
        fresh = np.ones(len(doc), bool)
        fresh[1:] = part["key"][1:] != part["key"][:-1]
        group = np.cumsum(fresh)
        span, longest = int(doc.max()) - int(doc.min()), int(line.max())
        bits = (int(group[-1]).bit_length(), span.bit_length(), longest.bit_length())
        if sum(bits) < 64:
            order = np.argsort(((group << bits[1] | (doc - doc.min())) << bits[2]) | line)
        else:
            order = np.lexsort((line, doc, group))
        part = {k: v[order] for k, v in part.items()}
        facts = part.pop("facts")
        part |= {"size": facts >> 32, "pos": (facts & (2**32 - 1)) >> 1, "asks": (facts & 1) == 1}
        i, j, far, full = _earlier(part, least, most)
        if not len(i):
            return None
        order = np.lexsort((j, far, i))
        i, j = i[order], j[order]
        own, first = np.unique(i, return_index=True)
        edges = pa.array(np.append(first, len(i)), pa.int32())
        lists = [pa.ListArray.from_arrays(edges, pa.array(part[c][j])) for c in ("doc_id", "line")]
        return pa.RecordBatch.from_arrays([pa.array(part["doc_id"][own]), pa.array(part["line"][own]), *lists, pa.array(full[own])], names=["doc_id", "line", "ds", "ls", "full"])

    names = ("key", "doc_id", "line", "facts", "b1", "b2")

    def run(batches):
        held: list[dict[str, np.ndarray]] = []
        n = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append({c: batch.column(c).to_numpy(zero_copy_only=False) for c in names})
            n += batch.num_rows
            if n < ROWS or held[0]["key"][0] == held[-1]["key"][-1]:
                continue
            whole = {c: np.concatenate([h[c] for h in held]) for c in names}
            cut = np.searchsorted(whole["key"], whole["key"][-1])  # the last key may go on
            if out := compare({c: v[:cut] for c, v in whole.items()}):
                yield out
            held = [{c: v[cut:] for c, v in whole.items()}]
            n -= cut
        if held and (out := compare({c: np.concatenate([h[c] for h in held]) for c in names})):
            yield out

    rows = postings.repartition("key").sortWithinPartitions("key").select(*names)
    return rows.mapInArrow(run, "doc_id long, line long, ds array<long>, ls array<long>, full boolean")


def _postings(lines: DataFrame, asks) -> DataFrame:
    """One row for each key of each line; facts: its size, its place in the order and whether it asks, in one number."""
    some = lines.filter(F.size("keys") > 0).select("doc_id", "line", "size", "b1", "b2", "places", asks.alias("asks"), F.posexplode("keys").alias("i", "key"))
    pos = F.coalesce(F.get("places", F.col("i")), F.col("i")).cast("long")
    facts = F.shiftleft("size", 32).bitwiseOR(F.shiftleft(pos, 1)).bitwiseOR(F.col("asks").cast("long"))
    return some.select("key", "doc_id", "line", facts.alias("facts"), "b1", "b2")


def _verified(pairs: DataFrame, docs: DataFrame, least: int) -> DataFrame:
    """The pairs (doc_id, line, of_doc, of_line) that are similar on their whole sets, with the digest of the line's set. Written; pairs goes."""
    ends = pairs.select("doc_id", "line").unionAll(pairs.select("of_doc", "of_line"))
    asked = written(ends.groupBy("doc_id").agg(F.collect_set("line").alias("lines")))
    items = written(_sets(docs.join(_small(asked), "doc_id")))
    x = items.toDF("doc_id", "line", "d1", "d2", "x")
    y = items.select(F.col("doc_id").alias("of_doc"), F.col("line").alias("of_line"), F.col("items").alias("y"))
    both = pairs.join(x, ["doc_id", "line"]).join(y, ["of_doc", "of_line"])
    shared = F.size(F.array_intersect("x", "y"))
    out = written(both.filter(100 * shared >= least * (F.size("x") + F.size("y") - shared)).select("doc_id", "line", "of_doc", "of_line", "d1", "d2"))
    discard(pairs, asked, items)
    return out


def _small(df: DataFrame) -> DataFrame:
    """A written table, marked for broadcast if it has few rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def _pairs(rows: DataFrame, first: bool) -> DataFrame:
    """Distinct (doc_id, line, of_doc, of_line) of the nearest candidates, or of all others."""
    if first:
        return rows.select("doc_id", "line", F.get("ds", F.lit(0)).alias("of_doc"), F.get("ls", F.lit(0)).alias("of_line")).distinct()
    both = F.slice(F.arrays_zip("ds", "ls"), F.lit(2), F.size("ds"))
    return rows.select("doc_id", "line", F.explode(both).alias("o")).select("doc_id", "line", F.col("o.ds").alias("of_doc"), F.col("o.ls").alias("of_line")).distinct()


def similar_lines(lines: DataFrame, docs: DataFrame, least: int, most: int) -> DataFrame:
    """(doc_id, line, of_doc, of_line, d1, d2): for each line that has any, earlier lines of other sets that it matches, at least one."""
    place = ["doc_id", "line"]
    rows = written(_candidates(_postings(lines, F.lit(True)), least, most))
    release(lines.sparkSession)  # the postings' shuffle isn't needed any more
    found = _verified(written(_pairs(rows, True)), docs, least)
    open_ = written(rows.filter("size(ds) > 1 or full").join(found.select(*place).distinct(), place, "left_anti"))
    discard(rows)
    rest = written(_pairs(open_, False))
    if not rest.isEmpty():
        more = _verified(rest, docs, least)
        open_, found = open_.join(more.select(*place).distinct(), place, "left_anti"), found.unionAll(more)
    last = written(open_.filter("full").select(*place).distinct())
    if not last.isEmpty():  # lines whose lists were full and held no match: all their candidates
        asking = _small(last.withColumn("asks", F.lit(True)))
        marked = lines.join(asking, place, "left").withColumn("asks", F.coalesce("asks", F.lit(False)))
        keys = _small(written(marked.filter("asks").select(F.explode("keys").alias("key")).distinct()))
        all_ = written(_candidates(_postings(marked, F.col("asks")).join(keys, "key", "left_semi"), least, 1 << 40))
        every = written(_pairs(all_, True).unionAll(_pairs(all_, False)).distinct())
        found = found.unionAll(_verified(every, docs, least))
    return found


def line_matches(docs: DataFrame, least: int = LEAST, min_words: int = MIN_WORDS, most: int = MOST, group: int = GROUP) -> DataFrame:
    """(doc_id, line, of_doc, of_line) of each line that is removed and an earlier line that it matches; docs has unique ids."""
    held = docs.sparkSession.sparkContext.broadcast(rarity(docs))
    lines = written(_lines(docs, held, least, min_words, group))
    near = similar_lines(lines, docs, least, most)
    place = F.struct("doc_id", "line")
    both = lines.select("d1", "d2", place.alias("f"), F.lit(None).cast("struct<doc_id: bigint, line: bigint>").alias("m"))
    both = both.unionAll(near.select("d1", "d2", F.lit(None).cast("struct<doc_id: bigint, line: bigint>"), F.struct(F.col("of_doc").alias("doc_id"), F.col("of_line").alias("line"))))
    sets = both.groupBy("d1", "d2").agg(F.min("f").alias("f"), F.count("f").alias("n"), F.min("m").alias("m"))
    # a copy may have matched a line that stands after its set's first place
    sets = sets.withColumn("m", F.when(F.col("m") < F.col("f"), F.col("m"))).filter("n > 1 or m is not null")
    known = _small(written(sets.select("d1", "d2", F.coalesce("m", "f").alias("g"))))
    hits = lines.select("doc_id", "line", "d1", "d2").join(known, ["d1", "d2"]).filter(F.col("g") < place)
    hits = written(hits.select("doc_id", "line", F.col("g.doc_id").alias("of_doc"), F.col("g.line").alias("of_line")))
    discard(lines)
    return hits


def deduplicated(docs: DataFrame, least: int = LEAST, min_words: int = MIN_WORDS, most: int = MOST, group: int = GROUP) -> DataFrame:
    """doc_id, text (kept lines, joined by line feeds), n_lines, n_removed for every document (unique ids)."""
    hits = line_matches(docs, least, min_words, most, group)
    gone = _small(written(hits.groupBy("doc_id").agg(F.collect_list(F.col("line").cast("int")).alias("gone"))))
    feeds = F.coalesce(F.octet_length("text") - F.octet_length(F.replace("text", F.lit("\n"), F.lit(""))), F.lit(0))
    out = docs.join(gone, "doc_id", "left").withColumn("gone", F.coalesce("gone", F.array().cast("array<int>")))

    def rest(lines):
        """lines is split once, however many of it stay."""
        return F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("gone")), lambda k: lines[k]), "\n")

    kept = F.when(F.size("gone") == 0, F.col("text")).otherwise(F.transform(F.array(F.split("text", "\n")), rest)[0])
    return out.select("doc_id", kept.alias("text"), (feeds + 1).cast("long").alias("n_lines"), F.size("gone").cast("long").alias("n_removed"))


def op9(spark, sf_dir: str) -> DataFrame:
    docs = one_row_per_id(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return deduplicated(docs).select(shown(), "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def brute(rows: list[tuple], least: int = LEAST, min_words: int = MIN_WORDS) -> dict:
    """Slow check: {doc_id: (n_lines, n_removed, digest)}."""
    import re

    lines = []
    for d, t in sorted(rows, key=lambda r: NULL_ID if r[0] is None else r[0]):
        for k, line in enumerate((t or "").split("\n")):
            low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line)
            lines.append((d, k, line, frozenset(re.findall(r"[^\x20\x09-\x0D]+", low))))
    alike = lambda x, y: 100 * len(x & y) >= least * len(x | y)
    out = {d: [0, 0, []] for d, _ in rows}
    for i, (d, _, line, s) in enumerate(lines):
        own = out[d]
        own[0] += 1
        if len(s) >= min_words and any(len(o[3]) >= min_words and alike(s, o[3]) for o in lines[:i]):
            own[1] += 1
        else:
            own[2].append(line)
    return {d: (a, b, hashlib.sha256("\n".join(x).encode()).hexdigest()) for d, (a, b, x) in out.items()}
