"""Sequence columns: letters, 2-bit packing, reverse complement, k-mers, signatures. Built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from markerpanel.errors import PanelError

LETTERS = "ACGT"
ALPHABET = "abcdefghijklmnopqrstuvwxyz"


def col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def dna_letters(text) -> Column:
    """Stand-in for reads: the a-z of a lowered text, letter i as ACGT[i mod 4]."""
    return F.translate(F.regexp_replace(F.lower(col(text)), "[^a-z]", ""), ALPHABET, "".join(LETTERS[i % 4] for i in range(26)))


def let(value, body) -> Column:
    """body(value), with value computed once a row even where body uses it many times or inside lambdas."""
    return F.transform(F.array(col(value)), body)[0]


def _cut(seq: Column, pattern: str, group: int = 0) -> Column:
    """All matches of a pattern, found in one pass from left to right; null gives an empty array."""
    return F.coalesce(F.regexp_extract_all(seq, F.lit(pattern), F.lit(group)), F.array().cast("array<string>"))


def pieces(seq, size: int) -> Column:
    """Consecutive pieces of a sequence; a remainder is dropped."""
    return _cut(col(seq), f"(?s).{{{size}}}")


def is_dna(seq) -> Column:
    return col(seq).rlike("^[ACGT]+$")


def pack_tag(seq) -> Column:
    """Header byte (length mod 4), then two bits a base, first base highest, zero padding. BINARY."""

    def packed(s: Column) -> Column:
        n = F.length(s)
        padded = F.rpad(F.translate(s, LETTERS, "0123"), F.floor((n + 3) / 4).cast("int") * 4, F.lit("0"))
        # 32 bases are one unsigned 64-bit number
        words = F.transform(_cut(padded, ".{1,32}"), lambda w: F.lpad(F.conv(w, 4, 16), F.floor(F.length(w) / 2).cast("int"), F.lit("0")))
        return F.when(n.isNotNull(), F.unhex(F.concat(F.lpad(F.hex(n % 4), 2, "0"), F.array_join(words, ""))))

    return let(seq, packed)


def unpack_tag(packed) -> Column:
    def bases(h: Column) -> Column:
        n_bytes = F.floor(F.length(h) / 2) - 1
        rest = F.conv(F.substring(h, 1, 2), 16, 10).cast("int")
        length = (n_bytes * 4 - F.when(rest == 0, F.lit(0)).otherwise(4 - rest)).cast("int")
        words = F.transform(_cut(F.substring(h, F.lit(3), F.length(h)), ".{1,16}"), lambda w: F.lpad(F.conv(w, 16, 4), F.length(w) * 2, F.lit("0")))
        return F.when(h.isNotNull(), F.substring(F.translate(F.array_join(words, ""), "0123", LETTERS), F.lit(1), length))

    return let(F.hex(col(packed)), bases)


def revcomp(seq) -> Column:
    return F.reverse(F.translate(col(seq), LETTERS, LETTERS[::-1]))


def kmers(seq, k: int) -> Column:
    """All windows of k bases, left to right; empty if the sequence is shorter."""
    if not 1 <= k <= 32:
        raise PanelError(f"k must be in 1..32, got {k}")
    return _cut(col(seq), f"(?s)(?=(.{{{k}}}))", 1)


def canonical_kmer(kmer) -> Column:
    return F.least(col(kmer), revcomp(kmer))


def canonical_signature(seq, k: int, order: str = "lex") -> Column:
    """The least canonical k-mer: by letters (the order of the 2-bit code) or by hash. Null below k bases."""
    if not 1 <= k <= 32:
        raise PanelError(f"k must be in 1..32, got {k}")

    def windows(both: Column) -> Column:
        """Each window beside the window of the reverse complement that mirrors it: one reversal per sequence."""
        s, rc = both["s"], both["rc"]
        n = F.length(s) - k + 1
        own = F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.least(F.substring(s, i, F.lit(k)), F.substring(rc, n - i + 1, F.lit(k))))
        return F.when(n > 0, own).otherwise(F.array().cast("array<string>"))

    own = F.transform(F.array(F.struct(col(seq).alias("s"), revcomp(seq).alias("rc"))), windows)[0]
    if order == "lex":
        return F.array_min(own)
    if order == "hash":
        return F.array_min(F.transform(own, lambda x: F.struct(F.xxhash64(x).alias("h"), x.alias("k"))))["k"]
    raise PanelError(f"order {order!r}")


def kmer_code(kmer) -> Column:
    """The unsigned 64-bit code as DECIMAL(20,0): a signed BIGINT would be wrong for 32 bases."""
    return F.conv(F.translate(col(kmer), LETTERS, "0123"), 4, 10).cast("decimal(20,0)")


def substitutions(seq) -> Column:
    """Every single-base substitution: array of (at, base, mutant)."""
    s = col(seq)
    per = lambda i: F.transform(F.filter(F.array(*map(F.lit, LETTERS)), lambda b: b != F.substring(s, i, F.lit(1))), lambda b: F.struct(i.alias("at"), b.alias("base"), F.concat(F.substring(s, F.lit(1), i - 1), b, F.substring(s, i + 1, F.length(s))).alias("mutant")))
    return F.flatten(F.transform(F.sequence(F.lit(1), F.length(s)), per))


def hamming(a, b) -> Column:
    """Differing places of two sequences of one length."""
    x, y = F.split(col(a), ""), F.split(col(b), "")
    return F.aggregate(F.zip_with(x, y, lambda p, q: (p != q).cast("int")), F.lit(0), lambda s, v: s + F.coalesce(v, F.lit(1)))


def html_text(html) -> Column:
    """Visible text: scripts, styles, comments and tags become spaces."""
    s = F.regexp_replace(col(html), "(?is)<(script|style)[^>]*>.*?</\\1>|<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(s, "(?s)<[^>]*>", " "), "\\s+", " "))
