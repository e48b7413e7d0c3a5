"""Rule bitmask ledger: every rule is evaluated once per document and leaves one bit; policies and
ablations are then bit operations on the ledger. DataFrame functions only.

Inputs: any DataFrame with doc_id and text; other columns are ignored. A null or empty text has no
words, so it fails too_few_words and is not kept. Rows stand alone: repeated rows and null ids give
one ledger row each. Whole texts are read, of any length. An empty table gives an empty ledger.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the contract.
WORD_GAP = "[\\x20\\x09-\\x0D]+"
GAP_CHARS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 8


def _let(value: Column, body) -> Column:
    """body(value) with value computed once per row, also where body uses it inside lambdas."""
    return F.transform(F.array(value), body)[0]


def _repeat_words(words: Column) -> Column:
    """Number of words inside windows of WINDOW words that occur twice or more."""

    def pairs(hashes: Column, gap: int) -> Column:
        """Hash of a stretch and of the stretch ``gap`` words on, over all places where both fit."""
        whole = F.size(hashes) - gap
        return F.when(whole > 0, F.zip_with(F.slice(hashes, F.lit(1), F.greatest(whole, F.lit(0))), F.slice(hashes, F.lit(gap + 1), F.greatest(whole, F.lit(0))), lambda a, b: F.xxhash64(a, b))).otherwise(F.array().cast("array<bigint>"))

    def covered(hashes: Column) -> Column:
        marked = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def starts(rows: Column) -> Column:
            same = lambda x, k: F.coalesce(F.get(rows, k)["h"] == x["h"], F.lit(False))
            return F.sort_array(F.transform(F.filter(rows, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))

        def union(at: Column) -> Column:
            gaps = F.transform(at, lambda p, k: F.least(F.lit(WINDOW), F.coalesce(F.get(at, k + 1) - p, F.lit(WINDOW))))
            return F.aggregate(gaps, F.lit(0).cast("long"), lambda s, g: s + g)

        return _let(_let(marked, starts), union)

    def count(hashes: Column) -> Column:
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0).cast("long")).otherwise(covered(hashes))

    one = F.transform(words, lambda w: F.xxhash64(w))
    windows = _let(_let(_let(one, lambda h: pairs(h, 1)), lambda h: pairs(h, 2)), lambda h: pairs(h, 4))
    return F.when(F.size(words) < WINDOW, F.lit(0).cast("long")).otherwise(_let(windows, count))


def measured(docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """The key column and the base measures of each text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    bare = lambda s: F.translate(s, GAP_CHARS, "")
    # a regex split leaves an empty piece at an end that has a gap
    words = F.filter(F.split(text, WORD_GAP), lambda w: w != "")
    lines = F.filter(F.split(text, "\n"), lambda s: bare(s) != "")
    counts = lambda w: F.struct(F.size(w).cast("long").alias("n"), _repeat_words(w).alias("r"))
    return docs.select(
        key,
        _let(words, counts).alias("w"),
        F.char_length(bare(text)).cast("long").alias("word_chars"),
        (F.char_length(text) - F.char_length(F.translate(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        _let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("d"))).alias("l"),
        (F.char_length(text) - F.char_length(F.translate(text, "!", ""))).cast("long").alias("n_bangs"),
    ).select(key, F.col("w.n").alias("n_words"), "word_chars", "n_symbols", F.col("l.d").alias("n_dup_lines"), F.col("w.r").alias("n_repeat_words"), F.col("l.n").alias("n_lines"), "n_bangs")


@dataclass(frozen=True)
class Rule:
    """``fails`` is true where a document breaks the rule; it sees the columns of measured()."""

    name: str
    fails: str


#: Bit k of the ledger belongs to the k-th rule. New rules go to the end, so that stored bits stay valid.
RULES = (
    Rule("too_few_words", "n_words < 20"),
    Rule("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    Rule("symbol_heavy", "10 * n_symbols > n_words"),
    Rule("duplicate_lines", "10 * n_dup_lines > 3 * n_lines"),
    Rule("bang_heavy", "10 * n_bangs > n_words"),
    Rule("odd_word_length", "word_chars < 2 * n_words or word_chars > 15 * n_words"),
)
#: Versioned policies: the rules whose bit rejects a document.
POLICIES = {
    "base": ("too_few_words", "repeated_windows"),
    "v1": ("too_few_words", "repeated_windows", "symbol_heavy", "duplicate_lines", "bang_heavy", "odd_word_length"),
}


def mask(rules) -> int:
    names = [r.name for r in RULES]
    return sum(1 << names.index(x) for x in rules)


def ledger(docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """measured() and failure_bits: bit k is set where RULES[k] fails."""
    bits = None
    for k, rule in enumerate(RULES):
        bit = F.when(F.expr(rule.fails), F.lit(1 << k)).otherwise(F.lit(0)).cast("long")
        bits = bit if bits is None else bits.bitwiseOR(bit)
    return measured(docs, key).withColumn("failure_bits", bits)


def apply_policy(led: DataFrame, policy: str = "v1") -> DataFrame:
    """Adds base_failed and kept; nothing is measured again."""
    bits = F.col("failure_bits")
    return led.withColumns({"base_failed": bits.bitwiseAND(mask(POLICIES["base"])) != 0, "kept": bits.bitwiseAND(mask(POLICIES["base"]) | mask(POLICIES[policy])) == 0})


def accepted(docs: DataFrame, policy: str = "v1") -> DataFrame:
    """The rows of docs that a policy keeps, with their own columns (whatever their names) and no others."""
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), "text")
    return apply_policy(ledger(rows, "row"), policy).filter("kept").select("row.*")


def ablation(led: DataFrame, policy: str = "v1") -> DataFrame:
    """For each rule of a policy: rejected by it, rejected by it alone, and kept if it were dropped.

    The ledger shrinks to one row per bit pattern before anything else, at most 2 ** len(RULES) rows.
    """
    patterns = led.groupBy("failure_bits").agg(F.count(F.lit(1)).alias("n"))
    whole = mask(POLICIES[policy])
    rules = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(mask([r])).cast("long").alias("bit")) for r in POLICIES[policy]]))
    bits = F.col("failure_bits").bitwiseAND(F.lit(whole).cast("long"))
    hit = bits.bitwiseAND(F.col("r.bit")) != 0
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0)).cast("long")
    return patterns.withColumn("r", rules).groupBy(F.col("r.rule").alias("rule")).agg(total(hit).alias("n_rejected"), total(hit & (bits == F.col("r.bit"))).alias("n_only"), total((bits == 0) | (bits == F.col("r.bit"))).alias("n_kept_without"))


def op5(spark, sf_dir: str) -> DataFrame:
    from markerpanel.llm.common import table

    led = apply_policy(ledger(table(spark, sf_dir, "documents").select("doc_id", "text")))
    return led.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failure_bits")


#: DuckDB: the windows are unnested and counted, a different route than the array functions above.
OP5_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words,
             list_filter(string_split(text, chr(10)), lambda s: regexp_matches(s, '[^\x20\x09-\x0D]')) AS lines FROM d),
win AS (SELECT doc_id, unnest(range(0, len(words) - 7)) AS i, words FROM w WHERE len(words) >= 8),
keyed AS (SELECT doc_id, i, array_to_string(list_slice(words, i + 1, i + 8), ' ') AS k FROM win),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM keyed) WHERE c > 1),
hit AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM twice) GROUP BY doc_id),
m AS (SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words,
             CAST(length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
             CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
             CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
             CAST(coalesce(hit.n, 0) AS BIGINT) AS n_repeat_words, len(lines) AS n_lines,
             length(regexp_replace(text, '[^!]', '', 'g')) AS n_bangs
      FROM w LEFT JOIN hit ON w.doc_id = hit.doc_id),
b AS (SELECT *, CAST((CASE WHEN n_words < 20 THEN 1 ELSE 0 END) + (CASE WHEN 100 * n_repeat_words > 30 * n_words THEN 2 ELSE 0 END)
      + (CASE WHEN 10 * n_symbols > n_words THEN 4 ELSE 0 END) + (CASE WHEN 10 * n_dup_lines > 3 * n_lines THEN 8 ELSE 0 END)
      + (CASE WHEN 10 * n_bangs > n_words THEN 16 ELSE 0 END)
      + (CASE WHEN word_chars < 2 * n_words OR word_chars > 15 * n_words THEN 32 ELSE 0 END) AS BIGINT) AS failure_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, failure_bits % 4 <> 0 AS base_failed,
       failure_bits = 0 AS kept, failure_bits FROM b
"""
