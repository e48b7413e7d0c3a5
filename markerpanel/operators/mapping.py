"""Candidates on reference contigs: exact seeds, votes per diagonal, verification. No external aligner."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from markerpanel.functions import dna

#: Contig seeds up to this many are broadcast (about 50 bytes each); more are joined by shuffle.
BROADCAST_SEEDS = 2_000_000


def seeds(contigs: DataFrame, k: int) -> DataFrame:
    """kmer, contig, pos of every window of every contig."""
    return contigs.select("contig", F.posexplode(dna.kmers("seq", k)).alias("pos", "kmer"))


def map_markers(tags: DataFrame, contigs: DataFrame, k: int = 24, min_votes: int = 1, max_occ: int | None = None) -> DataFrame:
    """marker, contig, strand, pos, votes: the best place of each tag (most votes; ties to the least contig, forward, least pos).

    pos is where the tag (or its reverse complement) would begin on the contig. max_occ passes over seeds that
    occur on the contigs more often; without it none is passed over.
    """
    index = seeds(contigs, k)
    if max_occ is not None:
        index = index.join(index.groupBy("kmer").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") <= max_occ).select("kmer"), "kmer")
    both = F.explode(F.array(F.struct(F.lit("+").alias("strand"), F.col("marker").alias("s")), F.struct(F.lit("-").alias("strand"), dna.revcomp("marker").alias("s"))))
    probes = tags.select("marker", both.alias("o")).select("marker", "o.strand", F.posexplode(dna.kmers("o.s", k)).alias("off", "kmer"))
    small = index.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS
    hits = probes.join(F.broadcast(index) if small else index, "kmer")
    votes = hits.groupBy("marker", "contig", "strand", (F.col("pos") - F.col("off")).alias("pos")).agg(F.count(F.lit(1)).alias("votes")).filter(F.col("votes") >= min_votes)
    w = Window.partitionBy("marker").orderBy(F.desc("votes"), "contig", F.when(F.col("strand") == "+", 0).otherwise(1), "pos")
    return votes.withColumn("r", F.row_number().over(w)).filter("r = 1").select("marker", "contig", "strand", "pos", "votes")


def verified(hits: DataFrame, contigs: DataFrame) -> DataFrame:
    """Adds mismatches: places in which the tag differs from the contig where both have letters."""
    seq = F.when(F.col("strand") == "+", F.col("marker")).otherwise(dna.revcomp("marker"))
    skip = F.greatest(-F.col("pos"), F.lit(0))
    both = hits.join(contigs.select("contig", F.col("seq").alias("_c")), "contig").withColumn("_t", seq)
    size = F.least(F.length("_t") - skip, F.length("_c") - F.greatest("pos", F.lit(0)))
    a = F.expr("substring(_t, cast(greatest(-pos, 0) as int) + 1, length(_t))")
    b = F.expr("substring(_c, cast(greatest(pos, 0) as int) + 1, length(_t))")
    both = both.withColumns({"_n": size, "_a": a, "_b": b})
    cut = lambda c: F.expr(f"substring({c}, 1, cast(_n as int))")
    return both.withColumn("mismatches", dna.hamming(cut("_a"), cut("_b"))).drop("_c", "_t", "_n", "_a", "_b")


def contig_enrichment(hits: DataFrame, counts: DataFrame, signif: DataFrame) -> DataFrame:
    """contig, n_tags, n_biased: located tags, and those in a set of significant markers."""
    marked = hits.join(signif.select("marker").distinct().withColumn("b", F.lit(1)), "marker", "left")
    return marked.groupBy("contig").agg(F.count(F.lit(1)).alias("n_tags"), F.count("b").alias("n_biased"))


def range_hits(hits: DataFrame, windows: DataFrame, width: int = 64) -> DataFrame:
    """hits (contig, pos) in windows (contig, lo, hi; hi excluded), joined on bins of positions instead of a nested loop."""
    bins = windows.withColumn("bin", F.explode(F.sequence(F.expr(f"lo div {width}"), F.expr(f"(hi - 1) div {width}"))))
    rows = hits.withColumn("bin", F.floor(F.col("pos") / width).cast(bins.schema["bin"].dataType))
    return rows.join(bins, ["contig", "bin"]).filter("pos >= lo and pos < hi").drop("bin")
