"""Commands over reads and panels: process, freq, distrib, depth, signif, subset, merge, dedup."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.functions import dna
from markerpanel.plans import evidence, presence
from markerpanel.sources.panels import Panel


# -- table building -------------------------------------------------------------------------------
@dataclass(frozen=True)
class IngestPlan:
    entries: int
    partitions: int


def plan_ingest(n_bytes: int, tag_bytes: int = 26, partition_bytes: int = 128 << 20) -> IngestPlan:
    """Planned table entries (floor 1,024, ceiling 4 million a task; a plan only, no marker is ever dropped) and shuffle partitions."""
    entries = max(1024, min(4_000_000, n_bytes // max(1, tag_bytes)))
    return IngestPlan(entries, max(1, math.ceil(n_bytes / partition_bytes)))


def process(reads: DataFrame, min_depth: int = 1, on_invalid: str = "drop", packed: bool = True) -> DataFrame:
    """(tag, ind, depth): equal tags counted per individual; reads has ind, seq.

    Tags travel packed, two bits a base, and are counted before and after one shuffle. on_invalid: reads with
    other letters are dropped, raise an error, or keep their text as key (then keys are text).
    """
    ok = dna.is_dna("seq")
    if on_invalid == "drop":
        reads = reads.filter(ok)
    elif on_invalid == "error":
        reads = reads.withColumn("seq", F.when(ok, F.col("seq")).otherwise(F.raise_error(F.concat(F.lit("not ACGT: "), F.coalesce("seq", F.lit("null"))))))
    elif on_invalid != "text_key":
        raise PanelError(f"on_invalid {on_invalid!r}")
    packed = packed and on_invalid != "text_key"
    key = dna.pack_tag("seq") if packed else F.col("seq")
    cells = reads.select(key.alias("tag"), "ind").groupBy("tag", "ind").agg(F.count(F.lit(1)).cast("int").alias("depth"))
    if min_depth > 1:
        deep = cells.groupBy("tag").agg(F.max("depth").alias("most")).filter(F.col("most") >= min_depth).select("tag")
        cells = cells.join(deep, "tag", "left_semi")
    return cells


def assemble(cells: DataFrame) -> DataFrame:
    """Sparse rows: marker, cells array of (ind, depth) by ind."""
    return cells.groupBy("marker").agg(F.array_sort(F.collect_list(F.struct("ind", "depth"))).alias("cells"))


def reached(sparse: DataFrame, min_depth: int) -> DataFrame:
    """Sparse rows that some individual reaches the depth in."""
    return sparse.filter(F.exists("cells", lambda c: c["depth"] >= min_depth))


def merge_panels(panels: list[Panel], same_name: str = "sum", dedup_k: int | None = None) -> Panel:
    """Tables put together: depths of one individual add up, or each table's individuals get their own names."""
    cells = groups = None
    for k, p in enumerate(panels):
        c, g = p.cells, p.groups
        if same_name == "prefix":
            name = F.concat(F.lit(f"{k}:"), F.col("ind").cast("string"))
            c, g = c.withColumn("ind", name), g.withColumn("ind", name)
        elif same_name != "sum":
            raise PanelError(f"same_name {same_name!r}")
        c = c.select("marker", "ind", "depth")
        cells = c if cells is None else cells.unionByName(c)
        groups = g if groups is None else groups.unionByName(g)
    out = Panel(cells.groupBy("marker", "ind").agg(F.sum("depth").cast("int").alias("depth")), groups.select("ind", "grp").distinct())
    return dedup_by_signature(out, dedup_k) if dedup_k else out


def dedup_by_signature(panel: Panel, k: int, order: str = "lex") -> Panel:
    """Tags of equal signature become one marker, the signature; depths add up. Off unless asked for."""
    sig = dna.canonical_signature("marker", k, order)
    cells = panel.cells.select(F.coalesce(sig, F.col("marker")).alias("marker"), "ind", "depth")
    return Panel(cells.groupBy("marker", "ind").agg(F.sum("depth").cast("int").alias("depth")), panel.groups)


def representatives(panel: Panel, k: int, order: str = "lex") -> DataFrame:
    """signature, tag: the deepest tag of each signature (ties to the greater tag), n_tags."""
    total = panel.cells.groupBy("marker").agg(F.sum("depth").alias("total")).withColumn("signature", dna.canonical_signature("marker", k, order))
    return total.groupBy("signature").agg(F.max(F.struct("total", "marker"))["marker"].alias("tag"), F.count(F.lit(1)).alias("n_tags"))


def packing_ratio(tags: DataFrame) -> DataFrame:
    """Bytes of text and packed tags; tags has column marker (text)."""
    return tags.agg(F.count(F.lit(1)).alias("n_tags"), F.sum(F.octet_length("marker")).alias("text_bytes"), F.sum(F.octet_length(dna.pack_tag("marker"))).alias("packed_bytes")).withColumn("ratio", F.col("text_bytes") / F.col("packed_bytes"))


# -- summaries ------------------------------------------------------------------------------------
def freq(panel: Panel, d: int = 1) -> DataFrame:
    """n_ind, n_markers: markers by the number of individuals that carry them."""
    carriers = panel.cells.filter(F.col("depth") >= d).groupBy("marker").agg(F.count(F.lit(1)).alias("n_ind"))
    return carriers.groupBy("n_ind").agg(F.count(F.lit(1)).alias("n_markers"))


def singleton_fraction(panel: Panel, depths: list[int]) -> DataFrame:
    """depth, markers, singletons, fraction; one scan for all depths."""
    at = F.explode(F.array(*map(F.lit, depths))).alias("min_depth")
    rows = panel.cells.select("marker", "depth", at).filter(F.col("depth") >= F.col("min_depth"))
    carriers = rows.groupBy("min_depth", "marker").agg(F.count(F.lit(1)).alias("n"))
    out = carriers.groupBy("min_depth").agg(F.count(F.lit(1)).alias("markers"), F.count_if(F.col("n") == 1).alias("singletons"))
    return out.withColumn("fraction", F.col("singletons") / F.col("markers"))


def distrib(panel: Panel, d: int = 1, test: str = "yates", correction: str = "bonferroni", alpha: float = 0.05, engine: str = "conditional") -> DataFrame:
    """g1, g2, n_markers, stat, p, p_corr, signif, bias: the lattice with its test."""
    n1, n2 = panel.sizes()
    lat = evidence.panel_lattice(panel, d, engine)
    out = evidence.corrected(evidence.with_test(lat, n1, n2, test), correction, alpha)
    return out.withColumn("bias", F.col("g1") / n1 - F.col("g2") / n2)


def histogram(panel: Panel, d: int | None = None) -> DataFrame:
    """ind, depth, freq over markers that some individual carries with depth >= d (all, without d)."""
    cells = panel.cells
    if d is not None and d > 1:
        kept = cells.groupBy("marker").agg(F.max("depth").alias("most")).filter(F.col("most") >= d).select("marker")
        cells = cells.join(kept, "marker", "left_semi")
    return cells.groupBy("ind", "depth").agg(F.count(F.lit(1)).alias("freq"))


def sparse_median(hist: DataFrame, n_markers: int, zeros: bool = True, *more) -> DataFrame:
    """ind, median: exact, from the histogram of nonzero depths and the number of zeros, and ``more`` aggregates of it.

    Ranks are sums over the few distinct depths of an individual, so nothing is sorted but these.
    """
    w = Window.partitionBy("ind")
    run = hist.withColumn("upto", F.sum("freq").over(w.orderBy("depth").rowsBetween(Window.unboundedPreceding, 0))).withColumn("filled", F.sum("freq").over(w))
    n = F.lit(n_markers) if zeros else F.col("filled")
    z = F.lit(n_markers) - F.col("filled") if zeros else F.lit(0)
    run = run.withColumns({"lo": F.floor((n - 1) / 2) - z, "hi": F.floor(n / 2) - z})
    at = lambda r: F.when(F.col(r) < 0, F.lit(0)).otherwise(F.when((F.col("upto") > F.col(r)) & (F.col("upto") - F.col("freq") <= F.col(r)), F.col("depth")))
    return run.groupBy("ind").agg(((F.max(at("lo")) + F.max(at("hi"))) / 2).alias("median"), *more)


def depth_summary(panel: Panel, d: int = 1, zeros: bool = True) -> DataFrame:
    """Per individual, over markers retained at d: reads, retained (its own markers), min, max, mean and exact median depth.

    Zeros count in min, mean and median, unless zeros is off.
    """
    cells = panel.cells
    if d > 1:
        cells = cells.groupBy("marker").agg(F.max("depth").alias("most")).filter(F.col("most") >= d)
    m = cells.select("marker").distinct().count()
    n = F.lit(m) if zeros else F.col("retained")
    own = sparse_median(histogram(panel, d), m, zeros, F.sum(F.col("depth").cast("long") * F.col("freq")).alias("reads"), F.sum("freq").alias("retained"), F.min("depth").alias("least"), F.max("depth").alias("max_d"))
    own = own.withColumn("min_d", F.when(F.lit(zeros) & (F.col("retained") < m), F.lit(0)).otherwise(F.col("least")).cast("int")).withColumn("mean_d", F.col("reads") / n)
    everyone = panel.groups.select("ind").distinct()
    out = everyone.join(F.broadcast(own), "ind", "left")
    zero = {c: F.coalesce(c, F.lit(0)) for c in ("reads", "retained", "min_d", "max_d")} | {c: F.coalesce(c, F.lit(0.0)) for c in ("mean_d", "median")}
    return out.select("ind", *[v.alias(c) for c, v in zero.items()])


# -- tests ----------------------------------------------------------------------------------------
def signif(panel: Panel, d: int = 1, test: str = "yates", correction: str = "bonferroni", alpha: float = 0.05, denominator: str = "tested", engine: str = "conditional") -> DataFrame:
    """marker, g1, g2, stat, p, p_corr of the markers that pass. Two passes: the lattice, then a broadcast join with its passing cells."""
    n1, n2 = panel.sizes()
    counts = presence.group_counts(panel, d, engine)
    lat = evidence.corrected(evidence.with_test(presence.lattice(counts), n1, n2, test), correction, alpha, denominator)
    passing = lat.filter("signif and g1 + g2 > 0").select("g1", "g2", "stat", "p", "p_corr")
    return presence.back(counts, passing, n1, n2).select("marker", "g1", "g2", "stat", "p", "p_corr")


def subset(panel: Panel, d: int = 1, g1=(0, None), g2=(0, None), ind=(0, None), test: str = "yates", correction: str = "bonferroni") -> DataFrame:
    """Markers whose carrier counts are in the ranges (ends included), with total depth, p and corrected p."""
    n1, n2 = panel.sizes()
    counts = presence.group_counts(panel, d)
    lat = evidence.corrected(evidence.with_test(presence.lattice(counts), n1, n2, test), correction)
    for name, (lo, hi) in (("g1", g1), ("g2", g2), ("n_ind", ind)):
        counts = counts.filter(F.col(name) >= lo)
        if hi is not None:
            counts = counts.filter(F.col(name) <= hi)
    chosen = presence.back(counts, lat.select("g1", "g2", "stat", "p", "p_corr"), n1, n2)
    total = panel.cells.groupBy("marker").agg(F.sum("depth").alias("total_depth"))
    return chosen.join(total, "marker").select("marker", "g1", "g2", "n_ind", "total_depth", "stat", "p", "p_corr")


def to_fasta(rows: DataFrame, seq: str = "marker") -> DataFrame:
    """One text column: header line with counts and p, then the sequence."""
    return rows.select(F.concat(F.lit(">"), F.concat_ws("|", F.substring(F.sha2(F.col(seq), 256), 1, 12), F.col("g1").cast("string"), F.col("g2").cast("string")), F.lit("\n"), F.col(seq)).alias("value"))


def qc_report(panel: Panel, depths: list[int] = [1]) -> DataFrame:  # noqa: B006
    """Advice only: nothing is filtered. Singleton share by depth (NaN without markers), and whether the larger group is over 1.5 times the smaller.

    Every depth has its row, if no marker reaches it as well.
    """
    n1, n2 = panel.sizes()
    asked = panel.cells.sparkSession.range(1).select(F.explode(F.array(*map(F.lit, sorted(set(depths))))).alias("min_depth"))
    zero = {c: F.coalesce(c, F.lit(0)) for c in ("markers", "singletons")} | {"fraction": F.coalesce("fraction", F.lit(math.nan))}
    out = asked.join(F.broadcast(singleton_fraction(panel, depths)), "min_depth", "left").withColumns(zero)
    return out.withColumns({"n1": F.lit(n1), "n2": F.lit(n2), "unbalanced": F.lit(max(n1, n2) > 1.5 * max(1, min(n1, n2)))})
