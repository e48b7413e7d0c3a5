"""Hybrid triage: strict, posterior and weak rows, one exploratory row if there are none, panel-level calls."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.functions.kernels import Prior
from markerpanel.plans import evidence, presence
from markerpanel.sources.panels import Panel

COLUMNS = ("marker", "g1", "g2", "p", "p_corr", "strict", "log_bf", "log_odds", "posterior", "class", "strict_only", "direction")


def evidence_lattice(panel: Panel, d: int = 1, prior: Prior = Prior(), alpha: float = 0.05, tau_post: float = 0.9, tau_bf: float = 10.0, engine: str = "conditional") -> DataFrame:
    n1, n2 = panel.sizes()
    return evidence.annotate(evidence.panel_lattice(panel, d, engine), n1, n2, prior, alpha, tau_post, tau_bf)


def best_first():
    """Order of the exploratory row: posterior, Bayes factor, then the smaller p."""
    return F.struct("log_odds", "log_bf", (-F.col("p")).alias("np"))


def triage(panel: Panel, d: int = 1, prior: Prior = Prior(), alpha: float = 0.05, tau_post: float = 0.9, tau_bf: float = 10.0, engine: str = "conditional", exploratory: bool = True) -> DataFrame:
    """Markers that pass a threshold, with their grade; if none does, the best marker as exploratory (unless that is off).

    The lattice says whether any cell passes, so a panel without signal needs no second look at its markers
    but for the one row.
    """
    n1, n2 = panel.sizes()
    counts = presence.group_counts(panel, d, engine)
    lat = evidence.annotate(evidence.tested(presence.lattice(counts)), n1, n2, prior, alpha, tau_post, tau_bf).persist()
    graded = lat.filter("class <> 'none'")
    if not exploratory or graded.limit(1).count():
        return presence.back(counts, graded, n1, n2).select(*COLUMNS)
    best = lat.withColumn("order", best_first()).agg(F.max(F.struct("order", "g1", "g2"))["order"].alias("order"))
    # cells of equal evidence: the least marker over all of them
    top = lat.withColumn("order", best_first()).join(F.broadcast(best), "order").withColumn("class", F.lit("exploratory"))
    rows = presence.back(counts, top.drop("order"))
    return rows.agg(F.min_by(F.struct(*COLUMNS), "marker").alias("r")).filter("r is not null").select("r.*")


def grade_partition(rows: DataFrame) -> DataFrame:
    return rows.groupBy("class").agg(F.count(F.lit(1)).alias("n"))


def partition_of_lattice(lat: DataFrame) -> DataFrame:
    """The same from the lattice, without touching markers."""
    return lat.filter("class <> 'none'").groupBy("class").agg(F.sum("n_markers").alias("n"))


def grade_crosstab(lat: DataFrame, tau_post: float = 0.9, log_tau_bf: float = 2.302585092994046) -> DataFrame:
    """Markers by the three thresholds, with subtotals (cube)."""
    flags = lat.select("strict", (F.col("posterior") > tau_post).alias("post_ok"), (F.col("log_bf") > log_tau_bf).alias("bf_ok"), "n_markers")
    return flags.cube("strict", "post_ok", "bf_ok").agg(F.sum("n_markers").alias("n"))


def panel_call(lat: DataFrame, least: int = 1) -> DataFrame:
    """One row: counts per direction and the panel's call, from strict and posterior rows."""
    calls = lambda k: F.coalesce(F.sum(F.when(F.col("class").isin("strict", "posterior") & (F.col("direction") == k), F.col("n_markers"))), F.lit(0))
    out = lat.agg(calls("xy").alias("n_xy"), calls("zw").alias("n_zw"), F.coalesce(F.sum(F.when(F.col("class") == "strict", F.col("n_markers"))), F.lit(0)).alias("n_strict"))
    side = F.when((F.col("n_xy") < least) & (F.col("n_zw") < least), "no call").when((F.col("n_xy") >= least) & (F.col("n_zw") >= least), "both directions").when(F.col("n_xy") >= least, "xy").otherwise("zw")
    strength = F.when(side == "no call", side).when(F.col("n_strict") > 0, F.concat(side, F.lit(" strict"))).otherwise(F.concat(F.lit("putative "), side))
    return out.withColumn("call", strength)


def rank_candidates(rows: DataFrame, n: int = 20) -> DataFrame:
    """The n best rows below or above any threshold (a top-k report)."""
    return rows.orderBy(F.desc("log_odds"), F.desc("log_bf"), "p", "marker").limit(n)


def overlap(rows: DataFrame, listed: DataFrame) -> DataFrame:
    """Graded rows by class and by membership in a published list (column marker)."""
    marked = rows.join(listed.select("marker").distinct().withColumn("listed", F.lit(True)), "marker", "left")
    return marked.groupBy("class", F.coalesce("listed", F.lit(False)).alias("listed")).agg(F.count(F.lit(1)).alias("n"))


def provenance(prior: Prior, d: int, n_tests: int, **settings) -> str:
    """Parameters of a run as one JSON line, for report headers."""
    return json.dumps({"min_depth": d, "n_tests": n_tests, "linked": repr(prior.linked), "null": repr(prior.null), "w": prior.w, "pi": prior.pi, "shapes": list(prior.shapes)} | settings, sort_keys=True)
