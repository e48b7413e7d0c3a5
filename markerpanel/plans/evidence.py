"""Evidence on the lattice: tests, corrections, Bayes factors, posteriors, grades."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from markerpanel.errors import PanelError, choose
from markerpanel.functions import kernels as k
from markerpanel.plans import presence
from markerpanel.sources.panels import Panel

CORRECTIONS = ("bonferroni", "none", "fdr")


def tested(lat: DataFrame) -> DataFrame:
    """Cells of markers that some grouped individual carries."""
    return lat.filter("g1 + g2 > 0")


def bh_lattice(lat: DataFrame, p: str = "p") -> DataFrame:
    """Adds p_adj, exact Benjamini-Hochberg over markers, from at most L rows.

    All markers of a cell share p, so the largest rank of a p value is the number of markers up to it.
    The windows run over lattice rows only.
    """
    up = Window.orderBy(p).rangeBetween(Window.unboundedPreceding, 0)
    ranked = lat.withColumn("rank", F.sum("n_markers").over(up)).withColumn("m", F.sum("n_markers").over(Window.partitionBy(F.lit(1))))
    down = Window.orderBy(F.desc(p)).rangeBetween(Window.unboundedPreceding, 0)
    return ranked.withColumn("p_adj", F.least(F.lit(1.0), F.min(F.col(p) * F.col("m") / F.col("rank")).over(down))).drop("rank", "m")


def bh_window(pvalues: DataFrame, p: str = "p") -> DataFrame:
    """The materialising way: every row ranked in one window. Only for tests and as a baseline."""
    up = Window.orderBy(p).rangeBetween(Window.unboundedPreceding, 0)
    ranked = pvalues.withColumn("rank", F.count(F.lit(1)).over(up)).withColumn("m", F.count(F.lit(1)).over(Window.partitionBy(F.lit(1))))
    down = Window.orderBy(F.desc(p)).rangeBetween(Window.unboundedPreceding, 0)
    return ranked.withColumn("p_adj", F.least(F.lit(1.0), F.min(F.col(p) * F.col("m") / F.col("rank")).over(down))).drop("rank", "m")


def bh_range(df: DataFrame, p: str = "p", q: float = 0.05, cells: int = 4096, most: int = 1_000_000) -> DataFrame:
    """Rows kept by Benjamini-Hochberg at q for continuous p, without ranking rows.

    Rows are counted in ``cells`` ranges of -log10 p. A range whose last rank can't pass even at its least p has no
    cut in it, so the largest passing p lies in few ranges. One with more than ``most`` distinct p is cut into
    ``cells`` ranges of its own, and so on; only what is left is ranked. Counts are exact.
    """

    def largest(rows: DataFrame, lo: float, hi: float, before: int, m: int | None) -> float | None:
        """The greatest passing p among the rows, whose -log10 p lies in lo..hi; ``before``: rows of smaller p."""
        at = F.least(F.floor((hi - F.col("_l")) / (hi - lo) * cells), F.lit(cells - 1))
        hist = sorted((r.b, r.n, r.least, r.most, r.kinds) for r in rows.groupBy(at.alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min(p).alias("least"), F.max(p).alias("most"), F.approx_count_distinct(p).alias("kinds")).collect())
        m = m or sum(n for _, n, *_ in hist)
        seen, open_ = before, []
        for b, n, least, top, kinds in hist:
            if least <= q * (seen + n) / m:
                open_.append((b, seen, least, top, kinds))
            seen += n
        for _, seen, least, top, kinds in reversed(open_):  # the last range with a passing rank decides
            some = rows.filter(F.col(p).between(least, top))
            if kinds > most and least < top:
                cut = largest(some, -math.log10(max(top, 1e-300)), -math.log10(max(least, 1e-300)), seen, m)
            else:
                ranked = some.groupBy(p).agg(F.count(F.lit(1)).alias("n")).withColumn("rank", F.lit(seen) + F.sum("n").over(Window.orderBy(p)))
                cut = ranked.filter(F.col(p) <= q * F.col("rank") / m).agg(F.max(p)).first()[0]
            if cut is not None:
                return cut
        return None

    logged = df.withColumn("_l", -F.log10(F.greatest(F.col(p), F.lit(1e-300))))
    cut = largest(logged, 0.0, 300.0, 0, None)
    return df.filter(F.col(p) <= (F.lit(cut) if cut is not None else F.lit(-1.0)))


def with_test(lat: DataFrame, n1: int, n2: int, test: str = "yates") -> DataFrame:
    """Adds stat (chi2 or G; null for Fisher) and p."""
    stat = {"yates": lambda: k.yates_chi2("g1", "g2", n1, n2), "pearson": lambda: k.yates_chi2("g1", "g2", n1, n2, False), "g": lambda: k.g_stat("g1", "g2", n1, n2), "fisher": lambda: F.lit(None).cast("double")}
    return lat.withColumn("stat", choose(test, stat)()).withColumn("p", k.p_value(test, "g1", "g2", n1, n2))


def corrected(lat: DataFrame, correction: str = "bonferroni", alpha: float = 0.05, denominator: str = "tested") -> DataFrame:
    """Adds n_tests, p_corr and signif to a lattice with p. Strict inequality but for the step-up rule."""
    if denominator not in ("all", "tested"):
        raise PanelError(f"denominator {denominator!r}")
    one = Window.partitionBy(F.lit(1))
    n = F.sum("n_markers" if denominator == "all" else F.when(F.col("g1") + F.col("g2") > 0, F.col("n_markers")).otherwise(0)).over(one)
    lat = lat.withColumn("n_tests", n)
    if correction == "bonferroni":
        return lat.withColumn("p_corr", F.least(F.lit(1.0), F.col("p") * F.col("n_tests"))).withColumn("signif", (F.col("n_tests") > 0) & (F.col("p") < F.try_divide(F.lit(alpha), "n_tests")))
    if correction == "none":
        return lat.withColumn("p_corr", F.col("p")).withColumn("signif", F.col("p") < alpha)
    if correction == "fdr":
        return bh_lattice(lat).withColumnRenamed("p_adj", "p_corr").withColumn("signif", F.col("p_corr") <= alpha)
    raise PanelError(f"correction {correction!r}; known: {', '.join(CORRECTIONS)}")


def annotate(lat: DataFrame, n1: int, n2: int, prior: k.Prior = k.Prior(), alpha: float = 0.05, tau_post: float = 0.9, tau_bf: float = 10.0, denominator: str = "tested") -> DataFrame:
    """p, strict, log_bf, log_odds, posterior, class and direction of every cell."""
    out = corrected(with_test(lat, n1, n2), "bonferroni", alpha, denominator).withColumnRenamed("signif", "strict")
    out = out.withColumns({"log_bf": k.log_bf("g1", "g2", n1, n2, prior.shapes), "log_odds": k.log_odds("g1", "g2", n1, n2, prior)})
    out = out.withColumn("posterior", k.logistic_guard(F.col("log_odds")))
    return out.withColumns({"class": grade(tau_post, tau_bf), "strict_only": F.col("strict") & (F.col("posterior") <= tau_post)}).withColumn("direction", direction(n1, n2))


def grade(tau_post: float, tau_bf: float):
    """strict, posterior, weak, or none. Strict wins over the rest."""
    import math

    return F.when(F.col("strict"), F.lit("strict")).when(F.col("posterior") > tau_post, F.lit("posterior")).when(F.col("log_bf") > math.log(tau_bf), F.lit("weak")).otherwise(F.lit("none"))


def direction(n1: int, n2: int):
    """xy: more carriers in group 1; zw: more in group 2; unsupported: equal shares or no grade."""
    gap = F.col("g1") * F.lit(n2).cast("long") - F.col("g2") * F.lit(n1).cast("long")
    return F.when((F.col("class") == "none") | (gap == 0), F.lit("unsupported")).when(gap > 0, F.lit("xy")).otherwise(F.lit("zw"))


def panel_lattice(panel: Panel, d: int = 1, engine: str = "conditional", only_tested: bool = True) -> DataFrame:
    lat = presence.lattice(presence.group_counts(panel, d, engine))
    return tested(lat) if only_tested else lat
