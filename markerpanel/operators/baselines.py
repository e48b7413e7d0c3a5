"""Baselines: each returns what the method it stands against returns, in the way the method avoids."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.functions import dna
from markerpanel.functions import kernels as k
from markerpanel.plans import evidence, joins, presence
from markerpanel.sources.panels import Panel

#: Columns of a materialised wide table.
MOST_WIDE = 1_000


def wide(panel: Panel, d: int = 1) -> tuple[DataFrame, list[tuple[str, int | None]]]:
    """The whole matrix as one column per individual (c0, c1, ...), persisted, and the columns' groups."""
    members = panel.members()
    if len(members) > MOST_WIDE:
        raise PanelError(f"a wide table has at most {MOST_WIDE} individuals")
    table = panel.cells.groupBy("marker").pivot("ind", [m for m, _ in members]).agg(F.first("depth"))
    names = [f"c{i}" for i in range(len(members))]
    return table.toDF("marker", *names).fillna(0, names).persist(), list(zip(names, (g for _, g in members), strict=True))


def materialized(command: str, panel: Panel, d: int = 1, alpha: float = 0.05, g1=(0, None), g2=(0, None)) -> DataFrame:
    """freq, distrib, signif, subset or depth over the materialised matrix, one test per marker. The matrix stays cached."""
    table, cols = wide(panel, d)
    n1, n2 = panel.sizes()
    count = lambda g: sum(((F.col(c) >= d).cast("int") for c, own in cols if g is None or own == g), F.lit(0)).cast("int")
    total = sum((F.col(c).cast("long") for c, _ in cols), F.lit(0))
    counts = table.select("marker", count(1).alias("g1"), count(2).alias("g2"), count(None).alias("n_ind"), total.alias("total_depth"))
    if command == "freq":
        return counts.filter("n_ind > 0").groupBy("n_ind").agg(F.count(F.lit(1)).alias("n_markers"))
    if command == "depth":
        each = table.select("marker", F.explode(F.array(*[F.struct(F.lit(m).alias("ind"), F.col(c).alias("depth")) for (c, _), (m, _) in zip(cols, panel.members(), strict=True)])).alias("x"))
        return each.select("x.*").groupBy("ind").agg(F.sum("depth").alias("reads"), F.count_if(F.expr("depth > 0")).alias("retained"), F.min("depth").alias("min_d"), F.max("depth").alias("max_d"), F.avg("depth").alias("mean_d"), F.expr("percentile(depth, 0.5)").alias("median"))
    rows = counts.filter("n_ind > 0" if command == "subset" else "g1 + g2 > 0").withColumns({"stat": k.yates_chi2("g1", "g2", n1, n2), "p": k.p_value("yates", "g1", "g2", n1, n2)})
    n = rows.count()
    rows = rows.withColumn("p_corr", F.least(F.lit(1.0), F.col("p") * n))
    if command == "signif":
        return rows.filter(F.col("p") < alpha / max(1, n)).select("marker", "g1", "g2", "stat", "p", "p_corr")
    if command == "subset":
        for name, (lo, hi) in (("g1", g1), ("g2", g2)):
            rows = rows.filter(F.col(name).between(lo, 2**31 - 1 if hi is None else hi))
        return rows.select("marker", "g1", "g2", "n_ind", "total_depth", "stat", "p", "p_corr")
    if command == "distrib":
        return rows.groupBy("g1", "g2").agg(F.count(F.lit(1)).alias("n_markers"), F.first("stat").alias("stat"), F.first("p").alias("p"))
    raise PanelError(f"command {command!r}")


def merge_materialized(panels: list[Panel]) -> DataFrame:
    """marker, ind, depth of tables put together as whole matrices: outer joins of the wide tables, column by column sums."""
    members = sorted({m for p in panels for m, _ in p.members()})
    out = None
    for p in panels:
        table, cols = wide(p)
        names = {m: c for (m, _), (c, _) in zip(p.members(), cols, strict=True)}
        table = table.select("marker", *[(F.col(names[m]) if m in names else F.lit(0)).alias(f"m{i}") for i, m in enumerate(members)])
        if out is None:
            out = table
        else:
            a, b = out.alias("a"), table.alias("b")
            out = a.join(b, "marker", "full").select("marker", *[(F.coalesce(f"a.m{i}", F.lit(0)) + F.coalesce(f"b.m{i}", F.lit(0))).alias(f"m{i}") for i in range(len(members))])
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("ind"), F.col(f"m{i}").cast("int").alias("depth")) for i, m in enumerate(members)]))
    return out.select("marker", each.alias("x")).select("marker", "x.*").filter("depth > 0")


def process_serial(reads: DataFrame) -> DataFrame:
    """Counting in one task."""
    return reads.filter(dna.is_dna("seq")).coalesce(1).groupBy("seq", "ind").agg(F.count(F.lit(1)).cast("int").alias("depth"))


def gamma_q(a: float, x: float) -> float:
    """Regularised upper incomplete gamma: series below a + 1, continued fraction above."""
    if x <= 0:
        return 1.0
    front = math.exp(a * math.log(x) - x - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        for i in range(1, 500):
            term *= x / (a + i)
            total += term
            if term < total * 1e-17:
                break
        return 1 - front * total
    tiny, b = 1e-300, x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 500):
        an = -i * (i - a)
        b += 2
        d, c = an * d + b, b + an / c
        d, c = 1 / (d if abs(d) > tiny else tiny), c if abs(c) > tiny else tiny
        h *= d * c
        if abs(d * c - 1) < 1e-16:
            break
    return front * h


def chi2_sf_general(x, df: int = 1):
    """Upper tail for any degree of freedom, as an Arrow UDF."""
    tail = F.pandas_udf(lambda s: s.map(lambda v: gamma_q(df / 2, v / 2)).astype("float64"), "double")
    return tail(x)


def median_dense(panel: Panel) -> DataFrame:
    """ind, median over every cell, zeros written out."""
    full = panel.cells.select("marker").distinct().crossJoin(panel.groups.select("ind").distinct()).join(panel.cells, ["marker", "ind"], "left").fillna(0, ["depth"])
    return full.groupBy("ind").agg(F.expr("percentile(depth, 0.5)").alias("median"))


def pca_svd(cells: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(singular values squared, right singular vectors) of the centred matrix, collected. Small panels only."""
    rows = cells.select("marker", "ind", "depth").toPandas().pivot(index="marker", columns="ind", values="depth").fillna(0)
    x = rows.sort_index(axis=1).to_numpy(float)
    _, s, vt = np.linalg.svd(x - x.mean(0), full_matrices=False)
    return s**2, vt.T


def pca_mllib(cells: DataFrame, n: int = 2):
    """Library PCA over dense rows: explained variance of the first n components."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    names = sorted(r[0] for r in cells.select("ind").distinct().collect())
    table = cells.groupBy("marker").pivot("ind", names).agg(F.first("depth")).fillna(0)
    vec = table.select(array_to_vector(F.array(*[F.col(f"`{c}`").cast("double") for c in table.columns if c != "marker"])).alias("v"))
    return PCA(k=n, inputCol="v", outputCol="o").fit(vec).explainedVariance


def map_exact_contains(tags: DataFrame, contigs: DataFrame, k_: int = 24) -> DataFrame:
    """marker, contig: some window of the tag (or its reverse complement) stands on the contig; every pair, no places or votes.

    A window stands there in reverse if it is a reversed window of the contig, so only the contigs' windows are
    reversed. Each text is looked up once by equality, and gives all contigs that have it.
    """
    both = F.concat(dna.kmers("seq", k_), F.transform(dna.kmers("seq", k_), dna.revcomp))
    index = contigs.select("contig", F.explode(both).alias("w")).groupBy("w").agg(F.collect_set("contig").alias("contigs"))
    probes = tags.select("marker", F.explode(F.array_distinct(dna.kmers("marker", k_))).alias("w"))
    hits = probes.join(joins.if_small(index), "w")
    return hits.select("marker", F.explode("contigs").alias("contig")).distinct()


def evidence_per_marker(panel: Panel, d: int = 1, engine: str = "expr", prior: k.Prior = k.Prior()) -> DataFrame:
    """p, ln Bayes factor and posterior evaluated for every marker row, as columns or in an Arrow UDF."""
    n1, n2 = panel.sizes()
    counts = presence.group_counts(panel, d).filter("g1 + g2 > 0")
    if engine == "expr":
        return counts.withColumns({"p": k.p_value("yates", "g1", "g2", n1, n2), "log_bf": k.log_bf("g1", "g2", n1, n2, prior.shapes), "posterior": k.posterior("g1", "g2", n1, n2, prior)})
    if engine != "arrow":
        raise PanelError(f"engine {engine!r}")

    def values(g1: pd.Series, g2: pd.Series) -> pd.DataFrame:
        out = [scalar_evidence(int(a), int(b), n1, n2) for a, b in zip(g1, g2, strict=True)]
        return pd.DataFrame(out, columns=["p", "log_bf", "posterior"])

    udf = F.pandas_udf(values, "p double, log_bf double, posterior double")
    return counts.withColumn("e", udf("g1", "g2")).select("marker", "g1", "g2", "n_ind", "e.*")


def scalar_evidence(a: int, b: int, n1: int, n2: int, q: float = 0.9, null: float = 0.5, w: float = 0.5, pi: float = 0.01) -> tuple[float, float, float]:
    """Platform erfc and lgamma, for default profiles."""
    n, c = n1 + n2, a + b
    gap = max(0.0, abs(a * (n2 - b) - b * (n1 - a)) - n / 2)
    x = 0.0 if not (n1 * n2 * c * (n - c)) else gap * gap * n / (n1 * n2 * c * (n - c))
    lb = lambda u, v: math.lgamma(u) + math.lgamma(v) - math.lgamma(u + v)
    bf = lb(a + 1, n1 - a + 1) + lb(b + 1, n2 - b + 1) - lb(c + 1, n - c + 1)
    ll = lambda m, r: m * math.log(r) + (n - m) * math.log(1 - r)
    one, two = ll(a + n2 - b, q) + math.log(w), ll(n1 - a + b, q) + math.log(1 - w)
    odds = max(one, two) + math.log1p(math.exp(-abs(one - two))) - ll(c, null) + math.log(pi / (1 - pi))
    return max(1e-16, math.erfc(math.sqrt(x / 2))), bf, 1 / (1 + math.exp(-max(-20.0, min(20.0, odds))))


def downsample(panel: Panel, fraction: float, d: int = 1, alpha: float = 0.05) -> DataFrame:
    """kept_calls, all_calls: strict calls that survive thinning the markers by a hash (a sampling operator)."""
    from markerpanel.operators.commands import signif

    cut = int(fraction * 10_000)
    thin = Panel(panel.cells.filter(F.pmod(F.xxhash64("marker"), F.lit(10_000)) < cut), panel.groups, panel.held)
    few, every = signif(thin, d, alpha=alpha).select("marker"), signif(panel, d, alpha=alpha).select("marker")
    return every.join(few.withColumn("k", F.lit(1)), "marker", "left").agg(F.count("k").alias("kept_calls"), F.count(F.lit(1)).alias("all_calls"))


def segregation_classes(df: DataFrame, error: float = 0.01) -> DataFrame:
    """Complementary idea: loci of a cross by likelihood. df: locus, sons_alt, sons, daughters_alt, daughters.

    autosomal: both sexes carry the allele in half of the offspring; linked: only one sex carries it; no
    information: too few offspring to tell (log ratio under 3).
    """
    ll = lambda x, n, q: F.col(x) * math.log(q) + (F.col(n) - F.col(x)) * math.log(1 - q)
    auto = ll("sons_alt", "sons", 0.5) + ll("daughters_alt", "daughters", 0.5)
    link = F.greatest(ll("sons_alt", "sons", 1 - error) + ll("daughters_alt", "daughters", error), ll("sons_alt", "sons", error) + ll("daughters_alt", "daughters", 1 - error))
    gap = link - auto
    return df.withColumn("class", F.when(F.abs(gap) < math.log(20), "no information").when(gap > 0, "linked").otherwise("autosomal"))


def group_coverage_contrast(cells: DataFrame, groups: DataFrame) -> DataFrame:
    """Complementary idea: per contig (marker), mean normalised depth of group 1 over that of group 2."""
    total = Window.partitionBy("ind")
    share = cells.withColumn("share", F.col("depth") / F.sum("depth").over(total)).join(F.broadcast(groups.select("ind", "grp").distinct()), "ind")
    n = groups.select("ind", "grp").distinct().groupBy().agg(F.count_if(F.expr("grp = 1")).alias("n1"), F.count_if(F.expr("grp = 2")).alias("n2"))
    out = share.groupBy("marker").agg(F.sum(F.when(F.col("grp") == 1, F.col("share"))).alias("s1"), F.sum(F.when(F.col("grp") == 2, F.col("share"))).alias("s2"))
    return out.crossJoin(F.broadcast(n)).select("marker", F.try_divide(F.coalesce("s1", F.lit(0.0)) / F.col("n1"), F.coalesce("s2", F.lit(0.0)) / F.col("n2")).alias("ratio"))
