"""Sensitivity studies, procedure comparison, k-mer audit, empirical-Bayes fit, tuning on planted truth. All but the
audit work on the lattice, so grids and searches never scan markers again."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.functions import dna
from markerpanel.functions import kernels as k
from markerpanel.plans import evidence, presence
from markerpanel.sources.panels import Panel

PIS = (0.001, 0.005, 0.01, 0.02, 0.05, 0.1)
RATES = (0.80, 0.85, 0.90, 0.95)
FAMILIES = {
    "fixed_default": k.Prior(),
    "fixed_dropout": k.Prior(linked=k.Fixed(0.8)),
    "beta_tight": k.Prior(linked=k.Beta(9, 1), null=k.Beta(5, 5)),
    "beta_loose": k.Prior(linked=k.Beta(4, 1), null=k.Beta(2, 2)),
    "beta_flat": k.Prior(linked=k.Beta(1, 1), null=k.Beta(1, 1)),
}


def prior_grid(lat: DataFrame, n1: int, n2: int, pis=PIS, rates=RATES, tau: float = 0.9) -> DataFrame:
    """pi, q, n: markers with posterior above tau in each cell of the grid."""
    ratios = F.explode(F.array(*[F.struct(F.lit(q).alias("q"), k.log_likelihood_ratio("g1", "g2", n1, n2, k.Prior(linked=k.Fixed(q))).alias("llr")) for q in rates]))
    grid = lat.select("n_markers", ratios.alias("r")).select("n_markers", "r.*")
    odds = F.explode(F.array(*[F.struct(F.lit(pi).alias("pi"), F.lit(math.log(pi / (1 - pi))).alias("lo")) for pi in pis]))
    grid = grid.select("*", odds.alias("o")).select("q", "o.pi", "n_markers", k.logistic_guard(F.col("llr") + F.col("o.lo")).alias("post"))
    return grid.groupBy("pi", "q").agg(F.coalesce(F.sum(F.when(F.col("post") > tau, F.col("n_markers"))), F.lit(0)).alias("n"))


def grid_range(grid: DataFrame) -> DataFrame:
    return grid.agg(F.min("n").alias("least"), F.max("n").alias("most"))


def family_grid(lat: DataFrame, n1: int, n2: int, families=None, tau: float = 0.9) -> DataFrame:
    """profile, n: markers above tau under each prevalence family."""
    families = families or FAMILIES
    each = F.explode(F.array(*[F.struct(F.lit(name).alias("profile"), k.posterior("g1", "g2", n1, n2, p).alias("post")) for name, p in families.items()]))
    return lat.select("n_markers", each.alias("f")).groupBy("f.profile").agg(F.coalesce(F.sum(F.when(F.col("f.post") > tau, F.col("n_markers"))), F.lit(0)).alias("n"))


def lattice_by_depth(panel: Panel, depths: list[int]) -> DataFrame:
    """min_depth, g1, g2, n_markers for several depths in one scan."""
    at = F.explode(F.array(*map(F.lit, depths))).alias("min_depth")
    rows = panel.grouped().select("marker", "depth", "grp", at).filter(F.col("depth") >= F.col("min_depth"))
    counts = rows.groupBy("min_depth", "marker").agg(F.count_if(F.col("grp") == 1).cast("int").alias("g1"), F.count_if(F.col("grp") == 2).cast("int").alias("g2"))
    return counts.filter("g1 + g2 > 0").groupBy("min_depth", "g1", "g2").agg(F.count(F.lit(1)).alias("n_markers"))


def depth_sweep(panel: Panel, depths: list[int], alpha: float = 0.05, tau_post: float = 0.9, tau_bf: float = 10.0, prior: k.Prior = k.Prior()) -> DataFrame:
    """min_depth, n_tests, n_strict, n_posterior, n_bf."""
    n1, n2 = panel.sizes()
    lat = lattice_by_depth(panel, depths)
    n = lat.groupBy("min_depth").agg(F.sum("n_markers").alias("n_tests"))
    rows = lat.join(F.broadcast(n), "min_depth").withColumns({"p": k.p_value("yates", "g1", "g2", n1, n2), "post": k.posterior("g1", "g2", n1, n2, prior), "bf": k.log_bf("g1", "g2", n1, n2, prior.shapes)})
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n_markers"))), F.lit(0))
    return rows.groupBy("min_depth", "n_tests").agg(total(F.col("p") < alpha / F.col("n_tests")).alias("n_strict"), total(F.col("post") > tau_post).alias("n_posterior"), total(F.col("bf") > math.log(tau_bf)).alias("n_bf"))


def procedure_comparison(lat: DataFrame, n1: int, n2: int, alpha: float = 0.05, tau: float = 0.9) -> DataFrame:
    """procedure, n: Bonferroni with Yates, step-up with Fisher and with G, posterior above tau."""
    out = None
    for name, test, correction in (("bonferroni_yates", "yates", "bonferroni"), ("bh_fisher", "fisher", "fdr"), ("bh_g", "g", "fdr")):
        rows = evidence.corrected(evidence.with_test(lat, n1, n2, test), correction, alpha)
        part = rows.agg(F.coalesce(F.sum(F.when(F.col("signif"), F.col("n_markers"))), F.lit(0)).alias("n")).select(F.lit(name).alias("procedure"), "n")
        out = part if out is None else out.unionAll(part)
    post = lat.agg(F.coalesce(F.sum(F.when(k.posterior("g1", "g2", n1, n2) > tau, F.col("n_markers"))), F.lit(0)).alias("n"))
    return out.unionAll(post.select(F.lit("posterior").alias("procedure"), "n"))


# -- k-mer audit ----------------------------------------------------------------------------------
def seeded_sample(tags: DataFrame, n: int = 250, seed: str = "7") -> DataFrame:
    """n tags by a hash of tag and seed: the same ones anywhere."""
    return tags.select("marker").distinct().orderBy(F.md5(F.concat(F.col("marker"), F.lit(seed))), "marker").limit(n)


def kmer_recall(tags: DataFrame, ks=(8, 16, 24, 32), sample: int = 250, seed: str = "7", order: str = "lex") -> DataFrame:
    """k, cases, kept, recall: mutants (each single substitution of sampled tags) whose signature stays."""
    own = F.array(*[dna.canonical_signature("marker", n, order) for n in ks])
    mutants = seeded_sample(tags, sample, seed).select(own.alias("own"), F.explode(dna.substitutions("marker")).alias("m")).select("own", F.col("m.mutant").alias("mutant"))
    # spread: the sample is one small partition, its mutants are many
    mutants = mutants.repartition(mutants.sparkSession.sparkContext.defaultParallelism)
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("k"), (F.get("own", F.lit(i)) == dna.canonical_signature("mutant", n, order)).alias("same")) for i, n in enumerate(ks)]))
    out = mutants.select(each.alias("s")).groupBy("s.k").agg(F.count(F.lit(1)).alias("cases"), F.count_if("s.same").alias("kept"))
    return out.withColumn("recall", F.col("kept") / F.col("cases"))


def kmer_false_merge(tags: DataFrame, n: int, least: int = 10, order: str = "lex") -> DataFrame:
    """signature, n_tags, far: tags of one signature, and how many differ from its representative in ``least`` places or more."""
    rows = tags.select("marker").distinct().withColumn("signature", dna.canonical_signature("marker", n, order))
    heads = rows.groupBy("signature").agg(F.min("marker").alias("head"), F.count(F.lit(1)).alias("n_tags")).filter("n_tags > 1")
    return rows.join(heads, "signature").groupBy("signature", "n_tags").agg(F.count_if(F.levenshtein("marker", "head") >= least).alias("far"))


# -- empirical Bayes, tuning ----------------------------------------------------------------------
def _ratios(lat: DataFrame, n1: int, n2: int, prior: k.Prior) -> list[tuple[float, int]]:
    """At most L rows, collected: log likelihood ratio and number of markers."""
    presence.check_sizes(n1, n2)
    return [(r.llr, r.n_markers) for r in lat.select(k.log_likelihood_ratio("g1", "g2", n1, n2, prior).alias("llr"), "n_markers").collect()]


def fit_prior(lat: DataFrame, n1: int, n2: int, prior: k.Prior = k.Prior(), max_iter: int = 200, tol: float = 1e-8) -> tuple[float, int, bool]:
    """pi by expectation-maximisation over the lattice: (pi, iterations, converged)."""
    rows = _ratios(lat, n1, n2, prior)
    total = sum(n for _, n in rows)
    if not total:
        raise PanelError("no tested marker")
    pi = prior.pi
    for step in range(1, max_iter + 1):
        odds = math.log(pi / (1 - pi))
        new = sum(n / (1 + math.exp(-max(-700.0, min(700.0, r + odds)))) for r, n in rows) / total
        new = min(max(new, 1e-12), 1 - 1e-12)
        if abs(new - pi) < tol:
            return new, step, True
        pi = new
    return pi, max_iter, False


def truth_lattice(counts: DataFrame, truth) -> DataFrame:
    """g1, g2, truth, n_markers; truth: a boolean column of marker."""
    return counts.filter("g1 + g2 > 0").groupBy("g1", "g2", truth.alias("truth")).agg(F.count(F.lit(1)).alias("n_markers"))


def confusion(lat: DataFrame, called) -> DataFrame:
    """tp, fp, fn, tn, precision, recall of a boolean column over a truth lattice."""
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n_markers"))), F.lit(0))
    t = F.col("truth")
    out = lat.agg(total(called & t).alias("tp"), total(called & ~t).alias("fp"), total(~called & t).alias("fn"), total(~called & ~t).alias("tn"))
    return out.withColumns({"precision": F.try_divide("tp", F.col("tp") + F.col("fp")), "recall": F.try_divide("tp", F.col("tp") + F.col("fn"))})


def pr_curve(lat: DataFrame, n1: int, n2: int, taus=(0.1, 0.5, 0.9, 0.99), prior: k.Prior = k.Prior()) -> DataFrame:
    """tau, tp, fp, fn, precision, recall of the posterior."""
    rows = lat.withColumn("post", k.posterior("g1", "g2", n1, n2, prior)).select("*", F.explode(F.array(*map(F.lit, taus))).alias("tau"))
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n_markers"))), F.lit(0))
    c, t = F.col("post") > F.col("tau"), F.col("truth")
    out = rows.groupBy("tau").agg(total(c & t).alias("tp"), total(c & ~t).alias("fp"), total(~c & t).alias("fn"))
    return out.withColumns({"precision": F.try_divide("tp", F.col("tp") + F.col("fp")), "recall": F.try_divide("tp", F.col("tp") + F.col("fn"))})


def tune_triage(lat: DataFrame, n1: int, n2: int, trials: int = 50, seed: int = 1) -> list[dict]:
    """Seeded random search of (pi, q, tau) for the F1 on a truth lattice; every trial is returned, best first.

    The driver holds one row per cell and truth value.
    """
    import random

    rng = random.Random(seed)
    rates = [round(0.7 + 0.025 * i, 3) for i in range(11)]
    ratio = [k.log_likelihood_ratio("g1", "g2", n1, n2, k.Prior(linked=k.Fixed(q))).alias(f"q{i}") for i, q in enumerate(rates)]
    rows = lat.select("truth", "n_markers", *ratio).collect()
    out = []
    for _ in range(trials):
        i, pi, tau = rng.randrange(len(rates)), 10 ** rng.uniform(-4, -0.5), rng.uniform(0.5, 0.99)
        cut = math.log(tau / (1 - tau)) - math.log(pi / (1 - pi))
        tp = sum(r.n_markers for r in rows if r.truth and r[f"q{i}"] > cut)
        fp = sum(r.n_markers for r in rows if not r.truth and r[f"q{i}"] > cut)
        fn = sum(r.n_markers for r in rows if r.truth) - tp
        out.append({"q": rates[i], "pi": pi, "tau": tau, "tp": tp, "fp": fp, "fn": fn, "f1": 2 * tp / max(1, 2 * tp + fp + fn)})
    return sorted(out, key=lambda t: -t["f1"])


def empirical_error_rates(panel: Panel, d: int = 1, reps: int = 20, seed: int = 1, alpha: float = 0.05, truth=None) -> DataFrame:
    """rep, calls: strict calls with group labels permuted by a seeded hash; their share of reps with a call is the
    family-wise error rate reached. One scan: every repetition is a pair of counts per marker.

    With truth (a boolean column of marker) rep -1 has the labels as they are, and false_calls and fdr (their share of
    the calls, 0 without calls) are added; under permuted labels every call is false."""
    members = [(m, g) for m, g in panel.members() if g is not None]
    n1, n2 = panel.sizes()
    import random

    rows = []
    for rep in range(reps):
        labels = [g for _, g in members]
        random.Random(seed * 1000 + rep).shuffle(labels)
        rows += [(rep, m, g) for (m, _), g in zip(members, labels, strict=True)]
    if truth is not None:
        rows += [(-1, m, g) for m, g in members]
    kind = panel.groups.schema["ind"].dataType.simpleString()
    shuffled = panel.cells.sparkSession.createDataFrame(rows, f"rep int, ind {kind}, grp int")
    hits = panel.cells.filter(F.col("depth") >= d).join(F.broadcast(shuffled), "ind")
    counts = hits.groupBy("rep", "marker").agg(F.count_if(F.expr("grp = 1")).cast("int").alias("g1"), F.count_if(F.expr("grp = 2")).cast("int").alias("g2"))
    real = F.lit(False) if truth is None else (F.col("rep") < 0) & truth
    lat = counts.groupBy("rep", "g1", "g2", real.alias("real")).agg(F.count(F.lit(1)).alias("n_markers"))
    n = lat.groupBy("rep").agg(F.sum("n_markers").alias("n_tests"))
    p = lat.join(F.broadcast(n), "rep").withColumn("p", k.p_value("yates", "g1", "g2", n1, n2))
    called = F.col("p") < alpha / F.col("n_tests")
    total = lambda which, name: F.coalesce(F.sum(F.when(which, F.col("n_markers"))), F.lit(0)).alias(name)
    if truth is None:
        return p.groupBy("rep").agg(total(called, "calls"))
    out = p.groupBy("rep").agg(total(called, "calls"), total(called & ~F.col("real"), "false_calls"))
    return out.withColumn("fdr", F.when(F.col("calls") > 0, F.col("false_calls") / F.col("calls")).otherwise(0.0))
