"""Numbers: worked examples, identities, error of the panels, packing and k-mers."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from markerpanel.errors import EngineUnavailable, PanelError, ProfileError
from markerpanel.functions import dna
from markerpanel.functions import kernels as k
from markerpanel.functions.erfc import chi2_1df_sf, erfc_value
from markerpanel.operators import baselines


def test_erfc_panels():
    worst = {False: 0.0, True: 0.0}
    for i in range(0, 120_001, 7):
        t = i * 6 / 120_001
        worst[t >= 4.75] = max(worst[t >= 4.75], abs(erfc_value(t) / math.erfc(t) - 1))
        assert 0 <= erfc_value(t) <= 1
    assert worst[False] < 1e-15 and worst[True] < 2e-14
    assert erfc_value(6.0) == 0.0


def test_single_polynomial_fails():
    """One polynomial over the whole range in the raw variable: its terms cancel, so values past 4 are lost."""
    x = (np.cos(np.pi * (np.arange(41) + 0.5) / 41) + 1) * 3
    c = np.linalg.solve(np.vander(x, 41, increasing=True), [math.erfc(v) for v in x])
    at = [sum(cc * t**i for i, cc in enumerate(c)) for t in np.linspace(4, 6, 50)]
    assert max(abs(v / math.erfc(t) - 1) for v, t in zip(at, np.linspace(4, 6, 50), strict=True)) > 1e-2


def rows(spark, pairs):
    return spark.createDataFrame(pairs, "g1 int, g2 int").repartition(2)


def test_worked_examples(spark):
    df = rows(spark, [(10, 0), (5, 5), (0, 0)])
    got = {(r.g1, r.g2): r for r in df.select("*", k.yates_chi2("g1", "g2", 10, 10).alias("x"), k.fisher_exact("g1", "g2", 10, 10).alias("f"), k.log_bf("g1", "g2", 10, 10).alias("bf"), k.log_odds("g1", "g2", 10, 10).alias("lo"), k.p_value("yates", "g1", "g2", 10, 10).alias("p")).collect()}
    assert got[10, 0].x == pytest.approx(16.2) and got[10, 0].f == pytest.approx(2 / math.comb(20, 10))
    assert got[5, 5].x == 0 and got[5, 5].p == pytest.approx(1)
    assert got[0, 0].x == 0 and got[0, 0].p == pytest.approx(1)
    assert got[10, 0].bf == pytest.approx(math.log(184756 * 21 / 121))
    assert got[10, 0].lo == pytest.approx(math.log(0.5 * 0.9**20 + 0.5 * 0.1**20) - 20 * math.log(0.5) + math.log(1 / 99))


def test_critical_values(spark):
    crit = {3.841458820694124: 0.05, 6.634896601021214: 0.01, 10.827566170662733: 0.001, 0.0039321400000195: 0.95}
    got = spark.createDataFrame([(x,) for x in crit], "x double").select("x", chi2_1df_sf(F.col("x")).alias("p"), baselines.chi2_sf_general(F.col("x")).alias("q")).collect()
    for r in got:
        assert r.p == pytest.approx(crit[r.x], rel=1e-6) and r.q == pytest.approx(r.p, rel=1e-10)


def test_against_scalar_route(spark):
    pairs = [(a, b) for a in range(0, 14) for b in range(0, 10)]
    got = rows(spark, pairs).select("*", k.p_value("yates", "g1", "g2", 13, 9).alias("p"), k.log_bf("g1", "g2", 13, 9).alias("bf"), k.posterior("g1", "g2", 13, 9).alias("post")).collect()
    for r in got:
        p, bf, post = baselines.scalar_evidence(r.g1, r.g2, 13, 9)
        assert r.p == pytest.approx(p, rel=1e-12) and r.bf == pytest.approx(bf, abs=1e-10) and r.post == pytest.approx(post, rel=1e-9)


def test_symmetry_and_bounds(spark):
    pairs = [(a, b) for a in range(11) for b in range(11)]
    f = lambda a, b: [k.p_value("yates", a, b, 10, 10), k.log_bf(a, b, 10, 10), k.posterior(a, b, 10, 10), k.fisher_exact(a, b, 10, 10)]
    for r in rows(spark, pairs).select(*[c.alias(f"a{i}") for i, c in enumerate(f("g1", "g2"))], *[c.alias(f"b{i}") for i, c in enumerate(f("g2", "g1"))]).collect():
        for i in range(4):
            assert r[f"a{i}"] == pytest.approx(r[f"b{i}"], rel=1e-9, abs=1e-12)
        assert 0 < r.a3 <= 1 + 1e-12


def test_evidence_sums_to_one(spark):
    got = spark.range(0, 13).select(F.col("id").cast("int").alias("k")).select("k", k.log_evidence_beta("k", 12, 2.5, 0.7).alias("e")).collect()
    assert sum(math.comb(12, r.k) * math.exp(r.e) for r in got) == pytest.approx(1)


def test_validation():
    with pytest.raises(ProfileError):
        k.Beta(0, 1)
    with pytest.raises(ProfileError):
        k.Prior(pi=1.0)
    with pytest.raises(ProfileError):
        k.Fixed(1.0)
    with pytest.raises(PanelError):
        dna.kmers("x", 33)


def test_packing(spark):
    rng = random.Random(1)
    tags = ["ACGT", "A", "T" * 188, "C" * 189] + ["".join(rng.choice("ACGT") for _ in range(n)) for n in range(1, 251)]
    got = spark.createDataFrame([(t,) for t in tags], "t string").select("t", dna.pack_tag("t").alias("p"), dna.unpack_tag(dna.pack_tag("t")).alias("u"), dna.revcomp(dna.revcomp("t")).alias("r")).collect()
    for r in got:
        assert r.u == r.t == r.r and len(r.p) == 1 + -(-len(r.t) // 4) and r.p[0] == len(r.t) % 4
    assert bytes(got[0].p) == bytes([0, 0x1B])


def test_signatures(spark):
    rng = random.Random(2)
    tags = ["".join(rng.choice("ACGT") for _ in range(rng.randrange(4, 60))) for _ in range(60)]
    comp = str.maketrans("ACGT", "TGCA")
    got = spark.createDataFrame([(t,) for t in tags], "t string").select("t", dna.canonical_signature("t", 8).alias("s"), dna.canonical_signature(dna.revcomp("t"), 8).alias("r"), dna.canonical_signature("t", 8, "hash").alias("h"), dna.canonical_signature(dna.revcomp("t"), 8, "hash").alias("hr")).collect()
    for r in got:
        want = min((min(r.t[i : i + 8], r.t[i : i + 8].translate(comp)[::-1]) for i in range(len(r.t) - 7)), default=None)
        assert r.s == r.r == want and r.h == r.hr
    code = spark.createDataFrame([("T" * 32,)], "t string").select(dna.kmer_code("t").alias("c")).first().c
    assert int(code) == 2**64 - 1


def test_fmt6(spark):
    values = [0.5, 100.0, 1234567.0, 1e-5, 0.0, -2.25, 1 / 3, 1e300, 123456.0, 0.0001]
    for r in spark.createDataFrame([(v,) for v in values], "v double").select("v", k.fmt6("v").alias("s")).collect():
        assert r.s == f"{r.v:.6g}"


def test_engines_are_named(spark):
    from markerpanel.plans.presence import group_counts
    from markerpanel.sources.panels import planted_strict

    with pytest.raises(EngineUnavailable):
        group_counts(planted_strict(spark, "/root/testdata/sf0.001"), engine="gpu")
