"""Panels end to end: published counts of the fixtures, engines against baselines, plans, files, profiles, streams."""

import gzip
import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from markerpanel import profile, sqlfuncs
from markerpanel.errors import PanelError, ProfileError
from markerpanel.operators import baselines, commands, measures, pca, robustness, triage
from markerpanel.plans import evidence, plancheck, presence
from markerpanel.sources import files
from markerpanel.sources import panels as pn
from markerpanel.streaming import streams

D, SMALL = "/root/testdata/sf0.01", "/root/testdata/sf0.001"


def test_entry(spark):
    assert sorted(r.marker for r in __spark_entry__.entry(spark).collect()) == [3, 7, 28, 32]


@pytest.mark.parametrize(("name", "d", "expected"), [("P1", 1, {"weak": 23}), ("P2", 1, {"strict": 32}), ("P3", 1, {"posterior": 21, "weak": 14}), ("P2", 3, {"strict": 26, "weak": 8}), ("P7", 1, {"strict": 52, "weak": 115})])
def test_published_grades(spark, name, d, expected):
    lat = triage.evidence_lattice(pn.PANELS[name](spark, D), d)
    assert {r["class"]: r.n for r in triage.partition_of_lattice(lat).collect()} == expected


def test_prior_grid_is_the_published_one(spark):
    p = pn.planted_hypothesis(spark, D)
    grid = {(r.q, r.pi): r.n for r in robustness.prior_grid(evidence.panel_lattice(p), *p.sizes()).collect()}
    want = ["0 16 21 21 27 30", "16 21 21 27 27 30", "16 21 21 27 27 30", "21 21 21 27 27 27"]
    assert [[grid[q, pi] for pi in robustness.PIS] for q in robustness.RATES] == [list(map(int, w.split())) for w in want]


def test_empirical_bayes(spark):
    p = pn.planted_hypothesis(spark, D)
    pi, steps, done = robustness.fit_prior(evidence.panel_lattice(p), *p.sizes())
    assert done and steps == 7 and abs(pi - 0.0301) < 1e-4


def test_engines_and_baselines_agree(spark):
    p = pn.planted_strict(spark, SMALL)
    a, b = presence.group_counts(p, engine="bitset"), presence.group_counts(p)
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0
    assert measures.digest(commands.signif(p).select("marker", "g1", "g2")) == measures.digest(baselines.materialized("signif", p).select("marker", "g1", "g2"))


def test_wide_bitsets(spark):
    n = 2200  # beyond one array of aggregates
    cells = spark.range(n).select(F.lit(1).alias("marker"), F.col("id").alias("ind"), F.lit(1).alias("depth")).filter("ind % 3 = 0")
    p = pn.Panel(cells, pn._parity_groups(spark, n))
    assert presence.group_counts(p, engine="bitset").collect() == presence.group_counts(p).collect()


def test_plans_are_bounded(spark):
    p = pn.planted_hypothesis(spark, SMALL)
    plancheck.assert_bounded(presence.lattice(presence.group_counts(p)))
    plan = commands.signif(p)
    plancheck.assert_bounded(presence.group_counts(p))
    assert plancheck.broadcasts(plan) >= 1 and not plancheck.python_nodes(plan)
    with pytest.raises(AssertionError):
        plancheck.assert_bounded(evidence.bh_window(spark.range(9).selectExpr("id / 10 as p")))


def test_gram_and_svd(spark):
    cells = pn.planted_strict(spark, SMALL).cells
    c, names, _ = pca.centred(cells)
    c2, _, _ = pca.centred(cells, "gram_sql")
    values, vectors = baselines.pca_svd(cells)
    own = np.linalg.eigvalsh(c)[::-1]
    assert np.allclose(c, c2) and np.allclose(own[: len(values)], values)
    trace = pca.pca_trace(cells).first()[0]
    assert abs(own.sum() - trace) < 1e-6 * trace
    comps, _ = pca.sample_pca(cells, k=len(names))
    assert abs(sum(r.fraction for r in comps.collect()) - 1) < 1e-9


def test_exploratory_row_and_empty_panel(spark):
    p = pn.planted_strict(spark, SMALL)
    rows = triage.triage(p, alpha=1e-12, tau_post=1.0, tau_bf=1e12).collect()
    assert len(rows) == 1 and rows[0]["class"] == "exploratory"
    assert triage.triage(pn.Panel(p.cells.limit(0), p.groups)).count() == 0


def test_process_rules(spark):
    reads = spark.createDataFrame([("a", "ACGT"), ("a", "ACGT"), ("b", "ACGT"), ("b", "ACGN"), ("b", None)], "ind string, seq string")
    assert {(r.ind, r.depth) for r in commands.process(reads).collect()} == {("a", 2), ("b", 1)}
    assert commands.process(reads, on_invalid="text_key").filter("tag = 'ACGN'").count() == 1
    with pytest.raises(Exception, match="not ACGT"):
        commands.process(reads, on_invalid="error").collect()
    with pytest.raises(PanelError):
        commands.process(reads, on_invalid="guess")


def test_files(spark, tmp_path):
    text = "@r1\nACGT\n+\nIIII\n@r2\nACGN\n+\nIIII\n"
    (tmp_path / "fq").mkdir()
    (tmp_path / "fq/ind1.fastq").write_text(text)
    (tmp_path / "fq/ind2.fq.gz").write_bytes(gzip.compress(text.encode()))
    reads = files.read_fastq(spark, f"{tmp_path}/fq")
    assert sorted((r.ind, r.seq) for r in reads.collect()) == [(i, s) for i in ("ind1", "ind2") for s in ("ACGN", "ACGT")]
    (tmp_path / "big").mkdir()
    (tmp_path / "big/ind9.fastq").write_text("".join(f"@r{k}\nACGT{'ACGT'[k % 4] * (k % 9)}\n+\n@III{'@' * (k % 9)}\n" for k in range(5000)))
    spark.conf.set("spark.sql.files.maxPartitionBytes", "10000")
    try:
        big = files.read_fastq(spark, f"{tmp_path}/big")
        assert sorted((r.read_id, r.seq, r.qual) for r in big.collect()) == [(k, "ACGT" + "ACGT"[k % 4] * (k % 9), "@III" + "@" * (k % 9)) for k in range(5000)]
    finally:
        spark.conf.unset("spark.sql.files.maxPartitionBytes")
    (tmp_path / "bad").mkdir()
    (tmp_path / "bad/x.fastq").write_text("@r\nACGT\n+\n")
    with pytest.raises(Exception, match="4-line records"):
        files.read_fastq(spark, f"{tmp_path}/bad").collect()
    p = pn.planted_strict(spark, SMALL)
    files.write_panel(p, f"{tmp_path}/panel")
    back = files.read_panel(spark, f"{tmp_path}/panel")
    assert measures.digest(back.cells.select("marker", "ind", "depth")) == measures.digest(p.cells.select("marker", "ind", "depth"))
    files.write_wide(p, f"{tmp_path}/wide", "min_depth=1")
    wide = files.read_wide(spark, f"{tmp_path}/wide").selectExpr("cast(marker as long) marker", "cast(ind as long) ind", "depth")
    assert measures.digest(wide) == measures.digest(p.cells.select("marker", "ind", "depth"))


def test_profiles(tmp_path):
    (tmp_path / "p.toml").write_text('schema = 1\npi = 0.02\n[linked]\nfamily = "beta"\na = 9\nb = 1\n')
    p = profile.load(f"{tmp_path}/p.toml", alpha=0.01)
    assert p["alpha"] == 0.01 and repr(profile.prior(p).linked) == "Beta(a=9.0, b=1.0)"
    sums = profile.write_archive(f"{tmp_path}/a.zip", p, [__file__])
    assert len(sums) == 2
    for bad in ({"nope": 1}, {"schema": 2}, {"linked": {"family": "fixed", "a": 1}}, {"pi": 2.0}):
        with pytest.raises(ProfileError):
            profile.hydrate(bad)


def test_sql_functions(spark):
    from markerpanel.functions import kernels as k

    sqlfuncs.register(spark)
    df = spark.createDataFrame([(8, 1), (5, 5), (0, 0)], "g1 long, g2 long")
    got = df.select(F.expr("mp_yates_chi2(g1, g2, 10, 10)").alias("a"), k.yates_chi2("g1", "g2", 10, 10).alias("b"), F.expr("mp_posterior_fixed(g1, g2, 10, 10, 0.9D, 0.01D)").alias("c"), k.posterior("g1", "g2", 10, 10).alias("d")).collect()
    for r in got:
        assert r.a == pytest.approx(r.b) and r.c == pytest.approx(r.d)
    got = df.select(F.expr("mp_g_stat(g1, g2, 10, 10)").alias("a"), k.g_stat("g1", "g2", 10, 10).alias("b")).collect()
    assert all(r.a == pytest.approx(r.b, abs=1e-12) for r in got)
    got = spark.sql("SELECT t.s, w.pos, w.kmer FROM VALUES ('ACGTA'), ('AC') AS t(s), LATERAL mp_kmer_windows(t.s, 4) w").collect()
    assert sorted(map(tuple, got)) == [("ACGTA", 0, "ACGT"), ("ACGTA", 1, "CGTA")]


def test_step_up_by_ranges_splits_again(spark):
    df = spark.range(4000).select(F.pow(F.rand(5), F.lit(6.0)).alias("p"), "id")
    want = {r.id for r in evidence.bh_window(df).filter("p_adj <= 0.05").collect()}
    assert 0 < len(want) < 4000
    for cells, most in ((4096, 10**6), (4, 50), (2, 1)):
        assert {r.id for r in evidence.bh_range(df, cells=cells, most=most).collect()} == want, (cells, most)


def _stream(query, name):
    q = query.writeStream.format("memory").queryName(name).outputMode("complete" if name.startswith("c_") else "append").start()
    q.processAllAvailable()
    q.stop()


def test_streams(spark, tmp_path):
    from markerpanel.sources.tables import events

    (tmp_path / "in").mkdir()
    shutil.copy(f"{SMALL}/events.parquet", f"{tmp_path}/in/a.parquet")
    rows = streams.read_events(spark, f"{tmp_path}/in")
    _stream(streams.depth_table(rows.select(F.col("event_type").alias("marker"), F.col("user_id").alias("ind"))), "c_depth")
    want = events(spark, SMALL).groupBy("event_type", "user_id").count()
    got = spark.sql("select marker, ind, depth from c_depth")
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0
    _stream(streams.unique_reads(rows), "unique")
    assert spark.sql("select * from unique").count() == events(spark, SMALL).count()
    _stream(streams.interval_join(rows), "pairs")
    twin = __spark_entry__.queries()["events_interval_join"](spark, SMALL)
    assert spark.sql("select * from pairs").count() == twin.count()
    sink = streams.RunningTriage(f"{tmp_path}/t", 1, 1, lambda ind: 1 + ind % 2)
    q = rows.select(F.col("event_type").alias("marker"), F.col("user_id").alias("ind")).writeStream.foreachBatch(sink).start()
    q.processAllAvailable()
    q.stop()
    sink(events(spark, SMALL).select(F.col("event_type").alias("marker"), F.col("user_id").alias("ind")), 0)  # a repeated batch changes nothing
    assert spark.read.parquet(f"{tmp_path}/t/cells").agg(F.sum("depth")).first()[0] == events(spark, SMALL).count()


def test_registered_studies_run_whole(spark):
    from markerpanel.workloads import QUERIES

    d = "/root/testdata/sf0.001"
    assert QUERIES["fmt6_check"](spark, d).first().points == spark.read.parquet(f"{d}/lineitem.parquet").count()
    assert QUERIES["m34_tuning"](spark, d).count() == 50
    rows = {r.rep: r for r in QUERIES["c20_error_rates"](spark, d).collect()}
    assert rows.keys() == set(range(-1, 20))
    assert all(r.false_calls == r.calls for k, r in rows.items() if k >= 0)
    assert rows[-1].calls >= rows[-1].false_calls and all(r.fdr == (r.false_calls / r.calls if r.calls else 0) for r in rows.values())
