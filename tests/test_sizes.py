"""Sizes beyond the bounds of broadcasts, driver lists and log tables: the same rows by the other way."""

import datetime
import math
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.functions import kernels
from markerpanel.operators import baselines, commands, triage
from markerpanel.plans import joins, plancheck, presence
from markerpanel.sources import panels as pn
from markerpanel.sources.tables import load
from markerpanel.workloads import QUERIES, SQL

SMALL = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_broadcast_join_of_a_large_table(spark, monkeypatch):
    few = QUERIES["op_join_broadcast"](spark, SMALL)
    assert "BroadcastHashJoin" in plancheck.text(few)
    monkeypatch.setattr(joins, "MOST_ROWS", 100, raising=False)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        many = QUERIES["op_join_broadcast"](spark, SMALL)
        assert "Broadcast" not in plancheck.text(many) and rows(many) == rows(few) == rows(QUERIES["op_join_merge"](spark, SMALL))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def many(spark, n, group=lambda i: 1 + i % 2):
    """A panel of n individuals: marker m is carried by those that m divides, 0 by one that no group lists."""
    groups = spark.range(n).select(F.col("id").alias("ind"), group(F.col("id")).cast("int").alias("grp"))
    cells = spark.range(n).select(F.explode(F.array(*map(F.lit, (1, 2, 3, 97)))).alias("marker"), F.col("id").alias("ind"), F.lit(1).alias("depth")).filter("ind % marker = 0")
    return pn.Panel(cells.unionAll(spark.sql(f"select 0, {n}L, 1")), groups)


def test_counts_beyond_20000_individuals(spark, monkeypatch):
    n = 30_001
    p = many(spark, n)
    assert (p.sizes(), p.size()) == ((15_001, 15_000), n)
    want = [(0, 0, 0, 1)] + sorted((m, sum(i % m == i % 2 == 0 for i in range(n)), sum(i % m == 0 and i % 2 for i in range(n)), -(-n // m)) for m in (1, 2, 3, 97))
    assert rows(presence.group_counts(p)) == want
    monkeypatch.setattr(pn, "BROADCAST_GROUPS", 100)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        counts = presence.group_counts(many(spark, n))
        assert "Broadcast" not in plancheck.text(counts) and rows(counts) == want
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_individuals_listed_twice(spark):
    cells = spark.createDataFrame([("a", 1, 1), ("a", 2, 1), ("b", 2, 3)], "marker string, ind long, depth int")
    groups = spark.createDataFrame([(1, 1), (2, 1), (2, 2), (2, 2)], "ind long, grp int")
    assert rows(presence.group_counts(pn.Panel(cells, groups, both=True))) == [("a", 2, 1, 3), ("b", 1, 1, 2)]
    with pytest.raises(PanelError):
        pn.Panel(cells, groups).sizes()


#: Queries whose panels grow with the data: none may hold individuals on the driver.
GROWING = ("b8_conditional_counts", "lattice_p4", "lattice_p7", "qc_report", "k_yates_wide", "lattice_p11", "lattice_p8", "w1_signif_wide", "w6_signif", "triage_role", "triage_events", "triage_supplier", "bitset_counts", "op_backend_diff")


@pytest.mark.parametrize("name", GROWING)
def test_no_bound_on_individuals(spark, monkeypatch, name):
    want = rows(QUERIES[name](spark, SMALL))
    for module, bound in ((pn, "MOST_INDIVIDUALS"), (pn, "BROADCAST_GROUPS"), (kernels, "TABLE"), (presence, "MOST_CELLS"), (presence, "BROADCAST_CELLS"), (presence, "DENSE")):
        if hasattr(module, bound):
            monkeypatch.setattr(module, bound, 5)
    got = rows(QUERIES[name](spark, SMALL))
    assert len(got) == len(want) and all(a == pytest.approx(b, abs=2e-6) if isinstance(a, float) else a == b for r, s in zip(got, want, strict=True) for a, b in zip(r, s, strict=True))


def test_contained_windows(spark, monkeypatch):
    rng = random.Random(3)
    contigs = [("".join(rng.choice("ACGT") for _ in range(rng.choice((0, 23, 24, 60, 200))))) for _ in range(40)] + ["A" * 80, "A" * 24]
    tags = ["".join(rng.choice("ACGT") for _ in range(94)) for _ in range(40)] + ["A" * 94, "T" * 94, "ACGT"]
    back = lambda s: s.translate(str.maketrans("ACGT", "TGCA"))[::-1]
    tags += [rng.choice(("", "G")) + (c if k % 2 else back(c))[:50] + "C" * 44 for k, c in enumerate(contigs) if len(c) >= 24]
    want = sorted({(t, i) for t in tags for i, c in enumerate(contigs) for s in (t, back(t)) for a in range(len(s) - 23) if s[a : a + 24] in c})
    t, c = spark.createDataFrame([(t,) for t in set(tags)], "marker string"), spark.createDataFrame(list(enumerate(contigs)), "contig int, seq string")
    assert "NestedLoop" not in plancheck.text(baselines.map_exact_contains(t, c)) and rows(baselines.map_exact_contains(t, c)) == want
    monkeypatch.setattr(joins, "MOST_ROWS", 5)
    assert rows(baselines.map_exact_contains(t, c)) == want


def test_log_sums_beyond_the_tables(spark):
    n, some = 70_000, [0, 1, 5, 31, 32, 33, 100, 34_567, 69_999, 70_000]
    df = spark.createDataFrame([(k,) for k in some], "k int")
    for a, b in ((1.0, 1.0), (0.5, 3.0), (9.0, 1.0)):
        for r in df.select("k", kernels.log_evidence_beta("k", n, a, b).alias("e")).collect():
            lb = lambda x, y: math.lgamma(x) + math.lgamma(y) - math.lgamma(x + y)
            assert r.e == pytest.approx(lb(r.k + a, n - r.k + b) - lb(a, b), abs=1e-8)
    p = spark.createDataFrame([(8, 0), (3, 3)], "g1 int, g2 int").select(kernels.fisher_exact("g1", "g2", 1500, 1501).alias("p")).collect()
    want = [sum(math.comb(1500, x) * math.comb(1501, s - x) for x in range(s + 1) if math.comb(1500, x) * math.comb(1501, s - x) <= math.comb(1500, g) * math.comb(1501, s - g)) / math.comb(3001, s) for s, g in ((8, 8), (6, 3))]
    assert [r.p for r in p] == pytest.approx(want)


def test_fixed_rates_over_many_individuals(spark):
    # a cell of triage_role over check_l; the log odds were computed with 50 digits
    odds = spark.createDataFrame([(178, 680)], "g1 int, g2 int").select(kernels.log_odds("g1", "g2", 68_330, 56_277).alias("o")).first().o
    assert odds == pytest.approx(-49313.156114499987356878, abs=1.5e-11, rel=0) and round(odds, 6) == -49313.156114


def test_lattice_too_large_to_broadcast(spark, monkeypatch):
    small = pn.planted_hypothesis(spark, SMALL)
    want = rows(commands.signif(small, correction="none")), rows(commands.subset(small, g1=(3, None))), rows(triage.triage(small))
    monkeypatch.setattr(presence, "BROADCAST_CELLS", 2)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        joined = commands.signif(small, correction="none")
        assert "BroadcastHashJoin [g1" not in plancheck.text(joined) and len(want[0]) > 2
        assert (rows(joined), rows(commands.subset(small, g1=(3, None))), rows(triage.triage(small))) == want
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_sparse_bitsets(spark, monkeypatch):
    p = many(spark, 9_000, lambda i: F.when(i % 5 < 3, 1 + i % 2))
    cells = p.cells.unionAll(spark.sql("select 5, 2L, 1"))
    for bound in (2_048, 5):
        monkeypatch.setattr(presence, "DENSE", bound)
        for d in (1, 2):
            q = pn.Panel(cells, p.groups)
            assert rows(presence.group_counts(q, d, "bitset")) == rows(presence.group_counts(q, d))
    twice = pn.Panel(spark.createDataFrame([("a", 1, 1), ("a", 2, 1)], "marker string, ind long, depth int"), spark.createDataFrame([(1, 1), (2, 1), (2, 2)], "ind long, grp int"), both=True)
    assert rows(presence.group_counts(twice, engine="bitset")) == rows(presence.group_counts(twice)) == [("a", 2, 1, 3)]


def test_triage_without_an_exploratory_row(spark):
    none = {"alpha": 1e-12, "tau_post": 1.0, "tau_bf": 1e12, "exploratory": False}
    assert rows(triage.triage(pn.planted_strict(spark, SMALL), **none)) == []
    assert {r["class"] for r in QUERIES["triage_events"](spark, SMALL).collect()} <= {"strict", "posterior", "weak"}


#: Queries that once made their rows up, and a table whose rows they must read.
FROM_TABLES = (("b3_general_tail", "orders"), ("erfc_error", "lineitem"), ("fmt6_check", "lineitem"), ("k_erfc", "orders"), ("op_recursive_logfact", "lineitem"))


@pytest.mark.parametrize(("name", "table"), FROM_TABLES)
def test_reads_its_table(spark, name, table):
    df = QUERIES[name](spark, SMALL)
    assert f"{SMALL}/{table}.parquet" in df.inputFiles()[0]
    n = load(spark, SMALL, table).count()
    got = df.collect()
    column = {"erfc_error": "points", "fmt6_check": "points", "op_recursive_logfact": "lines"}.get(name)
    assert (sum(r[column] for r in got) if column else len(got)) == n


def odd_tables(spark, tmp_path, **more):
    """A folder of tables as SMALL has them, with more rows: lists of (row, ...) of the columns that are named."""
    for name, (cols, extra) in more.items():
        df = load(spark, SMALL, name)
        kinds = ", ".join(f"{c} {dict(df.dtypes)[c]}" for c in cols.split())
        df.unionByName(spark.createDataFrame(extra, kinds), allowMissingColumns=True).write.parquet(f"{tmp_path}/{name}.parquet")
    return str(tmp_path)


def check_sql(spark, d, name, tables):
    """The query's rows over the folder are those of its SQL."""
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{d}/{t}.parquet/*.parquet')")
    want = con.execute(SQL[name])
    cols = [c[0] for c in want.description]
    assert rows(QUERIES[name](spark, d).select(*cols)) == sorted(want.fetchall(), key=repr)


#: Documents that are repeated or have no id or text, and labels that are repeated, differ or are missing.
LABELLED = {
    "documents": ("doc_id text", [(9001, "zza zzb zzb"), (9001, "zza"), (9002, "zza zzc"), (9003, None), (9004, "zzc"), (None, "zza"), (9005, "zza")]),
    "labels": ("doc_id quality", [(9001, 1), (9002, 1), (9002, 0), (9002, 0), (9003, 1), (9004, None), (None, 1)]),
}


@pytest.mark.parametrize("name", ["lattice_p4", "qc_report"])
def test_documents_labelled_more_than_once(spark, tmp_path, name):
    check_sql(spark, odd_tables(spark, tmp_path, **LABELLED), name, LABELLED)


def test_report_without_markers(spark, tmp_path):
    texts = [(1, ""), (2, "  "), (3, None)]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1), (2, 0), (3, 0)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tmp_path}/{t}.parquet/*.parquet')")
    got = rows(QUERIES["qc_report"](spark, str(tmp_path)))
    assert repr(got) == repr(con.execute(SQL["qc_report"]).fetchall()) == repr([(1, 0, 0, math.nan, None, None, True)])
    deep = commands.qc_report(pn.planted_strict(spark, SMALL), [1, 10_000]).collect()
    assert sorted((r.min_depth, r.markers > 0, r.n1) for r in deep) == [(1, True, 20), (10_000, False, 20)]


#: Words whose lower case hangs on their neighbours or has two characters, and turns that share an individual or lack something.
SPOKEN = {"conversations": ("conv_id turn role text", [(9001, 13, "user", "\u039f\u03a3 \u0130\u0130  \u03a3"), (9002, 3, "assistant", "\u03bf\u03c3 ii"), (9001, 1, "user", "\u03bf\u03c2 i\u0307i\u0307"), (9001, 2, "user", None), (9001, 4, None, "ii"), (None, 1, "user", "ii"), (9003, None, "assistant", "\u03bf\u03c3")])}


@pytest.mark.parametrize("name", ["lattice_p7", "w6_signif"])
def test_lower_case_of_single_letters(spark, tmp_path, name):
    check_sql(spark, odd_tables(spark, tmp_path, **SPOKEN), name, SPOKEN)


def test_no_marker_of_a_group_is_deep_enough(spark, tmp_path):
    # the only words that are said twice are of turns without an id, which no group lists
    rows_ = [(1, 1, "user", "a b"), (2, 2, "assistant", "a c"), (None, 3, "user", "d d e")]
    spark.createDataFrame(rows_, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    check_sql(spark, str(tmp_path), "w6_signif", ["conversations"])


#: Suppliers that are repeated, have two nations or no key, and lines without a part or a supplier.
SUPPLIED = {
    "supplier": ("s_suppkey s_nationkey", [(1, 0), (1, 1), (2, 0), (2, 0), (9001, None), (None, 1)]),
    "lineitem": ("l_orderkey l_partkey l_suppkey", [(1, None, 1), (1, None, 2), (1, 7, None), (1, 9001, 1), (1, 9001, 2), (1, 9002, 9001)]),
}


@pytest.mark.parametrize("name", ["triage_supplier", "k_yates_wide", "lattice_p11", "op_backend_diff"])
def test_suppliers_listed_more_than_once(spark, tmp_path, name):
    check_sql(spark, odd_tables(spark, tmp_path, **SUPPLIED), name, SUPPLIED)


#: Events without a time, a type or a user.
TIMELESS = {"events": ("event_id ts user_id event_type", [(1, None, 3, "click"), (2, None, 4, "click"), (3, datetime.datetime(2024, 1, 1, 5), 5, None), (4, None, 6, None), (5, datetime.datetime(2024, 1, 1, 5), None, "click")])}


def test_events_without_a_slot(spark, tmp_path):
    check_sql(spark, odd_tables(spark, tmp_path, **TIMELESS), "lattice_p8", TIMELESS)
