"""SQL surface: views of a panel and temporary SQL functions that Catalyst inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession

from markerpanel.sources.panels import Panel

FUNCTIONS = {
    "mp_yates_chi2": "(g1 BIGINT, g2 BIGINT, n1 BIGINT, n2 BIGINT) RETURNS DOUBLE RETURN CASE WHEN g1 + g2 = 0 OR g1 + g2 = n1 + n2 OR n1 * n2 = 0 THEN 0D ELSE power(greatest(2 * abs(g1 * (n2 - g2) - g2 * (n1 - g1)) - (n1 + n2), 0) / 2D, 2) * (n1 + n2) / (double(n1 * n2) * (g1 + g2) * (n1 + n2 - g1 - g2)) END",
    "mp_pearson_chi2": "(g1 BIGINT, g2 BIGINT, n1 BIGINT, n2 BIGINT) RETURNS DOUBLE RETURN CASE WHEN g1 + g2 = 0 OR g1 + g2 = n1 + n2 OR n1 * n2 = 0 THEN 0D ELSE power(double(abs(g1 * (n2 - g2) - g2 * (n1 - g1))), 2) * (n1 + n2) / (double(n1 * n2) * (g1 + g2) * (n1 + n2 - g1 - g2)) END",
    "mp_g_cell": "(o BIGINT, r BIGINT, c BIGINT, n BIGINT) RETURNS DOUBLE RETURN CASE WHEN o > 0 AND r > 0 THEN o * ln(double(o) * n / (double(r) * c)) ELSE 0D END",
    "mp_g_stat": "(g1 BIGINT, g2 BIGINT, n1 BIGINT, n2 BIGINT) RETURNS DOUBLE RETURN greatest(2 * (mp_g_cell(g1, g1 + g2, n1, n1 + n2) + mp_g_cell(g2, g1 + g2, n2, n1 + n2) + mp_g_cell(n1 - g1, n1 + n2 - g1 - g2, n1, n1 + n2) + mp_g_cell(n2 - g2, n1 + n2 - g1 - g2, n2, n1 + n2)), 0D)",
    "mp_posterior_fixed": "(g1 BIGINT, g2 BIGINT, n1 BIGINT, n2 BIGINT, q DOUBLE, prior DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-greatest(least(ln(0.5 * exp((g1 + n2 - g2) * ln(q) + (n1 - g1 + g2) * ln(1 - q)) + 0.5 * exp((n1 - g1 + g2) * ln(q) + (g1 + n2 - g2) * ln(1 - q))) - (n1 + n2) * ln(0.5D) + ln(prior / (1 - prior)), 20D), -20D)))",
    "mp_revcomp": "(s STRING) RETURNS STRING RETURN reverse(translate(s, 'ACGT', 'TGCA'))",
}


def _kmer_windows():
    from pyspark.sql.functions import udtf

    @udtf(returnType="pos int, kmer string")
    class KmerWindows:
        """Rows of a lateral join: every window of k bases of a sequence, with its place."""

        def eval(self, seq: str, k: int):
            for at in range(len(seq or "") - k + 1):
                yield at, seq[at : at + k]

    return KmerWindows


def register(spark: SparkSession, panel: Panel | None = None, name: str = "panel") -> None:
    for f, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {f}{body}")
    spark.udtf.register("mp_kmer_windows", _kmer_windows())
    if panel is not None:
        panel.cells.createOrReplaceTempView(f"{name}_cells")
        panel.groups.createOrReplaceTempView(f"{name}_groups")
