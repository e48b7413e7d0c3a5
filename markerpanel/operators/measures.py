"""Cost and accuracy measures: agreement, digests, speedups, efficiency, crossover, error of the kernels."""

from __future__ import annotations

import math
import resource
import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def timed(make, reps: int = 5, **labels) -> list[dict]:
    """Raw rows of repeated runs: wall seconds, CPU of this process, peak memory, status. A failure is a row too."""
    out = []
    for rep in range(reps):
        use, began, status = resource.getrusage(resource.RUSAGE_SELF), time.perf_counter(), "ok"
        try:
            make().write.format("noop").mode("overwrite").save()
        except Exception as x:  # kept with the run, as a status
            status = type(x).__name__
        now = resource.getrusage(resource.RUSAGE_SELF)
        out.append(labels | {"rep": rep, "wall_s": time.perf_counter() - began, "user_s": now.ru_utime - use.ru_utime, "system_s": now.ru_stime - use.ru_stime, "max_rss_mb": now.ru_maxrss / 1024, "status": status})
    return out


def summary(raw: DataFrame, *keys: str) -> DataFrame:
    return raw.filter("status = 'ok'").groupBy(*keys).agg(F.median("wall_s").alias("median_s"), F.stddev_samp("wall_s").alias("sd_s"), F.max("max_rss_mb").alias("max_rss_mb"), F.count(F.lit(1)).alias("reps"))


def geo_mean(df: DataFrame, ratio: str = "speedup") -> DataFrame:
    return df.agg(F.exp(F.avg(F.ln(ratio))).alias("geo_mean"))


def parallel_efficiency(df: DataFrame) -> DataFrame:
    """Adds speedup against one thread and its share of linear; df: command, threads, median_s."""
    one = F.first("median_s").over(Window.partitionBy("command").orderBy("threads"))
    return df.withColumn("speedup", one / F.col("median_s")).withColumn("efficiency", F.col("speedup") / F.col("threads"))


def crossover(df: DataFrame, factor: float = 10.0) -> DataFrame:
    """First size whose speedup exceeds the factor; df: size, speedup."""
    return df.filter(F.col("speedup") > factor).agg(F.min("size").alias("first_size"))


def max_rel_diff(a: DataFrame, b: DataFrame, keys: list[str], value: str) -> DataFrame:
    """n, missing, worst absolute and relative difference of a column over a full outer join; null keys meet each other."""
    y = b.select(*[F.col(c).alias(f"_{i}") for i, c in enumerate(keys)], F.col(value).alias("y"))
    both = a.select(*keys, F.col(value).alias("x")).join(y, [F.col(c).eqNullSafe(F.col(f"_{i}")) for i, c in enumerate(keys)], "full")
    gap = F.abs(F.col("x") - F.col("y"))
    return both.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("x").isNull() != F.col("y").isNull()).alias("missing"), F.coalesce(F.max(gap), F.lit(0.0)).alias("worst_abs"), F.coalesce(F.max(F.try_divide(gap, F.abs("y"))), F.lit(0.0)).alias("worst_rel"))


def digest(df: DataFrame) -> str:
    """One digest of all rows, whatever their order: sums of two row hashes and the count."""
    cols = [F.col(c).cast("string") for c in sorted(df.columns)]
    row = F.concat_ws("\x1f", *[F.coalesce(c, F.lit("\x00")) for c in cols])
    part = lambda at: F.sum(F.conv(F.substring(F.sha2(row, 256), at, 15), 16, 10).cast("decimal(38,0)"))
    r = df.agg(part(1).alias("a"), part(16).alias("b"), F.count(F.lit(1)).alias("n")).first()
    return f"{int(r.a or 0):x}-{int(r.b or 0):x}-{r.n}"


def recovery(found: DataFrame, reference: DataFrame, key: str = "marker") -> DataFrame:
    """n_reference, n_found: reference rows that are found."""
    both = reference.select(key).distinct().join(found.select(key).distinct().withColumn("k", F.lit(1)), key, "left")
    return both.agg(F.count(F.lit(1)).alias("n_reference"), F.count("k").alias("n_found"))


def erfc_error(rows: DataFrame) -> DataFrame:
    """part, points, worst: relative error of the panels against the platform function at t, below and above 4.75."""
    from markerpanel.functions.erfc import erfc_panels

    platform = F.pandas_udf(lambda s: s.map(math.erfc), "double")
    rows = rows.select("t").withColumns({"ours": erfc_panels(F.col("t")), "theirs": platform("t")})
    return rows.groupBy(F.when(F.col("t") < 4.75, "below 4.75").otherwise("to 6").alias("part")).agg(F.count(F.lit(1)).alias("points"), F.max(F.abs(F.col("ours") / F.col("theirs") - 1)).alias("worst"))


def fmt6_check(rows: DataFrame) -> DataFrame:
    """points, mismatches of the formatter against the platform's %g over doubles x."""
    from markerpanel.functions.kernels import fmt6

    c_style = F.pandas_udf(lambda s: s.map(lambda v: f"{v:.6g}"), "string")
    return rows.agg(F.count(F.lit(1)).alias("points"), F.count_if(fmt6("x") != c_style("x")).alias("mismatches"))


def sparsity(panel) -> DataFrame:
    """cells, size, zero_share of the whole matrix."""
    n = panel.size()
    return panel.cells.agg(F.count(F.lit(1)).alias("cells"), (F.countDistinct("marker") * n).alias("size")).withColumn("zero_share", 1 - F.col("cells") / F.col("size"))


def total_bases(reads: DataFrame, seq: str = "seq") -> DataFrame:
    return reads.agg(F.sum(F.length(seq)).cast("long").alias("bases"))


def memory_bound(queue: int, longest_row: int, n_ind: int) -> int:
    """Bytes of a streaming scan: queued rows and one in hand, and two presence words a 64 individuals."""
    return (queue + 1) * longest_row + 16 * -(-n_ind // 64)
