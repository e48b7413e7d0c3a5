"""Sample PCA from an accumulated Gram matrix. X'X - m mu mu' needs one pass; only n x n numbers leave the executors."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.errors import EngineUnavailable, PanelError

#: Individuals whose Gram matrix the driver may hold (n^2 doubles).
MOST = 4_000


def indexed(cells: DataFrame) -> tuple[DataFrame, list]:
    """cells with a dense individual number i, and the individuals in order."""
    names = sorted(r[0] for r in cells.select("ind").distinct().limit(MOST + 1).collect())
    if len(names) > MOST:
        raise PanelError(f"more than {MOST} individuals")
    kind = cells.schema["ind"].dataType.simpleString()
    index = cells.sparkSession.createDataFrame([(n, i) for i, n in enumerate(names)], f"ind {kind}, i int")
    return cells.join(F.broadcast(index), "ind"), names


def gram_sql(cells: DataFrame) -> DataFrame:
    """i, j, c (i <= j): raw sums of products over markers, by a self join on marker. Exact in DECIMAL for integer depths."""
    a, b = cells.alias("a"), cells.alias("b")
    kind = "double" if cells.schema["depth"].dataType.simpleString() in ("double", "float") else "decimal(38,0)"
    pairs = a.join(b, (F.col("a.marker") == F.col("b.marker")) & (F.col("a.i") <= F.col("b.i")))
    return pairs.groupBy(F.col("a.i").alias("i"), F.col("b.i").alias("j")).agg(F.sum((F.col("a.depth") * F.col("b.depth")).cast(kind)).alias("c"))


def gram_arrow(cells: DataFrame, n: int) -> DataFrame:
    """The same from sparse rows: each task adds up n x n partial sums, which are then summed.

    Integer depths are added in int64; a task whose sums could overflow raises instead of rounding.
    """
    exact = cells.schema["depth"].dataType.simpleString() not in ("double", "float")
    rows = cells.groupBy("marker").agg(F.collect_list(F.struct("i", "depth")).alias("x")).select("x")

    def run(batches):
        total = np.zeros((n, n), np.int64 if exact else np.float64)
        bound = 0
        for batch in batches:
            x = batch.column(0)
            flat = x.flatten()
            who, val = (flat.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            sizes = np.diff(x.offsets.to_numpy())
            at = np.repeat(np.arange(len(sizes)), sizes)
            for lo in range(0, len(sizes), 4096):
                pick = (at >= lo) & (at < lo + 4096)
                dense = np.zeros((min(4096, len(sizes) - lo), n), total.dtype)
                dense[at[pick] - lo, who[pick]] = val[pick]
                if exact and dense.size:
                    bound += int(np.abs(dense).max()) ** 2 * len(dense)
                    if bound >= 2**63:
                        raise OverflowError("partial Gram sums may leave 64 bits; use smaller partitions")
                total += dense.T @ dense
        i, j = np.nonzero(np.triu(total))
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(total[i, j])], names=["i", "j", "c"])

    part = rows.mapInArrow(run, f"i int, j int, c {'long' if exact else 'double'}")
    return part.groupBy("i", "j").agg(F.sum(F.col("c").cast("decimal(38,0)" if exact else "double")).alias("c"))


def totals(cells: DataFrame) -> DataFrame:
    return cells.groupBy("i").agg(F.sum(F.col("depth").cast("double")).alias("s"))


def retained(cells: DataFrame, d: int | None) -> DataFrame:
    """Raw depths of markers that some individual carries at depth d."""
    if d is None or d <= 1:
        return cells
    kept = cells.groupBy("marker").agg(F.max("depth").alias("most")).filter(F.col("most") >= d).select("marker")
    return cells.join(kept, "marker", "left_semi")


def centred(cells: DataFrame, engine: str = "gram_arrow", d: int | None = None) -> tuple[np.ndarray, list, int]:
    """(C, individuals, m). Zeros of individuals without a cell count through m."""
    cells, names = indexed(retained(cells.select("marker", "ind", "depth"), d))
    n = len(names)
    if engine not in ("gram_arrow", "gram_sql"):
        raise EngineUnavailable(engine)
    m = cells.select("marker").distinct().count()
    c, s = np.zeros((n, n)), np.zeros(n)
    for r in (gram_sql(cells) if engine == "gram_sql" else gram_arrow(cells, n)).collect():
        c[r.i, r.j] = c[r.j, r.i] = float(r.c)
    for r in totals(cells).collect():
        s[r.i] = r.s
    return c - np.outer(s, s) / max(1, m), names, m


def normalize_signs(v: np.ndarray) -> np.ndarray:
    """Each column's entry of largest size (the first of equals) becomes positive."""
    top = np.abs(np.round(v, 12)).argmax(0)
    return v * np.where(v[top, np.arange(v.shape[1])] < 0, -1.0, 1.0)


def sample_pca(cells: DataFrame, k: int = 2, engine: str = "gram_arrow", d: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(components: component, eigenvalue, fraction; coordinates: ind, component, loading)."""
    spark = cells.sparkSession
    c, names, _ = centred(cells, engine, d)
    values, vectors = np.linalg.eigh(c) if len(c) else (np.zeros(0), np.zeros((0, 0)))
    order = np.argsort(-values)
    values, vectors = np.maximum(values[order], 0), normalize_signs(vectors[:, order]) if len(c) else vectors
    total = float(values.sum()) or 1.0
    comps = spark.createDataFrame([(i + 1, float(v), float(v) / total) for i, v in enumerate(values[:k])], "component int, eigenvalue double, fraction double")
    kind = cells.schema["ind"].dataType.simpleString()
    coords = spark.createDataFrame([(names[r], i + 1, float(vectors[r, i])) for r in range(len(names)) for i in range(min(k, len(values)))], f"ind {kind}, component int, loading double")
    return comps, coords


def pc_group_shift(coords: DataFrame, groups: DataFrame) -> DataFrame:
    """component, shift: mean loading of group 1 minus that of group 2."""
    both = coords.join(groups.select("ind", "grp").distinct(), "ind")
    return both.groupBy("component").agg((F.avg(F.when(F.col("grp") == 1, F.col("loading"))) - F.avg(F.when(F.col("grp") == 2, F.col("loading")))).alias("shift"))


def pc_covariates(coords: DataFrame, cells: DataFrame) -> DataFrame:
    """component, r: correlation of loadings with total depth."""
    depth = cells.groupBy("ind").agg(F.sum(F.col("depth").cast("double")).alias("total"))
    return coords.join(depth, "ind").groupBy("component").agg(F.corr("loading", "total").alias("r"))


def pca_trace(cells: DataFrame) -> DataFrame:
    """Trace of the centred Gram matrix, which the eigenvalues sum to."""
    m = cells.agg(F.countDistinct("marker")).first()[0]
    per = cells.groupBy("ind").agg(F.sum(F.col("depth").cast("double") ** 2).alias("q"), F.sum(F.col("depth").cast("double")).alias("s"))
    return per.agg(F.sum(F.col("q") - F.col("s") * F.col("s") / max(1, m)).alias("trace"))
