"""Shared parts: reading tables, defined treatment of ids, the shared scratch folder, batch iteration."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null id inside joins and sorts; never shown.
NULL_ID = -(2**63)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A fresh path in the folder that driver and executors share.

    The cluster names it in spark.checkpoint.dir. Only on a local master, where one machine is all there is (tests),
    an unset folder is made here; elsewhere that is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if root is None:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError(f"spark.checkpoint.dir must name a folder that the executors of {master} share")
        root = f"file://{tempfile.mkdtemp(prefix='markerpanel-')}"
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """Cut the lineage by a Parquet table in the shared folder: columnar and small, so later scans prune columns."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/t"
    df.write.parquet(path)
    out = spark.read.parquet(path)
    out._scratch = path
    return out


def held(df: DataFrame) -> DataFrame:
    """Keep a table that several steps read on the executors' disks: no files in the shared folder.

    Lineage stays, so what a lost executor held is computed again. For steps of one job; loops use written().
    The caller unpersists it after the last action that needs it.
    """
    return df.persist(StorageLevel.DISK_ONLY)


def discard(*tables: DataFrame) -> None:
    """Delete tables of written() that nothing will read again."""
    for t in tables:
        path = t.sparkSession._jvm.org.apache.hadoop.fs.Path(t._scratch)
        path.getFileSystem(t.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path.getParent(), True)


def release(spark: SparkSession) -> None:
    """Let go of shuffle files that nothing refers to: Spark drops them when the driver collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def keyed(docs: DataFrame, *cols: str, key: str = "doc_id") -> DataFrame:
    """Only the id (null becomes NULL_ID, any integral or castable type becomes long) and the columns asked for."""
    return docs.select(F.coalesce(F.col(key).cast("long"), F.lit(NULL_ID)).alias(key), *cols)


def shown(key: str = "doc_id"):
    """The id column for output: NULL_ID turns null again."""
    return F.nullif(F.col(key), F.lit(NULL_ID)).alias(key)


def one_row_per_id(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(id, text) with each id once.

    Ids are meant to be unique. One cheap pass over the ids alone tells whether they are; only if not,
    rows of one id are merged and the greatest text stays (null below all), whatever their order.
    """
    df = keyed(docs, text, key=key)
    if df.groupBy(key).count().filter("count > 1").limit(1).count():
        return df.groupBy(key).agg(F.max(text).alias(text))
    return df


def unique_rows(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Whole rows with each id once: of rows that repeat an id the one of the greatest text stays."""
    if not docs.groupBy(key).count().filter("count > 1").limit(1).count():
        return docs
    whole = F.struct(*[docs[c] for c in docs.columns])
    return docs.groupBy(docs[key].alias("_key")).agg(F.max_by(whole, F.struct(docs[text].isNotNull(), docs[text], F.xxhash64(*[docs[c] for c in docs.columns if not docs.schema[c].dataType.simpleString().startswith("map")]))).alias("_row")).select("_row.*")


def with_ids(docs: DataFrame, ids: DataFrame, how: str, key: str = "doc_id", most: int = 1_000_000) -> DataFrame:
    """docs whose id is (left_semi) or isn't (left_anti) among ``ids``, null ids included. Up to ``most`` ids are broadcast."""
    ids = written(ids.select(F.coalesce(F.col(key).cast("long"), F.lit(NULL_ID)).alias("_id")).distinct())
    right = F.broadcast(ids) if ids.count() <= most else ids
    return docs.join(right, F.coalesce(docs[key].cast("long"), F.lit(NULL_ID)) == F.col("_id"), how)


def strings(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    """One chunk of text as large binary, null as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.fill_null("").cast(pa.large_string()).cast(pa.large_binary())


def sliced(n_bytes, limit: int) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts take about ``limit`` bytes; a longer row stands alone."""
    start, size = 0, 0
    for i, k in enumerate(n_bytes):
        if size and size + k > limit:
            yield start, i
            start, size = i, 0
        size += k
    if start < len(n_bytes):
        yield start, len(n_bytes)


def arrow_map(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]]], schema: str) -> DataFrame:
    """mapInArrow with per-task state: ``make`` is called once a task, what it returns once a batch."""

    def run(batches):
        step = make()
        for batch in batches:
            if batch.num_rows:
                yield from step(batch)

    return df.mapInArrow(run, schema)


def public_file(name: str) -> str:
    """Path of a public vocabulary file; the package that holds them is installed on every node."""
    try:
        import public_tokenizers

        return public_tokenizers.path(name)
    except ImportError:
        return os.path.join("/opt/tokenizers", name)
