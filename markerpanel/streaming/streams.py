"""Streaming variants: depth tables, windows, de-duplication, bitset state, running triage, Gram sums. Each has a batch twin."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from markerpanel.functions.kernels import Prior
from markerpanel.plans import evidence, presence
from markerpanel.sources.tables import SCHEMAS


def read_events(spark: SparkSession, folder: str, per_trigger: int | None = None) -> DataFrame:
    """Events from a folder of Parquet files, ts as TIMESTAMP (watermarks reject NTZ)."""
    reader = spark.readStream.schema(SCHEMAS["events"])
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def depth_table(rows: DataFrame) -> DataFrame:
    """T1: marker, ind, depth, in update mode."""
    return rows.groupBy("marker", "ind").agg(F.count(F.lit(1)).alias("depth"))


def windowed(rows: DataFrame, size: str = "6 hours", slide: str | None = None, late: str = "2 days") -> DataFrame:
    """T2: events and reads by window and type; rows later than the watermark are dropped (T3)."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sessions(rows: DataFrame, gap: str = "6 hours", late: str = "2 days") -> DataFrame:
    return rows.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def counted_late(rows: DataFrame, horizon: str, name: str = "late") -> DataFrame:
    """T3: observes how many rows lie behind a fixed horizon; rows pass unchanged."""
    return rows.observe(name, F.count(F.lit(1)).alias("rows"), F.count_if(F.col("ts") < F.lit(horizon).cast("timestamp")).alias("late"))


def unique_reads(rows: DataFrame, key: str = "event_id", late: str = "2 days") -> DataFrame:
    """T4: repeated ids within the watermark go."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


class PresenceState(StatefulProcessor):
    """T5: one word array per marker; a row comes out when a marker's count pair changes."""

    def __init__(self, masks: tuple[list[int], list[int]]):
        self.masks = [[m & (1 << 64) - 1 for m in mask] for mask in masks]

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.words = handle.getValueState("words", "words array<bigint>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        old = self.words.get()
        words = [w & (1 << 64) - 1 for w in old[0]] if old else [0] * len(self.masks[0])
        pair = lambda: tuple(sum((w & m).bit_count() for w, m in zip(words, mask, strict=True)) for mask in self.masks)
        before = pair()
        for pdf in rows:
            for i in pdf["i"]:
                words[int(i) // 64] |= 1 << int(i) % 64
        signed = [w - (1 << 64) if w >> 63 else w for w in words]
        self.words.update((signed,))
        after = pair()
        if after != before or not old:
            yield pd.DataFrame({"marker": [key[0]], "g1": [after[0]], "g2": [after[1]]})

    def close(self) -> None:
        pass


def presence_stream(rows: DataFrame, masks: tuple[list[int], list[int]]) -> DataFrame:
    """rows: marker string, i (number of the individual)."""
    return rows.groupBy("marker").transformWithStateInPandas(PresenceState(masks), "marker string, g1 int, g2 int", "Update", "none")


class RunningTriage:
    """T6: foreachBatch sink. Cells add up in a store of batches; N grows, so every batch is graded anew on the
    lattice of all cells so far. Writing is idempotent by batch number (T9)."""

    def __init__(self, path: str, n1: int, n2: int, group_of: Callable, prior: Prior = Prior()):
        self.path, self.n1, self.n2, self.group_of, self.prior = path, n1, n2, group_of, prior

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        cells = batch.groupBy("marker", "ind").agg(F.count(F.lit(1)).alias("depth"))
        cells.write.mode("overwrite").parquet(f"{self.path}/cells/epoch={epoch}")

    def graded(self, spark: SparkSession) -> DataFrame:
        cells = spark.read.parquet(f"{self.path}/cells").select("marker", "ind").distinct()
        grp = self.group_of(F.col("ind"))
        counts = cells.groupBy("marker").agg(F.count_if(grp == 1).cast("int").alias("g1"), F.count_if(grp == 2).cast("int").alias("g2"), F.count(F.lit(1)).cast("int").alias("n_ind"))
        lat = evidence.annotate(evidence.tested(presence.lattice(counts)), self.n1, self.n2, self.prior)
        return presence.back(counts, lat.filter("class <> 'none'"))


def with_groups(rows: DataFrame, groups: DataFrame) -> DataFrame:
    """T7: stream-static join with the (small, checked) group map."""
    return rows.join(F.broadcast(groups), "ind", "left")


def interval_join(rows: DataFrame, late: str = "2 days") -> DataFrame:
    """T7: views and purchases of one user within an hour; both sides bounded by watermarks."""
    views = rows.filter("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u0"), F.col("ts").alias("t0")).withWatermark("t0", late)
    buys = rows.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", late)
    return views.join(buys, F.expr("u0 = u1 and t1 >= t0 and t1 <= t0 + interval 1 hour")).select("view_id", "purchase_id")


class RunningGram:
    """T8: foreachBatch sink of additive Gram partials, one folder a batch; total() sums them."""

    def __init__(self, path: str):
        self.path = path

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from markerpanel.operators.pca import gram_sql

        gram_sql(batch.select("marker", "i", "depth")).write.mode("overwrite").parquet(f"{self.path}/epoch={epoch}")

    def total(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(self.path).groupBy("i", "j").agg(F.sum("c").alias("c"))
