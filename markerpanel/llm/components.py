"""Connected components of an edge table.

Up to SOLO edges, a checked number of 16 bytes each, are joined up by one task. Beyond it, alternating
large-star and small-star rounds keep labels and links distributed: each round is two shuffles with a minimum per
node, combined before the shuffle, and ends in a table in the shared folder. The driver sees one number per round.
Both ways give the same rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm.common import discard, held, written

#: Edges that one task joins up.
SOLO = 1_000_000


def joined_up(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, smallest node reached): labels go down along the edges, and to the labels' labels, until all are at rest."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    label = np.arange(len(nodes))
    while True:
        least = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, label[a], least)
        np.minimum.at(new, label[b], least)
        new = new[new]
        new = new[new]
        if (new == label).all():
            return nodes, nodes[label]
        label = new


def _solo(links: DataFrame) -> DataFrame:
    def run(batches):
        parts = [(x.column(0).to_numpy(), x.column(1).to_numpy()) for x in batches]
        if parts:
            nodes, least = joined_up(*(np.concatenate(c) for c in zip(*parts, strict=True)))
            for lo in range(0, len(nodes), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + 100_000]) for c in (nodes, least)], names=["node", "component"])

    return links.coalesce(1).mapInArrow(run, "node long, component long")


def components(edges: DataFrame, solo: int = SOLO) -> DataFrame:
    """edges (a, b): longs, any order, loops and repeats allowed. Returns (node, component): the smallest node reached."""
    first = held(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    few = first.count() <= solo
    links = written(_solo(first) if few else first)
    first.unpersist()
    if few:
        return links
    while True:
        both = links.select("u", "v").unionAll(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # large star: every larger neighbour goes to the smallest of the neighbourhood
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = written(large.filter("u <> v").distinct())
        # small star: a node and its smaller neighbours go to the smallest of these
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(least, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(least.select("u", F.col("m").alias("v")))
        small = written(small.filter("u <> v").distinct())
        before = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        after = small.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        discard(links, large)
        links = small
        if before == after:
            break
    nodes = links.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.unionAll(links.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
