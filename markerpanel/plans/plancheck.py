"""Assertions on physical plans: what a plan must not do to marker rows."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> list[str]:
    return re.findall(r"Exchange (\w+partitioning\([^)]*\)|SinglePartition)", text(df))


def broadcasts(df: DataFrame) -> int:
    return text(df).count("BroadcastExchange")


def python_nodes(df: DataFrame) -> list[str]:
    return re.findall(r"(\w*(?:Python|Arrow|Pandas)\w*)", text(df))


def assert_bounded(df: DataFrame) -> None:
    """No row-level window, sort or join in one partition: SinglePartition may only follow a partial aggregate."""
    plan = text(df).split("\n")
    for at, line in enumerate(plan):
        if "Exchange SinglePartition" in line:
            below = next((x for x in plan[at + 1 :] if x.strip()), "")
            if "partial_" not in below and "LocalLimit" not in below and "TakeOrdered" not in below:
                raise AssertionError(f"rows meet in one partition: {line.strip()} over {below.strip()}")
