"""python -m markerpanel.cli COMMAND --panel DIR --out DIR [--profile FILE]: commands over a stored panel."""

from __future__ import annotations

import argparse

from pyspark.sql import SparkSession

from markerpanel import profile
from markerpanel.operators import commands, triage
from markerpanel.sources.files import read_panel

COMMANDS = ("freq", "distrib", "depth", "signif", "triage")


def run(spark: SparkSession, command: str, panel, p: dict):
    d = p["min_depth"]
    if command == "freq":
        return commands.freq(panel, d)
    if command == "depth":
        return commands.depth_summary(panel, d)
    if command == "triage":
        return triage.triage(panel, d, profile.prior(p), p["alpha"], p["tau_post"], p["tau_bf"])
    return {"distrib": commands.distrib, "signif": commands.signif}[command](panel, d, p["test"], p["correction"], p["alpha"])


def main(args: list[str] | None = None) -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("command", choices=COMMANDS)
    parser.add_argument("--panel", required=True)
    parser.add_argument("--out", required=True)
    parser.add_argument("--profile")
    a = parser.parse_args(args)
    p = profile.load(a.profile) if a.profile else profile.hydrate({})
    spark = SparkSession.builder.getOrCreate()
    run(spark, a.command, read_panel(spark, a.panel), p).write.mode("errorifexists").parquet(a.out)


if __name__ == "__main__":
    main()
