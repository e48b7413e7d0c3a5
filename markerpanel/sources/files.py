"""Readers and writers: FASTQ, wide marker tables, group maps, locus lists, FASTA, panel stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.sources.panels import Panel

MOST_WIDE = 1_000


def read_fastq(spark: SparkSession, path: str) -> DataFrame:
    """ind (file name without endings), read_id, seq, qual of 4-line records; plain or gzip, one file per individual.

    Files are read as lines by the splittable text source, of any size (a gzip file is one streaming task). A line's
    number is its place in its block of the file plus the lines of the blocks before, so a record is four lines that
    meet by number; they are put together before the shuffle where one task has them all.
    """
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("at"))
    blocks = lines.groupBy("file", "block").agg(F.min("at").alias("first"), F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("file").orderBy("block")
    blocks = blocks.select("file", "block", "first", F.coalesce(F.sum("n").over(before.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy("file")).alias("whole"))
    named = lines.join(F.broadcast(blocks), ["file", "block"]).withColumn("number", F.col("at") - F.col("first") + F.col("before"))
    part = lambda k: F.max(F.when(F.col("number") % 4 == k, F.trim("value")))
    records = named.groupBy("file", F.floor(F.col("number") / 4).alias("read_id")).agg(part(0).alias("head"), part(1).alias("seq"), part(2).alias("plus"), part(3).alias("qual"), F.any_value("whole").alias("whole"))
    sound = F.col("head").startswith("@") & F.col("plus").startswith("+") & (F.col("whole") % 4 == 0)
    ind = F.regexp_extract("file", "([^/.]+)[^/]*$", 1)
    seq = F.when(sound, F.upper("seq")).otherwise(F.raise_error(F.concat("file", F.lit(" isn't a file of 4-line records"))))
    return records.select(ind.alias("ind"), "read_id", seq.alias("seq"), "qual")


def write_wide(panel: Panel, path: str, header: str = "") -> None:
    """Tab-separated wide table with a header line of individuals, after comment lines that begin with #."""
    names = [m for m, _ in panel.members()]
    if len(names) > MOST_WIDE:
        raise PanelError(f"a wide table has at most {MOST_WIDE} individuals")
    wide = panel.cells.groupBy("marker").pivot("ind", names).agg(F.first("depth"))
    cols = [F.coalesce(F.col(f"`{c}`"), F.lit(0)).cast("string") for c in wide.columns[1:]]
    first = (f"#{header}\n" if header else "") + "marker\t" + "\t".join(map(str, names))
    spark = panel.cells.sparkSession
    rows = wide.select(F.concat_ws("\t", F.col("marker").cast("string"), *cols).alias("value"))
    spark.createDataFrame([(first,)], "value string").coalesce(1).write.text(f"{path}/header")
    rows.write.text(f"{path}/rows")


def read_wide(spark: SparkSession, path: str) -> DataFrame:
    """cells (marker, ind, depth) of a table written by write_wide; zeros are dropped."""
    head = [r.value for r in spark.read.text(f"{path}/header").collect() if not r.value.startswith("#")][0].split("\t")[1:]
    f = F.split("value", "\t")
    rows = spark.read.text(f"{path}/rows").select(F.get(f, F.lit(0)).alias("marker"), F.posexplode(F.slice(f, 2, len(head))).alias("i", "depth"))
    names = F.array(*map(F.lit, head))
    return rows.select("marker", F.get(names, F.col("i")).alias("ind"), F.col("depth").cast("int").alias("depth")).filter("depth > 0")


def read_groups(spark: SparkSession, path: str, group1: str, group2: str) -> DataFrame:
    """ind, grp of a two-column tab-separated map; other labels become null."""
    rows = spark.read.csv(path, sep="\t", schema="ind string, label string", comment="#")
    return rows.select("ind", F.when(F.col("label") == group1, 1).when(F.col("label") == group2, 2).cast("int").alias("grp"))


def locus_table_to_panel(rows: DataFrame, locus: str, sample: str, depth: str, groups: DataFrame) -> Panel:
    """Another pipeline's long export as a panel."""
    cells = rows.select(F.col(locus).alias("marker"), F.col(sample).alias("ind"), F.col(depth).cast("int").alias("depth")).filter("depth > 0")
    return Panel(cells.groupBy("marker", "ind").agg(F.sum("depth").cast("int").alias("depth")), groups)


def write_panel(panel: Panel, path: str, codec: str = "zstd", buckets: int = 8) -> None:
    """Columnar store: cells by bucket of the marker, groups beside them."""
    cells = panel.cells.withColumn("bucket", F.pmod(F.xxhash64("marker"), F.lit(buckets)))
    cells.repartition("bucket", "marker").sortWithinPartitions("marker").write.option("compression", codec).partitionBy("bucket").parquet(f"{path}/cells")
    panel.groups.write.option("compression", codec).parquet(f"{path}/groups")


def read_panel(spark: SparkSession, path: str) -> Panel:
    return Panel(spark.read.parquet(f"{path}/cells").drop("bucket"), spark.read.parquet(f"{path}/groups"))


def write_fasta(rows: DataFrame, path: str) -> None:
    from markerpanel.operators.commands import to_fasta

    to_fasta(rows).write.text(path)
