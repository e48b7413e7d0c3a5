"""Panels: builders of (cells, groups) from the given tables. cells: marker, ind, depth > 0. groups: ind, grp 1, 2 or null."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from markerpanel.errors import PanelError
from markerpanel.functions import dna
from markerpanel.sources.tables import load

#: Individuals that the driver holds by name, for dense bitsets and wide tables. Counts have no bound.
MOST_INDIVIDUALS = 20_000
#: Individuals up to whom a group map is sent to every task; a larger one is joined by shuffle.
BROADCAST_GROUPS = 500_000


@dataclass(frozen=True)
class Panel:
    """``cells`` is the depth table without zeros; ``groups`` lists every individual once.

    With ``both``, individuals may be listed in both groups; they count in each, and twice among all carriers.
    With ``each``, they may be listed any number of times, and every listing counts, as in a join with ``groups``.
    """

    cells: DataFrame
    groups: DataFrame
    held: dict = field(default_factory=dict, compare=False)
    both: bool = False
    each: bool = False

    def group_map(self) -> DataFrame:
        rows = self.groups.select("ind", "grp")
        return rows if self.each else rows.distinct()

    def _sizes(self) -> tuple[int, int, int, int, int]:
        """Listings of group 1 and of group 2, individuals, listings in all and of one individual at most; counted where they are, read once."""
        if "sizes" not in self.held:
            each = self.group_map().groupBy("ind").agg(*[F.count_if(F.col("grp") == k).alias(f"n{k}") for k in (1, 2)], F.count(F.lit(1)).alias("listed"))
            r = each.agg(F.sum("n1").alias("n1"), F.sum("n2").alias("n2"), F.count(F.lit(1)).alias("n"), F.sum("listed").alias("rows"), F.max("listed").alias("listed")).first()
            if (r.listed or 0) > 1 and not (self.both or self.each):
                raise PanelError("an individual is in both groups")
            self.held["sizes"] = (r.n1 or 0, r.n2 or 0, r.n, r.rows or 0, r.listed or 0)
        return self.held["sizes"]

    def members(self) -> list[tuple]:
        """(ind, grp) of all individuals, by ind; read once, at most MOST_INDIVIDUALS."""
        if "members" not in self.held:
            rows = self.groups.select("ind", "grp").distinct().limit(MOST_INDIVIDUALS + 1).collect()
            if len(rows) > MOST_INDIVIDUALS:
                raise PanelError(f"more than {MOST_INDIVIDUALS} individuals")
            if len({r.ind for r in rows}) < len(rows):
                raise PanelError("an individual is in both groups")
            self.held["members"] = sorted(((r.ind, r.grp) for r in rows), key=lambda r: (r[0] is None, r[0]))
        return self.held["members"]

    def sizes(self) -> tuple[int, int]:
        return self._sizes()[:2]

    def size(self) -> int:
        return self._sizes()[2]

    def repeated(self) -> bool:
        """Whether an individual is listed more than once."""
        return self._sizes()[4] > 1

    def joined(self, cells: DataFrame, each: DataFrame, key: str = "ind") -> DataFrame:
        """Rows of cells with what ``each`` has of their individual (or word of them); broadcast if there are few listings."""
        return cells.join(F.broadcast(each) if self._sizes()[3] <= BROADCAST_GROUPS else each, key, "left")

    def grouped(self) -> DataFrame:
        """cells with grp."""
        return self.joined(self.cells, self.group_map()).select("marker", "ind", "depth", "grp")


def counted(rows: DataFrame, groups: DataFrame, both: bool = False, each: bool = False) -> Panel:
    """Panel of rows (marker, ind): depth is their number."""
    return Panel(rows.groupBy("marker", "ind").agg(F.count(F.lit(1)).cast("int").alias("depth")), groups, both=both, each=each)


def _all(rows: DataFrame, grp) -> DataFrame:
    return rows.select("ind").distinct().withColumn("grp", grp.cast("int"))


def trade_nation(spark: SparkSession, d: str) -> Panel:
    line = load(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("marker"))
    orders = load(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    cust = load(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("ind"))
    nation = load(spark, d, "nation")
    grp = F.when(F.col("n_regionkey") <= 1, 1).when(F.col("n_regionkey") >= 3, 2)
    return counted(line.join(orders, "l_orderkey").join(cust, "c_custkey").select("marker", "ind"), nation.select(F.col("n_nationkey").alias("ind"), grp.cast("int").alias("grp")))


def _parity_groups(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("ind"), (1 + F.col("id") % 2).cast("int").alias("grp"))


def _planted(spark: SparkSession, d: str, div: int, mod: int, n: int, spared: str) -> DataFrame:
    line = load(spark, d, "lineitem").select(F.expr(f"l_partkey div {div}").alias("marker"), "l_orderkey", "l_linenumber", "l_returnflag")
    lost = f"(marker % {mod} = 3 and l_orderkey % 2 = 1{spared}) or (marker % {mod} = 7 and l_orderkey % 2 = 0)"
    return line.filter(f"not ({lost})").withColumn("ind", F.col("l_orderkey") % n)


def planted_strict_rows(spark: SparkSession, d: str) -> DataFrame:
    return _planted(spark, d, 5, 25, 40, "")


def planted_strict(spark: SparkSession, d: str) -> Panel:
    return counted(planted_strict_rows(spark, d).select("marker", "ind"), _parity_groups(spark, 40))


def planted_hypothesis(spark: SparkSession, d: str) -> Panel:
    return counted(_planted(spark, d, 2, 50, 20, " and l_linenumber <> 1").select("marker", "ind"), _parity_groups(spark, 20))


def words(text):
    # letter by letter, as SQL has it: Spark's lower() has another sigma at a word's end, and two characters for a dotted capital I
    alone = F.replace(F.replace(F.col(text), F.lit("\u03a3"), F.lit("\u03c3")), F.lit("\u0130"), F.lit("i"))
    return F.filter(F.split(F.lower(alone), " "), lambda w: w != "")


def token_quality(spark: SparkSession, d: str) -> Panel:
    rows = load(spark, d, "documents").join(load(spark, d, "labels"), "doc_id").select(F.col("doc_id").alias("ind"), "quality", F.explode(words("text")).alias("marker"))
    groups = load(spark, d, "documents").select("doc_id").join(load(spark, d, "labels"), "doc_id").select(F.col("doc_id").alias("ind"), F.when(F.col("quality") == 1, 1).otherwise(2).alias("grp"))
    # a document that is repeated, or labelled more than once, counts as often
    return counted(rows.select("marker", "ind"), groups, each=True)


def token_lang_balanced(spark: SparkSession, d: str) -> Panel:
    docs = load(spark, d, "documents").select("doc_id", "lang", "text")
    first = None
    for lang in ("en", "fr"):  # a top-k of ids, as the panel is defined
        part = docs.filter(F.col("lang") == lang).select("doc_id").orderBy("doc_id").limit(30)
        first = part if first is None else first.unionAll(part)
    docs = docs.join(F.broadcast(first), "doc_id")
    rows = docs.select(F.explode(words("text")).alias("marker"), F.col("doc_id").alias("ind"))
    return counted(rows, docs.select(F.col("doc_id").alias("ind"), F.when(F.col("lang") == "en", 1).otherwise(2).alias("grp")))


def _source_group():
    return 1 + F.substring("ind", 4, 9).cast("int") % 2


def token_source(spark: SparkSession, d: str) -> Panel:
    docs = load(spark, d, "documents").select(F.col("source").alias("ind"), "text")
    return counted(docs.select(F.explode(words("text")).alias("marker"), "ind"), _all(docs, _source_group()))


def token_role(spark: SparkSession, d: str) -> Panel:
    talk = load(spark, d, "conversations").filter(F.col("role").isin("user", "assistant")).select((F.col("conv_id") * 10 + F.col("turn")).alias("ind"), "role", "text")
    groups = talk.select("ind", F.when(F.col("role") == "user", 1).otherwise(2).alias("grp")).distinct()
    # a conversation of more than ten turns shares individuals with the next ones
    return counted(talk.select(F.explode(words("text")).alias("marker"), "ind"), groups, both=True)


def event_slot(ts="ts"):
    """6-hour slot and event type, as one string; null if either is."""
    return F.concat(F.date_format(F.timestamp_seconds(F.floor(F.unix_seconds(F.col(ts)) / 21600) * 21600), "yyyy-MM-dd HH"), F.lit("|"), "event_type")


def event_user(spark: SparkSession, d: str) -> Panel:
    from markerpanel.sources.tables import events

    rows = events(spark, d).select(event_slot().alias("marker"), F.col("user_id").alias("ind"))
    return counted(rows, _all(rows, 1 + F.col("ind") % 2))


def reads(spark: SparkSession, d: str, size: int = 94) -> DataFrame:
    """(ind, doc_id, seq): DNA pieces of the documents, by source."""
    docs = load(spark, d, "documents")
    return docs.select(F.col("source").alias("ind"), "doc_id", F.explode(dna.pieces(dna.dna_letters("text"), size)).alias("seq"))


def dna_tag(spark: SparkSession, d: str) -> Panel:
    rows = reads(spark, d)
    groups = load(spark, d, "documents").select(F.col("source").alias("ind"))
    return counted(rows.select(F.col("seq").alias("marker"), "ind"), _all(groups, _source_group()))


def contigs(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "benchmark").select(F.col("item_id").alias("contig"), dna.dna_letters("text").alias("seq"))


def embedding_dim(spark: SparkSession, d: str) -> DataFrame:
    """Dense cells (marker, ind, depth double)."""
    return load(spark, d, "embeddings").select(F.col("vec_id").alias("marker"), F.posexplode("embedding").alias("ind", "depth")).withColumn("depth", F.col("depth").cast("double"))


def part_supplier(spark: SparkSession, d: str) -> Panel:
    line = load(spark, d, "lineitem").select(F.col("l_partkey").alias("marker"), F.col("l_suppkey").alias("ind"))
    groups = load(spark, d, "supplier").select(F.col("s_suppkey").alias("ind"), (1 + F.col("s_nationkey") % 2).cast("int").alias("grp"))
    # a supplier that is repeated counts as often, whatever its nations
    return counted(line, groups, each=True)


PANELS = {"P1": trade_nation, "P2": planted_strict, "P3": planted_hypothesis, "P4": token_quality, "P5": token_lang_balanced, "P6": token_source, "P7": token_role, "P8": event_user, "P9": dna_tag, "P11": part_supplier}
