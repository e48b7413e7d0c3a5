"""Presence, group counts and the lattice: the histogram of a panel over count pairs.

Every statistic depends on a count pair only, so a panel of any size is reduced to at most
(n1 + 1)(n2 + 1) rows before anything is evaluated, and evidence goes back by a broadcast join.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from markerpanel.errors import PanelError, choose
from markerpanel.plans import joins
from markerpanel.sources.panels import Panel

#: Lattice rows that the driver may collect for a fit (each is two numbers).
MOST_CELLS = 2_000_000
#: Lattice rows that are broadcast (each is about ten numbers).
BROADCAST_CELLS = 250_000
#: Individuals up to whom a marker's bitset is one array of words.
DENSE = 2_048


def _conditional(panel: Panel, d: int) -> DataFrame:
    rows = panel.grouped().filter(F.col("depth") >= d)
    return rows.groupBy("marker").agg(F.count_if(F.col("grp") == 1).cast("int").alias("g1"), F.count_if(F.col("grp") == 2).cast("int").alias("g2"), F.count(F.lit(1)).cast("int").alias("n_ind"))


def group_masks(panel: Panel) -> tuple[list[int], list[int]]:
    """Words of 64 bits, one bit an individual in the order of members(), for both groups."""
    members = panel.members()
    masks: tuple[list[int], list[int]] = ([], [])
    for k, mask in ((1, masks[0]), (2, masks[1])):
        for start in range(0, len(members), 64):
            word = sum(1 << i for i, (_, g) in enumerate(members[start : start + 64]) if g == k)
            mask.append(word - (1 << 64) if word >> 63 else word)
    return masks


def presence_words(panel: Panel, d: int = 1) -> DataFrame:
    """marker, words: bit i of word j is set if individual 64 j + i has depth >= d. Combined before the shuffle."""
    members = panel.members()
    spark = panel.cells.sparkSession
    kind = panel.groups.schema["ind"].dataType
    index = spark.createDataFrame([(m, i) for i, (m, _) in enumerate(members)], f"ind {kind.simpleString()}, i int")
    rows = panel.cells.filter(F.col("depth") >= d).join(F.broadcast(index), "ind")
    n_words = max(1, -(-len(members) // 64))
    bit = F.expr("shiftleft(1L, i % 64)")
    if n_words <= 32:
        parts = [F.coalesce(F.bit_or(F.when(F.col("i") < 64, bit) if n_words == 1 else F.when(F.expr(f"i div 64 = {w}"), bit)), F.lit(0).cast("long")) for w in range(n_words)]
        return rows.groupBy("marker").agg(F.array(*parts).alias("words"))
    sparse = rows.groupBy("marker", F.expr("i div 64").alias("w")).agg(F.bit_or(bit).alias("bits"))
    found = sparse.groupBy("marker").agg(F.map_from_entries(F.collect_list(F.struct("w", "bits"))).alias("m"))
    return found.select("marker", F.transform(F.sequence(F.lit(0), F.lit(n_words - 1)), lambda w: F.coalesce(F.try_element_at("m", w.cast("long")), F.lit(0).cast("long"))).alias("words"))


def bit_places(panel: Panel) -> DataFrame:
    """ind, grp, w, bit: a bit of a numbered word for each listed individual and group, about 4,096 individuals to a block.

    Places follow from the data alone, and no task or driver has all individuals.
    """
    blocks = max(1, panel.size() // 4096)
    at = F.row_number().over(Window.partitionBy("b").orderBy("ind", "grp")) - 1
    placed = panel.group_map().withColumn("b", F.pmod(F.xxhash64("ind"), F.lit(blocks))).withColumn("i", at)
    return placed.select("ind", "grp", F.expr("b * 2147483648L + i div 64").alias("w"), F.expr("shiftleft(1L, i % 64)").alias("bit"))


def _sparse(panel: Panel, d: int) -> DataFrame:
    """Bitsets of which only words with a bit are held, so neither masks nor words grow with the number of individuals."""
    places = bit_places(panel)
    mask = lambda k: F.coalesce(F.bit_or(F.when(F.col("grp") == k, F.col("bit"))), F.lit(0).cast("long"))
    masks = places.groupBy("w").agg(mask(1).alias("ones"), mask(2).alias("twos"))
    rows = panel.joined(panel.cells.filter(F.col("depth") >= d), places.select("ind", "w", "bit"))
    # individuals that no group lists have no bit, and are counted as they are
    words = rows.groupBy("marker", "w").agg(F.bit_or("bit").alias("bits"), F.count(F.lit(1)).alias("n"))
    words = panel.joined(words, masks, "w")
    total = lambda c: F.sum(c).cast("int")
    carried = lambda m: F.coalesce(total(F.bit_count(F.col("bits").bitwiseAND(F.col(m)))), F.lit(0))
    every = F.when(F.col("w").isNull(), F.col("n")).otherwise(F.bit_count("bits"))
    return words.groupBy("marker").agg(carried("ones").alias("g1"), carried("twos").alias("g2"), total(every).alias("n_ind"))


def _bitset(panel: Panel, d: int) -> DataFrame:
    return _dense(panel, d) if panel.size() <= DENSE and not panel.repeated() else _sparse(panel, d)


def _dense(panel: Panel, d: int) -> DataFrame:
    ones, twos = group_masks(panel)
    words = presence_words(panel, d)

    def carried(mask: list[int]):
        return sum((F.bit_count(F.get("words", F.lit(k)).bitwiseAND(F.lit(m).cast("long"))) for k, m in enumerate(mask)), F.lit(0)).cast("int")

    every = sum((F.bit_count(F.get("words", F.lit(k))) for k in range(max(1, len(ones)))), F.lit(0)).cast("int")
    return words.select("marker", carried(ones).alias("g1"), carried(twos).alias("g2"), every.alias("n_ind"))


def group_counts(panel: Panel, d: int = 1, engine: str = "conditional") -> DataFrame:
    """marker, g1, g2 (carriers per group) and n_ind (all carriers), for markers with a carrier.

    Individuals in neither group count in n_ind only.
    """
    if d < 1:
        raise PanelError("a minimum depth is at least 1")
    return choose(engine, {"conditional": _conditional, "bitset": _bitset})(panel, d)


def lattice(counts: DataFrame) -> DataFrame:
    """g1, g2, n_markers."""
    return counts.groupBy("g1", "g2").agg(F.count(F.lit(1)).alias("n_markers"))


def back(counts: DataFrame, cells: DataFrame, n1: int = 0, n2: int = 0) -> DataFrame:
    """Evidence of count pairs back on markers: a broadcast join, as the lattice is bounded by the group sizes.

    Beyond BROADCAST_CELLS possible cells the real ones are counted (few: a panel of N cells has under 2 N ** (2 / 3)
    different pairs), and joined by shuffle if they are too many as well.
    """
    if (n1 + 1) * (n2 + 1) > BROADCAST_CELLS:
        cells = cells.persist()
        if not joins.small(cells, BROADCAST_CELLS):
            return counts.join(cells, ["g1", "g2"])
    return counts.join(F.broadcast(cells), ["g1", "g2"])


def check_sizes(n1: int, n2: int) -> None:
    if (n1 + 1) * (n2 + 1) > MOST_CELLS:
        raise PanelError(f"a lattice of {n1} x {n2} individuals is too large to collect")
