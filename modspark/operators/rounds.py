"""Parallel rounds of moves that never lower the modularity.

Proposals are made against one frozen state. (1) Of proposers that are neighbours, only the one of the higher priority stays, so no link
weight of a kept move can change. (2) In order of priority, a cluster's admitted moves are tested with the volumes that all moves
before them could bring about at worst. Replayed one by one, each admitted move then has a positive gain; the first proposer always passes.

The order of admission is by ranges of the gain (eighths of an octave, greatest first), by ranges of ids, by gain, by id. Any order is
sure; this one can be cut: sums over whole ranges are added up per cluster, and each range is ordered by itself, so a giant cluster's proposals
are never one task's.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import MAX_INT_2M

#: Proposals from which sums are made range by range; the order, and so the result, is the same below.
SPLIT_FROM = 1_000_000


def independent_set(arcs: DataFrame, proposals: DataFrame) -> DataFrame:
    """Proposals without a neighbouring proposal of higher priority (gain, then the lower id). arcs need only those of proposers."""
    mine = proposals.select(F.col("src"), F.col("gain").alias("g1"))
    theirs = proposals.select(F.col("src").alias("dst"), F.col("gain").alias("g2"))
    beaten = arcs.where("src <> dst").join(mine, "src").join(theirs, "dst").where((F.col("g2") > F.col("g1")) | ((F.col("g2") == F.col("g1")) & (F.col("dst") < F.col("src")))).select("src").distinct()
    return proposals.join(beaten, "src", "left_anti")


def running(df: DataFrame, key: str, out: str, n: int = 0, split_from: int | None = None) -> DataFrame:
    """out: sum of d over the rows of the same key before this one in the order of admission. n: about how many rows there are."""
    ranges = [F.floor(F.log2(F.col("gain").cast("double")) * 8).cast("int"), F.shiftright("src", 16)]
    before = [F.col("gain_range").desc(), F.col("id_range")]
    order = [*before, F.col("gain").desc(), F.col("src")]
    told = df.withColumn("gain_range", ranges[0]).withColumn("id_range", ranges[1])
    past = lambda w: F.coalesce(F.sum("d").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    if n < (SPLIT_FROM if split_from is None else split_from):
        return told.withColumn(out, past(Window.partitionBy(key).orderBy(*order))).drop("gain_range", "id_range")
    sums = told.groupBy(key, "gain_range", "id_range").agg(F.sum("d").alias("d"))
    sums = sums.withColumn("ahead", past(Window.partitionBy(key).orderBy(*before))).drop("d")
    inside = told.withColumn("inside", past(Window.partitionBy(key, "gain_range", "id_range").orderBy(*order[2:])))
    return inside.join(sums, [key, "gain_range", "id_range"]).withColumn(out, F.col("ahead") + F.col("inside")).select(*df.columns, out)


def admit(proposals: DataFrame, two_m: int, n: int = 0, split_from: int | None = None) -> DataFrame:
    """src, cur, target, gain, d, k - k_cur of the proposals that are sure to gain whatever the earlier ones do."""
    kind = "long" if two_m < MAX_INT_2M else "decimal(38,0)"
    c = lambda x: x.cast(kind)
    both = running(running(proposals, "target", "joined", n, split_from), "cur", "left", n, split_from)
    sure = c(F.lit(two_m)) * c(F.col("k") - F.col("k_cur")) - c(F.col("d")) * c(F.col("d") + F.col("vol_can") + F.col("joined") - (F.col("vol_cur") - F.col("left")))
    return both.where(sure > 0).select("src", "cur", "target", "gain", "d", (F.col("k") - F.col("k_cur")).alias("links"))


def commit(assign: DataFrame, moves: DataFrame) -> DataFrame:
    m = moves.select(F.col("src").alias("id"), "target")
    return assign.join(m, "id", "left").select("id", F.coalesce("target", "cid").alias("cid"))
