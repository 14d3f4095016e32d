"""Scores as columns: candidate clusters, the gain of a move, the best cluster. No UDF, all inside generated code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import MAX_INT_2M


def move_gain(k_can: Column, k_cur: Column, d: Column, vol_can: Column, vol_cur: Column, m: float) -> Column:
    """Change of modularity when a node of weighted degree d moves; vol_cur holds the node itself."""
    return (k_can - k_cur) / F.lit(float(m)) - d / F.lit(2.0 * m * m) * (d + vol_can - vol_cur)


def move_gain_int(k_can: Column, k_cur: Column, d: Column, vol_can: Column, vol_cur: Column, two_m: int) -> Column:
    """The gain times 2m^2: a whole number with the gain's sign and order. Beyond 64 bits it is a DECIMAL(38,0)."""
    kind = "long" if two_m < MAX_INT_2M else "decimal(38,0)"
    c = lambda x: x.cast(kind)
    return c(F.lit(two_m)) * c(k_can - k_cur) - c(d) * c(d + vol_can - vol_cur)


def cluster_volumes(nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """cid, vol, size."""
    return nodes.select("id", "wdeg").join(assign, "id").groupBy("cid").agg(F.sum("wdeg").alias("vol"), F.count("*").alias("size"))


def candidate_links(arcs: DataFrame, assign: DataFrame) -> DataFrame:
    """src, cid, k: weight of each node's arcs into each neighbouring cluster. Sums combine before the shuffle; loops are left out."""
    ends = assign.select(F.col("id").alias("dst"), "cid")
    return arcs.where("src <> dst").join(ends, "dst").groupBy("src", "cid").agg(F.sum("w").alias("k"))


def scored_candidates(arcs: DataFrame, nodes: DataFrame, assign: DataFrame, two_m: int, volumes: DataFrame | None = None) -> DataFrame:
    """src, cur, cid, k, k_cur, d, vol, vol_cur, gain of every other neighbouring cluster of every node in arcs."""
    vols = (cluster_volumes(nodes, assign) if volumes is None else volumes).select("cid", "vol")
    links = candidate_links(arcs, assign)
    own = assign.select(F.col("id").alias("src"), F.col("cid").alias("cur"))
    mine = links.join(own, "src").withColumn("k_own", F.when(F.col("cid") == F.col("cur"), F.col("k")).otherwise(0))
    with_cur = mine.withColumn("k_cur", F.sum("k_own").over(Window.partitionBy("src"))).where("cid <> cur")
    d = nodes.select(F.col("id").alias("src"), F.col("wdeg").alias("d"))
    full = with_cur.join(d, "src").join(vols, "cid").join(vols.select(F.col("cid").alias("cur"), F.col("vol").alias("vol_cur")), "cur")
    return full.select("src", "cur", "cid", "k", "k_cur", "d", "vol", "vol_cur", move_gain_int(F.col("k"), F.col("k_cur"), F.col("d"), F.col("vol"), F.col("vol_cur"), two_m).alias("gain"))


def best_cluster(scored: DataFrame) -> DataFrame:
    """src, cur, target, gain, and what admission needs of it: the greatest positive gain, ties to the least cluster id."""
    best = scored.where("gain > 0").groupBy("src").agg(F.max(F.struct("gain", (-F.col("cid")).alias("neg"), "cur", "k", "k_cur", "d", "vol", "vol_cur")).alias("b"))
    return best.select("src", F.col("b.cur").alias("cur"), (-F.col("b.neg")).alias("target"), "b.gain", "b.k", "b.k_cur", "b.d", F.col("b.vol").alias("vol_can"), "b.vol_cur")


def gain_components(scored: DataFrame, two_m: int) -> DataFrame:
    """The gain's two parts: of links, which change only with a neighbour's move, and of volumes."""
    kind = "long" if two_m < MAX_INT_2M else "decimal(38,0)"
    link = F.lit(two_m).cast(kind) * (F.col("k") - F.col("k_cur")).cast(kind)
    volume = -F.col("d").cast(kind) * (F.col("d") + F.col("vol") - F.col("vol_cur")).cast(kind)
    return scored.select("src", "cid", link.alias("link_part"), volume.alias("volume_part"), "gain")
