"""Connected components of edge tables by alternating large-star and small-star steps.

Each step is one aggregate (a minimum per node, combined before the shuffle) and one join; tables between steps are written to the
shared folder. Nothing but two sums reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """large: of each node, the larger neighbours are tied to the least of all. Else: the smaller ones (and the node)."""
    if large:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    tied = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
    return tied.union(least.select("u", F.col("m").alias("v")))


def components(edges: DataFrame) -> DataFrame:
    """node, root: of every node in edges (u, v: long), the least node of its component."""
    now = common.keep(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    seen = None
    while True:
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v") % (1 << 40))).first()
        if not mark[0] or tuple(mark) == seen:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen, before = tuple(mark), now
        now = common.keep(_star(_star(now, True).distinct(), False).distinct(), "edges")
        common.drop_scratch(now.sparkSession, before)
