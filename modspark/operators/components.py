"""Connected components by minimum labels with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io


def connected_components(arcs: DataFrame, nodes: DataFrame) -> DataFrame:
    """id, cid: the least node of each node's component. Per round: one minimum over neighbours, one jump to the label's label."""
    label = io.settle(nodes.select("id", F.col("id").alias("cid")), "labels")
    while True:
        near = arcs.join(label.select(F.col("id").alias("dst"), "cid"), "dst").groupBy("src").agg(F.min("cid").alias("m"))
        low = label.join(near, label["id"] == near["src"], "left").select("id", "cid", F.least("cid", F.coalesce("m", "cid")).alias("low"))
        # a root takes the least label that any of its members found
        hook = low.groupBy("cid").agg(F.min("low").alias("hook"))
        hooked = io.settle(low.join(hook, "cid").select("id", F.least("low", "hook").alias("cid")), "labels")
        up = hooked.select(F.col("id").alias("cid"), F.col("cid").alias("up"))
        nxt = io.settle(hooked.join(up, "cid").select("id", F.col("up").alias("cid")), "labels")
        changed = nxt.join(label.select("id", F.col("cid").alias("was")), "id").where("cid <> was").limit(1).count()
        label = nxt
        if not changed:
            return label
