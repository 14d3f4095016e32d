"""Functions for SQL users, and kernels as UDFs where columns can't say it."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prep import Graph


def register(spark: SparkSession, graph: Graph, assign: DataFrame, prefix: str = "ms") -> None:
    """Temporary views <prefix>_arcs, _nodes, _assign, _volumes, _quotient, and the SQL function modularity_gain."""
    from ..operators import quotient
    from . import scoring

    views = {"arcs": graph.arcs, "nodes": graph.nodes, "assign": assign, "volumes": scoring.cluster_volumes(graph.nodes, assign), "quotient": quotient.contract(graph.arcs, assign)}
    for name, df in views.items():
        df.createOrReplaceTempView(f"{prefix}_{name}")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION modularity_gain(k_can BIGINT, k_cur BIGINT, d BIGINT, vol_can BIGINT, vol_cur BIGINT, two_m BIGINT) "
        "RETURNS BIGINT RETURN two_m * (k_can - k_cur) - d * (d + vol_can - vol_cur)"
    )


def entropy_udaf():
    """Grouped aggregate: entropy of the values' counts, in nats."""

    @F.pandas_udf("double")
    def entropy(v: pd.Series) -> float:
        p = v.value_counts(normalize=True).sort_index()
        return float(-(p * p.map(lambda x: math.log(x))).sum())

    return entropy


def gain_udf():
    """Scalar pandas form of the gain, for callers without columns of the right types."""

    @F.pandas_udf("long")
    def gain(batches: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
        for k_can, k_cur, d, vol_can, vol_cur, two_m in batches:
            yield two_m * (k_can - k_cur) - d * (d + vol_can - vol_cur)

    return gain


def split_words_udtf():
    """Table function: position and word of a text."""

    @F.udtf(returnType="pos: int, word: string")
    class SplitWords:
        def eval(self, text: str):
            for i, w in enumerate((text or "").split()):
                yield i, w

    return SplitWords


def neighbours_udtf():
    """Table function: the neighbours and weights of a node's adjacency arrays, heaviest first, ties by id."""

    @F.udtf(returnType="place: int, dst: bigint, w: bigint")
    class Neighbours:
        def eval(self, ids: list, weights: list):
            for i, (w, d) in enumerate(sorted(zip((-w for w in weights or []), ids or [], strict=True))):
                yield i, d, -w

    return Neighbours


def cluster_figures(nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """cid, n, vol, heaviest: a group of Arrow tables per cluster."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def figures(table: pa.Table) -> pa.Table:
        one = lambda x: pa.array([x], pa.int64())
        return pa.table({"cid": table["cid"][:1].combine_chunks(), "n": one(table.num_rows), "vol": one(pc.sum(table["wdeg"]).as_py()), "heaviest": one(pc.max(table["wdeg"]).as_py())})

    return nodes.join(assign, "id").select("cid", "wdeg").groupBy("cid").applyInArrow(figures, "cid long, n long, vol long, heaviest long")


def bisect_groups(arcs: DataFrame, assign: DataFrame, seed: int = 1) -> DataFrame:
    """id, half: every cluster split into two blocks that differ by two nodes at most, a cluster per group."""
    from ..functions.measures import labelled_arcs
    from ..operators import kernels

    inner = labelled_arcs(arcs, assign).where("cs = cd").select(F.col("cs").alias("cid"), "src", "dst", "w")
    alone = assign.select("cid", F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0).cast("long").alias("w"))

    def halve(pdf: pd.DataFrame) -> pd.DataFrame:
        import random

        ids = sorted(pdf["src"].unique().tolist())
        place = {x: i for i, x in enumerate(ids)}
        g = kernels.Mem(len(ids), sorted((place[a], place[b], w) for a, b, w in zip(pdf["src"].tolist(), pdf["dst"].tolist(), pdf["w"].tolist(), strict=True) if w))
        block = set(kernels.bisect(g, list(range(len(ids))), random.Random(seed), min(0.03, 2 / len(ids))))
        return pd.DataFrame({"id": ids, "half": [int(i in block) for i in range(len(ids))], "cid": int(pdf["cid"].iloc[0])})

    return inner.unionByName(alone).groupBy("cid").applyInPandas(halve, "id long, half int, cid long")
