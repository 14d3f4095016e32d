"""Looking at a clustering: its largest clusters, members, boundaries, and why a node is where it is."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import measures, scoring
from ..operators.prep import Graph


def top_clusters(graph: Graph, assign: DataFrame, k: int = 10) -> DataFrame:
    return scoring.cluster_volumes(graph.nodes, assign).orderBy(F.col("vol").desc(), "cid").limit(k)


def cluster_members(graph: Graph, assign: DataFrame, cid: int) -> DataFrame:
    return assign.where(F.col("cid") == cid).join(graph.nodes, "id").select("id", "okey", "wdeg")


def boundary_nodes(graph: Graph, assign: DataFrame) -> DataFrame:
    """Nodes with a neighbour in another cluster, and the weight that leaves them."""
    return measures.labelled_arcs(graph.arcs, assign).where("cs <> cd").groupBy(F.col("src").alias("id"), F.col("cs").alias("cid")).agg(F.sum("w").alias("leaving"))


def cluster_edges(graph: Graph, assign: DataFrame, cid: int) -> DataFrame:
    return measures.labelled_arcs(graph.arcs, assign).where((F.col("cs") == cid) & (F.col("cd") == cid) & (F.col("src") < F.col("dst"))).select("src", "dst", "w")


def explain_move(graph: Graph, assign: DataFrame, node: int) -> DataFrame:
    """All candidates of a node with their links, volume and gain; the arcs are filtered first."""
    return scoring.scored_candidates(graph.arcs.where(F.col("src") == node), graph.nodes, assign, graph.two_m)
