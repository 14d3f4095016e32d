"""Louvain: local moves and contraction in turns; exact in one task, or by parallel rounds over the whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import io
from ..config import MAX_INT_2M, ClusterConfig, RestreamConfig
from . import jvm, kernels, onepass, quotient, restream
from .local import run_local
from .prep import Graph


def louvain_exact(graph: Graph, seed: int | None = None, max_levels: int = 30):
    """assign, and the modularity numerator after each level."""
    loops = jvm.LOUVAIN, [int(seed is not None), seed or 0, max_levels], list
    return run_local(graph, lambda g, order: kernels.louvain(g, seed, None, max_levels), None, loops)


def contracted(graph: Graph, assign: DataFrame) -> Graph:
    """The quotient as a graph whose ids are the clusters' names."""
    arcs = io.settle(quotient.as_arcs(quotient.contract(graph.arcs, assign)), "qarcs")
    deg = arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"), F.sum("w").alias("wdeg"))
    cw = graph.nodes.join(assign, "id").groupBy(F.col("cid").alias("id")).agg(F.sum("cw").alias("cw"))
    zero = F.lit(0).cast("long")
    nodes = cw.join(deg, "id", "left").select("id", F.col("id").cast("string").alias("okey"), F.col("id").alias("rank"), F.coalesce("deg", zero).alias("deg"), F.coalesce("wdeg", zero).alias("wdeg"), "cw")
    return Graph(arcs, io.settle(nodes, "qnodes"))


def louvain_parallel(graph: Graph, max_levels: int = 30, max_sweeps: int = 50, max_subrounds: int = 24, min_rel_gain: float = 1e-3, start: DataFrame | None = None) -> DataFrame:
    """Parallel rounds from singletons (or start: id, cid), contraction to the quotient, and again on it; labels are unfolded at the end.

    A level ends where a sweep adds less than min_rel_gain of the modularity.
    """
    top, level = None, graph
    cfg = RestreamConfig(min_rel_gain=min_rel_gain, max_rounds=max_sweeps, max_subrounds=max_subrounds, time_limit_s=None)
    for _ in range(max_levels):
        begin = onepass.init_singletons(level.nodes) if start is None else start
        start = None
        own, _ = restream.restream_parallel(level, io.settle(begin, "assign"), cfg)
        top = own if top is None else io.settle(quotient.project(top, own.select(F.col("id").alias("cid"), F.col("cid").alias("lab"))), "unfold")
        k, n = own.select("cid").distinct().count(), level.nodes.count()
        if k == n or k <= 1:
            break
        level = contracted(level, own)
    return top


def louvain(graph: Graph, seed: int | None = None, cfg: ClusterConfig | None = None) -> DataFrame:
    arcs = graph.nodes.agg(F.sum("deg")).first()[0] or 0
    small = arcs <= (cfg or ClusterConfig()).exact_limit_arcs and graph.two_m < MAX_INT_2M
    return louvain_exact(graph, seed)[0] if small else louvain_parallel(graph)


def label_propagation(arcs: DataFrame, nodes: DataFrame, max_cw: int | None = None, rounds: int = 3, seed: int | None = None) -> DataFrame:
    """Synchronous rounds: each node takes the label of the greatest link weight (ties: the least label), on even or odd ids (seed: halves drawn
    by hash) in turn.

    max_cw: labels whose members' weight would exceed it admit nodes in order of link weight, as far as there is room.
    """
    label = io.settle(nodes.select("id", F.col("id").alias("cid")), "labels")
    half = lambda r: F.pmod("id" if seed is None else F.xxhash64("id", F.lit(seed + r // 2)), F.lit(2))
    for r in range(rounds):
        links = arcs.where("src <> dst").join(label.select(F.col("id").alias("dst"), "cid"), "dst").groupBy("src", "cid").agg(F.sum("w").alias("k"))
        pick = links.groupBy("src").agg(F.max(F.struct("k", (-F.col("cid")).alias("neg"))).alias("b")).select(F.col("src").alias("id"), (-F.col("b.neg")).alias("to"), F.col("b.k").alias("k"))
        wish = label.join(pick, "id").where((F.col("to") != F.col("cid")) & (half(r) == r % 2)).select("id", "to", "k")
        if max_cw is not None:
            size = label.join(nodes.select("id", "cw"), "id").groupBy(F.col("cid").alias("to")).agg(F.sum("cw").alias("size"))
            w = Window.partitionBy("to").orderBy(F.col("k").desc(), "id")
            wish = wish.join(nodes.select("id", "cw"), "id").join(size, "to", "left").withColumn("after", F.coalesce("size", F.lit(0)) + F.sum("cw").over(w)).where(F.col("after") <= max_cw).select("id", "to", "k")
        old, label = label, io.settle(label.join(wish.select("id", "to"), "id", "left").select("id", F.coalesce("to", "cid").alias("cid")), "labels")
        io.drop(old)
    return label
