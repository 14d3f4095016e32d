"""One pass over the node stream: exact in one task, in waves over all tasks, or in chunks of sub-rounds."""

from __future__ import annotations

import itertools

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..config import MAX_INT_2M, ClusterConfig
from ..functions import scoring
from . import jvm, kernels, rounds, waves
from .local import run_local
from .prep import Graph


def init_singletons(nodes: DataFrame) -> DataFrame:
    return nodes.select("id", F.col("id").alias("cid"))


def stream_pass_exact(graph: Graph, candidates: str = "assigned") -> DataFrame:
    """Node by node in rank order, in one task. For graphs below the limit, and what the other forms are measured against."""
    loops = jvm.PASS, [int(candidates != "assigned")], list
    return run_local(graph, lambda g, order: (kernels.stream_pass(g, order, candidates), []), None, loops)[0]


def _place_in_order(graph: Graph, assign: DataFrame, arcs: DataFrame) -> DataFrame:
    """src, target: the nodes that arcs begin at choose one after the other in rank order, in one task that gets their arcs alone."""
    begun = arcs.select("src").distinct()
    known = assign.join(begun.withColumnRenamed("src", "id").union(arcs.select("dst")).distinct(), "id", "left_semi")
    null = F.lit(0).cast("long")
    vols = scoring.cluster_volumes(graph.nodes, assign).join(known.select("cid").distinct(), "cid", "left_semi")
    own = graph.nodes.join(begun.withColumnRenamed("src", "id"), "id", "left_semi")
    rows = arcs.where("src <> dst").select(F.lit(0).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").cast("decimal(38,0)").alias("c"))
    rows = rows.union(own.select(F.lit(1), "id", "rank", F.col("wdeg").cast("decimal(38,0)")))
    rows = rows.union(known.select(F.lit(2), "id", "cid", null.cast("decimal(38,0)")))
    rows = rows.union(vols.select(F.lit(3), "cid", null, F.col("vol").cast("decimal(38,0)")))
    two_m = graph.two_m

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        links: dict[int, list] = {}
        nodes, label, vol = [], {}, {}
        for kind, a, b, c in zip(pdf["kind"].tolist(), pdf["a"].tolist(), pdf["b"].tolist(), map(int, pdf["c"]), strict=True):
            if kind == 0:
                links.setdefault(a, []).append((b, c))
            elif kind == 1:
                nodes.append((b, a, c))
            elif kind == 2:
                label[a] = b
            else:
                vol[a] = c
        moved = kernels.place_in_order(sorted(nodes), links, label, vol, two_m)
        return pd.DataFrame({"src": list(moved), "target": list(moved.values())}, dtype="int64")

    return rows.groupBy(F.lit(0).alias("all")).applyInPandas(solve, "src long, target long")


def _settle_nodes(graph: Graph, assign: DataFrame, todo: DataFrame, arcs: DataFrame, max_subrounds: int, task_arcs: int = ClusterConfig.exact_limit_arcs) -> DataFrame:
    """The nodes of todo (id) choose among the clusters that arcs reach, in conflict-free sub-rounds; each moves once at most.

    After max_subrounds the nodes that are left choose in rank order, in one task, once their arcs are no more than task_arcs; until
    then further sub-rounds follow. Each admits a move, so none that still gains is left out.
    """
    left, mine = itertools.count(1), []
    while True:
        vols = scoring.cluster_volumes(graph.nodes, assign)
        props, n = io.settle_counted(scoring.best_cluster(scoring.scored_candidates(arcs, graph.nodes, assign, graph.two_m, vols)), "props")
        if not n:
            io.drop(props)
            return assign
        # arcs to earlier nodes alone show a conflict to one of its ends; both must see it
        both = arcs.select("src", "dst").union(arcs.select("dst", "src"))
        moves = io.settle(rounds.admit(rounds.independent_set(both, props), graph.two_m, n), "moves")
        old = [*mine, props]
        assign = io.settle(rounds.commit(assign, moves), "assign")
        arcs, n_arcs = io.settle_counted(arcs.join(moves.select("src"), "src", "left_anti"), "arcs")
        mine = [assign, arcs]
        io.drop(*old, moves)
        if next(left) >= max_subrounds and n_arcs <= task_arcs:
            return io.settle(rounds.commit(assign, _place_in_order(graph, assign, arcs)), "assign") if n_arcs else assign


def stream_pass_batches(graph: Graph, n_batches: int = 32, max_subrounds: int = 16, candidates: str = "assigned", task_arcs: int = ClusterConfig.exact_limit_arcs) -> DataFrame:
    """The stream in equal chunks of ranks; a chunk's nodes see the clusters of all earlier ranks and of their own chunk's, as they settle.

    Kept for the candidate rule "all" and for comparison: the waves come closer to the sequential pass in fewer rounds.
    """
    n = graph.nodes.count()
    assign = io.settle(init_singletons(graph.nodes), "assign")
    r = graph.nodes.select("id", "rank")
    step = max(1, -(-n // n_batches))
    for low in range(0, n, step):
        chunk = r.where((F.col("rank") >= low) & (F.col("rank") < low + step))
        arcs = graph.arcs.join(chunk.select(F.col("id").alias("src"), F.col("rank").alias("rs")), "src")
        if candidates == "assigned":
            arcs = arcs.join(r.select(F.col("id").alias("dst"), F.col("rank").alias("rd")), "dst").where("rd < rs")
        assign = _settle_nodes(graph, assign, chunk, io.settle(arcs.select("src", "dst", "w"), "chunk"), max_subrounds, task_arcs)
    return assign


def stream_pass_wavefront(graph: Graph, max_waves: int | None = None) -> DataFrame:
    """Waves of nodes whose earlier neighbours are all placed, without chunks: link weights are the sequential pass's, volumes those of the
    wave's beginning. As many waves as the longest path of rising ranks is long; nodes that max_waves leave over stay alone."""
    return waves.stream_pass_waves(graph, first=0, growth=1 << 40, ready=1.0, least=0.0, max_waves=max_waves)[0]


def in_one_task(graph: Graph, cfg: ClusterConfig) -> bool:
    arcs = graph.nodes.agg(F.sum("deg")).first()[0] or 0
    return arcs <= cfg.exact_limit_arcs and graph.two_m < MAX_INT_2M


def stream_pass(graph: Graph, cfg: ClusterConfig | None = None, with_quotient: bool = False) -> tuple[DataFrame, DataFrame | None]:
    """(assign, quotient or None). The beginning of the stream, up to the limit, node by node in one task, the rest in waves.

    The quotient is kept alongside the waves; a graph that one task places has none yet. The candidate rule "all" goes in chunks
    beyond the limit.
    """
    cfg = cfg or ClusterConfig()
    if in_one_task(graph, cfg):
        return stream_pass_exact(graph, cfg.candidates), None
    if cfg.candidates != "assigned":
        return stream_pass_batches(graph, cfg.n_batches, cfg.max_subrounds, cfg.candidates, cfg.exact_limit_arcs), None
    return waves.stream_pass_waves(graph, None, cfg.growth, cfg.ready, cfg.least, cfg.exact_limit_arcs, cfg.seed, None, with_quotient)[:2]
