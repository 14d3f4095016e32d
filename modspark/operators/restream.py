"""Local search by re-streaming: exact in one task, or in parallel rounds over the active nodes' arcs alone."""

from __future__ import annotations

import dataclasses
import functools
import pickle
import time

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io, schema
from ..config import MAX_INT_2M, ClusterConfig, RestreamConfig
from ..functions import measures, scoring
from . import jvm, kernels, rounds
from .local import arrays, graph_rows, held, run_local, told_frame
from .prep import Graph


def next_active(arcs: DataFrame, moves: DataFrame, include_movers: bool = False) -> DataFrame:
    """id: the neighbours of the movers."""
    near = arcs.join(moves.select("src"), "src", "left_semi").select(F.col("dst").alias("id"))
    return (near.union(moves.select(F.col("src").alias("id"))) if include_movers else near).distinct()


def active_arcs(arcs: DataFrame, active: DataFrame) -> DataFrame:
    """Arcs that begin at active nodes: with arcs sorted by src, most row groups of a late round are skipped."""
    return arcs.join(active.select(F.col("id").alias("src")), "src", "left_semi")


def proposals(arcs: DataFrame, graph: Graph, assign: DataFrame, vols: DataFrame) -> DataFrame:
    return scoring.best_cluster(scoring.scored_candidates(arcs, graph.nodes, assign, graph.two_m, vols))


def moved_volumes(vols: DataFrame, moves: DataFrame) -> DataFrame:
    """cid, vol after the moves (cur, target, d), and was: the volume before. Clusters that lose their last node stay, with volume 0."""
    change = moves.select(F.col("target").alias("cid"), "d").union(moves.select("cur", -F.col("d"))).groupBy("cid").agg(F.sum("d").alias("change"))
    return vols.select("cid", F.col("vol").alias("was")).join(change, "cid", "left").select("cid", (F.col("was") + F.coalesce("change", F.lit(0))).alias("vol"), "was")


def exact_gain(moves: DataFrame, vols: DataFrame, two_m: int) -> int:
    """What conflict-free moves add to the modularity's numerator: their links' weight, and the squares of the volumes that they change."""
    links = int(moves.agg(F.coalesce(F.sum("links"), F.lit(0)).alias("x")).first()["x"])
    v, w = F.col("vol").cast("decimal(38,0)"), F.col("was").cast("decimal(38,0)")
    squares = vols.where("vol <> was").agg(F.sum((v * v - w * w).cast("decimal(38,0)")).alias("x")).first()["x"]
    return 2 * two_m * links - int(squares or 0)


def subround(graph: Graph, assign: DataFrame, arcs: DataFrame, vols: DataFrame) -> tuple[DataFrame, DataFrame, int, int, DataFrame, int]:
    """One conflict-free set of moves: the new assignment and volumes, how many proposed, how many moved, the moves, and the gain."""
    props, n = io.settle_counted(proposals(arcs, graph, assign, vols), "props")
    if not n:
        return assign, vols, 0, 0, props, 0
    moves, moved = io.settle_counted(rounds.admit(rounds.independent_set(arcs, props), graph.two_m, n), "moves")
    io.drop(props)
    after = io.settle(moved_volumes(vols, moves), "volumes")
    return io.settle(rounds.commit(assign, moves), "assign"), after, n, moved, moves, exact_gain(moves, after, graph.two_m)


def restream_parallel(graph: Graph, assign: DataFrame, cfg: RestreamConfig | None = None, max_subrounds: int | None = None):
    """assign and trace rows. A sweep settles the active nodes in sub-rounds, whose arcs are read once; the relative gain is tested per sweep.

    Volumes and the score are carried along by what the moves change, not computed anew. A sweep ends where all proposed moves were
    admitted, none is left, or after max_subrounds (cfg's): what then still gains is active in the next sweep.
    """
    cfg, rows, began = cfg or RestreamConfig(), [], time.monotonic()
    now, active, scale = int(measures.modularity_num(measures.cluster_sums(graph.arcs, graph.nodes, assign)).first()["qnum"]), None, float(graph.two_m) ** 2
    vols, mine = io.settle(scoring.cluster_volumes(graph.nodes, assign), "volumes"), []
    n_all, arcs_all = (int(x or 0) for x in graph.nodes.agg(F.count("*"), F.sum("deg")).first())
    for r in range(cfg.max_rounds):
        before, moved, movers, open_, own = now, 0, [], False, []
        arcs, read, n_active = graph.arcs, arcs_all, n_all
        if active is not None:
            arcs, read = io.settle_counted(active_arcs(graph.arcs, active), "active")
            n_active, own = active.count(), [arcs]
        for _ in range(max_subrounds or cfg.max_subrounds):
            assign_, vols_, proposed, admitted, moves, gain = subround(graph, assign, arcs, vols)
            open_ = admitted < proposed
            if not admitted:
                io.drop(moves)
                break
            io.drop(vols, *mine)
            assign, vols, mine = assign_, vols_, [assign_]
            now, moved = now + gain, moved + admitted
            movers.append(moves)
            if not open_:
                break
        gained = now - before
        stop = ""
        if not moved:
            stop = "converged"
        elif now > 0 and gained < cfg.min_rel_gain * now:
            stop = "small gain"
        elif cfg.time_limit_s is not None and time.monotonic() - began > cfg.time_limit_s:
            stop = "time"
        elif r == cfg.max_rounds - 1:
            stop = "rounds"
        rows.append(("restream", r, n_active, moved, gained / scale, now / scale, read, stop))
        if not stop and cfg.active != "all":
            old, active = active, next_active(graph.arcs, functools.reduce(DataFrame.union, [m.select("src") for m in movers]).distinct(), cfg.include_movers)
            if open_:  # proposals that the last sub-round turned away
                active = active.union(arcs.select(F.col("src").alias("id"))).distinct()
            active = io.settle(active, "near")
            if old is not None:
                io.drop(old)
        io.drop(*own, *movers)
        if stop:
            break
    io.drop(vols)
    return assign, rows


def restream_exact(graph: Graph, assign: DataFrame, cfg: RestreamConfig | None = None):
    """The sequential rounds, in one task; assign and trace rows."""
    cfg = cfg or RestreamConfig()

    def run(g, order, label):
        began = time.monotonic()
        late = (lambda: time.monotonic() - began > cfg.time_limit_s) if cfg.time_limit_s is not None else None
        got, rows = kernels.restream(g, label, order, cfg.min_rel_gain, cfg.max_rounds, cfg.active, cfg.include_movers, late)
        scale = float(g.two_m) ** 2 or 1.0
        return got, [("restream", r, a, m, dq / scale, q / scale, read, stop) for r, a, m, dq, q, read, stop in rows]

    scale = float(graph.two_m) ** 2 or 1.0
    return run_local(graph, run, assign, (jvm.RESTREAM, _asked(cfg, [cfg.min_rel_gain]), lambda told: _told(told, scale).get(0, [])))


def _asked(cfg: RestreamConfig, gains: list[float]) -> list[int]:
    """Loops.restream()'s parameters."""
    late = -1 if cfg.time_limit_s is None else int(cfg.time_limit_s * 1000)
    return [cfg.max_rounds, int(cfg.active == "all"), int(cfg.include_movers), late, *map(jvm.bits, gains)]


def _told(told: list[int], scale: float) -> dict[int, list[tuple]]:
    """Trace rows by setting, of Loops.restream()'s numbers."""
    out: dict[int, list[tuple]] = {}
    for i in range(0, len(told), 8):
        x, r, active, moves, dq, q, read, stop = told[i : i + 8]
        out.setdefault(x, []).append(("restream", r, active, moves, dq / scale, q / scale, read, ("", "converged", "small gain", "time", "rounds")[stop]))
    return out


def restream_settings(graph: Graph, assign: DataFrame, settings: list[RestreamConfig]) -> list[tuple[DataFrame, list[tuple]]]:
    """restream_exact() under each of the settings, with no time limits. Those that differ in min_rel_gain alone are one task's, whose rounds
    are made once; the tasks run side by side."""
    alike: dict[RestreamConfig, list[int]] = {}
    for i, cfg in enumerate(settings):
        alike.setdefault(dataclasses.replace(cfg, min_rel_gain=0.0, time_limit_s=None), []).append(i)
    deals, two_m = list(alike.items()), float(graph.two_m)

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        cfg, which = deals[int(pdf["deal"].iloc[0])]
        g, ids, order, names = held(pdf)
        scale, out = float(g.two_m) ** 2 or 1.0, []
        for i, (label, rows) in zip(which, kernels.restream_many(g, names, order, [settings[i].min_rel_gain for i in which], cfg.max_rounds, cfg.active, cfg.include_movers), strict=True):
            told = [("restream", r, a, m, dq / scale, q / scale, read, stop) for r, a, m, dq, q, read, stop in rows]
            out.append(told_frame(ids, label, told).assign(setting=i))
        return pd.concat(out)

    def pack(pdf: pd.DataFrame) -> tuple:
        cfg, which = deals[int(pdf["deal"].iloc[0])]
        ids, arcs, weight, order, own = arrays(pdf)
        names, at = jvm.names(own)
        return (which, ids, names), jvm.request(jvm.RESTREAM, _asked(cfg, [settings[i].min_rel_gain for i in which]), len(ids), *arcs, weight, order, at)

    def unpack(tag: tuple, told, label) -> pd.DataFrame:
        which, ids, names = tag
        rows, by = _told(told.tolist(), two_m**2 or 1.0), names[label].reshape(len(which), len(ids))
        return pd.concat([told_frame(ids, by[k].tolist(), rows.get(k, [])).assign(setting=i) for k, i in enumerate(which)])

    rows = graph_rows(graph, assign).withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(len(deals) - 1))))
    grouped, schema_, spark = rows.repartitionByRange(len(deals), "deal").groupBy("deal"), "id long, cid long, rows binary, setting int", rows.sparkSession
    got = io.settle(jvm.run(spark, grouped, pack, unpack, schema_) if jvm.ready(spark, graph.two_m) else grouped.applyInPandas(solve, schema_), "settings")
    told = {r["setting"]: pickle.loads(r["rows"]) for r in got.where("id = -1").select("setting", "rows").collect()}
    return [(got.where((F.col("setting") == i) & (F.col("id") >= 0)).select("id", "cid"), told.get(i, [])) for i in range(len(settings))]


def restream(graph: Graph, assign: DataFrame, cfg: ClusterConfig | None = None):
    """Exact below the size limit, parallel beyond."""
    cfg = cfg or ClusterConfig()
    if graph.nodes.agg(F.sum("deg")).first()[0] or 0:
        small = graph.nodes.agg(F.sum("deg")).first()[0] <= cfg.exact_limit_arcs and graph.two_m < MAX_INT_2M
        return (restream_exact if small else restream_parallel)(graph, assign, cfg.restream)
    return assign, []


def trace_frame(spark, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, schema.TRACE)
