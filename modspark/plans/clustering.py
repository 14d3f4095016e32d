"""The pipeline with its two switches: one pass, then memetic refinement of the quotient, then re-streaming."""

from __future__ import annotations

import contextlib
import dataclasses
import threading
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..config import ClusterConfig, MemeticConfig, RestreamConfig
from ..functions import measures
from ..operators import memetic, onepass, prep, quotient, restream
from ..operators.prep import Graph, with_order

#: mode -> (refine the quotient, re-stream)
MODES = {"single_pass": (False, False), "single_pass_restream": (False, True), "single_pass_memetic": (True, False), "full": (True, True)}


@dataclass
class ClusterResult:
    """assign (id, cid), the quotient of the first pass if it was built, trace rows, figures of the run, and what watched its steps."""

    assign: DataFrame
    quotient: DataFrame | None = None
    trace: list[tuple] = field(default_factory=list)
    stats: dict = field(default_factory=dict)
    seen: list = field(default_factory=list)


class Steps:
    """The steps of runs on one graph, each made once, whichever threads ask for it: modes begin alike. watch(): a context around each step, kept
    with its result and seconds. keeps: all passes keep the quotient alongside, so that modes with and without it have one pass."""

    def __init__(self, watch=contextlib.nullcontext, keeps: bool = False):
        self.watch, self.keeps, self.done, self._locks, self._lock = watch, keeps, {}, {}, threading.Lock()

    def take(self, name: tuple, make) -> tuple:
        with self._lock:
            own = self._locks.setdefault(name, threading.Lock())
        with own:
            if name not in self.done:
                with self.watch() as seen:
                    t = time.monotonic()
                    got = make()
                    took = round(time.monotonic() - t, 3)
                self.done[name] = got, took, seen
            return self.done[name]


def cluster(graph: Graph, mode: str = "full", cfg: ClusterConfig | None = None, steps: Steps | None = None) -> ClusterResult:
    """steps: those of other runs on this graph, which are not made again; a step's seconds count in every mode that it is part of."""
    if mode not in MODES:
        raise ValueError(f"mode {mode!r} is none of {', '.join(MODES)}")
    cfg, steps = cfg or ClusterConfig(), steps or Steps()
    refine, again = MODES[mode]
    graph = steps.take(("order", cfg.order, cfg.seed), lambda: with_order(graph, cfg.order, cfg.seed))[0]
    out, took = ClusterResult(None), {}
    out.stats["mode"] = mode

    def timed(name, key, f):
        got, took[f"{name}_s"], seen = steps.take(key, f)
        out.seen.append(seen)
        return got

    # the waves keep the quotient alongside, where it is asked for; a graph that one task places has none yet
    keep = refine or steps.keeps
    first = ("pass", keep and not onepass.in_one_task(graph, cfg), dataclasses.replace(cfg, memetic=MemeticConfig(), restream=RestreamConfig()))

    def place():
        assign, kept = onepass.stream_pass(graph, cfg, keep)
        return assign, kept, assign.select("cid").distinct().count()

    out.assign, out.quotient, out.stats["k_pass"] = timed("pass", first, place)
    begun = first
    if refine:

        def evolve():
            kept = out.quotient if out.quotient is not None else io.settle(quotient.contract(graph.arcs, out.assign), "quotient")
            supernodes = io.settle(quotient.supernodes(kept, graph.nodes, out.assign), "supernodes")
            best, rows = memetic.memetic(kept, supernodes, cfg.memetic)
            before = measures.modularity_num(measures.cluster_sums(graph.arcs, graph.nodes, out.assign)).first()["qnum"]
            refined = io.settle(quotient.project(out.assign, best), "assign")
            after = measures.modularity_num(measures.cluster_sums(graph.arcs, graph.nodes, refined)).first()["qnum"]
            scale = float(graph.two_m) ** 2 or 1.0
            return refined if after >= before else out.assign, kept, [("memetic", r, 0, int(at >= 0), 0.0, best_q / scale, 0, kind) for _, _, r, kind, _, best_q, at in rows], kept.count()

        begun = ("memetic", first, cfg.memetic)
        out.assign, out.quotient, rows, out.stats["q_edges"] = timed("memetic", begun, evolve)
        out.trace += rows
        out.stats["engine"] = memetic.choose_engine(out.stats["q_edges"], graph.two_m, cfg.memetic)
    if again:
        out.assign, rows = timed("restream", ("restream", begun, cfg), lambda: restream.restream(graph, out.assign, cfg))
        out.trace += rows
        out.stats["arcs_read"] = [r[6] for r in rows]
    n, k = graph.nodes.count(), out.assign.select("cid").distinct().count()
    q = out.stats.get("q_edges", 0)
    out.stats |= took | {"n": n, "k": k, "state_rows": n + out.stats["k_pass"] + q, "seconds": round(sum(took.values()), 3)}
    out.stats["modularity"] = measures.modularity(graph.arcs, graph.nodes, out.assign)
    return out


def add_edges(graph: Graph, assign: DataFrame, edges: DataFrame, cfg: ClusterConfig | None = None):
    """A finished clustering continued on a grown graph. edges (u, v, w): between ids, new or old.

    New nodes begin alone; the ends of new edges and their neighbours are active. Returns the new graph, assign and trace rows.
    """
    pairs = graph.arcs.where("src < dst").select("src", "dst", "w").union(edges.where("u <> v").select(F.least("u", "v"), F.greatest("u", "v"), "w")).groupBy("src", "dst").agg(F.sum("w").alias("w"))
    arcs = io.settle(pairs.union(pairs.select("dst", "src", "w")), "arcs")
    ids = graph.nodes.select("id").union(edges.select("u")).union(edges.select("v")).distinct()
    grown = Graph(arcs, io.settle(prep.node_table(arcs, ids), "nodes"))
    begin = io.settle(ids.join(assign, "id", "left").select("id", F.coalesce("cid", "id").alias("cid")), "assign")
    got, rows = restream.restream(grown, begin, cfg)
    return grown, got, rows
