"""The one pass over all tasks: nodes are placed in waves, each seeing the clusters of nearly all of its earlier neighbours.

The stream is cut into chunks of ranks that grow geometrically, since early placements decide the most. A chunk's first one is placed node by node
in one task. In a later chunk, a node is ready once its placed neighbours hold ``ready`` of the weight of its earlier ones; where
fewer than ``least`` of the waiting nodes are ready, those with the greatest share go along (ties: drawn by hash). A wave is thereby
the next part of a stream order that differs little from the asked one, and a chunk takes a number of waves that depends on ``least`` alone.

A ready node joins the best cluster of its placed neighbours or stays alone, for good. Placed nodes never move, so a wave's nodes can only add
to each other's link weights; what they change is the volumes, and a cluster admits its joiners in an order of priority as
long as each gains whatever those before it did (the others wait for the next wave). So no placement lowers the modularity.

Per chunk, its arcs are read from their own directory and the earlier nodes' clusters are looked up once; between waves only the links of
waiting nodes to clusters are rewritten, and each arc within a chunk adds to them when its end is placed.
"""

from __future__ import annotations

import functools

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..config import MAX_INT_2M
from . import kernels, rounds
from .prep import Graph

#: Parts of a node's earlier weight that its readiness is told in.
SCALE = 1000


def chunk_cuts(n: int, first: int, growth: int) -> list[int]:
    """Ranks at which chunks begin after the first: first, then growth times as many nodes at each."""
    cuts, at = [], max(first, 0)
    while at < n:
        cuts.append(at)
        at = max(at + 1, 64, at * growth) if at else max(64, growth)
    return cuts


def prefix_size(graph: Graph, arcs_limit: int, parts: int = 1024) -> int:
    """How many nodes from the stream's beginning have no more than arcs_limit arcs in all."""
    n = graph.nodes.count()
    span = n
    while span > 0:
        width = max(1, -(-span // parts))
        got = graph.nodes.where(F.col("rank") < span).groupBy(F.floor(F.col("rank") / width).alias("part")).agg(F.sum("deg").alias("deg")).collect()
        total, fits = 0, 0
        for r in sorted(got, key=lambda r: r["part"]):
            total += r["deg"]
            if total > arcs_limit:
                break
            fits = min(n, (int(r["part"]) + 1) * width)
        if fits or width == 1:
            return min(fits, span)
        span = width
    return 0


def _place_prefix(graph: Graph, arcs: DataFrame, first: int) -> DataFrame:
    """id, cid, d of the first nodes, placed one after the other in one task that gets their arcs among themselves alone."""
    nodes = graph.nodes.where(F.col("rank") < first).select(F.lit(0).alias("kind"), F.col("id").alias("a"), F.col("rank").alias("b"), F.col("wdeg").alias("c"))
    rows = nodes.union(arcs.where("dst_rank < src_rank").select(F.lit(1), "src", "dst", "w"))
    two_m = graph.two_m

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        links: dict[int, list] = {}
        order, degree = [], {}
        for kind, a, b, c in zip(*(pdf[x].tolist() for x in ("kind", "a", "b", "c")), strict=True):
            if kind:
                links.setdefault(a, []).append((b, c))
            else:
                order.append((b, a, c))
                degree[a] = c
        label = {a: a for a in degree}
        kernels.place_in_order(sorted(order), links, label, dict(degree), two_m)
        return pd.DataFrame({"id": list(label), "cid": list(label.values()), "d": [degree[a] for a in label]}, dtype="int64")

    return rows.groupBy(F.lit(0).alias("all")).applyInPandas(solve, "id long, cid long, d long")


def begin_state(nodes: DataFrame, outer: DataFrame, back: DataFrame) -> DataFrame:
    """One row per waiting node (cid null: its degree d and earlier weight b) and per cluster it is linked with (k; kb: through earlier nodes)."""
    none, null = F.lit(0).cast("long"), F.lit(None).cast("long")
    own = nodes.join(back, "src", "left").select("src", null.alias("cid"), none.alias("k"), none.alias("kb"), "d", F.coalesce("b", none).alias("b"))
    return own.union(outer.groupBy("src", "cid").agg(F.sum("w").alias("k"), F.sum("wb").alias("kb")).select("src", "cid", "k", "kb", null, null))


def readiness(state: DataFrame) -> DataFrame:
    """src, d, score of the waiting nodes: the share of the earlier weight that is placed, in thousandths."""
    each = state.groupBy("src").agg(F.max("d").alias("d"), F.max("b").alias("b"), F.sum("kb").alias("have"))
    return each.select("src", "d", F.when(F.col("b") == 0, SCALE).otherwise(F.expr(f"(have * {SCALE}) div b")).alias("score"))


def ready_cut(counts: dict[int, int], ready: float, least: float) -> tuple[int, float]:
    """(score, share): nodes above the score are ready, and this share of those at it. counts: waiting nodes by score."""
    waiting = sum(counts.values())
    cut = -(-int(ready * SCALE * 1000) // 1000)
    if sum(n for s, n in counts.items() if s >= cut) >= least * waiting:
        return cut - 1, 0.0
    want = least * waiting
    for s in sorted(counts, reverse=True):
        if counts[s] >= want:
            return s, want / counts[s]
        want -= counts[s]
    return -1, 1.0


def wave_moves(state: DataFrame, ready: DataFrame, volumes: DataFrame, two_m: int, n_ready: int = 0) -> DataFrame:
    """id, cid, d of the ready nodes (src, d) that are placed now; those that a full cluster turns away are left out."""
    kind = "long" if two_m < MAX_INT_2M else "decimal(38,0)"
    links = state.where("cid is not null").join(ready, "src").select("src", state["cid"], "k", ready["d"])
    scored = links.join(volumes, "cid").withColumn("gain", F.lit(two_m).cast(kind) * F.col("k").cast(kind) - F.col("d").cast(kind) * F.col("vol").cast(kind)).where("gain > 0")
    best = scored.groupBy("src").agg(F.max(F.struct("gain", (-F.col("cid")).alias("neg"), "k", "vol")).alias("b"))
    wish = ready.join(best, "src", "left").select("src", "d", F.col("b.gain").alias("gain"), (-F.col("b.neg")).alias("target"), F.col("b.k").alias("k"), F.col("b.vol").alias("vol"))
    alone = wish.where("target is null").select(F.col("src").alias("id"), F.col("src").alias("cid"), "d")
    joined = rounds.running(wish.where("target is not null"), "target", "joined", n_ready)
    sure = F.lit(two_m).cast(kind) * F.col("k").cast(kind) - F.col("d").cast(kind) * (F.col("vol") + F.col("joined")).cast(kind)
    return alone.union(joined.where(sure > 0).select("src", "target", "d"))


def next_state(state: DataFrame, inner: DataFrame, placed: DataFrame) -> DataFrame:
    """The state without the placed nodes, and with what their arcs add to the waiting ones' links."""
    new = inner.join(placed.select(F.col("id").alias("dst"), "cid"), "dst").select("src", "cid", F.col("w").alias("k"), F.col("wb").alias("kb"), F.lit(None).cast("long").alias("d"), F.lit(None).cast("long").alias("b"))
    new = new.join(state.where("cid is null").select("src"), "src", "left_semi")  # those placed before wait no more
    left = state.union(new).join(placed.select(F.col("id").alias("src")), "src", "left_anti")
    return left.groupBy("src", "cid").agg(F.sum("k").alias("k"), F.sum("kb").alias("kb"), F.max("d").alias("d"), F.max("b").alias("b"))


def _union(frames: list[DataFrame]) -> DataFrame:
    return functools.reduce(DataFrame.union, frames)


def stream_pass_waves(graph: Graph, first: int | None = None, growth: int = 4, ready: float = 0.9, least: float = 0.1, prefix_arcs: int = 2_000_000, seed: int = 1, max_waves: int | None = None, with_quotient: bool = False):
    """(assign, quotient or None, trace rows). first: nodes that one task places (None: as many as have prefix_arcs arcs in all).

    ready 0 places a chunk's nodes at once, ready 1 with least 0 waits for all earlier neighbours. max_waves: stop so early, nodes that
    wait then stay alone. with_quotient: the quotient, kept alongside: each chunk adds the edges whose later end it placed.
    Trace rows: (chunk, wave, waiting, ready score, placed).
    """
    nodes = graph.nodes.select(F.col("id").alias("src"), "rank", F.col("wdeg").alias("d"))
    n = graph.nodes.count()
    first = prefix_size(graph, prefix_arcs) if first is None else min(first, n)
    cuts = chunk_cuts(n, first, growth)
    number = lambda r: functools.reduce(lambda a, b: a + b, [(F.col(r) >= c).cast("int") for c in cuts], F.lit(0))
    rank = nodes.select("src", "rank")
    arcs = graph.arcs.where("src <> dst").join(rank.withColumnRenamed("rank", "src_rank"), "src").join(rank.select(F.col("src").alias("dst"), F.col("rank").alias("dst_rank")), "dst")
    arcs = arcs.withColumn("chunk", number("src_rank")).where(F.col("chunk") >= number("dst_rank"))
    # each chunk's arcs in a directory of their own
    arcs = io.settle(arcs.select("src", "dst", "w", "src_rank", "dst_rank", "chunk"), "stream", "chunk")
    done, deltas, trace = [], [], []
    if first > 0:
        done.append(io.settle(_place_prefix(graph, arcs.where("chunk = 0"), first), "prefix"))
        if with_quotient:
            deltas.append(io.settle(_delta(arcs.where("chunk = 0"), done[0], None), "delta"))
    wave, stopped = 0, False
    for c, low in enumerate(cuts, 1):
        high = cuts[c] if c < len(cuts) else n
        mine = arcs.where(F.col("chunk") == c).withColumn("wb", F.when(F.col("dst_rank") < F.col("src_rank"), F.col("w")).otherwise(0).cast("long"))
        inner = mine.where(F.col("dst_rank") >= low)
        early = _union(done) if done else None
        own = nodes.where((F.col("rank") >= low) & (F.col("rank") < high)).select("src", "d")
        outer = mine.where(F.col("dst_rank") < low)
        known = early.select(F.col("id").alias("dst"), "cid") if early is not None else own.select(F.col("src").alias("dst"), F.col("src").alias("cid")).limit(0)
        state = io.settle(begin_state(own, outer.join(known, "dst"), mine.groupBy("src").agg(F.sum("wb").alias("b"))), "waiting")
        volumes = io.settle(early.groupBy("cid").agg(F.sum("d").alias("vol")), "volumes") if early is not None else None
        waiting, here = high - low, []
        while waiting and not stopped:
            status = readiness(state)
            counts = {int(r["score"]): int(r["n"]) for r in status.groupBy("score").agg(F.count("*").alias("n")).collect()}  # at most SCALE + 1 rows
            cut, part = ready_cut(counts, ready, least)
            drawn = F.pmod(F.xxhash64("src", F.lit(seed), F.lit(wave)), F.lit(1 << 20)) < F.lit(max(1, round(part * (1 << 20))))
            chosen = (F.col("score") > cut) | ((F.col("score") == cut) & drawn) if part else F.col("score") > cut
            now = here + ([volumes] if volumes is not None else [])
            vols = _union([x.select("cid", F.col("d" if "d" in x.columns else "vol").alias("vol")) for x in now]).groupBy("cid").agg(F.sum("vol").alias("vol")) if now else own.select(F.col("src").alias("cid"), F.col("d").alias("vol")).limit(0)
            placed, n_placed = io.settle_counted(wave_moves(state, status.where(chosen).select("src", "d"), vols, graph.two_m, waiting), "placed")
            if not n_placed and part:  # the draw took none
                io.drop(placed)
                placed, n_placed = io.settle_counted(wave_moves(state, status.where(F.col("score") >= cut).select("src", "d"), vols, graph.two_m, waiting), "placed")
            trace.append((c, wave, waiting, cut, n_placed))
            here.append(placed)
            waiting -= n_placed
            wave += 1
            stopped = max_waves is not None and wave >= max_waves
            if waiting and not stopped:
                old, state = state, io.settle(next_state(state, inner, placed), "waiting")
                io.drop(old)
        rest = own.select(F.col("src").alias("id"), F.col("src").alias("cid"), "d")
        chunk = _union(here) if here else rest.limit(0)
        if waiting:
            chunk = chunk.union(rest.join(chunk.select("id"), "id", "left_anti"))
        chunk = io.settle(chunk, "chunk")
        io.drop(state, *here, *([volumes] if volumes is not None else []))
        if with_quotient:
            deltas.append(io.settle(_delta(mine, chunk, known), "delta"))
        done.append(chunk)
    out = io.settle(_union(done).select("id", "cid"), "assign") if done else graph.nodes.select("id", F.col("id").alias("cid"))
    quotient = None
    if with_quotient:
        from .quotient import merge_quotient

        loops = graph.arcs.where("src = dst").join(out.select(F.col("id").alias("src"), "cid"), "src").select(F.col("cid").alias("ci"), F.col("cid").alias("cj"), "w")
        quotient = io.settle(merge_quotient(*deltas, loops), "quotient")
    io.drop(arcs, *done, *deltas)
    return out, quotient, trace


def _delta(arcs: DataFrame, own: DataFrame, early: DataFrame | None) -> DataFrame:
    """ci, cj, w of the edges whose later end is in a chunk (own: its nodes' clusters; early: dst, cid of the nodes before it)."""
    once = arcs.where("dst_rank < src_rank").select("src", "dst", "w")
    mine = own.select(F.col("id").alias("dst"), "cid")
    ends = (mine if early is None else mine.union(early)).withColumnRenamed("cid", "cd")
    both = once.join(own.select(F.col("id").alias("src"), F.col("cid").alias("cs")), "src").join(ends, "dst")
    w = F.when(F.col("cs") == F.col("cd"), 2 * F.col("w")).otherwise(F.col("w"))
    return both.select(F.least("cs", "cd").alias("ci"), F.greatest("cs", "cd").alias("cj"), w.alias("w")).groupBy("ci", "cj").agg(F.sum("w").alias("w"))
