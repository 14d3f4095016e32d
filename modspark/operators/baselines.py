"""What the methods are compared with: the volume-capped edge stream, in-memory memetic clustering, trivial clusterings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..config import MemeticConfig
from ..functions import numbering
from . import kernels, memetic
from .prep import Graph


def edge_table(graph: Graph, order: str = "input", seed: int = 1, truth: DataFrame | None = None) -> DataFrame:
    """seq, u, v in stream order: input (by ids), shuffle, or intra_first (edges within a true class before the others)."""
    e = graph.arcs.where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"))
    by = [F.col("u"), F.col("v")]
    if order == "shuffle":
        by = [F.md5(F.concat_ws("-", "u", "v", F.lit(seed))), *by]
    elif order == "intra_first":
        a, b = truth.select(F.col("id").alias("u"), F.col("label").alias("lu")), truth.select(F.col("id").alias("v"), F.col("label").alias("lv"))
        e = e.join(a, "u", "left").join(b, "v", "left")
        by = [F.coalesce((F.col("lu") != F.col("lv")).cast("int"), F.lit(1)), *by]
    return numbering.ranked(e, by, "seq").select("seq", "u", "v")


def cap(graph: Graph, v_max) -> int | None:
    """v_max as a number: "n", "sqrt" (2m over the root of n), or itself."""
    n = graph.nodes.count()
    return {"n": n, "sqrt": int(graph.two_m / max(n, 1) ** 0.5)}.get(v_max, v_max)


def edge_stream_capped(graph: Graph, v_max=10_000, order: str = "input", seed: int = 1, truth: DataFrame | None = None, materialise: bool = False) -> DataFrame:
    """id, cid. The state (degree and community of a node, volume of a community) is sequential: one task, in order of seq.

    materialise: the edges are held in memory before the pass, in place of being read as a stream; the result is the same.
    """
    return edge_stream_sweep(graph, [v_max], order, seed, truth, materialise).drop("v_max")


def edge_stream_sweep(graph: Graph, caps: list, order: str = "input", seed: int = 1, truth: DataFrame | None = None, materialise: bool = False) -> DataFrame:
    """v_max, id, cid for several caps; the edges are read once."""
    edges = edge_table(graph, order, seed, truth)
    if materialise:
        edges = edges.persist()
        edges.count()
    limits = [(str(c), cap(graph, c)) for c in caps]
    nodes = graph.nodes.select(F.lit(-1).cast("long").alias("seq"), F.col("id").alias("u"), F.col("id").alias("v"))

    def run(batches):
        """Nodes come first, in order of their ids, then the edges in order of seq; no more than a batch of them is held."""
        ids, states, known = np.empty(0, np.int64), [], []
        for batch in batches:
            seq, u, v = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("seq", "u", "v"))
            k = int(np.count_nonzero(seq < 0))
            known.append(u[:k])
            if k == len(seq):
                continue
            if not states:
                ids, known = np.concatenate(known), []
                states = [kernels.EdgeStream(len(ids), most) for _, most in limits]
            a, b = np.searchsorted(ids, u[k:]).tolist(), np.searchsorted(ids, v[k:]).tolist()
            for state in states:
                state.feed(zip(a, b, strict=True))
        if not states:
            ids = np.concatenate([ids, *known])
            states = [kernels.EdgeStream(len(ids), most) for _, most in limits]
        for (name, _), state in zip(limits, states, strict=True):
            label = np.frombuffer(state.label, np.int64)
            for at in range(0, len(ids), 1 << 16):
                part = ids[at : at + (1 << 16)]
                yield pa.record_batch({"v_max": pa.array([name] * len(part), pa.string()), "id": pa.array(part), "cid": pa.array(ids[label[at : at + (1 << 16)]])})

    ordered = nodes.union(edges).repartition(1).sortWithinPartitions("seq", "u")
    out = io.settle(ordered.mapInArrow(run, "v_max string, id long, cid long"), "edgestream")
    if materialise:
        edges.unpersist()
    return out


def edge_stream_batches(graph: Graph, v_max=10_000, n_batches: int = 8, order: str = "input") -> DataFrame:
    """The same rule in batches, for edge streams that no task can order: in a batch, each node decides once, on its first edge, against the
    volumes of the batch's end; two nodes that would swap are kept from it by the lighter side's id."""
    edges = edge_table(graph, order)
    limit, m = cap(graph, v_max), edges.count()
    state = io.settle(graph.nodes.select("id", F.col("id").alias("cid"), F.lit(0).cast("long").alias("d")), "state")
    step = max(1, -(-m // n_batches))
    for low in range(0, m, step):
        part = edges.where((F.col("seq") >= low) & (F.col("seq") < low + step))
        inc = part.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count("*").alias("more"))
        state = io.settle(state.join(inc, "id", "left").select("id", "cid", (F.col("d") + F.coalesce("more", F.lit(0))).alias("d")), "state")
        vol = state.groupBy("cid").agg(F.sum("d").alias("vol"))
        s = state.join(vol, "cid")
        x = part.join(s.select(F.col("id").alias("u"), F.col("cid").alias("cu"), F.col("vol").alias("volu")), "u").join(s.select(F.col("id").alias("v"), F.col("cid").alias("cv"), F.col("vol").alias("volv")), "v").where("cu <> cv")
        x = x if limit is None else x.where((F.col("volu") <= limit) & (F.col("volv") <= limit))
        goes = F.col("volu") <= F.col("volv")
        move = x.select("seq", F.when(goes, F.col("u")).otherwise(F.col("v")).alias("id"), F.when(goes, F.col("v")).otherwise(F.col("u")).alias("other"), F.when(goes, F.col("cv")).otherwise(F.col("cu")).alias("to"))
        first = move.groupBy("id").agg(F.min(F.struct("seq", "to", "other")).alias("b")).select("id", "b.to", "b.other")
        busy = first.select(F.col("id").alias("other"), F.lit(True).alias("moves"))
        ok = first.join(busy, "other", "left").where(F.col("moves").isNull() | (F.col("id") < F.col("other"))).select("id", "to")
        state = io.settle(state.join(ok, "id", "left").select("id", F.coalesce("to", "cid").alias("cid"), "d"), "state")
    return state.select("id", "cid")


def memetic_inmemory(graph: Graph, cfg: MemeticConfig | None = None):
    """The evolution on the whole graph: the quotient of singletons."""
    edges = graph.arcs.where("src < dst").select(F.col("src").alias("ci"), F.col("dst").alias("cj"), "w")
    supernodes = graph.nodes.select(F.col("id").alias("cid"), "cw", F.lit(0).cast("long").alias("self_w"), F.col("wdeg").alias("vol"))
    got, rows = memetic.memetic(edges, supernodes, cfg)
    return got.select(F.col("cid").alias("id"), F.col("lab").alias("cid")), rows


def trivial_one(nodes: DataFrame) -> DataFrame:
    return nodes.select("id", F.lit(0).cast("long").alias("cid"))


def trivial_singletons(nodes: DataFrame) -> DataFrame:
    return nodes.select("id", F.col("id").alias("cid"))
