"""One task that holds a whole (small or quotient) graph and runs a kernel on it."""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from . import jvm, kernels
from .prep import Graph


def graph_rows(graph: Graph, assign: DataFrame | None = None) -> DataFrame:
    """kind, a, b, c: what held() makes a graph of. Nodes are of kind 0, arcs 1, and a clustering to begin from 2."""
    nodes = graph.nodes.select(F.lit(0).alias("kind"), F.col("id").alias("a"), F.col("rank").alias("b"), F.col("cw").alias("c"))
    rows = nodes.union(graph.arcs.select(F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").alias("c")))
    if assign is not None:
        rows = rows.union(assign.select(F.lit(2).alias("kind"), F.col("id").alias("a"), F.col("cid").alias("b"), F.lit(0).cast("long").alias("c")))
    return rows


def arrays(pdf: pd.DataFrame):
    """Of graph_rows(): ids; src, dst, w as places, sorted; node weights; the stream's order; and the clusters' names or None."""
    kind, a, b, c = (pdf[x].to_numpy() for x in ("kind", "a", "b", "c"))
    n0, n1, n2 = kind == 0, kind == 1, kind == 2
    by_id = a[n0].argsort()
    ids, ranks, weight = a[n0][by_id], b[n0][by_id], c[n0][by_id]
    src, dst, w = np.searchsorted(ids, a[n1]), np.searchsorted(ids, b[n1]), c[n1]
    by = np.lexsort((w, dst, src))
    names = b[n2][np.argsort(a[n2], kind="stable")] if n2.any() else None
    return ids, (src[by], dst[by], w[by]), weight, ranks.argsort(kind="stable"), names


def held(pdf: pd.DataFrame):
    """The graph of graph_rows() with places for ids, the ids, the stream's order, and the clusters' names (they stay names: they need not be places)."""
    ids, arcs, weight, order, names = arrays(pdf)
    g = kernels.Mem(len(ids), zip(*(x.tolist() for x in arcs), strict=True), weight.tolist())
    return g, ids, order.tolist(), None if names is None else names.tolist()


def told_frame(ids, cid, told) -> pd.DataFrame:
    return pd.DataFrame({"id": [*ids.tolist(), -1], "cid": [*cid, 0], "rows": [b""] * len(ids) + [pickle.dumps(told)]})


def run_local(graph: Graph, kernel, assign: DataFrame | None = None, loops: tuple | None = None):
    """kernel(g, order[, label]) -> (labels, rows), in one ordered task. Returns (assign, rows).

    Callers check the size: the task gets one row per arc and node. Ids may have gaps; they are mapped to places in id order, so that
    ties go to the lesser id, and back. loops (what, parameters, rows of its numbers): the same in the JVM, where it can be had.
    """
    begun, schema = assign is not None, "id long, cid long, rows binary"

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        g, ids, order, names = held(pdf)
        if not begun:
            label, told = kernel(g, order)
            label = [int(ids[x]) for x in label]
        else:
            label, told = kernel(g, order, names)
        return told_frame(ids, label, told)

    def pack(pdf: pd.DataFrame) -> tuple:
        ids, arcs, weight, order, own = arrays(pdf)
        names, at = (ids, []) if own is None else jvm.names(own)
        return (ids, names), jvm.request(loops[0], loops[1], len(ids), *arcs, weight, order, at)

    rows = graph_rows(graph, assign)
    grouped = rows.groupBy(F.lit(0).alias("all"))
    if loops is not None and jvm.ready(rows.sparkSession, graph.two_m):
        out = jvm.run(rows.sparkSession, grouped, pack, lambda tag, told, label: told_frame(tag[0], tag[1][label].tolist(), loops[2](told.tolist())), schema)
    else:
        out = grouped.applyInPandas(solve, schema)
    out = io.settle(out, "local")
    told = out.where("id = -1").select("rows").first()
    return out.where("id >= 0").select("id", "cid"), pickle.loads(told[0]) if told else []
