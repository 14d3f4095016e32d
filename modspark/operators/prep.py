"""From raw edges to the engine's graph: no directions, loops or parallel edges; dense ids; both arcs of every edge."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..functions import numbering


@dataclass
class Graph:
    """arcs (src, dst, w) in both directions; nodes (id, okey, rank, deg, wdeg, cw). two_m: the arcs' weight."""

    arcs: DataFrame
    nodes: DataFrame

    _two_m: int | None = None

    @property
    def two_m(self) -> int:
        if self._two_m is None:
            self._two_m = int(self.nodes.agg(F.coalesce(F.sum("wdeg"), F.lit(0))).first()[0])
        return self._two_m


def simple_edges(edges: DataFrame, unit: bool = True) -> DataFrame:
    """a < b, w of every pair of different keys that edges (a, b[, w]) join; parallel edges merge. Null ends are dropped: they join nothing."""
    w = F.col("w") if "w" in edges.columns else F.lit(1)
    pair = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), w.cast("long").alias("w"), (F.col("a").isNull() | F.col("b").isNull()).alias("none")).where("not none and a <> b and w > 0")
    merged = pair.groupBy("a", "b").agg(F.sum("w").alias("w"))
    return merged.withColumn("w", F.lit(1).cast("long")) if unit else merged


def dense_ids(keys: DataFrame) -> DataFrame:
    """okey -> id 0..n-1 in the keys' order, numbered range by range."""
    return numbering.ranked(keys, [F.col("okey")], "id")


def normalise_graph(edges: DataFrame, extra_keys: DataFrame | None = None, unit: bool = True, keep: bool = True) -> Graph:
    """The graph of edges (a, b[, w]); extra_keys (okey): isolated nodes to hold as well."""
    pairs = simple_edges(edges, unit)
    pairs = io.settle(pairs, "pairs") if keep else pairs
    keys = pairs.select(F.col("a").cast("string").alias("okey"), F.col("a").alias("k")).union(pairs.select(F.col("b").cast("string"), F.col("b"))).distinct()
    if extra_keys is not None:
        keys = keys.union(extra_keys.select(F.col("okey").cast("string").alias("okey"), F.col("okey").alias("k"))).where("k is not null").distinct()
    ids = dense_ids(keys.select(F.col("k").alias("okey"), F.col("okey").alias("name")))
    ids = io.settle(ids.select(F.col("okey").alias("k"), "name", "id"), "ids") if keep else ids.select(F.col("okey").alias("k"), "name", "id")
    half = pairs.join(ids.select(F.col("k").alias("a"), F.col("id").alias("u")), "a").join(ids.select(F.col("k").alias("b"), F.col("id").alias("v")), "b").select("u", "v", "w")
    arcs = half.select(F.col("u").alias("src"), F.col("v").alias("dst"), "w").union(half.select("v", "u", "w"))
    arcs = io.settle(arcs, "arcs") if keep else arcs
    nodes = node_table(arcs, ids)
    return Graph(arcs, io.settle(nodes, "nodes") if keep else nodes)


def node_table(arcs: DataFrame, ids: DataFrame | None = None) -> DataFrame:
    """Degrees by one aggregate. ids (id[, name]): all nodes, isolated ones included."""
    deg = arcs.groupBy("src").agg(F.count("*").alias("deg"), F.sum("w").alias("wdeg")).withColumnRenamed("src", "id")
    if ids is None:
        out = deg.withColumn("okey", F.col("id").cast("string"))
    else:
        name = "name" if "name" in ids.columns else F.col("id").cast("string")
        out = ids.select("id", F.col(name).alias("okey") if isinstance(name, str) else name.alias("okey")).join(deg, "id", "left")
    zero = F.lit(0).cast("long")
    return out.select("id", "okey", F.col("id").alias("rank"), F.coalesce("deg", zero).alias("deg"), F.coalesce("wdeg", zero).alias("wdeg"), F.lit(1).cast("long").alias("cw"))


def with_order(graph: Graph, order: str = "input", seed: int = 1, key: DataFrame | None = None) -> Graph:
    """The graph streamed in another order: input, reverse, hash, degree, first_seen, bfs (layers of breadth-first search from each
    component's least id), or time (key: id, ts). Ranks are given range by range.

    first_seen: nodes as they come up in the edges sorted by their ends, as a crawl would number them; sides of bipartite graphs mix.
    """
    if order == "input":
        return graph
    if order == "first_seen":
        seen = graph.arcs.groupBy(F.col("src").alias("id")).agg(F.min(F.struct(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"))).alias("ts"))
        return with_order(graph, "time", key=seen)
    if order == "bfs":
        return with_order(graph, "time", key=bfs_layers(graph))
    by = {"reverse": [F.col("id").desc()], "hash": [F.xxhash64(F.col("id"), F.lit(seed)), F.col("id")], "degree": [F.col("wdeg").desc(), F.col("id")], "time": [F.col("ts"), F.col("id")]}[order]
    nodes = graph.nodes if key is None else graph.nodes.join(key, "id", "left")
    ranked = numbering.ranked(nodes.drop("rank"), by, "rank")
    return Graph(graph.arcs, io.settle(ranked.select("id", "okey", "rank", "deg", "wdeg", "cw"), "nodes"), graph._two_m)


def bfs_layers(graph: Graph) -> DataFrame:
    """id, ts: the distance from the least id of the node's component; one round per layer, over the arcs of the layer's nodes."""
    from .components import connected_components

    comp = connected_components(graph.arcs, graph.nodes)
    layer, depth = io.settle(comp.where("id = cid").select("id"), "layer"), 0
    seen = [layer.select("id", F.lit(0).cast("long").alias("ts"))]
    known = io.settle(seen[0], "seen")
    while True:
        depth += 1
        near = graph.arcs.join(layer.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id")).distinct().join(known, "id", "left_anti")
        layer, n = io.settle_counted(near, "layer")
        if not n:
            return known
        old, known = known, io.settle(known.union(layer.select("id", F.lit(depth).cast("long").alias("ts"))), "seen")
        io.drop(old)


def graph_stats(graph: Graph) -> DataFrame:
    """One row: nodes, edges, total arc weight, greatest degree, density."""
    n = graph.nodes.agg(F.count("*").alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.sum("wdeg").alias("two_m"), F.max("deg").alias("max_deg"), F.count_if(F.col("deg") == 0).alias("isolated"))
    return n


def semi_subgraph(arcs: DataFrame, ids: DataFrame) -> DataFrame:
    """Arcs with both ends among ids (id)."""
    inside = ids.select("id").distinct()
    return arcs.join(inside, arcs["src"] == inside["id"], "left_semi").join(inside, F.col("dst") == inside["id"], "left_semi")
