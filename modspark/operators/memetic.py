"""Memetic refinement: populations of clusterings of the quotient graph.

A quotient that a task can hold evolves in islands: one population per task, with exchanges between epochs. Beyond that, one population
of tables evolves by the same rules (``evolve_tables``): every member is a table, and individuals, overlays, both recombinations, mutation,
fitness and cut distance are joins, aggregates and the parallel rounds.
"""

from __future__ import annotations

import functools
import pickle
import random
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import io
from ..config import MAX_INT_2M, MemeticConfig, RestreamConfig
from ..functions import measures
from . import jvm, kernels, louvain, quotient, restream
from .prep import Graph


def overlay(*assigns: DataFrame) -> DataFrame:
    """cid, lab: together if and only if together in all; named by the least member. Inputs: (cid, lab)."""
    out = assigns[0].select("cid", F.col("lab").alias("l0"))
    for i, a in enumerate(assigns[1:], 1):
        out = out.join(a.select("cid", F.col("lab").alias(f"l{i}")), "cid")
    cell = [f"l{i}" for i in range(len(assigns))]
    named = out.groupBy(*cell).agg(F.min("cid").alias("lab"))  # the minimum combines before the shuffle, whatever a cell's size
    return out.join(named, cell).select("cid", "lab")


def cut_symdiff(edges: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: edges (ci, cj) that exactly one of the clusterings (cid, lab) cuts. One scan."""
    x = edges.where("ci <> cj")
    for name, c in (("a", a), ("b", b)):
        x = x.join(c.select(F.col("cid").alias("ci"), F.col("lab").alias(f"{name}i")), "ci").join(c.select(F.col("cid").alias("cj"), F.col("lab").alias(f"{name}j")), "cj")
    return x.agg(F.coalesce(F.sum(((F.col("ai") != F.col("aj")) != (F.col("bi") != F.col("bj"))).cast("long")), F.lit(0)).alias("distance"))


def fitness(edges: DataFrame, population: DataFrame) -> DataFrame:
    """ind, two_m, qnum of every member, in one plan."""
    arcs = quotient.as_arcs(edges)
    p = population
    x = arcs.join(p.select("ind", F.col("cid").alias("src"), F.col("lab").alias("ls")), "src").join(p.select("ind", F.col("cid").alias("dst"), F.col("lab").alias("ld")), ["ind", "dst"])
    each = x.groupBy("ind", "ls").agg(F.sum("w").alias("vol"), F.sum(F.when(F.col("ls") == F.col("ld"), F.col("w")).otherwise(0)).alias("k2"))
    v = F.col("vol").cast("decimal(38,0)")
    t = each.groupBy("ind").agg(F.sum("vol").alias("two_m"), F.sum("k2").alias("k2"), F.sum(v * v).alias("vol2"))
    return t.select("ind", "two_m", (F.col("two_m").cast("decimal(38,0)") * F.col("k2") - F.col("vol2")).cast("decimal(38,0)").alias("qnum"))


def tournament_winner(fit: DataFrame, draws: DataFrame) -> DataFrame:
    """draws (round, ind): round, and the fittest drawn member; ties to the lesser number."""
    best = draws.join(fit, "ind").groupBy("round").agg(F.max(F.struct("qnum", (-F.col("ind")).alias("neg"))).alias("b"))
    return best.select("round", (-F.col("b.neg")).alias("winner"), F.col("b.qnum").alias("qnum"))


def cut_distances(edges: DataFrame, population: DataFrame, child: DataFrame) -> DataFrame:
    """ind, distance: edges that exactly one of the member and the child cuts. One scan for all members."""
    x = edges.where("ci <> cj").join(child.select(F.col("cid").alias("ci"), F.col("lab").alias("ki")), "ci").join(child.select(F.col("cid").alias("cj"), F.col("lab").alias("kj")), "cj")
    x = x.join(population.select("ind", F.col("cid").alias("ci"), F.col("lab").alias("pi")), "ci").join(population.select("ind", F.col("cid").alias("cj"), F.col("lab").alias("pj")), ["ind", "cj"])
    return x.groupBy("ind").agg(F.sum(((F.col("ki") != F.col("kj")) != (F.col("pi") != F.col("pj"))).cast("long")).alias("distance"))


def replacement_choice(edges: DataFrame, population: DataFrame, child: DataFrame) -> DataFrame:
    """Zero or one row: the member to give way to the child (cid, lab): not better than it, and cut most alike."""
    own = population.unionByName(child.withColumn("ind", F.lit(-1)))
    fit = fitness(edges, own)
    q = fit.where("ind = -1").select(F.col("qnum").alias("qc"))
    far = cut_distances(edges, population, child)
    able = fit.where("ind >= 0").join(F.broadcast(q)).where("qnum <= qc").join(far, "ind")
    return able.agg(F.min(F.struct("distance", "qnum", "ind")).alias("b")).where("b is not null").select(F.col("b.ind").alias("ind"), F.col("b.distance").alias("distance"))


def choose_engine(n_edges: int, two_m: int, cfg: MemeticConfig) -> str:
    return "island" if n_edges <= cfg.island_max_edges and two_m < MAX_INT_2M else "tables"


# --- one population of tables ---


def quotient_graph(edges: DataFrame, supernodes: DataFrame) -> Graph:
    """The quotient (ci, cj, w) and its supernodes as a graph; ids are the clusters' names."""
    arcs = io.settle(quotient.as_arcs(edges), "arcs")
    deg = arcs.groupBy(F.col("src").alias("cid")).agg(F.count("*").alias("deg"))
    nodes = supernodes.join(deg, "cid", "left").select(F.col("cid").alias("id"), F.col("cid").cast("string").alias("okey"), F.col("cid").alias("rank"), F.coalesce("deg", F.lit(0)).cast("long").alias("deg"), F.col("vol").alias("wdeg"), "cw")
    return Graph(arcs, io.settle(nodes, "nodes"))


def score(graph: Graph, member: DataFrame) -> int:
    return int(measures.modularity_num(measures.cluster_sums(graph.arcs, graph.nodes, member)).first()["qnum"] or 0)


def individual_table(graph: Graph, seed: int) -> DataFrame:
    """A start for the population: bounded label propagation with drawn halves, then Louvain from it."""
    r = random.Random(seed)
    total, heaviest, n = (int(x or 0) for x in graph.nodes.agg(F.sum("cw"), F.max("cw"), F.count("*")).first())
    bound = max(heaviest, int(total / (2 + r.random() * max(2, n // 4))))
    return louvain.louvain_parallel(graph, start=louvain.label_propagation(graph.arcs, graph.nodes, bound, 3, r.randrange(1 << 30)))


def _named(a: DataFrame) -> DataFrame:
    return a.select(F.col("id").alias("cid"), F.col("cid").alias("lab"))


def recombine_flat_table(graph: Graph, a: DataFrame, b: DataFrame) -> DataFrame:
    """Louvain on what the overlay of both contracts to."""
    cells = io.settle(overlay(_named(a), _named(b)).select(F.col("cid").alias("id"), F.col("lab").alias("cid")), "overlay")
    top = louvain.louvain_parallel(louvain.contracted(graph, cells))
    return io.settle(quotient.project(cells, _named(top)), "child")


def recombine_multilevel_table(graph: Graph, a: DataFrame, b: DataFrame, better: DataFrame, seed: int, levels: int = 6) -> DataFrame:
    """Coarsens inside the overlay's cells, starts at the coarsest level from the better parent, refines on every level back."""
    cfg = RestreamConfig(min_rel_gain=1e-3, time_limit_s=None)
    cells, own, level, path = overlay(_named(a), _named(b)).select(F.col("cid").alias("id"), F.col("lab").alias("cell")), better, graph, []
    for k in range(levels):
        total, n = (int(x or 0) for x in level.nodes.agg(F.sum("cw"), F.count("*")).first())
        cells = io.settle(cells, "cells")
        ends = cells.select(F.col("id").alias("dst"), F.col("cell").alias("other"))
        inside = level.arcs.join(cells.select(F.col("id").alias("src"), "cell"), "src").join(ends, "dst").where("cell = other").select("src", "dst", "w")
        to = louvain.label_propagation(inside, level.nodes, max(2, total // 4), 2, seed + k)
        if to.select("cid").distinct().count() == n:
            break
        path.append((level, to))
        level = louvain.contracted(level, to)
        # a coarse node lies in one cell, and so in one cluster of the parent
        cells = cells.join(to, "id").groupBy(F.col("cid").alias("id")).agg(F.min("cell").alias("cell"))
        own = io.settle(own.withColumnRenamed("cid", "lab").join(to, "id").groupBy(F.col("cid").alias("id")).agg(F.min("lab").alias("cid")), "own")
    child, _ = restream.restream_parallel(level, own, cfg)
    for fine, to in reversed(path):
        child, _ = restream.restream_parallel(fine, io.settle(quotient.project(to, _named(child)), "child"), cfg)
    return child


def split_table(graph: Graph, member: DataFrame, seed: int, most: int = 200_000) -> DataFrame:
    """Every cluster in two blocks of about equal weight: by growth and exchange in a task of its own up to most rows, by hash beyond."""
    own = member.withColumnRenamed("cid", "lab")
    there = own.select(F.col("id").alias("dst"), F.col("lab").alias("other"))
    inside = graph.arcs.where("src <> dst").join(own.withColumnRenamed("id", "src"), "src").join(there, "dst").where("lab = other").select("lab", F.col("src").alias("a"), F.col("dst").alias("b"), "w")
    rows = inside.union(graph.nodes.join(own, "id").select("lab", F.col("id").alias("a"), F.lit(None).cast("long").alias("b"), F.col("cw").alias("w")))
    size = rows.groupBy("lab").agg(F.count("*").alias("rows"))
    small, large = rows.join(size.where(F.col("rows") <= most).select("lab"), "lab", "left_semi"), own.join(size.where(F.col("rows") > most).select("lab"), "lab", "left_semi")

    def halve(pdf: pd.DataFrame) -> pd.DataFrame:
        node = pdf["b"].isna().to_numpy()
        ids = sorted(pdf["a"][node].tolist())
        place = {x: i for i, x in enumerate(ids)}
        weight = [0] * len(ids)
        for x, w in zip(pdf["a"][node].tolist(), pdf["w"][node].tolist(), strict=True):
            weight[place[x]] = w
        arcs = sorted((place[x], place[int(y)], w) for x, y, w in zip(pdf["a"][~node].tolist(), pdf["b"][~node].tolist(), pdf["w"][~node].tolist(), strict=True))
        block = set(kernels.bisect(kernels.Mem(len(ids), arcs, weight), list(range(len(ids))), random.Random(seed + ids[0])))
        first = [ids[min(block)] if block else 0, ids[min(set(range(len(ids))) - block)] if len(block) < len(ids) else 0]
        return pd.DataFrame({"id": ids, "cid": [first[i not in block] for i in range(len(ids))]})

    cut = small.groupBy("lab").applyInPandas(halve, "id long, cid long")
    side = large.select("id", "lab", F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(2)).alias("side"))
    return io.settle(cut.union(side.join(side.groupBy("lab", "side").agg(F.min("id").alias("cid")), ["lab", "side"]).select("id", "cid")), "split")


def evolve_tables(graph: Graph, cfg: MemeticConfig):
    """(id, cid) of the best member and rows (epoch, island, round, kind, child, best, replaced), as of one island. Scores are kept per member."""
    r, began = random.Random(cfg.seed), time.monotonic()
    edges = graph.arcs.where("src <= dst").select(F.col("src").alias("ci"), F.col("dst").alias("cj"), "w")
    pop = [individual_table(graph, r.randrange(1 << 30)) for _ in range(cfg.population)]
    fit, rows = [score(graph, p) for p in pop], []

    def pick():
        return max(r.sample(range(len(pop)), min(cfg.tournament, len(pop))), key=lambda i: (fit[i], -i))

    for k in range(cfg.max_rounds):
        if cfg.time_limit_s is not None and time.monotonic() - began > cfg.time_limit_s:
            break
        i, j = pick(), pick()
        for _ in range(8):
            if i != j or len(pop) < 2:
                break
            j = pick()
        better, seed = max((i, j), key=lambda x: (fit[x], -x)), r.randrange(1 << 30)
        if r.random() < cfg.p_mutation:
            kind, a, b = "mutation", split_table(graph, pop[i], seed), split_table(graph, pop[j], seed + 1)
            child = recombine_multilevel_table(graph, a, b, max((a, b), key=lambda x: score(graph, x)), seed)
        elif r.random() < cfg.p_flat:
            kind, child = "flat", recombine_flat_table(graph, pop[i], pop[j])
        else:
            kind, child = "multilevel", recombine_multilevel_table(graph, pop[i], pop[j], pop[better], seed)
        q = score(graph, child)
        if kind != "mutation" and q < fit[better]:
            child, q = pop[better], fit[better]
        able = [x for x in range(len(pop)) if fit[x] <= q]
        at = -1
        if able:
            members = [_named(pop[x]).select(F.lit(x).alias("ind"), "cid", "lab") for x in able]
            far = {int(x["ind"]): int(x["distance"]) for x in cut_distances(edges, functools.reduce(DataFrame.unionByName, members), _named(child)).collect()}  # a row per member
            at = min(able, key=lambda x: (far.get(x, 0), fit[x], x))
            pop[at], fit[at] = child, q
        rows.append((0, 0, k, kind, q, max(fit), at))
    return pop[max(range(len(pop)), key=lambda x: (fit[x], -x))], rows


# --- islands ---


def _held(pdf: pd.DataFrame):
    """ids; src, dst, w as places, sorted; node weights; and clusterings to begin from. Rows of kind 0 are supernodes, 1 arcs, 2 labels."""
    kind, a, b, w = (pdf[x].to_numpy() for x in ("kind", "a", "cw", "w"))
    own = kind == 0
    by = a[own].argsort()
    ids, weight = a[own][by], b[own][by]
    arc, given = kind == 1, kind == 2
    src, dst = np.searchsorted(ids, a[arc]), np.searchsorted(ids, b[arc])
    order = np.lexsort((w[arc], dst, src))
    starts = np.zeros((len(np.unique(w[given])), len(ids)), np.int64)
    starts[w[given].astype(np.int64), np.searchsorted(ids, a[given])] = np.searchsorted(ids, b[given])
    return ids, (src[order], dst[order], w[arc][order]), weight, starts


def _island_frame(island: int, ids, label, qnum: int, trace: list) -> pd.DataFrame:
    first: dict[int, int] = {}
    lab = [first.setdefault(c, i) for i, c in zip(ids.tolist(), label, strict=True)]
    return pd.DataFrame({"island": island, "cid": [*ids.tolist(), -1], "lab": [*lab, 0], "told": [b""] * len(ids) + [pickle.dumps((qnum, trace))]})


def _seed(cfg: MemeticConfig, epoch: int, island: int) -> int:
    return cfg.seed * 1000 + epoch * 100 + island


def _island(cfg: MemeticConfig, epoch: int, epochs: int, share: int):
    """The kernel of one island and epoch."""

    def evolve(pdf: pd.DataFrame) -> pd.DataFrame:
        island = int(pdf["island"].iloc[0])
        ids, arcs, weight, starts = _held(pdf)
        g = kernels.Mem(len(ids), zip(*(x.tolist() for x in arcs), strict=True), weight.tolist())
        t0 = time.monotonic()
        late = (lambda: time.monotonic() - t0 > cfg.time_limit_s / epochs) if cfg.time_limit_s is not None else None
        label, trace, _ = kernels.evolve(g, max(cfg.population, len(starts)), share, _seed(cfg, epoch, island), cfg.p_mutation, cfg.p_flat, cfg.tournament, starts.tolist(), late)
        return _island_frame(island, ids, label, g.qnum(label), trace)

    return evolve


def _island_loops(cfg: MemeticConfig, epoch: int, epochs: int, share: int):
    """The same in the JVM: what packs an island, and reads the answer."""

    def pack(pdf: pd.DataFrame) -> tuple:
        island = int(pdf["island"].iloc[0])
        ids, arcs, weight, starts = _held(pdf)
        late = -1 if cfg.time_limit_s is None else int(cfg.time_limit_s / epochs * 1000)
        params = [max(cfg.population, len(starts)), share, _seed(cfg, epoch, island), jvm.bits(cfg.p_mutation), jvm.bits(cfg.p_flat), cfg.tournament, late]
        return (island, ids), jvm.request(jvm.EVOLVE, params, len(ids), *arcs, weight, *starts)

    def unpack(tag: tuple, told, label) -> pd.DataFrame:
        rows = [(r, ("mutation", "flat", "multilevel")[kind], q, best, at) for r, kind, q, best, at in told[:-1].reshape(-1, 5).tolist()]
        return _island_frame(*tag, label.tolist(), int(told[-1]), rows)

    return pack, unpack


def memetic(edges: DataFrame, supernodes: DataFrame, cfg: MemeticConfig | None = None):
    """cid, lab: the best clustering of the quotient (ci, cj, w), and trace rows (epoch, island, round, kind, child, best, replaced).

    Each island is one task: it reads the quotient from the table, evolves with its own seed, and hands its best on; in the second epoch every
    island begins with all islands' best.
    """
    cfg = cfg or MemeticConfig()
    n_edges = edges.count()
    two_m = int(supernodes.agg(F.coalesce(F.sum("vol"), F.lit(0))).first()[0])
    if choose_engine(n_edges, two_m, cfg) != "island":
        got, told = evolve_tables(quotient_graph(edges, supernodes), cfg)
        return _named(got), told
    null = F.lit(0).cast("long")
    rows = supernodes.select(F.lit(0).alias("kind"), F.col("cid").alias("a"), "cw", null.alias("w")).union(quotient.as_arcs(edges).select(F.lit(1), "src", "dst", "w"))
    told, best, told_as = [], None, "island int, cid long, lab long, told binary"
    epochs = 2 if cfg.islands > 1 else 1
    began = time.monotonic()
    for epoch in range(epochs):
        share = max(1, cfg.max_rounds // epochs)
        copies = rows.withColumn("island", F.explode(F.sequence(F.lit(0), F.lit(cfg.islands - 1))))

        grouped = copies.repartitionByRange(cfg.islands, "island").groupBy("island")  # small islands, too, evolve side by side
        if jvm.ready(edges.sparkSession, two_m):
            made = jvm.run(edges.sparkSession, grouped, *_island_loops(cfg, epoch, epochs, share), told_as)
        else:
            made = grouped.applyInPandas(_island(cfg, epoch, epochs, share), told_as)
        got = io.settle(made, "islands")
        marks = {r["island"]: pickle.loads(r["told"]) for r in got.where("cid = -1").select("island", "told").collect()}
        told += [(epoch, i, *row) for i, (_, trace) in sorted(marks.items()) for row in trace]
        win = max(marks, key=lambda i: (marks[i][0], -i))
        best = got.where((F.col("island") == win) & (F.col("cid") >= 0)).select("cid", "lab")
        # the islands' best, for all islands of the next epoch
        rows = rows.union(got.where("cid >= 0").select(F.lit(2), "cid", "lab", F.col("island").cast("long")))
        if cfg.time_limit_s is not None and time.monotonic() - began > cfg.time_limit_s:
            break
    return best, told
