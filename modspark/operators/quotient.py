"""The quotient graph: one supernode per cluster, edges summed by unordered cluster pair, inner weight as a loop counted twice."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.measures import labelled_arcs


def contract(arcs: DataFrame, assign: DataFrame) -> DataFrame:
    """ci <= cj, w. Works on quotient arcs as well, whose loops carry their weight in both directions already."""
    half = labelled_arcs(arcs.where("src <= dst"), assign)
    w = F.when((F.col("cs") == F.col("cd")) & (F.col("src") != F.col("dst")), 2 * F.col("w")).otherwise(F.col("w"))
    return half.select(F.least("cs", "cd").alias("ci"), F.greatest("cs", "cd").alias("cj"), w.alias("w")).groupBy("ci", "cj").agg(F.sum("w").alias("w"))


def supernodes(quotient: DataFrame, nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """cid, cw (members), self_w, vol."""
    own = nodes.select("id", "cw", "wdeg").join(assign, "id").groupBy("cid").agg(F.sum("cw").alias("cw"), F.sum("wdeg").alias("vol"))
    loops = quotient.where("ci = cj").select(F.col("ci").alias("cid"), F.col("w").alias("self_w"))
    return own.join(loops, "cid", "left").select("cid", "cw", F.coalesce("self_w", F.lit(0)).cast("long").alias("self_w"), "vol")


def quotient_delta(arcs: DataFrame, ranks: DataFrame, assign: DataFrame, low: int, high: int) -> DataFrame:
    """What the nodes of ranks low .. high - 1 add: every edge whose later end is among them."""
    r = ranks.select("id", "rank")
    late = arcs.join(r.where((F.col("rank") >= low) & (F.col("rank") < high)).select(F.col("id").alias("src"), F.col("rank").alias("rs")), "src")
    early = late.join(r.select(F.col("id").alias("dst"), F.col("rank").alias("rd")), "dst").where("rd < rs").select("src", "dst", "w")
    both = labelled_arcs(early, assign)
    return both.select(F.least("cs", "cd").alias("ci"), F.greatest("cs", "cd").alias("cj"), F.when(F.col("cs") == F.col("cd"), 2 * F.col("w")).otherwise(F.col("w")).alias("w")).groupBy("ci", "cj").agg(F.sum("w").alias("w"))


def merge_quotient(*parts: DataFrame) -> DataFrame:
    """Deltas add up, in any order and grouping."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("ci", "cj").agg(F.sum("w").alias("w"))


def as_arcs(quotient: DataFrame) -> DataFrame:
    """The quotient as arcs: cross edges in both directions, loops once with their doubled weight."""
    cross = quotient.where("ci <> cj")
    return cross.select(F.col("ci").alias("src"), F.col("cj").alias("dst"), "w").union(cross.select("cj", "ci", "w")).union(quotient.where("ci = cj").select("ci", "cj", "w"))


def project(assign: DataFrame, qassign: DataFrame) -> DataFrame:
    """id, cid: a clustering of the supernodes (cid, lab) carried over to the nodes."""
    return assign.join(qassign, "cid").select("id", F.col("lab").alias("cid"))


def modularity_num_quotient(quotient: DataFrame, qassign: DataFrame) -> DataFrame:
    """two_m and qnum of a clustering of the quotient, from its own edges alone."""
    q = as_arcs(quotient)
    a = qassign.select(F.col("cid").alias("src"), F.col("lab").alias("ls"))
    b = qassign.select(F.col("cid").alias("dst"), F.col("lab").alias("ld"))
    each = q.join(a, "src").join(b, "dst").groupBy("ls").agg(F.sum("w").alias("vol"), F.sum(F.when(F.col("ls") == F.col("ld"), F.col("w")).otherwise(0)).alias("k2"))
    v = F.col("vol").cast("decimal(38,0)")
    return each.agg(F.count("*").alias("k"), F.sum("vol").alias("two_m"), F.sum("k2").alias("k2"), F.sum(v * v).alias("vol2")).select("k", "two_m", (F.col("two_m").cast("decimal(38,0)") * F.col("k2") - F.col("vol2")).cast("decimal(38,0)").alias("qnum"))
