"""Quality of a clustering. Every measure is one or two aggregates; whole-number forms are exact."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def labelled_arcs(arcs: DataFrame, assign: DataFrame) -> DataFrame:
    """arcs with cs and cd, the clusters of both ends."""
    a = assign.select(F.col("id").alias("src"), F.col("cid").alias("cs"))
    b = assign.select(F.col("id").alias("dst"), F.col("cid").alias("cd"))
    return arcs.join(a, "src").join(b, "dst")


def cluster_sums(arcs: DataFrame, nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """cid, size, vol, k2 (inner weight in both directions), cut, n2 (inner arcs)."""
    inner = labelled_arcs(arcs, assign).groupBy(F.col("cs").alias("cid")).agg(
        F.sum(F.when(F.col("cs") == F.col("cd"), F.col("w")).otherwise(0)).alias("k2"), F.sum(F.when(F.col("cs") != F.col("cd"), F.col("w")).otherwise(0)).alias("cut"), F.count_if(F.col("cs") == F.col("cd")).alias("n2")
    )
    vols = nodes.select("id", "wdeg").join(assign, "id").groupBy("cid").agg(F.count("*").alias("size"), F.sum("wdeg").alias("vol"))
    zero = F.lit(0).cast("long")
    return vols.join(inner, "cid", "left").select("cid", "size", "vol", *[F.coalesce(c, zero).alias(c) for c in ("k2", "cut", "n2")])


def totals(sums: DataFrame) -> DataFrame:
    """One row of everything that the measures need."""
    v = F.col("vol").cast("decimal(38,0)")
    return sums.agg(
        F.count("*").alias("k"), F.sum("size").alias("n"), F.sum("vol").alias("two_m"), F.sum("k2").alias("k2"), F.sum(v * v).alias("vol2"), F.sum("n2").alias("n2"), F.sum("cut").alias("cut2"),
        F.sum(F.col("size") * (F.col("size") - 1) / 2).cast("long").alias("pairs_in"),
    )


def modularity_num(sums: DataFrame) -> DataFrame:
    """qnum = 2m * sum(K2) - sum(vol^2), and two_m: modularity is qnum / two_m^2."""
    t = totals(sums)
    return t.select("k", "n", "two_m", (F.col("two_m").cast("decimal(38,0)") * F.col("k2") - F.col("vol2")).cast("decimal(38,0)").alias("qnum"))


def modularity(arcs: DataFrame, nodes: DataFrame, assign: DataFrame) -> float | None:
    r = modularity_num(cluster_sums(arcs, nodes, assign)).first()
    return float(r["qnum"]) / float(r["two_m"]) ** 2 if r["two_m"] else None


def modularity_by_cluster(sums: DataFrame) -> DataFrame:
    """cid and what it adds to the modularity."""
    two_m = sums.agg(F.sum("vol")).first()[0]
    x = float(two_m)
    return sums.select("cid", "size", "vol", (F.col("k2") / x - (F.col("vol") / x) * (F.col("vol") / x)).alias("q"))


def _one(sums: DataFrame, **exprs) -> DataFrame:
    return totals(sums).select(*[e.alias(k) for k, e in exprs.items()])


def coverage(sums: DataFrame) -> DataFrame:
    return _one(sums, coverage=F.col("k2") / F.col("two_m"))


def expected_coverage(sums: DataFrame) -> DataFrame:
    return _one(sums, expected_coverage=F.col("vol2").cast("double") / F.col("two_m") / F.col("two_m"))


def performance(arcs: DataFrame, nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """Share of node pairs that are joined within a cluster or not joined across clusters; pairs are counted, never made."""
    t = totals(cluster_sums(arcs, nodes, assign))
    m = arcs.agg((F.count("*") / 2).cast("long").alias("m"))
    pairs = F.col("n") * (F.col("n") - 1) / 2
    inner = F.col("n2") / 2
    return t.join(m).select(((inner + pairs - F.col("pairs_in") - (F.col("m") - inner)) / pairs).alias("performance"))


def conductance(sums: DataFrame) -> DataFrame:
    """Greatest and mean cut over the smaller side's volume, and 1 - the greatest; clusters without a side are null."""
    two_m = sums.agg(F.sum("vol")).first()[0]
    side = F.least(F.col("vol"), F.lit(two_m) - F.col("vol"))
    phi = F.when(side > 0, F.col("cut") / side)
    return sums.select(phi.alias("phi")).agg(F.max("phi").alias("max_conductance"), F.avg("phi").alias("mean_conductance"), (1 - F.max("phi")).alias("inter_cluster"))


def surprise(arcs: DataFrame, nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """Asymptotic form: edges times the divergence of the inner share of edges from the inner share of pairs."""
    t = totals(cluster_sums(arcs, nodes, assign)).join(arcs.agg((F.count("*") / 2).cast("long").alias("m")))
    q, e = F.col("n2") / 2 / F.col("m"), F.col("pairs_in") / (F.col("n") * (F.col("n") - 1) / 2)
    part = lambda a, b: F.when((a > 0) & (b > 0), a * F.ln(a / b)).otherwise(0.0)
    return t.select((F.col("m") * (part(q, e) + part(1 - q, 1 - e))).alias("surprise"))


def map_equation(arcs: DataFrame, nodes: DataFrame, assign: DataFrame) -> DataFrame:
    """Two-level description length of a random walk, in bits."""
    sums = cluster_sums(arcs, nodes, assign)
    two_m = float(sums.agg(F.sum("vol")).first()[0])
    plogp = lambda x: F.when(x > 0, x * F.log2(x)).otherwise(0.0)
    exit_, p = F.col("cut") / two_m, F.col("vol") / two_m
    by = sums.agg(F.sum(exit_).alias("out"), F.sum(plogp(exit_)).alias("a"), F.sum(plogp(exit_ + p)).alias("b"))
    each = nodes.agg(F.sum(plogp(F.col("wdeg") / two_m)).alias("c"))
    return by.join(each).select((plogp(F.col("out")) - 2 * F.col("a") - F.col("c") + F.col("b")).alias("map_equation"))


def contingency(assign: DataFrame, truth: DataFrame) -> DataFrame:
    """cid, label, n over the nodes that have a label. More than one label per node is refused."""
    if truth.groupBy("id").count().where("count > 1").limit(1).count():
        raise ValueError("overlapping truth: a node has more than one label")
    return assign.join(truth, "id").groupBy("cid", "label").agg(F.count("*").alias("n"))


def nmi(table: DataFrame) -> DataFrame:
    """mi, hx, hy and the mutual information over four means of the entropies, from a contingency table."""
    total = table.agg(F.sum("n").alias("t"))
    h = lambda by, name: table.groupBy(by).agg(F.sum("n").alias("x")).join(F.broadcast(total)).agg((-F.sum(F.col("x") / F.col("t") * F.ln(F.col("x") / F.col("t")))).alias(name))
    rows, cols = table.groupBy("cid").agg(F.sum("n").alias("nr")), table.groupBy("label").agg(F.sum("n").alias("nc"))
    cell = table.join(rows, "cid").join(cols, "label").join(F.broadcast(total))
    mi = cell.agg(F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") * F.col("t") / (F.col("nr") * F.col("nc")))).alias("mi"))
    t = mi.join(h("cid", "hx")).join(h("label", "hy"))
    both0 = (F.abs("hx") < 1e-12) & (F.abs("hy") < 1e-12)
    none = (F.abs("hx") < 1e-12) | (F.abs("hy") < 1e-12)
    over = lambda mean: F.when(both0, 1.0).when(none, 0.0).otherwise(F.greatest(F.col("mi"), F.lit(0.0)) / mean)
    return t.select("mi", "hx", "hy", over((F.col("hx") + F.col("hy")) / 2).alias("nmi_arithmetic"), over(F.sqrt(F.col("hx") * F.col("hy"))).alias("nmi_geometric"), over(F.greatest("hx", "hy")).alias("nmi_max"), over(F.least("hx", "hy")).alias("nmi_min"))


def cluster_profile(assign: DataFrame) -> DataFrame:
    """Clusters, nodes, sizes (min, median, max), singletons, and whether the clustering is trivial."""
    sizes = assign.groupBy("cid").agg(F.count("*").alias("size"))
    k, n = F.count("*"), F.sum("size")
    return sizes.agg(k.alias("k"), n.alias("n"), F.min("size").alias("min_size"), F.median("size").alias("median_size"), F.max("size").alias("max_size"), F.count_if(F.col("size") == 1).alias("singletons"), ((k == 1) | (k == n)).alias("is_trivial"))
