"""Synthetic graphs from spark.range alone: every edge is drawn by hashes, so a graph of any size is made in parallel and always the same."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _u(*parts) -> Column:
    """A uniform number in [0, 1) from a hash."""
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 40)) / float(1 << 40)


def ring_of_cliques(spark: SparkSession, cliques: int = 8, size: int = 5) -> DataFrame:
    inner = spark.range(cliques * size).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(size - 1)))).select(F.col("id").alias("a"), (F.floor(F.col("id") / size) * size + F.col("j")).alias("b")).where("a < b")
    ring = spark.range(cliques).select((F.col("id") * size).alias("a"), (F.pmod(F.col("id") + 1, F.lit(cliques)) * size + 1).alias("b"))
    return inner.union(ring)


def planted_partition(spark: SparkSession, n: int = 2000, blocks: int = 20, degree: int = 10, inner: float = 0.8, seed: int = 1) -> DataFrame:
    """n * degree / 2 drawn edges, a share of them within blocks of equal size; node i is in block i mod blocks."""
    m, per = n * degree // 2, n // blocks
    e = spark.range(m).select("id", (F.floor(_u("id", F.lit(seed)) * n)).cast("long").alias("a"), _u("id", F.lit(seed + 1)).alias("p"), _u("id", F.lit(seed + 2)).alias("q"))
    b = F.when(F.col("p") < inner, F.floor(F.col("q") * per) * blocks + F.pmod("a", F.lit(blocks))).otherwise(F.floor(F.col("q") * n))
    return e.select("a", b.cast("long").alias("b")).where("a <> b")


def planted_truth(spark: SparkSession, n: int = 2000, blocks: int = 20) -> DataFrame:
    return spark.range(n).select(F.col("id").cast("string").alias("okey"), F.pmod("id", F.lit(blocks)).cast("string").alias("label"))


def grid(spark: SparkSession, width: int = 40, height: int = 40) -> DataFrame:
    p = spark.range(width * height)
    return p.where(F.pmod("id", F.lit(width)) < width - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b")).union(p.where(F.col("id") < width * (height - 1)).select(F.col("id").alias("a"), (F.col("id") + width).alias("b")))


def random_geometric(spark: SparkSession, n: int = 2000, radius: float | None = None, seed: int = 1) -> DataFrame:
    """Points of the unit square within radius of one another; points meet through cells of the radius' width."""
    r = radius or 0.55 * math.sqrt(math.log(n) / n)
    p = spark.range(n).select("id", _u("id", F.lit(seed)).alias("x"), _u("id", F.lit(seed + 1)).alias("y")).withColumn("cx", F.floor(F.col("x") / r)).withColumn("cy", F.floor(F.col("y") / r))
    near = F.array(*[F.struct((F.col("cx") + dx).alias("cx"), (F.col("cy") + dy).alias("cy")) for dx in (-1, 0, 1) for dy in (-1, 0, 1)])
    left = p.select(F.col("id").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya"), F.explode(near).alias("c")).select("a", "xa", "ya", "c.cx", "c.cy")
    return left.join(p, ["cx", "cy"]).where(F.col("a") < F.col("id")).where((F.col("xa") - F.col("x")) ** 2 + (F.col("ya") - F.col("y")) ** 2 <= r * r).select("a", F.col("id").alias("b"))


def random_hyperbolic(spark: SparkSession, n: int = 2000, avg_degree: float = 8.0, alpha: float = 0.75, seed: int = 1) -> DataFrame:
    """Points of a hyperbolic disk within its radius of one another. Points are put into bands by radius; a point of an inner band meets a
    band through angular cells as wide as the two bands' greatest angle."""
    big = 2 * math.log(8 * n * alpha * alpha / (math.pi * avg_degree * (2 * alpha - 1) ** 2)) if alpha > 0.5 else 2 * math.log(n)
    r = F.acosh(1 + (math.cosh(alpha * big) - 1) * F.col("u")) / alpha
    p = spark.range(n).select("id", (_u("id", F.lit(seed)) * 2 * math.pi).alias("t"), _u("id", F.lit(seed + 1)).alias("u")).select("id", "t", r.alias("r"))
    edges_at = [0.0, *[big - k for k in range(int(big), -1, -1) if 0 < big - k < big], big]
    bands, grid = [(lo, hi) for lo, hi in zip(edges_at, edges_at[1:], strict=False)], []
    for i, (lo, _) in enumerate(bands):
        for j, (lo2, _) in list(enumerate(bands))[i:]:
            c = (math.cosh(lo) * math.cosh(lo2) - math.cosh(big)) / max(math.sinh(lo) * math.sinh(lo2), 1e-9)
            wide = math.pi if lo + lo2 <= big or c <= -1 else math.acos(min(1.0, c))
            cells = max(1, int(2 * math.pi / wide))
            grid.append((i, j, cells, 2 * math.pi / cells))
    # one join for all pairs of bands: their cells are part of the key
    pairs = F.broadcast(spark.createDataFrame(grid, "i int, j int, cells long, size double"))
    at = F.size(F.filter(F.array(*[F.lit(e) for e in edges_at]), lambda e: e <= F.col("r"))) - 1
    p = p.where((F.col("r") >= 0) & (F.col("r") < big)).withColumn("band", at)
    reach = F.array_distinct(F.array(*[F.pmod(F.floor(F.col("ta") / F.col("size")) + d, F.col("cells")) for d in (-1, 0, 1)]))
    a = p.select(F.col("id").alias("a"), F.col("t").alias("ta"), F.col("r").alias("ra"), F.col("band").alias("i")).join(pairs, "i").select("a", "ta", "ra", "i", "j", F.explode(reach).alias("cell"))
    b = p.select(F.col("id").alias("b"), F.col("t").alias("tb"), F.col("r").alias("rb"), F.col("band").alias("j")).join(pairs, "j").select("b", "tb", "rb", "i", "j", F.floor(F.col("tb") / F.col("size")).alias("cell"))
    x = a.join(b, ["i", "j", "cell"]).where("i < j or a < b")
    turn = F.lit(math.pi) - F.abs(F.lit(math.pi) - F.abs(F.col("ta") - F.col("tb")))
    near = F.cosh("ra") * F.cosh("rb") - F.sinh("ra") * F.sinh("rb") * F.cos(turn) <= math.cosh(big)
    return x.where(near).select("a", "b")


def power_law(spark: SparkSession, n: int = 2000, degree: int = 8, gamma: float = 2.5, seed: int = 1) -> DataFrame:
    """Ends drawn with a probability that falls as a power of the node's number; loops and parallels are merged by prep."""
    s = 1.0 / (gamma - 1.0)
    draw = lambda k: F.least(F.lit(n - 1), F.floor(n * F.pow(_u("id", F.lit(k)), 1.0 / (1.0 - s)))).cast("long")
    return spark.range(n * degree // 2).select(draw(seed).alias("a"), draw(seed + 1).alias("b")).where("a <> b")


SYNTH = {"S1": ring_of_cliques, "S2": planted_partition, "S3": grid, "S4": random_geometric, "S5": random_hyperbolic, "S6": power_law}
