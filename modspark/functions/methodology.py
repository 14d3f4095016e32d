"""How runs are compared: means, improvements, profiles, boxes. scores: instance, algo, metric, value; a null value is a failed run."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def geomean(scores: DataFrame) -> DataFrame:
    """Per algo and metric: the geometric mean, null if any run failed or isn't positive; and how many such runs there are."""
    bad = F.count_if(F.col("value").isNull() | (F.col("value") <= 0))
    return scores.groupBy("algo", "metric").agg(bad.alias("excluded"), F.when(bad == 0, F.exp(F.avg(F.ln(F.when(F.col("value") > 0, F.col("value")))))).alias("geomean"))


def common_instances(scores: DataFrame, algos: list[str]) -> DataFrame:
    """Scores of the instances on which all the algos finished."""
    ok = scores.where(F.col("algo").isin(algos)).groupBy("instance", "metric").agg(F.count("value").alias("done"), F.count_distinct("algo").alias("all")).where((F.col("done") == F.col("all")) & (F.col("all") == len(algos)))
    return scores.where(F.col("algo").isin(algos)).join(ok.select("instance", "metric"), ["instance", "metric"], "left_semi")


def _pair(scores: DataFrame, a: str, b: str) -> DataFrame:
    x = scores.where(F.col("algo") == a).select("instance", "metric", F.col("value").alias("x"))
    y = scores.where(F.col("algo") == b).select("instance", "metric", F.col("value").alias("y"))
    return x.join(y, ["instance", "metric"])


def improvement(scores: DataFrame, a: str, b: str) -> DataFrame:
    """Percent by which a's value exceeds b's."""
    return _pair(scores, a, b).select("instance", "metric", ((F.col("x") / F.col("y") - 1) * 100).alias("improvement_pct"))


def relative(scores: DataFrame, a: str, b: str) -> DataFrame:
    return _pair(scores, a, b).select("instance", "metric", (F.col("x") / F.col("y")).alias("relative"))


def performance_profile(scores: DataFrame, taus: list[float], better: str = "min") -> DataFrame:
    """metric, algo, tau, share of instances on which the algo is within the factor tau of the best. better: min or max (tau falls from 1)."""
    w = Window.partitionBy("instance", "metric")
    best = (F.min if better == "min" else F.max)("value").over(w)
    ratio = scores.withColumn("ratio", F.col("value") / best)
    near = (lambda t: F.col("ratio") <= t) if better == "min" else (lambda t: F.col("ratio") >= t)
    grid = ratio.withColumn("tau", F.explode(F.array(*[F.lit(float(t)) for t in taus])))
    return grid.groupBy("metric", "algo", "tau").agg(F.avg(F.when(near(F.col("tau")), 1.0).otherwise(0.0)).alias("share"))


def within(scores: DataFrame, a: str, b: str, share: float) -> DataFrame:
    """One row: on how many instances a's value is at least 1 - share of b's."""
    near = F.col("x") >= (1 - share) * F.col("y")
    return _pair(scores, a, b).agg(F.count("*").alias("instances"), F.count_if(near).alias("within"), F.avg(F.when(near, 1.0).otherwise(0.0)).alias("share"))


def box_summary(scores: DataFrame) -> DataFrame:
    """Five numbers per algo and metric."""
    q = [F.percentile("value", p).alias(n) for n, p in (("low", 0.0), ("q1", 0.25), ("mid", 0.5), ("q3", 0.75), ("high", 1.0))]
    return scores.groupBy("algo", "metric").agg(*q, F.count("value").alias("runs"))
