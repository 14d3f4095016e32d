"""Scores from a given table, to test the methodology on: of every part, the mean quantity of its lines as a share of the greatest.

An instance is a part, an algo a kind of lines; a part without lines of a kind is a failed run of it, a null.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import table

#: Algo and its lines, as SQL of either side. Quantities are whole numbers up to 50, so sums are exact in any order.
KINDS = (
    ("all", "true"), ("returned", "l_returnflag = 'R'"), ("accepted", "l_returnflag = 'A'"), ("open", "l_linestatus = 'O'"),
    ("filled", "l_linestatus = 'F'"), ("taxed", "l_tax >= 0.08"), ("undiscounted", "l_discount = 0"),
)
ALGOS = tuple(algo for algo, _ in KINDS)
METRIC = "quantity share"


def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    wide = l.groupBy(F.col("l_partkey").alias("instance")).agg(*[(F.avg(F.when(F.expr(lines), F.col("l_quantity"))) / 50).alias(algo) for algo, lines in KINDS])
    each = F.explode(F.array(*[F.struct(F.lit(algo).alias("algo"), F.lit(METRIC).alias("metric"), F.col(algo).alias("value")) for algo in ALGOS]))
    return wide.select("instance", each.alias("s")).select("instance", "s.*")


def scores_sql() -> str:
    shares = ", ".join(f"avg(l_quantity) FILTER (WHERE {lines}) / 50" for _, lines in KINDS)
    return f"SELECT instance, unnest({list(ALGOS)}) AS algo, '{METRIC}' AS metric, unnest(v) AS value FROM (SELECT l_partkey AS instance, [{shares}] AS v FROM lineitem GROUP BY 1)"
