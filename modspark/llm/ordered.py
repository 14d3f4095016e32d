"""Rows in ascending id order over many tasks, with the row after each.

Spark's range partitioner deals the rows out (its sample on the driver is bounded by the number of tasks), each task sorts
its own. A task works on its rows in order; what stands at its two ends is handed over as a row of its own, and the ends
of neighbouring tasks are joined afterwards.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common


def in_order(docs: DataFrame, *order: str) -> DataFrame:
    """docs dealt out by ranges of the first column and sorted by all of them; nulls first."""
    parts = common.task_count(docs, least=2)
    return docs.repartitionByRange(parts, order[0]).sortWithinPartitions(*order)


def next_part(parts: DataFrame) -> DataFrame:
    """part, before: for each non-empty task the one before it; one row per task, without texts."""
    return parts.withColumn("before", F.lag("part").over(Window.orderBy("part")))
