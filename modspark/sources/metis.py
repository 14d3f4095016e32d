"""METIS graph text: the first line holds nodes and edges, line i the neighbours of node i, numbered from 1."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prep import Graph, node_table


def write_metis(graph: Graph, path: str) -> None:
    """A folder of text parts in node order, the header first. Range-partitioned by node: no task sees the whole graph."""
    m = graph.arcs.where("src < dst").count()
    head = graph.nodes.agg(F.count("*").alias("n")).select(F.lit(-1).cast("long").alias("id"), F.concat_ws(" ", "n", F.lit(m)).alias("value"))
    lists = graph.arcs.groupBy(F.col("src").alias("id")).agg(F.concat_ws(" ", F.array_sort(F.collect_list(F.col("dst") + 1))).alias("line"))
    lines = graph.nodes.select("id").join(lists, "id", "left").select("id", F.coalesce("line", F.lit("")).alias("value"))
    head.union(lines).repartitionByRange("id").sortWithinPartitions("id").select("value").write.text(path)


def read_metis(spark: SparkSession, path: str) -> DataFrame:
    """arcs (src, dst, w). Lines get their numbers from their part and place: parts are read whole, in order, one per task."""
    from ..functions.numbering import numbered_lines

    lines = numbered_lines(spark, path)
    body = lines.where("line > 0").select((F.col("line") - 1).alias("src"), F.explode(F.filter(F.split("value", " "), lambda x: x != "")).alias("d"))
    return body.select("src", (F.col("d").cast("long") - 1).alias("dst"), F.lit(1).cast("long").alias("w"))


def graph_of(arcs: DataFrame) -> Graph:
    return Graph(arcs, node_table(arcs))
