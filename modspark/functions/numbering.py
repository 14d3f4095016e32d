"""Numbers in a global order without a single-task sort: of rows, and of lines of text that lies in several files."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import io


def ranked(df: DataFrame, order: list[Column], out: str) -> DataFrame:
    """df with its rows' places (from 0) in the given total order: dealt out by ranges, sorted range by range, and moved on by the sizes of
    the ranges before (one short row per task on the driver)."""
    placed = io.settle(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("placed_at", F.monotonically_increasing_id()), "ranked")
    part = F.shiftright("placed_at", 33)
    sizes = sorted((r["part"], r["n"]) for r in placed.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    base, begins = 0, []
    for p, n in sizes:
        begins.append((p, base))
        base += n
    told = df.sparkSession.createDataFrame(begins, "placed_part long, placed_base long")
    inside = F.col("placed_at").bitwiseAND(F.lit((1 << 33) - 1))
    joined = placed.withColumn("placed_part", part).join(F.broadcast(told), "placed_part")
    return joined.withColumn(out, F.col("placed_base") + inside).select(*[c for c in df.columns if c != out], out)


def numbered_lines(spark: SparkSession, path: str) -> DataFrame:
    """line (from 0, over all files by name), value. Offsets of files come from their counts; within a file, from the block and row order."""
    raw = spark.read.text(path).select("value", F.col("_metadata.file_name").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("at"))
    sizes = raw.groupBy("file").agg(F.count("*").alias("n"))
    base = sizes.withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("file", "base")
    inside = raw.withColumn("k", F.row_number().over(Window.partitionBy("file").orderBy("block", "at")) - 1)
    return inside.join(F.broadcast(base), "file").select((F.col("base") + F.col("k")).alias("line"), "value")
