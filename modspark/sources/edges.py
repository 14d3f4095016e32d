"""Edge lists from files of several formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

_LAYOUT = "a string, b string, w long"


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = ",") -> DataFrame:
    """a, b, w. csv and tsv without a header, json lines, orc, parquet; a missing weight is 1."""
    if fmt in ("csv", "tsv"):
        df = spark.read.schema(_LAYOUT).option("sep", "\t" if fmt == "tsv" else sep).csv(path)
    elif fmt == "json":
        df = spark.read.schema(_LAYOUT).json(path)
    elif fmt in ("orc", "parquet"):
        df = spark.read.format(fmt).load(path)
    else:
        raise ValueError(f"no reader for {fmt}")
    return df.fillna({"w": 1}) if "w" in df.columns else df


def write_assign(assign: DataFrame, path: str, fmt: str = "parquet") -> None:
    """A clustering, sorted by node within its parts, so that row groups can be skipped by id."""
    assign.repartitionByRange("id").sortWithinPartitions("id").write.format(fmt).mode("overwrite").save(path)
