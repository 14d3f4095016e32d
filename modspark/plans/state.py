"""Snapshots of a run: saved in numbered folders, resumed from the last complete one."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession


def save(path: str, number: int, **tables: DataFrame) -> None:
    """Tables of one step; the mark that makes the step complete is written last."""
    spark = next(iter(tables.values())).sparkSession
    for name, df in tables.items():
        df.write.mode("overwrite").parquet(f"{path}/step={number}/{name}")
    spark.createDataFrame([(number, json.dumps(sorted(tables)))], "step int, tables string").coalesce(1).write.mode("append").json(f"{path}/marks")


def resume(spark: SparkSession, path: str) -> tuple[int, dict[str, DataFrame]]:
    """The last complete step and its tables; (-1, {}) where there is none."""
    try:
        last = spark.read.schema("step int, tables string").json(f"{path}/marks").orderBy("step", ascending=False).first()
    except Exception as e:
        if "PATH_NOT_FOUND" in str(e):
            return -1, {}
        raise
    return (-1, {}) if last is None else (last["step"], {t: spark.read.parquet(f"{path}/step={last['step']}/{t}") for t in json.loads(last["tables"])})
