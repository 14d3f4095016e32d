"""Tables in and out, and cutting the lineage of loops."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_made: dict[str, weakref.ref] = {}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset and all run in one process (tests), a local folder."""
    got = spark.conf.get("spark.checkpoint.dir", None)
    if not got and not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
        raise ValueError("spark.checkpoint.dir is unset: executors of a cluster need a folder that all of them see")
    return (got or "file://" + os.path.join(tempfile.gettempdir(), f"modspark-{os.getpid()}")).rstrip("/")


def settle_counted(df: DataFrame, name: str = "state") -> tuple[DataFrame, int]:
    """settle(), and the number of rows, observed while they are written."""
    seen = Observation()
    return settle(df.observe(seen, F.count(F.lit(1)).alias("n")), name), int(seen.get["n"])


def settle(df: DataFrame, name: str = "state", *folders: str) -> DataFrame:
    """df written to the shared folder and read again: the plan of a loop's next round begins at files, and lost executors cost nothing.

    folders: columns whose values get directories of their own, so that a filter on them reads these alone. drop() deletes the table;
    what is left of them goes at the end of the process.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/modspark-{name}-{uuid.uuid4().hex}"
    _made[path] = weakref.ref(spark)
    (df.repartition(*folders) if folders else df).write.partitionBy(*folders).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._settled = path
    return out


def drop(*frames: DataFrame) -> None:
    """Deletes the tables of frames that settle() returned; other frames are left alone. Nothing may read them any more."""
    for df in frames:
        path = getattr(df, "_settled", None)
        if path in _made:
            _delete(path, _made.pop(path))


def _delete(path: str, ref: weakref.ref) -> None:
    spark = ref()
    try:
        if spark is not None and spark.sparkContext._jsc is not None:
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session has ended; its folder goes with it
        pass


@atexit.register
def _delete_all() -> None:
    for path, ref in _made.items():
        _delete(path, ref)
