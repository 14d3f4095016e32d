"""What the corpus operators share: scratch tables, partition planning, text helpers."""

from __future__ import annotations

import atexit
import math
import os
import tempfile
import uuid
import weakref

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Input bytes that one reduce task should get.
TASK_BYTES = 8 << 20
#: ASCII white space of the word rule ``[^\x20\x09-\x0D]+`` (fixed values).
SPACES = " \t\n\x0b\x0c\r"

_made: list[tuple[weakref.ref, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; where it is unset and all run in one process (tests), a local one."""
    got = spark.conf.get("spark.checkpoint.dir", None)
    if not got:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("spark.checkpoint.dir is unset: executors of a cluster need a folder that all of them see")
        got = "file://" + os.path.join(tempfile.gettempdir(), f"modspark-{os.getpid()}")
    return got.rstrip("/")


def _clear(ref, path):
    spark = ref()
    try:
        if spark is None or spark.sparkContext._jsc is None:
            return
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session is ending; the folder belongs to it
        pass


@atexit.register
def _clear_all():
    for ref, path in _made:
        _clear(ref, path)


def drop_scratch(spark: SparkSession, *frames: DataFrame) -> None:
    """Deletes scratch tables that no later step reads."""
    for df in frames:
        path = getattr(df, "_scratch_path", None)
        if path:
            _clear(weakref.ref(spark), path)


def scratch_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_folder(spark)}/modspark-{name}-{uuid.uuid4().hex}"
    _made.append((weakref.ref(spark), path))
    return path


def keep(df: DataFrame, name: str) -> DataFrame:
    """Writes df as a Parquet table in the shared folder and reads it again: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def input_bytes(df: DataFrame) -> int:
    """Bytes of df's files by the planner's statistics; of frames without files, by a count."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if size > 1 << 60:
        size = 256 * df.count()
    return size


def task_count(df: DataFrame, least: int = 1, task_bytes: int = TASK_BYTES) -> int:
    """Reduce tasks for df: grows with the input, so that a task's share doesn't."""
    return max(least, math.ceil(input_bytes(df) / task_bytes))


def whole_text(df: DataFrame, text_col: str = "text"):
    """The text column with null as empty."""
    return F.coalesce(F.col(text_col), F.lit(""))


def id_and_gone(id_col: str = "doc_id") -> list:
    """The id and whether it is null, as columns without nulls: pandas would turn an id column with nulls into floats."""
    return [F.coalesce(F.col(id_col).cast("long"), F.lit(0)).alias("doc_id"), F.col(id_col).cast("long").isNull().alias("gone")]


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like these that df doesn't have, in any case of letters."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def frame(rows: list[tuple], schema: str) -> pd.DataFrame:
    """rows as pandas; whole numbers stay whole where there are nulls among them."""
    columns = list(zip(*rows, strict=True)) or [()] * len(schema.split(", "))
    out = {}
    for (name, kind), values in zip((x.split() for x in schema.split(", ")), columns, strict=True):
        out[name] = pd.array(list(values), dtype="Int64") if kind in ("long", "int") else list(values)
    return pd.DataFrame(out)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
