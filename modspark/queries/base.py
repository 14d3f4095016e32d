"""Registration of queries, and the graphs that they share within a session."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prep import Graph, normalise_graph
from ..sources import graphs, synth

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_held: dict[tuple, Graph] = {}


def query(name: str, sql: str | None = None):
    """Registers fn(spark, sf_dir) under name, with its SQL if it has one."""

    def keep(fn):
        if name in QUERIES:
            raise ValueError(f"two queries are named {name}")
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn

    return keep


def graph(spark: SparkSession, sf_dir: str, name: str, unit: bool = True, **how) -> Graph:
    """A built graph; the same tables are used again within a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name, unit, tuple(sorted(how.items())))
    if key not in _held:
        if name == "T":
            rows = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (3, 5), (4, 5)]
            _held[key] = normalise_graph(spark.createDataFrame(rows, "a long, b long"), unit=unit)
        elif name in synth.SYNTH:
            _held[key] = normalise_graph(synth.SYNTH[name](spark, **how), unit=unit)
        elif name == "G1w":
            _held[key] = normalise_graph(graphs.copurchase_parts(spark, sf_dir, 2), unit=unit)
        else:
            _held[key] = graphs.build(spark, sf_dir, name, unit, **how)
    return _held[key]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mod_assign(g: Graph, k: int) -> DataFrame:
    """A fixed clustering: ids by remainder."""
    return g.nodes.select("id", F.pmod("id", F.lit(k)).alias("cid"))


def r6(c, name: str):
    """A double at six digits, as the SQL side rounds it."""
    return F.round(c.cast("double") if hasattr(c, "cast") else F.col(c).cast("double"), 6).alias(name)
