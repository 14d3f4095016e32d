"""Column layouts of the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame

ARCS = "src long, dst long, w long"
NODES = "id long, okey string, rank long, deg long, wdeg long, cw long"
ASSIGN = "id long, cid long"
VOLUMES = "cid long, vol long, size long"
QUOTIENT = "ci long, cj long, w long"
QNODES = "cid long, cw long, self_w long, vol long"
POPULATION = "ind int, cid long, lab long"
TRACE = "stage string, round int, active long, moves long, dq double, q double, arcs_read long, stop_reason string"
SCORES = "instance string, algo string, metric string, value double"


def columns(layout: str) -> list[str]:
    return [x.split()[0] for x in layout.split(", ")]


def require(df: DataFrame, layout: str, what: str) -> DataFrame:
    """df reduced to the layout's columns, or a ValueError that names those missing."""
    missing = [c for c in columns(layout) if c not in df.columns]
    if missing:
        raise ValueError(f"{what} lacks {', '.join(missing)}")
    return df.select(*columns(layout))
