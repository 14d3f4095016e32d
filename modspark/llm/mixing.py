"""Mixing sources to target weights by pivotal dependent rounding.

Each source gets a target size; a document's expected number of copies is its source's target over its source's size. The whole
part of it is taken for certain. The fractional parts are rounded against one another: two documents of a source meet, and mass
moves between them at random, keeping the sum of size times probability and each expectation, until one of them is taken or
left. So a source's total misses its target by less than one document. Leaves of at most LEAF rows round their own rows; what
a leaf cannot decide (one document) goes up a tree of FAN-fold nodes.

Defined results: null and empty texts have size 0 and are taken 0 words; a null source is a source of its own and comes last;
repeated rows are documents of their own, told apart by a number within their id, size and source; with nothing of any size all
targets are 0; an empty table gives an empty result. The same input gives the same result however it is partitioned.
"""

from __future__ import annotations

import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Weights of the sources in order, repeating; copies that a document gets at most.
WEIGHTS, MOST_COPIES = (5, 2, 1), 3
#: Sources up to which their targets are broadcast (a hundred bytes each).
MOST_BROADCAST = 50_000
#: Rows that a leaf of the tree has on average, and leaves or nodes that meet in one node.
LEAF, FAN = 4096, 16

_SPACE = r"[\x20\x09-\x0D]"


def word_count(text_col: str = "text"):
    """Column: runs of characters other than ASCII white space; null as 0."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lead = text.rlike(f"^{_SPACE}").cast("long")
    trail = text.rlike(rf"{_SPACE}\z").cast("long")
    cuts = F.size(F.split(text, f"{_SPACE}+", -1)).cast("long")
    return F.when(F.length(text) == 0, 0).otherwise(F.greatest(cuts - lead - trail, F.lit(0))).cast("long")


def row_print(id_col: str = "doc_id", text_col: str = "text", source_col: str = "source"):
    """Column: equal for rows that agree in id, source and text alone."""
    return F.xxhash64(F.col(id_col), F.col(id_col).isNull(), F.col(source_col), F.col(source_col).isNull(), F.col(text_col), F.col(text_col).isNull())


def target_sizes(sizes: dict, weights: tuple = WEIGHTS, most: float = MOST_COPIES) -> dict:
    """source -> target. The sum of all sizes is shared by weight; what exceeds most times a source's size is shared again
    among the others, until none exceeds. sizes: source (None last) -> size."""
    order = sorted(sizes, key=lambda s: (s is None, s))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    total, fixed = float(sum(sizes.values())), {}
    while True:
        rest, free = total - sum(fixed.values()), [s for s in order if s not in fixed]
        shared = sum(weight[s] for s in free)
        out = {s: rest * weight[s] / shared for s in free} if free else {}
        over = [s for s in free if out[s] > most * sizes[s]]
        if not over:
            return fixed | out
        fixed |= {s: float(most * sizes[s]) for s in over}


def _draw(seed: int, *parts) -> float:
    return xxhash.xxh3_64_intdigest("\0".join(map(str, parts)).encode(), seed) / 2.0**64


def round_pair(p: float, a: float, q: float, b: float, u: float) -> tuple[float, float]:
    """Moves mass between probabilities p and q of sizes a and b until one is 0 or 1; u is uniform.

    size times probability keeps its sum, and both expectations hold.
    """
    up = min((1 - p) * a, q * b)  # size that can move from q to p
    down = min(p * a, (1 - q) * b)
    if u * (up + down) < down:
        p, q = (1.0, q - up / b) if (1 - p) * a <= q * b else (p + up / a, 0.0)
    else:
        p, q = (0.0, q + down / b) if p * a <= (1 - q) * b else (p - down / a, 1.0)
    return p, q


ITEMS = "key string, source string, size long, whole long, p double, node long"
DECIDED = "key string, source string, size long, taken long, p double, whole long, node long"


def _settle(rows: list[tuple], seed: int, level: int) -> list[tuple]:
    """Rows in the given order: all but at most one are decided; p stays set on that one."""
    out, held = [], None
    for key, source, size, whole, p, node in rows:
        if p <= 1e-12 or p >= 1 - 1e-12 or size == 0:
            out.append((key, source, size, size * (whole + round(p)) if size else 0, None, whole, node))
            continue
        if held is None:
            held = (key, source, size, whole, p, node)
            continue
        k0, _, s0, w0, p0, _ = held
        p0, p1 = round_pair(p0, s0, p, size, _draw(seed, level, k0, key))
        pair = [(k0, source, s0, w0, p0, node), (key, source, size, whole, p1, node)]
        held = None
        for x in pair:
            if 1e-12 < x[4] < 1 - 1e-12:
                held = x
            else:
                out.append((x[0], x[1], x[2], x[2] * (x[3] + round(x[4])), None, x[3], x[5]))
    if held is not None:
        out.append((held[0], held[1], held[2], None, held[4], held[3], held[5]))
    return out


def mix(docs: DataFrame, weights: tuple = WEIGHTS, most: float = MOST_COPIES, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, print, size, source_size, target, copies (expected), taken of every row."""
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(text_col).alias("size"), row_print(id_col, text_col, source_col).alias("print"))
    sized = common.keep(src, "sizes")
    # one short row per source on the driver: sources are few by their nature, each weighted by hand
    per_source = [(r["source"], int(r["size"]), int(r["n"])) for r in sized.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("n")).collect()]
    sizes = {s: n for s, n, _ in per_source}
    targets = target_sizes(sizes, weights, most)
    leaves = {s: max(1, -(-n // LEAF)) for s, _, n in per_source}
    spark = docs.sparkSession
    told = spark.createDataFrame([(s, sizes[s], targets[s], targets[s] / sizes[s] if sizes[s] else 0.0, leaves[s]) for s in sizes], "source string, source_size long, target double, copies double, leaves long")
    if len(sizes) <= MOST_BROADCAST:
        told = F.broadcast(told)
    # repeated rows are counted, then told apart by a number: no task gets a group of them as rows
    alike = sized.groupBy("doc_id", "source", "size", "print").agg(F.count("*").alias("times"))
    numbered = alike.withColumn("number", F.explode(F.sequence(F.lit(1).cast("long"), F.col("times")))).drop("times")
    columns = [F.col(f"d.{c}") for c in numbered.columns]
    keyed = numbered.alias("d").join(told.alias("t"), F.col("d.source").eqNullSafe(F.col("t.source"))).select(*columns, "source_size", "target", "copies", "leaves")
    keyed = keyed.withColumn("key", F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.hex("print"), F.col("number")))
    whole = F.floor("copies").cast("long")
    items = keyed.select("key", "source", "size", whole.alias("whole"), (F.col("copies") - F.floor("copies")).alias("p"), F.pmod(F.xxhash64("key", F.lit(seed)), F.col("leaves")).alias("node"))

    def node(level):
        def settle(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values(["size", "key"], ascending=[False, True])  # what stays open is a short document then
            rows = list(zip(pdf["key"], [None if pd.isna(x) else x for x in pdf["source"]], pdf["size"].tolist(), pdf["whole"].tolist(), pdf["p"].tolist(), pdf["node"].tolist(), strict=True))
            return common.frame(_settle(rows, seed, level), DECIDED)

        return settle

    done, level = common.keep(items.groupBy("source", "node").applyInPandas(node(0), DECIDED), "leaves"), 0
    decided = [done.where("p is null")]
    open_, most_leaves = done.where("p is not null"), max(leaves.values(), default=1)
    while most_leaves > 1:
        level, most_leaves = level + 1, -(-most_leaves // FAN)
        up = open_.select("key", "source", "size", "whole", "p", F.floor(F.col("node") / FAN).cast("long").alias("node"))
        done = common.keep(up.groupBy("source", "node").applyInPandas(node(level), DECIDED), f"nodes{level}")
        decided.append(done.where("p is null"))
        open_ = done.where("p is not null")
    drawn = F.pmod(F.xxhash64("key", F.lit(seed), F.lit("last")), F.lit(1 << 40)) / float(1 << 40)  # at most one row per source
    decided.append(open_.withColumn("taken", F.col("size") * (F.col("whole") + F.when(drawn < F.col("p"), 1).otherwise(0))))
    taken = decided[0].select("key", F.col("taken"))
    for x in decided[1:]:
        taken = taken.unionByName(x.select("key", "taken"))
    return keyed.join(taken, "key").select("doc_id", "source", "print", "size", "source_size", "target", "copies", "taken")


def repeat(docs: DataFrame, **how) -> DataFrame:
    """docs with each row as often as the mix takes it; rows of no size are not taken. Equal rows stand for one another."""
    same, times, own, copy, of = common.fresh(docs, "print", "times", "print", "copy", "of")
    id_col = how.get("id_col", "doc_id")
    n = F.coalesce(F.try_divide("taken", "size").cast("int"), F.lit(0))
    wanted = mix(docs, **how).groupBy(F.col("print").alias(same), F.col("doc_id").alias(of)).agg(F.sum(n).cast("int").alias(times)).where(F.col(times) > 0)
    names = {k: how[k] for k in ("id_col", "text_col", "source_col") if k in how}
    one = docs.withColumn(own, row_print(**names)).dropDuplicates([own, id_col])
    joined = one.join(wanted, (F.col(own) == F.col(same)) & F.col(id_col).cast("long").eqNullSafe(F.col(of)))
    return joined.withColumn(copy, F.explode(F.array_repeat(F.lit(1), F.col(times)))).select(*docs.columns)


def op5_pivotal_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(common.documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


