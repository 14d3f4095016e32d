"""Graphs from the given tables: each builder gives raw edges (a, b[, w]); prep.normalise_graph makes a graph of them."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import io
from ..operators.prep import Graph, dense_ids, normalise_graph


def _t(spark, sf_dir, name):
    return io.load(spark, sf_dir, name)


def copurchase_parts(spark: SparkSession, sf_dir: str, min_w: int = 1) -> DataFrame:
    """Parts that stand in one order; weight: orders shared. Orders are short, so their pairs are few."""
    l = _t(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()  # noqa: E741
    other = l.select("l_orderkey", F.col("l_partkey").alias("b"))
    pairs = l.join(other, "l_orderkey").where("l_partkey < b").groupBy(F.col("l_partkey").alias("a"), "b").agg(F.count("*").alias("w"))
    return pairs.where(F.col("w") >= min_w)


def customer_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    l = _t(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")  # noqa: E741
    return o.join(l, F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.concat(F.lit("c"), "o_custkey").alias("a"), F.concat(F.lit("s"), "l_suppkey").alias("b")).agg(F.count("*").alias("w"))


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """region - nation - customer and supplier: a tree per region. Keys begin with a, b, c, d: the tree's upper levels are streamed first."""
    k = lambda p, c: F.concat(F.lit(p), F.col(c).cast("string"))
    n = _t(spark, sf_dir, "nation").select(k("b", "n_nationkey").alias("a"), k("a", "n_regionkey").alias("b"))
    c = _t(spark, sf_dir, "customer").select(k("b", "c_nationkey").alias("a"), k("c", "c_custkey").alias("b"))
    s = _t(spark, sf_dir, "supplier").select(k("b", "s_nationkey").alias("a"), k("d", "s_suppkey").alias("b"))
    return n.union(c).union(s)


def geo_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """okey, label: the nation of customers and suppliers."""
    c = _t(spark, sf_dir, "customer").select(F.concat(F.lit("c"), "c_custkey").alias("okey"), F.col("c_nationkey").cast("string").alias("label"))
    s = _t(spark, sf_dir, "supplier").select(F.concat(F.lit("d"), "s_suppkey").alias("okey"), F.col("s_nationkey").cast("string").alias("label"))
    return c.union(s)


def user_windows(spark: SparkSession, sf_dir: str, seconds: int = 300) -> DataFrame:
    """user_id, win: windows of time in which a user has events, each once."""
    e = _t(spark, sf_dir, "events").select("user_id", F.floor(F.unix_timestamp("ts") / seconds).alias("win"))
    return e.where("user_id is not null and win is not null").distinct()


def user_coactivity(spark: SparkSession, sf_dir: str, seconds: int = 300, min_w: int = 1) -> DataFrame:
    """Users with events in the same window of time; weight: windows shared."""
    e = io.settle(user_windows(spark, sf_dir, seconds), "windows")
    return shared_counts(e.select("win", F.col("user_id").alias("item"))).where(F.col("w") >= min_w)


def user_coactivity_edges(spark: SparkSession, sf_dir: str, seconds: int = 300) -> DataFrame:
    """u < v, w: the same on the graph's ids, as its arcs have them. Users are numbered before they are paired, so that no table of pairs is made."""
    e = io.settle(user_windows(spark, sf_dir, seconds), "windows")
    met = e.join(e.groupBy("win").agg(F.count("*").alias("n")).where("n > 1").select("win"), "win", "left_semi")
    ids = dense_ids(met.select(F.col("user_id").alias("okey")).distinct())
    mine = io.settle(met.join(ids.withColumnRenamed("okey", "user_id"), "user_id").select("win", F.col("id").alias("item")), "windows")
    return shared_counts(mine).select(F.col("a").alias("u"), F.col("b").alias("v"), "w")


def shared_counts(e: DataFrame, task_pairs: int = 2_000_000) -> DataFrame:
    """a < b, w: items that stand in the same wins, and in how many. e: (win, item), whole numbers, each once, without nulls.

    Pairs are counted in the task that makes them, and never shuffled or written: items are dealt to blocks, and the wins' items of each pair
    of blocks meet in one task. There are as many blocks as give a task some task_pairs pairs, before those of several wins merge.
    """
    n = F.col("n").cast("double")
    total = e.groupBy("win").agg(F.count("*").alias("n")).agg(F.sum(n * (n - 1) / 2)).first()[0] or 0.0
    blocks = max(1, math.ceil((2 * total / task_pairs) ** 0.5))
    packed = e.groupBy(F.pmod(F.xxhash64("item"), F.lit(blocks)).cast("int").alias("block"), "win").agg(F.collect_list("item").alias("items"))
    left = packed.select(F.explode(F.sequence(F.col("block"), F.lit(blocks - 1))).alias("j"), F.col("block").alias("i"), F.lit(0).alias("side"), "win", "items")
    right = packed.select(F.col("block").alias("j"), F.explode(F.sequence(F.lit(0), F.col("block"))).alias("i"), F.lit(1).alias("side"), "win", "items")
    both = left.union(right).select((F.col("i").cast("long") * blocks + F.col("j")).alias("at"), "side", "win", "items")

    def count(key: tuple, t: pa.Table) -> pa.Table:
        at = key[0].as_py()
        a, b, w = _count_pairs(*(t.filter(pc.equal(t["side"], side)) for side in (0, 1)), at // blocks == at % blocks, task_pairs)
        return pa.table({"a": a, "b": b, "w": w})

    # grouped as it is dealt: no further exchange
    return both.repartition(blocks * (blocks + 1) // 2, "at").groupBy("at").applyInArrow(count, "a long, b long, w long")


def _count_pairs(left: pa.Table, right: pa.Table, own: bool, chunk: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """a < b, w of the pairs that lists (win, items) of left and right with the same win make. own: both have the same items. Goes through the
    left items in order, so that a chunk of pairs holds all of its items' pairs."""

    def lists(t):
        items = t["items"].combine_chunks()
        items = items if isinstance(items, pa.ListArray) else pa.concat_arrays(items.chunks)
        size = pc.list_value_length(items).to_numpy(zero_copy_only=False).astype(np.int64)
        return t["win"].to_numpy(), size, items.flatten().to_numpy(zero_copy_only=False)

    out = [(np.empty(0, np.int64),) * 3]
    if left.num_rows and right.num_rows:
        (lw, ln, x), (rw, rn, y) = lists(left), lists(right)
        by = rw.argsort()
        place = np.minimum(np.searchsorted(rw, lw, sorter=by), len(rw) - 1)
        other = by[place]
        n = np.repeat(np.where(rw[other] == lw, rn[other], 0), ln)
        begin = np.repeat((rn.cumsum() - rn)[other], ln)
        by = x.argsort(kind="stable")
        x, n, begin = x[by], n[by], begin[by]
        names, y = np.unique(y, return_inverse=True)
        firsts = np.flatnonzero(np.r_[True, x[1:] != x[:-1]])
        upto = n.cumsum()
        before = (upto - n)[firsts]
        k = 0
        while k < len(firsts):
            k2 = max(k + 1, int(np.searchsorted(before, before[k] + chunk)))
            s, t = firsts[k], firsts[k2] if k2 < len(firsts) else len(x)
            c, own_x = n[s:t], x[firsts[k:k2]]
            at = np.arange(c.sum()) + np.repeat(begin[s:t] - (c.cumsum() - c), c)
            code = np.repeat(np.searchsorted(own_x, x[s:t]), c) * len(names) + y[at]
            if len(own_x) * len(names) <= 8 * len(code):
                w = np.bincount(code)
                code = np.flatnonzero(w)
                w = w[code]
            else:
                code, w = np.unique(code, return_counts=True)
            p, q = own_x[code // len(names)], names[code % len(names)]
            keep = p < q if own else slice(None)
            out.append((np.minimum(p, q)[keep], np.maximum(p, q)[keep], w[keep]))
            k = k2
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _shingles(df: DataFrame, key: str, words: int) -> DataFrame:
    """key, g: distinct word shingles."""
    w = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+", -1), lambda x: x != "")
    s = df.select(key, w.alias("w")).where(F.size("w") >= words)
    made = s.select(key, F.expr(f"transform(sequence(1, size(w) - {words - 1}), i -> array_join(slice(w, i, {words}), ' '))").alias("g"))
    return made.select(key, F.explode(F.array_distinct("g")).alias("g"))


def doc_shingle_graph(spark: SparkSession, sf_dir: str, words: int = 5, df_limit: int = 100, min_jaccard: float = 0.0) -> DataFrame:
    """Documents that share word shingles of at most df_limit documents; weight: shingles shared."""
    s = _shingles(_t(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", words).withColumn("h", F.xxhash64("g")).drop("g")
    df = s.groupBy("h").agg(F.count("*").alias("df")).where((F.col("df") > 1) & (F.col("df") <= df_limit)).select("h")
    rare = s.join(df, "h")
    pairs = rare.join(rare.select("h", F.col("doc_id").alias("b")), "h").where("doc_id < b").groupBy(F.col("doc_id").alias("a"), "b").agg(F.count("*").alias("w"))
    if min_jaccard <= 0:
        return pairs
    n = s.groupBy("doc_id").agg(F.count("*").alias("n"))
    full = pairs.join(n.select(F.col("doc_id").alias("a"), F.col("n").alias("na")), "a").join(n.select(F.col("doc_id").alias("b"), F.col("n").alias("nb")), "b")
    return full.where(F.col("w") / (F.col("na") + F.col("nb") - F.col("w")) >= min_jaccard).select("a", "b", "w")


def page_link_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the targets of their links."""
    p = _t(spark, sf_dir, "pages").select("page_id", "html")
    return p.select(F.concat(F.lit("p"), "page_id").alias("a"), F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("t")).select("a", F.concat(F.lit("t"), "t").alias("b")).distinct()


def embedding_knn(spark: SparkSession, sf_dir: str, k: int = 10, block: int = 512) -> DataFrame:
    """Each vector and its k nearest by cosine; ties to the lesser id. Components are rounded to four digits, so products are exact.

    All pairs of blocks are compared, a block pair per group; only k rows per vector and block leave a group.
    """
    import pandas as pd

    e = _t(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 10000).cast("int")).alias("v"))
    n = e.count()
    parts = max(1, -(-n // block))
    home = e.withColumn("home", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int"))
    grid = F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("other")
    left = home.select("vec_id", "v", F.col("home").alias("i"), grid).select("vec_id", "v", "i", F.col("other").alias("j"), F.lit(0).alias("side"))
    right = home.select("vec_id", "v", F.col("home").alias("j"), grid).select("vec_id", "v", F.col("other").alias("i"), "j", F.lit(1).alias("side"))

    def near(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = pdf[pdf["side"] == 0], pdf[pdf["side"] == 1].sort_values("vec_id")
        if not len(a) or not len(b):
            return pd.DataFrame({"a": [], "b": [], "s": []}).astype("int64")
        va, vb = np.stack(a["v"].to_numpy()).astype(np.float64), np.stack(b["v"].to_numpy()).astype(np.float64)
        s = np.rint(va @ vb.T).astype(np.int64)  # whole numbers below 2**53: exact in floating point
        ia, ib = a["vec_id"].to_numpy(), b["vec_id"].to_numpy()
        s[ia[:, None] == ib[None, :]] = np.iinfo(np.int64).min
        top = np.argsort(-s, axis=1, kind="stable")[:, : k + 1]
        rows = np.repeat(np.arange(len(ia)), top.shape[1])
        out = pd.DataFrame({"a": ia[rows], "b": ib[top.ravel()], "s": s[rows, top.ravel()]})
        return out[out["a"] != out["b"]]

    got = left.unionByName(right).groupBy("i", "j").applyInPandas(near, "a long, b long, s long")
    best = got.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.col("s").desc(), "b"))).where(F.col("r") <= k)
    return best.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def conversation_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn and the next one of its conversation."""
    c = _t(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    nxt = c.withColumn("n", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).where("n is not null")
    return nxt.select((F.col("conv_id") * 1000 + F.col("turn")).alias("a"), (F.col("conv_id") * 1000 + F.col("n")).alias("b"))


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    l = _t(spark, sf_dir, "lineitem")  # noqa: E741
    return l.select(F.concat(F.lit("o"), "l_orderkey").alias("a"), F.concat(F.lit("p"), "l_partkey").alias("b")).distinct()


def doc_benchmark(spark: SparkSession, sf_dir: str, words: int = 5) -> DataFrame:
    """Documents and the benchmark items that they share word shingles with; weight: shingles shared."""
    d = _shingles(_t(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", words)
    b = _shingles(_t(spark, sf_dir, "benchmark").select("item_id", "text"), "item_id", words)
    return d.join(b, "g").groupBy(F.concat(F.lit("d"), "doc_id").alias("a"), F.concat(F.lit("b"), "item_id").alias("b")).agg(F.count("*").alias("w"))


BUILDERS = {
    "G1": copurchase_parts, "G2": customer_supplier, "G3": geo_tree, "G4": user_coactivity, "G5": doc_shingle_graph, "G6": page_link_graph,
    "G7": embedding_knn, "G8": conversation_chain, "G9": order_part, "G10": doc_benchmark,
}


def build(spark: SparkSession, sf_dir: str, name: str, unit: bool = True, **how) -> Graph:
    return normalise_graph(BUILDERS[name](spark, sf_dir, **how), unit=unit)


def truth(spark: SparkSession, sf_dir: str, name: str, graph: Graph) -> DataFrame | None:
    """id, label of the nodes that have one."""
    if name == "G3":
        t = geo_truth(spark, sf_dir)
    elif name in ("G5",):
        t = _t(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("okey"), F.col("lang").alias("label"))
    elif name == "G8":
        return graph.nodes.select("id", F.floor(F.col("okey").cast("long") / 1000).cast("string").alias("label"))
    elif name == "G7":
        t = _t(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("okey"), F.col("label").cast("string").alias("label"))
    elif name == "G1":
        t = _t(spark, sf_dir, "part").select(F.col("p_partkey").cast("string").alias("okey"), F.col("p_brand").alias("label"))
    else:
        return None
    return graph.nodes.select("id", "okey").join(t, "okey").select("id", "label")
