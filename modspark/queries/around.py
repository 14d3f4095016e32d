"""Queries of the operators around the methods: scans, joins, aggregates, windows, functions, formats, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import io
from ..functions import scoring, udf
from ..operators import components, onepass
from ..plans import inspect, state
from ..sources import edges, metis
from ..streaming import streams
from .base import graph, mod_assign, query, r6, table
from .methods import _MOD, _SCORED, _facts, _FACTS
from .linescores import scores, scores_sql
from .sqlgraph import with_graph


def _scratch(spark, name):
    return f"{io.shared_folder(spark)}/modspark-{name}-{uuid.uuid4().hex}"


# --- scans, sinks, formats ---


@query("scan_prune_filter", "SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS qty FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' GROUP BY 1")
def _(spark, sf_dir):
    l = table(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= "1995-01-01") & (F.col("l_shipdate") < "1996-01-01"))  # noqa: E741
    return l.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


@query("scan_partition_prune", "SELECT count(*) AS n, min(l_orderkey) AS lo, max(l_orderkey) AS hi FROM lineitem WHERE l_orderkey % 16 = 3")
def _(spark, sf_dir):
    path = _scratch(spark, "buckets")
    table(spark, sf_dir, "lineitem").select("l_orderkey", F.pmod("l_orderkey", F.lit(16)).cast("int").alias("bucket")).write.partitionBy("bucket").parquet(path)
    return spark.read.parquet(path).where("bucket = 3").agg(F.count("*").alias("n"), F.min("l_orderkey").alias("lo"), F.max("l_orderkey").alias("hi"))


@query("sink_parquet_roundtrip", "SELECT count(*) AS n, round(sum(o_totalprice), 2) AS total, count(DISTINCT o_orderkey) AS keys FROM orders")
def _(spark, sf_dir):
    path = _scratch(spark, "orders")
    table(spark, sf_dir, "orders").write.parquet(path)
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.count_distinct("o_orderkey").alias("keys"))


@query("sink_csv_json_orc_roundtrip", "SELECT f AS format, a, b, w FROM (SELECT 'n' || n_nationkey AS a, 'r' || n_regionkey AS b, CAST(1 AS BIGINT) AS w FROM nation), (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS f)")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "nation").select(F.concat(F.lit("n"), "n_nationkey").alias("a"), F.concat(F.lit("r"), "n_regionkey").alias("b"), F.lit(1).cast("long").alias("w"))
    out = None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = _scratch(spark, fmt)
        e.write.format(fmt).save(path)
        got = edges.read_edges(spark, path, fmt).select(F.lit(fmt).alias("format"), "a", "b", "w")
        out = got if out is None else out.unionByName(got)
    return out


@query("metis_roundtrip", with_graph("G8", "SELECT src, dst, w FROM arcs"))
def _(spark, sf_dir):
    path = _scratch(spark, "metis")
    metis.write_metis(graph(spark, sf_dir, "G8"), path)
    return metis.read_metis(spark, path)


@query("state_save_resume", with_graph("G8", "SELECT 1 AS step, count(*) AS nodes, count(DISTINCT id % 3) AS k FROM nodes"))
def _(spark, sf_dir):
    g, path = graph(spark, sf_dir, "G8"), _scratch(spark, "steps")
    state.save(path, 0, assign=mod_assign(g, 2))
    state.save(path, 1, assign=mod_assign(g, 3))
    step, tables = state.resume(spark, path)
    return tables["assign"].agg(F.count("*").alias("nodes"), F.count_distinct("cid").alias("k")).select(F.lit(step).alias("step"), "nodes", "k")


@query("assign_write_sorted", with_graph("G6", "SELECT id % 7 AS cid, count(*) AS n FROM nodes GROUP BY 1"))
def _(spark, sf_dir):
    path = _scratch(spark, "assign")
    edges.write_assign(mod_assign(graph(spark, sf_dir, "G6"), 7), path)
    return spark.read.parquet(path).groupBy("cid").agg(F.count("*").alias("n"))


# --- filters, joins ---


@query("filter_active_predicate", with_graph("G6", "SELECT src, dst FROM arcs WHERE src IN (SELECT id FROM nodes WHERE deg > 5) AND src BETWEEN 10 AND 400"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    act = g.nodes.where("deg > 5").select(F.col("id").alias("src"))
    return g.arcs.where(F.col("src").between(10, 400)).join(act, "src", "left_semi").select("src", "dst")


@query("project_gain_expression", with_graph("G3", "SELECT src, cid, gain FROM scored", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G3")
    return scoring.scored_candidates(g.arcs, g.nodes, mod_assign(g, 7), g.two_m).select("src", "cid", "gain")


for _key, _hint in (("join_hash_equi", "shuffle_hash"), ("join_sort_merge", "merge")):

    @query(_key, "SELECT c_nationkey, count(*) AS orders, CAST(floor(sum(o_totalprice)) AS BIGINT) AS total FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
    def _(spark, sf_dir, hint=_hint):
        o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
        return o.join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.count("*").alias("orders"), F.floor(F.sum("o_totalprice")).cast("long").alias("total"))


@query("join_broadcast", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def _(spark, sf_dir):
    return table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@query("join_semi_anti", "SELECT 'big' AS kind, count(*) AS n FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50) UNION ALL SELECT 'none', count(*) FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)")
def _(spark, sf_dir):
    p, l = table(spark, sf_dir, "part").select("p_partkey"), table(spark, sf_dir, "lineitem").where("l_quantity >= 50").select(F.col("l_partkey").alias("p_partkey"))  # noqa: E741
    count = lambda how, name: p.join(l, "p_partkey", how).agg(F.count("*").alias("n")).select(F.lit(name).alias("kind"), "n")
    return count("left_semi", "big").union(count("left_anti", "none"))


@query("join_left_outer_unlabelled", "SELECT lang, coalesce(quality, -1) AS quality, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2")
def _(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    return d.groupBy("lang", F.coalesce("quality", F.lit(-1)).alias("quality")).agg(F.count("*").alias("n"))


@query("join_full_outer_diff", with_graph("G6", "SELECT count(*) AS differ FROM (SELECT id, id % 7 AS a FROM nodes WHERE id % 3 <> 0) x FULL JOIN (SELECT id, id % 14 AS b FROM nodes WHERE id % 5 <> 0) y USING (id) WHERE a IS DISTINCT FROM b"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7).where(F.pmod("id", F.lit(3)) != 0).withColumnRenamed("cid", "a")
    b = mod_assign(g, 14).where(F.pmod("id", F.lit(5)) != 0).withColumnRenamed("cid", "b")
    return a.join(b, "id", "full").where(~F.col("a").eqNullSafe(F.col("b"))).agg(F.count("*").alias("differ"))


@query("join_theta_nested_loop", f"WITH s AS ({scores_sql()}) SELECT tau, count(*) AS above FROM s, (SELECT unnest([0.25, 0.5, 0.75]) AS tau) t WHERE value >= tau GROUP BY 1")
def _(spark, sf_dir):
    taus = spark.createDataFrame([(0.25,), (0.5,), (0.75,)], "tau double")
    return scores(spark, sf_dir).join(F.broadcast(taus), F.col("value") >= F.col("tau")).groupBy("tau").agg(F.count("*").alias("above"))


@query("join_range_interval", "SELECT x.event_type AS a, y.event_type AS b, count(*) AS n FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE GROUP BY 1, 2")
def _(spark, sf_dir):
    """Range join through time cells of the interval's width: each event meets its own cell and the next one."""
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_type", F.floor(F.unix_timestamp("ts") / 600).alias("cell"))
    left = e.select("user_id", F.col("ts").alias("t0"), F.col("event_type").alias("a"), F.explode(F.array("cell", F.col("cell") + 1)).alias("cell"))
    near = left.join(e.select("user_id", "cell", F.col("ts").alias("t1"), F.col("event_type").alias("b")), ["user_id", "cell"]).where((F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr("INTERVAL 10 MINUTES")))
    return near.groupBy("a", "b").agg(F.count("*").alias("n"))


@query("join_asof", "SELECT e.event_id, s.event_id AS last_login FROM (SELECT * FROM events WHERE event_type = (SELECT max(event_type) FROM events)) e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = (SELECT min(event_type) FROM events) GROUP BY 1, 2) s ON e.user_id = s.user_id AND e.ts >= s.ts")
def _(spark, sf_dir):
    """As-of join by one sort: both sides in one stream per user, the last snapshot carried forward."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    kinds = e.agg(F.min("event_type").alias("lo"), F.max("event_type").alias("hi")).first()
    snaps = e.where(F.col("event_type") == kinds["lo"]).groupBy("user_id", "ts").agg(F.max("event_id").alias("snap"))
    both = e.where(F.col("event_type") == kinds["hi"]).select("user_id", "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("long").alias("snap")).unionByName(snaps.select("user_id", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), "snap"))
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_login", F.last("snap", ignorenulls=True).over(w)).where("side = 1").select("event_id", "last_login")


@query("join_self_cooccurrence", "SELECT shared, count(*) AS pairs FROM (SELECT x.l_partkey, y.l_partkey, count(*) AS shared FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey GROUP BY 1, 2) GROUP BY 1")
def _(spark, sf_dir):
    return graph(spark, sf_dir, "G1", False).arcs.where("src < dst").groupBy(F.col("w").alias("shared")).agg(F.count("*").alias("pairs"))


# --- aggregates ---


@query("agg_hash_partial_final", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS qty, min(l_partkey) AS lo, max(l_partkey) AS hi, round(avg(l_quantity), 6) AS mean FROM lineitem GROUP BY 1, 2")
def _(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"), F.min("l_partkey").alias("lo"), F.max("l_partkey").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("mean"))


@query("agg_sort_string_min", "SELECT o_custkey, min(o_orderpriority) AS first_priority, max(o_orderstatus) AS last_status FROM orders GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.min("o_orderpriority").alias("first_priority"), F.max("o_orderstatus").alias("last_status"))


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, CAST(sum(DISTINCT l_quantity) AS BIGINT) AS qty FROM lineitem GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps"), F.sum_distinct("l_quantity").cast("long").alias("qty"))


@query("agg_approx_distinct", "SELECT count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem")
def _(spark, sf_dir):
    x = table(spark, sf_dir, "lineitem").agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("about"))
    return x.select("exact", (F.abs(F.col("about") - F.col("exact")) <= 0.1 * F.col("exact")).alias("near"))


_GEO = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(spark, sf_dir):
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


@query("agg_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n {_GEO} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def _(spark, sf_dir):
    _geo(spark, sf_dir).createOrReplaceTempView("geo_rows")
    return spark.sql("SELECT r_name, c_mktsegment, count(*) AS n FROM geo_rows GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")


@query("agg_cube", f"SELECT r_name, c_mktsegment, grouping(r_name) * 2 + grouping(c_mktsegment) AS gid, count(*) AS n {_GEO} GROUP BY CUBE (r_name, c_mktsegment)")
def _(spark, sf_dir):
    return _geo(spark, sf_dir).cube("r_name", "c_mktsegment").agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"))


@query("agg_rollup", f"SELECT r_name, n_name, count(*) AS n {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def _(spark, sf_dir):
    return _geo(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("agg_pivot_scores", f"WITH s AS ({scores_sql()}) SELECT instance, max(value) FILTER (WHERE algo = 'all') AS all_q, max(value) FILTER (WHERE algo = 'returned') AS returned_q, max(value) FILTER (WHERE algo = 'accepted') AS accepted_q FROM s GROUP BY 1")
def _(spark, sf_dir):
    kinds = ["all", "returned", "accepted"]
    p = scores(spark, sf_dir).groupBy("instance").pivot("algo", kinds).max("value")
    return p.select("instance", *[F.col(k).alias(f"{k}_q") for k in kinds])


@query("agg_percentiles", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.25), 4) AS q1, round(median(o_totalprice), 4) AS mid, round(quantile_cont(o_totalprice, 0.9), 4) AS q9 FROM orders GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.25), 4).alias("q1"), F.round(F.median("o_totalprice"), 4).alias("mid"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("q9"))


@query("agg_max_by_argmax", with_graph("G3", "SELECT src, arg_max(dst, (w, -dst)) AS best FROM arcs GROUP BY 1"))
def _(spark, sf_dir):
    return graph(spark, sf_dir, "G3").arcs.groupBy("src").agg(F.max_by("dst", F.struct("w", -F.col("dst"))).alias("best"))


@query("agg_collect_adjacency", with_graph("G6", "SELECT src AS id, string_agg(CAST(dst AS VARCHAR), ' ' ORDER BY dst) AS nbrs FROM arcs GROUP BY 1"))
def _(spark, sf_dir):
    a = graph(spark, sf_dir, "G6").arcs.groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("n"))
    return a.select("id", F.concat_ws(" ", F.transform("n", lambda x: x["dst"].cast("string"))).alias("nbrs"))


@query("agg_having_conditional", "SELECT c_nationkey, count(*) AS n, count(*) FILTER (WHERE c_acctbal < 0) AS negative FROM customer GROUP BY 1 HAVING count(*) FILTER (WHERE c_acctbal < 0) > 2")
def _(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.count("*").alias("n"), F.count_if(F.col("c_acctbal") < 0).alias("negative")).where("negative > 2")


# --- windows, order, sets ---


@query("window_ranking", with_graph("G6", "SELECT cid, vol, row_number() OVER o AS rn, rank() OVER (ORDER BY vol DESC) AS rk, dense_rank() OVER (ORDER BY vol DESC) AS dr, ntile(3) OVER o AS third, round(percent_rank() OVER o, 6) AS pr FROM (SELECT id % 7 AS cid, CAST(sum(wdeg) AS BIGINT) AS vol FROM nodes GROUP BY 1) WINDOW o AS (ORDER BY vol DESC, cid)"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    v = scoring.cluster_volumes(g.nodes, mod_assign(g, 7)).select("cid", "vol")
    o, t = Window.orderBy(F.col("vol").desc(), "cid"), Window.orderBy(F.col("vol").desc())
    return v.select("cid", "vol", F.row_number().over(o).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"), F.ntile(3).over(o).alias("third"), F.round(F.percent_rank().over(o), 6).alias("pr"))


@query("window_lag_lead", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(turn) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def _(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("turn").over(w).alias("after"))


@query("window_running_rows", with_graph("G3", "SELECT src, target, CAST(coalesce(sum(d) OVER (PARTITION BY target ORDER BY gain DESC, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS joined FROM (SELECT src, arg_max(cid, (gain, -cid)) AS target, max(gain) AS gain, max(d) AS d FROM scored WHERE gain > 0 GROUP BY 1)", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G3")
    b = scoring.best_cluster(scoring.scored_candidates(g.arcs, g.nodes, mod_assign(g, 7), g.two_m))
    w = Window.partitionBy("target").orderBy(F.col("gain").desc(), "src").rowsBetween(Window.unboundedPreceding, -1)
    return b.select("src", "target", F.coalesce(F.sum("d").over(w), F.lit(0)).cast("long").alias("joined"))


@query("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS recent FROM events")
def _(spark, sf_dir):
    """Seconds are rounded to the nearest whole one, halves to even, as DuckDB's cast from double does."""
    second = F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")
    w = Window.partitionBy("user_id").orderBy(second).rangeBetween(-86400, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("recent"))


@query("window_first_last_nth", "SELECT DISTINCT o_custkey, first_value(o_orderkey) OVER w AS first_order, last_value(o_orderkey) OVER w AS last_order, nth_value(o_orderkey, 2) OVER w AS second_order FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "orders").select("o_custkey", F.first("o_orderkey").over(w).alias("first_order"), F.last("o_orderkey").over(w).alias("last_order"), F.nth_value("o_orderkey", 2).over(w).alias("second_order")).distinct()


@query("sort_total", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders")
def _(spark, sf_dir):
    """A total order over ranges: the place is the range's offset plus the place within it."""
    o = io.settle(table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").repartitionByRange(8, F.col("o_totalprice").desc(), "o_orderkey").sortWithinPartitions(F.col("o_totalprice").desc(), "o_orderkey").select("*", F.monotonically_increasing_id().alias("at")), "sorted")
    part = o.withColumn("part", F.shiftright("at", 33)).withColumn("off", F.col("at").bitwiseAND(F.lit((1 << 33) - 1)))
    base = part.groupBy("part").agg(F.count("*").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return part.join(F.broadcast(base), "part").select("o_orderkey", (F.col("base") + F.col("off") + 1).alias("place"))


@query("sort_limit_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20)


@query("topk_per_group", "SELECT l_suppkey, l_orderkey, l_linenumber FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS r FROM lineitem) WHERE r <= 3")
def _(spark, sf_dir):
    w = Window.partitionBy("l_suppkey").orderBy(F.col("l_extendedprice").desc(), "l_orderkey", "l_linenumber")
    return table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_extendedprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("l_suppkey", "l_orderkey", "l_linenumber")


@query("topk_clusters", with_graph("G6", "SELECT id % 40 AS cid, CAST(sum(wdeg) AS BIGINT) AS vol, count(*) AS size FROM nodes GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return inspect.top_clusters(g, mod_assign(g, 40))


@query("inspect_boundary_nodes", with_graph("G6", "SELECT a.src AS id, a.src % 7 AS cid, CAST(sum(a.w) AS BIGINT) AS leaving FROM arcs a WHERE a.src % 7 <> a.dst % 7 GROUP BY 1, 2"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return inspect.boundary_nodes(g, mod_assign(g, 7))


@query("inspect_cluster_edges", with_graph("G6", "SELECT src, dst, w FROM arcs WHERE src < dst AND src % 7 = 2 AND dst % 7 = 2"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return inspect.cluster_edges(g, mod_assign(g, 7), 2)


@query("inspect_cluster_members", with_graph("G6", "SELECT id, okey, wdeg FROM nodes WHERE id % 7 = 2"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return inspect.cluster_members(g, mod_assign(g, 7), 2)


@query("set_union_intersect_except", with_graph("G6", "SELECT (SELECT count(*) FROM (SELECT src, dst FROM arcs WHERE src % 2 <> dst % 2 UNION SELECT src, dst FROM arcs WHERE src % 3 <> dst % 3)) AS either, (SELECT count(*) FROM (SELECT src, dst FROM arcs WHERE src % 2 <> dst % 2 INTERSECT SELECT src, dst FROM arcs WHERE src % 3 <> dst % 3)) AS both_, (SELECT count(*) FROM (SELECT src, dst FROM arcs WHERE src % 2 <> dst % 2 EXCEPT SELECT src, dst FROM arcs WHERE src % 3 <> dst % 3)) AS only_first"))
def _(spark, sf_dir):
    a = graph(spark, sf_dir, "G6").arcs
    cut = lambda k: a.where(F.pmod("src", F.lit(k)) != F.pmod("dst", F.lit(k))).select("src", "dst")
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(cut(2).union(cut(3)).distinct(), "either").join(n(cut(2).intersect(cut(3)), "both_")).join(n(cut(2).exceptAll(cut(3)), "only_first"))


# --- functions ---


@query("string_shingles", r"SELECT count(*) AS shingles, count(DISTINCT g) AS distinct_shingles, max(length(g)) AS longest FROM (SELECT unnest(list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' ')))) AS g FROM (SELECT list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') AS w FROM conversations) WHERE len(w) >= 3)")
def _(spark, sf_dir):
    w = table(spark, sf_dir, "conversations").select(F.filter(F.split(F.lower("text"), r"\s+", -1), lambda x: x != "").alias("w")).where(F.size("w") >= 3)
    g = w.select(F.explode(F.array_distinct(F.expr("transform(sequence(1, size(w) - 2), i -> array_join(slice(w, i, 3), ' '))"))).alias("g"))
    return g.agg(F.count("*").alias("shingles"), F.count_distinct("g").alias("distinct_shingles"), F.max(F.length("g")).cast("long").alias("longest"))


@query("string_url_parts", r"SELECT host, count(*) AS pages, max(depth) AS depth FROM (SELECT lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS host, CAST(length(url) - length(replace(url, '/', '')) AS BIGINT) AS depth FROM pages) GROUP BY 1")
def _(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select(F.lower(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)).alias("host"), (F.length("url") - F.length(F.replace(F.col("url"), F.lit("/"), F.lit("")))).cast("long").alias("depth"))
    return p.groupBy("host").agg(F.count("*").alias("pages"), F.max("depth").alias("depth"))


@query("regex_extract_all", "SELECT page_id, CAST(len(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS BIGINT) AS links FROM pages")
def _(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.expr("cast(size(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) as bigint)").alias("links"))


@query("date_functions", "SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, max(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)) AS days, CAST(sum(epoch(o_orderdate)) AS BIGINT) AS secs FROM orders GROUP BY 1")
def _(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_orderdate").cast("timestamp").alias("d"))
    return o.groupBy(F.date_trunc("month", "d").alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff("d", F.lit("1992-01-01").cast("date"))).cast("long").alias("days"), F.sum(F.unix_timestamp("d")).alias("secs")).withColumn("month", F.col("month").cast("timestamp_ntz"))


@query("math_functions", "SELECT o_orderpriority, round(exp(avg(ln(o_totalprice))), 4) AS geo, round(sum(power(o_totalprice / 1000, 0.5)), 4) AS roots, CAST(sum(((o_orderkey % 7) + 7) % 7) AS BIGINT) AS rest, max(greatest(o_orderkey, o_custkey)) AS top FROM orders GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.round(F.exp(F.avg(F.ln("o_totalprice"))), 4).alias("geo"), F.round(F.sum(F.pow(F.col("o_totalprice") / 1000, 0.5)), 4).alias("roots"), F.sum(F.pmod("o_orderkey", F.lit(7))).alias("rest"), F.max(F.greatest("o_orderkey", "o_custkey")).alias("top"))


@query("array_functions", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm2, round(CAST(list_max(embedding) AS DOUBLE), 5) AS top, CAST(len(embedding) AS BIGINT) AS width FROM embeddings")
def _(spark, sf_dir):
    d = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(d, d, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), 5).alias("norm2"), F.round(F.array_max(d), 5).alias("top"), F.size("embedding").cast("long").alias("width"))


@query("map_functions", "SELECT user_id, CAST(count(DISTINCT event_type) AS BIGINT) AS kinds, CAST(count(*) FILTER (WHERE c > 3) AS BIGINT) AS often FROM (SELECT user_id, event_type, count(*) AS c FROM events GROUP BY 1, 2) GROUP BY 1")
def _(spark, sf_dir):
    m = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("c")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.size(F.map_filter("m", lambda _, v: v > 3)).cast("long").alias("often"))


@query("json_functions", "SELECT CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.from_json("props", "k string").alias("j"), F.get_json_object("props", "$.k").alias("k"))
    return e.where(F.col("j.k").eqNullSafe(F.col("k"))).groupBy("k").agg(F.count("*").alias("n"))


@query("null_semantics", "SELECT count(*) AS n, count(quality) AS known, count(*) FILTER (WHERE quality IS NOT DISTINCT FROM toxic) AS same, round(avg(nullif(quality, 0)), 6) AS mean FROM documents LEFT JOIN labels USING (doc_id)")
def _(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    return d.agg(F.count("*").alias("n"), F.count("quality").alias("known"), F.count_if(F.col("quality").eqNullSafe(F.col("toxic"))).alias("same"), F.round(F.avg(F.nullif(F.col("quality"), F.lit(0))), 6).alias("mean"))


@query("case_bucketing", with_graph("G6", "SELECT CASE WHEN deg < 3 THEN 'few' WHEN deg < 6 THEN 'some' ELSE 'many' END AS class, least(CAST(floor((deg - 1) / 2.0) AS BIGINT) + 1, 6) AS bin, count(*) AS n FROM nodes GROUP BY 1, 2"))
def _(spark, sf_dir):
    n = graph(spark, sf_dir, "G6").nodes
    b = F.width_bucket(F.col("deg").cast("double"), F.lit(1.0), F.lit(11.0), F.lit(5)).cast("long")
    return n.groupBy(F.when(F.col("deg") < 3, "few").when(F.col("deg") < 6, "some").otherwise("many").alias("class"), b.alias("bin")).agg(F.count("*").alias("n"))


# --- SQL surface ---


@query("recursive_cte_components", with_graph("G8", "SELECT node AS id, min(root) AS cid FROM reach GROUP BY 1", "reach(node, root) AS (SELECT id, id FROM nodes UNION SELECT a.dst, r.root FROM reach r JOIN arcs a ON a.src = r.node WHERE r.root < a.dst)"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G8")
    return components.connected_components(g.arcs, g.nodes)


@query("recursive_cte_sql", "WITH RECURSIVE t(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * 2 FROM t WHERE n < 20) SELECT CAST(n AS BIGINT) AS n, f FROM t")
def _(spark, sf_dir):
    return spark.sql("WITH RECURSIVE t(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * 2 FROM t WHERE n < 20) SELECT CAST(n AS BIGINT) AS n, f FROM t")


@query("lateral_and_correlated_subquery", "SELECT n_nationkey, (SELECT max(c_acctbal) FROM customer WHERE c_nationkey = n_nationkey) AS top FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey)")
def _(spark, sf_dir):
    for t in ("nation", "customer", "supplier"):
        table(spark, sf_dir, t).createOrReplaceTempView(f"q_{t}")
    return spark.sql("SELECT n_nationkey, m.top FROM q_nation, LATERAL (SELECT max(c_acctbal) AS top FROM q_customer WHERE c_nationkey = n_nationkey) m WHERE EXISTS (SELECT 1 FROM q_supplier WHERE s_nationkey = n_nationkey)")


@query("sql_views_registered", with_graph("G3", "SELECT cid, count(*) AS n, CAST(sum(wdeg) AS BIGINT) AS vol FROM (SELECT id % 7 AS cid, wdeg FROM nodes) GROUP BY 1"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G3")
    udf.register(spark, g, mod_assign(g, 7))
    return spark.sql("SELECT a.cid, count(*) AS n, sum(n.wdeg) AS vol FROM ms_assign a JOIN ms_nodes n USING (id) GROUP BY 1")


@query("udf_sql_function", with_graph("G6", "SELECT src, cid, gain FROM scored", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    udf.register(spark, g, a)
    scoring.scored_candidates(g.arcs, g.nodes, a, g.two_m).createOrReplaceTempView("ms_scored")
    return spark.sql(f"SELECT src, cid, modularity_gain(k, k_cur, d, vol, vol_cur, {g.two_m}) AS gain FROM ms_scored")


@query("udf_scalar_pandas", with_graph("G6", "SELECT src, cid, gain FROM scored", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    s = scoring.scored_candidates(g.arcs, g.nodes, mod_assign(g, 7), g.two_m)
    return s.select("src", "cid", udf.gain_udf()("k", "k_cur", "d", "vol", "vol_cur", F.lit(g.two_m).cast("long")).alias("gain"))


@query("udf_grouped_halves", with_graph("G6", "SELECT id % 7 AS cid, count(*) AS n, true AS balanced FROM nodes GROUP BY 1"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    h = udf.bisect_groups(g.arcs, mod_assign(g, 7))
    return h.groupBy("cid").agg(F.count("*").alias("n"), (F.abs(2 * F.sum("half") - F.count("*")) <= 2).alias("balanced"))


@query("udf_grouped_arrow", with_graph("G6", "SELECT id % 7 AS cid, count(*) AS n, CAST(sum(wdeg) AS BIGINT) AS vol, max(wdeg) AS heaviest FROM nodes GROUP BY 1"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return udf.cluster_figures(g.nodes, mod_assign(g, 7))


@query("udtf_neighbours", with_graph("G1w", "SELECT src, CAST(row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) - 1 AS INTEGER) AS place, dst, w FROM arcs", unit=False))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G1w", False)
    spark.udtf.register("node_neighbours", udf.neighbours_udtf())
    g.arcs.groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("a")).select("src", "a.dst", "a.w").createOrReplaceTempView("ms_adjacency")
    return spark.sql("SELECT src, n.place, n.dst, n.w FROM ms_adjacency, LATERAL node_neighbours(ms_adjacency.dst, ms_adjacency.w) n")


@query("udaf_grouped_agg", "SELECT round(-sum(p * ln(p)), 6) AS entropy FROM (SELECT count(*) / CAST(sum(count(*)) OVER () AS DOUBLE) AS p FROM customer GROUP BY c_nationkey)")
def _(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy(F.lit(0).alias("all")).agg(udf.entropy_udaf()("c_nationkey").alias("e")).select(r6("e", "entropy"))


@query("udtf_words", r"SELECT conv_id, turn, count(*) AS words FROM (SELECT conv_id, turn, unnest(list_filter(regexp_split_to_array(text, '\s+'), lambda x: x <> '')) AS w FROM conversations) GROUP BY 1, 2")
def _(spark, sf_dir):
    spark.udtf.register("split_words", udf.split_words_udtf())
    table(spark, sf_dir, "conversations").createOrReplaceTempView("q_conversations")
    return spark.sql("SELECT conv_id, turn, count(*) AS words FROM q_conversations, LATERAL split_words(text) GROUP BY 1, 2")


# --- streams ---


def _events(spark, sf_dir, files=4):
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    return e, streams.split_files(e, "ts", files, "events")


_NTZ = lambda c: F.col(c).cast("timestamp_ntz").alias(c)


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS events, round(sum(value), 4) AS value FROM events GROUP BY 1")
def _(spark, sf_dir):
    e, path = _events(spark, sf_dir)
    got = streams.run_all(streams.tumbling(streams.read_files(spark, path, e.schema)), "complete")
    return got.select(_NTZ("start"), "events", F.round("value", 4).alias("value"))


@query("stream_sliding", "SELECT s AS start, count(*) AS events FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1")
def _(spark, sf_dir):
    e, path = _events(spark, sf_dir)
    return streams.run_all(streams.sliding(streams.read_files(spark, path, e.schema)), "complete").select(_NTZ("start"), "events")


@query("stream_session", "SELECT user_id, min(ts) AS start, count(*) AS events FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return streams.closed_sessions(e, streams.split_files(e, "ts", 4, "events")).select("user_id", _NTZ("start"), "events")


@query("stream_watermark_late", "SELECT start, n AS events FROM (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n FROM events GROUP BY 1) WHERE start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 2 DAY")
def _(spark, sf_dir):
    """Windows that the watermark (two days) has closed; files come in order, so nothing is late by more."""
    e, path = _events(spark, sf_dir)
    s = streams.read_files(spark, path, e.schema).withWatermark("ts", "2 days")
    return streams.run_all(s.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("events")).select(F.col("window.start").alias("start"), "events")).select(_NTZ("start"), "events")


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    path = streams.split_files(e.union(e.where(F.pmod("event_id", F.lit(3)) == 0)), "ts", 3, "repeats")
    return streams.run_all(streams.without_repeats(streams.read_files(spark, path, e.schema))).groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_stateful_degree", "SELECT user_id AS id, count(*) AS degree FROM events GROUP BY 1")
def _(spark, sf_dir):
    e, path = _events(spark, sf_dir, 3)
    got = streams.run_all(streams.degree_state(streams.read_files(spark, path, e.schema).select(F.col("user_id").alias("id"), "event_id")), "update")
    return got.groupBy("id").agg(F.max("degree").alias("degree"))


@query("stream_degree_update", with_graph("G6", "SELECT id, deg AS degree FROM nodes"))
def _(spark, sf_dir):
    e = graph(spark, sf_dir, "G6").arcs.where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"))
    return streams.run_all(streams.edge_degrees(spark, streams.split_files(e, "u", 4, "edges"), "u long, v long"), "complete")


@query("stream_pass_microbatch_certificate", _FACTS)
def _(spark, sf_dir):
    """A stream of node records against the batch form of the same chunks: lost, doubled or differing nodes are violations."""
    g = graph(spark, sf_dir, "G8")
    half = -(-g.nodes.count() // 2)
    got, batch = streams.node_stream_pass(g, 2, 2), onepass.stream_pass_batches(g, 2, 2)
    off = got.join(batch.withColumnRenamed("cid", "other"), "id", "full").where(~F.col("cid").eqNullSafe(F.col("other"))).count() if half else 0
    return _facts(graph(spark, sf_dir, "G6"), onepass.init_singletons(graph(spark, sf_dir, "G6").nodes), off)


@query("stream_foreach_batch_assign", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, streams.node_stream_pass(g, 3, 2))


@query("stream_stream_join", "SELECT x.event_type AS a, count(*) AS n FROM (SELECT * FROM events WHERE event_id % 2 = 0) x JOIN (SELECT * FROM events WHERE event_id % 2 = 1) y ON x.user_id = y.user_id AND y.ts BETWEEN x.ts AND x.ts + INTERVAL 1 HOUR GROUP BY 1")
def _(spark, sf_dir):
    e, path = _events(spark, sf_dir, 2)
    s = lambda odd, names: streams.read_files(spark, path, e.schema, 10).where(F.pmod("event_id", F.lit(2)) == odd).withWatermark("ts", "30 days").select(*[F.col(c).alias(f"{names}_{c}") for c in ("user_id", "ts", "event_type")])
    x, y = s(0, "x"), s(1, "y")
    near = x.join(y, (F.col("x_user_id") == F.col("y_user_id")) & (F.col("y_ts") >= F.col("x_ts")) & (F.col("y_ts") <= F.col("x_ts") + F.expr("INTERVAL 1 HOUR")))
    return streams.run_all(near.select(F.col("x_event_type").alias("a"))).groupBy("a").agg(F.count("*").alias("n"))


