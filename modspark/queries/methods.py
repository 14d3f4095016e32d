"""Queries of the methods, baselines and measures."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..config import ClusterConfig, MemeticConfig, RestreamConfig
from ..functions import measures, methodology, scoring
from ..operators import baselines, components, kernels, louvain, memetic, onepass, quotient, restream, waves
from ..operators.local import run_local
from ..plans import clustering
from ..sources import graphs
from . import linescores
from .base import graph, mod_assign, query, r6, table
from .sqlgraph import edge_stream, one_pass, wave_pass, with_graph
from .sqlgraph import restream as restream_sql

# --- graphs ---

for _key, _name, _unit in (
    ("prep_copurchase_edges", "G1", False), ("prep_customer_supplier", "G2", False), ("prep_geo_tree", "G3", True), ("prep_user_coactivity", "G4", False), ("prep_doc_shingles", "G5", False),
    ("prep_page_links", "G6", True), ("prep_embedding_knn", "G7", True), ("prep_conversation_chain", "G8", True), ("prep_order_part", "G9", True), ("prep_doc_benchmark", "G10", False),
):

    def _edges(spark, sf_dir, name=_name, unit=_unit):
        if name == "G4":  # as many pairs as users' windows make: none is kept
            return graphs.user_coactivity_edges(spark, sf_dir)
        return graph(spark, sf_dir, name, unit).arcs.where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w")

    query(_key, with_graph(_name, "SELECT u, v, w FROM half" if _unit else "SELECT least(u, v) AS u, greatest(u, v) AS v, w FROM half", unit=_unit).replace("SELECT u, v, w FROM half", "SELECT least(u, v) AS u, greatest(u, v) AS v, w FROM half"))(_edges)


@query("prep_normalise_dedup", "SELECT least(l_partkey, l_suppkey) AS a, greatest(l_partkey, l_suppkey) AS b, count(*) AS w FROM lineitem WHERE l_partkey <> l_suppkey GROUP BY 1, 2")
def _(spark, sf_dir):
    from ..operators.prep import simple_edges

    return simple_edges(table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b")), unit=False)


@query("graph_degree_table", with_graph("G6", "SELECT id, okey, deg, wdeg FROM nodes"))
def _(spark, sf_dir):
    return graph(spark, sf_dir, "G6").nodes.select("id", "okey", "deg", "wdeg")


@query("graph_stats", with_graph("G2", "SELECT count(*) AS n, CAST(sum(deg) / 2 AS BIGINT) AS m, CAST(sum(wdeg) AS BIGINT) AS two_m, max(deg) AS max_deg, CAST(0 AS BIGINT) AS isolated FROM nodes", unit=False))
def _(spark, sf_dir):
    from ..operators.prep import graph_stats

    return graph_stats(graph(spark, sf_dir, "G2", False))


@query("graph_degree_histogram", with_graph("G9", "SELECT deg, count(*) AS nodes FROM nodes GROUP BY 1"))
def _(spark, sf_dir):
    return graph(spark, sf_dir, "G9").nodes.groupBy("deg").agg(F.count("*").alias("nodes"))


# --- measures: G3 by nation, G6 by remainder ---

_NATION = "asg AS MATERIALIZED (SELECT n.id, coalesce(CAST(coalesce(c.c_nationkey, s.s_nationkey) AS BIGINT), 1000 + n.id) AS cid FROM nodes n LEFT JOIN customer c ON n.okey = 'c' || c.c_custkey LEFT JOIN supplier s ON n.okey = 'd' || s.s_suppkey)"
_MOD = "asg AS MATERIALIZED (SELECT id, id % 7 AS cid FROM nodes)"
_SUMS = """la AS MATERIALIZED (SELECT x.cid AS cs, y.cid AS cd, a.src, a.dst, a.w FROM arcs a JOIN asg x ON x.id = a.src JOIN asg y ON y.id = a.dst),
sums AS MATERIALIZED (SELECT v.cid, v.size, v.vol, coalesce(i.k2, 0) AS k2, coalesce(i.cut, 0) AS cut, coalesce(i.n2, 0) AS n2 FROM
  (SELECT cid, count(*) AS size, CAST(sum(wdeg) AS BIGINT) AS vol FROM nodes JOIN asg USING (id) GROUP BY 1) v LEFT JOIN
  (SELECT cs, CAST(sum(CASE WHEN cs = cd THEN w ELSE 0 END) AS BIGINT) AS k2, CAST(sum(CASE WHEN cs <> cd THEN w ELSE 0 END) AS BIGINT) AS cut, count(*) FILTER (WHERE cs = cd) AS n2 FROM la GROUP BY 1) i ON i.cs = v.cid),
t AS MATERIALIZED (SELECT count(*) AS k, CAST(sum(size) AS BIGINT) AS n, CAST(sum(vol) AS BIGINT) AS two_m, CAST(sum(k2) AS BIGINT) AS k2, CAST(sum(vol * vol) AS BIGINT) AS vol2, CAST(sum(n2) AS BIGINT) AS n2, CAST(sum(size * (size - 1) / 2) AS BIGINT) AS pairs_in FROM sums),
mm AS (SELECT CAST(count(*) / 2 AS BIGINT) AS m FROM arcs)"""


def _on(name: str, body: str, assign: str | None = None) -> str:
    return with_graph(name, body, f"{assign or (_NATION if name == 'G3' else _MOD)}, {_SUMS}")


def _nation(spark, sf_dir):
    g = graph(spark, sf_dir, "G3")
    t = graphs.geo_truth(spark, sf_dir).select("okey", F.col("label").cast("long").alias("c"))
    return g, g.nodes.join(t, "okey", "left").select("id", F.coalesce("c", F.col("id") + 1000).alias("cid"))


def _both(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    return g, a, measures.cluster_sums(g.arcs, g.nodes, a)


@query("modularity_by_nation", _on("G3", "SELECT k, n, two_m, CAST(two_m * k2 - vol2 AS BIGINT) AS qnum, round((two_m * k2 - vol2) / (two_m * 1.0 * two_m), 6) AS q FROM t"))
def _(spark, sf_dir):
    g, a = _nation(spark, sf_dir)
    x = measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, a))
    return x.select("k", "n", "two_m", F.col("qnum").cast("long").alias("qnum"), r6(F.col("qnum").cast("double") / F.col("two_m") / F.col("two_m"), "q"))


@query("modularity_by_cluster", _on("G6", "SELECT cid, size, vol, round(k2 / CAST((SELECT two_m FROM t) AS DOUBLE) - (vol / CAST((SELECT two_m FROM t) AS DOUBLE)) ** 2, 6) AS q FROM sums"))
def _(spark, sf_dir):
    _g, _a, s = _both(spark, sf_dir)
    return measures.modularity_by_cluster(s).select("cid", "size", "vol", r6("q", "q"))


@query("coverage", _on("G6", "SELECT round(k2 / CAST(two_m AS DOUBLE), 6) AS coverage FROM t"))
def _(spark, sf_dir):
    return measures.coverage(_both(spark, sf_dir)[2]).select(r6("coverage", "coverage"))


@query("expected_coverage", _on("G6", "SELECT round(vol2 / CAST(two_m AS DOUBLE) / two_m, 6) AS expected_coverage FROM t"))
def _(spark, sf_dir):
    return measures.expected_coverage(_both(spark, sf_dir)[2]).select(r6("expected_coverage", "expected_coverage"))


@query("performance_measure", _on("G6", "SELECT round((n2 / 2.0 + n * (n - 1) / 2.0 - pairs_in - (m - n2 / 2.0)) / (n * (n - 1) / 2.0), 6) AS performance FROM t, mm"))
def _(spark, sf_dir):
    g, a, _ = _both(spark, sf_dir)
    return measures.performance(g.arcs, g.nodes, a).select(r6("performance", "performance"))


@query("conductance", _on("G6", "SELECT round(max(p), 6) AS max_conductance, round(avg(p), 6) AS mean_conductance, round(1 - max(p), 6) AS inter_cluster FROM (SELECT cut / CAST(nullif(least(vol, (SELECT two_m FROM t) - vol), 0) AS DOUBLE) AS p FROM sums)"))
def _(spark, sf_dir):
    x = measures.conductance(_both(spark, sf_dir)[2])
    return x.select(*[r6(c, c) for c in x.columns])


@query("surprise", _on("G6", "SELECT round(m * (q * ln(q / e) + (1 - q) * ln((1 - q) / (1 - e))), 4) AS surprise FROM (SELECT m, n2 / 2.0 / m AS q, pairs_in / (n * (n - 1) / 2.0) AS e FROM t, mm)"))
def _(spark, sf_dir):
    g, a, _ = _both(spark, sf_dir)
    return measures.surprise(g.arcs, g.nodes, a).select(F.round("surprise", 4).alias("surprise"))


@query("map_equation", _on("G6", """SELECT round((CASE WHEN o > 0 THEN o * log2(o) ELSE 0 END) - 2 * a - c + b, 6) AS map_equation FROM
  (SELECT sum(x) AS o, sum(CASE WHEN x > 0 THEN x * log2(x) ELSE 0 END) AS a, sum((x + p) * log2(x + p)) AS b FROM (SELECT cut / CAST((SELECT two_m FROM t) AS DOUBLE) AS x, vol / CAST((SELECT two_m FROM t) AS DOUBLE) AS p FROM sums)),
  (SELECT sum(d * log2(d)) AS c FROM (SELECT wdeg / CAST((SELECT two_m FROM t) AS DOUBLE) AS d FROM nodes))"""))
def _(spark, sf_dir):
    g, a, _ = _both(spark, sf_dir)
    return measures.map_equation(g.arcs, g.nodes, a).select(r6("map_equation", "map_equation"))


@query("trivial_one_zero", with_graph("G6", "SELECT count(*) AS nodes, CAST(0 AS BIGINT) AS qnum FROM nodes"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, baselines.trivial_one(g.nodes))).select(F.col("n").alias("nodes"), F.col("qnum").cast("long").alias("qnum"))


@query("trivial_singletons", with_graph("G6", "SELECT count(*) AS nodes, CAST(-sum(wdeg * wdeg) AS BIGINT) AS qnum FROM nodes"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, baselines.trivial_singletons(g.nodes))).select(F.col("n").alias("nodes"), F.col("qnum").cast("long").alias("qnum"))


_LABELS = "lab AS MATERIALIZED (SELECT n.id, coalesce(c.c_nationkey, s.s_nationkey) AS label FROM nodes n LEFT JOIN customer c ON n.okey = 'c' || c.c_custkey LEFT JOIN supplier s ON n.okey = 'd' || s.s_suppkey WHERE coalesce(c.c_nationkey, s.s_nationkey) IS NOT NULL), cell AS MATERIALIZED (SELECT id % 7 AS cid, CAST(label AS VARCHAR) AS label, count(*) AS n FROM lab GROUP BY 1, 2)"


def _cells(spark, sf_dir):
    g = graph(spark, sf_dir, "G3")
    return measures.contingency(mod_assign(g, 7), graphs.truth(spark, sf_dir, "G3", g))


@query("contingency_table", with_graph("G3", "SELECT cid, label, n FROM cell", _LABELS))
def _(spark, sf_dir):
    return _cells(spark, sf_dir)


@query("nmi_four_norms", with_graph("G3", """SELECT round(mi, 6) AS mi, round(hx, 6) AS hx, round(hy, 6) AS hy, round(2 * mi / (hx + hy), 6) AS nmi_arithmetic, round(mi / sqrt(hx * hy), 6) AS nmi_geometric, round(mi / greatest(hx, hy), 6) AS nmi_max, round(mi / least(hx, hy), 6) AS nmi_min FROM
  (SELECT sum(c.n / t * ln(c.n * t / (a.n * b.n))) AS mi FROM cell c JOIN (SELECT cid, CAST(sum(n) AS DOUBLE) AS n FROM cell GROUP BY 1) a USING (cid) JOIN (SELECT label, CAST(sum(n) AS DOUBLE) AS n FROM cell GROUP BY 1) b USING (label), (SELECT CAST(sum(n) AS DOUBLE) AS t FROM cell)),
  (SELECT -sum(n / t * ln(n / t)) AS hx FROM (SELECT CAST(sum(n) AS DOUBLE) AS n FROM cell GROUP BY cid), (SELECT CAST(sum(n) AS DOUBLE) AS t FROM cell)),
  (SELECT -sum(n / t * ln(n / t)) AS hy FROM (SELECT CAST(sum(n) AS DOUBLE) AS n FROM cell GROUP BY label), (SELECT CAST(sum(n) AS DOUBLE) AS t FROM cell))""", _LABELS))
def _(spark, sf_dir):
    x = measures.nmi(_cells(spark, sf_dir))
    return x.select(*[r6(c, c) for c in x.columns])


@query("cluster_profile", with_graph("G3", "SELECT count(*) AS k, CAST(sum(s) AS BIGINT) AS n, min(s) AS min_size, median(s) AS median_size, max(s) AS max_size, count(*) FILTER (WHERE s = 1) AS singletons, count(*) = 1 OR count(*) = sum(s) AS is_trivial FROM (SELECT cid, count(*) AS s FROM asg GROUP BY 1)", _NATION))
def _(spark, sf_dir):
    return measures.cluster_profile(_nation(spark, sf_dir)[1])


# --- scoring on G6 by remainder ---

_SCORED = """la AS MATERIALIZED (SELECT a.src, y.cid, CAST(sum(a.w) AS BIGINT) AS k FROM arcs a JOIN asg y ON y.id = a.dst GROUP BY 1, 2),
vols AS MATERIALIZED (SELECT cid, CAST(sum(wdeg) AS BIGINT) AS vol FROM nodes JOIN asg USING (id) GROUP BY 1),
scored AS MATERIALIZED (SELECT la.src, me.cid AS cur, la.cid, la.k, coalesce(o.k, 0) AS k_cur, n.wdeg AS d, v.vol, vc.vol AS vol_cur,
  CAST((SELECT two_m FROM tot) * (la.k - coalesce(o.k, 0)) - n.wdeg * (n.wdeg + v.vol - vc.vol) AS BIGINT) AS gain
  FROM la JOIN asg me ON me.id = la.src LEFT JOIN la o ON o.src = la.src AND o.cid = me.cid JOIN nodes n ON n.id = la.src JOIN vols v ON v.cid = la.cid JOIN vols vc ON vc.cid = me.cid WHERE la.cid <> me.cid)"""


def _scored(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return g, scoring.scored_candidates(g.arcs, g.nodes, mod_assign(g, 7), g.two_m)


@query("candidate_links", with_graph("G6", "SELECT src, cid, k FROM la", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return scoring.candidate_links(g.arcs, mod_assign(g, 7))


@query("move_gain_all", with_graph("G6", "SELECT * FROM scored", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    return _scored(spark, sf_dir)[1]


@query("move_gain_real", with_graph("G6", "SELECT src, cid, round((k - k_cur) / m - d / (2 * m * m) * (d + vol - vol_cur), 9) AS gain FROM scored, (SELECT two_m / 2.0 AS m FROM tot)", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g, s = _scored(spark, sf_dir)
    return s.select("src", "cid", F.round(scoring.move_gain(F.col("k"), F.col("k_cur"), F.col("d"), F.col("vol"), F.col("vol_cur"), g.two_m / 2), 9).alias("gain"))


@query("best_cluster_fixed", with_graph("G6", "SELECT src, arg_max(cid, (gain, -cid)) AS target, max(gain) AS gain FROM scored WHERE gain > 0 GROUP BY 1", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    return scoring.best_cluster(_scored(spark, sf_dir)[1]).select("src", "target", "gain")


@query("gain_components", with_graph("G6", "SELECT src, cid, CAST((SELECT two_m FROM tot) * (k - k_cur) AS BIGINT) AS link_part, CAST(-d * (d + vol - vol_cur) AS BIGINT) AS volume_part, gain FROM scored", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g, s = _scored(spark, sf_dir)
    return scoring.gain_components(s, g.two_m)


@query("explain_move", with_graph("G6", "SELECT cid, k, vol, gain FROM scored WHERE src = (SELECT arg_max(id, (deg, -id)) FROM nodes)", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    from ..plans.inspect import explain_move

    g = graph(spark, sf_dir, "G6")
    hub = g.nodes.orderBy(F.col("deg").desc(), "id").first()["id"]
    return explain_move(g, mod_assign(g, 7), hub).select("cid", "k", "vol", "gain")


# --- one pass ---

for _name in ("G3", "G6", "G8"):

    @query(f"single_pass_assigned_{_name.lower()}" if _name != "G6" else "single_pass_assigned", with_graph(_name, "SELECT node AS id, cid FROM st", one_pass("assigned")))
    def _(spark, sf_dir, name=_name):
        return onepass.stream_pass_exact(graph(spark, sf_dir, name))

    @query(f"single_pass_all_{_name.lower()}" if _name != "G6" else "single_pass_all", with_graph(_name, "SELECT node AS id, cid FROM st", one_pass("all")))
    def _(spark, sf_dir, name=_name):
        return onepass.stream_pass_exact(graph(spark, sf_dir, name), "all")


@query("single_pass_worked_example", with_graph("T", "SELECT node AS id, cid FROM st", one_pass("assigned")))
def _(spark, sf_dir):
    return onepass.stream_pass_exact(graph(spark, sf_dir, "T"))


@query("single_pass_order_desc", with_graph("G6", "SELECT node AS id, cid FROM st", one_pass("assigned", "id DESC")))
def _(spark, sf_dir):
    from ..operators.prep import with_order

    return onepass.stream_pass_exact(with_order(graph(spark, sf_dir, "G6"), "reverse"))


@query("single_pass_order_degree", with_graph("G8", "SELECT node AS id, cid FROM st", one_pass("assigned", "wdeg DESC, id")))
def _(spark, sf_dir):
    from ..operators.prep import with_order

    return onepass.stream_pass_exact(with_order(graph(spark, sf_dir, "G8"), "degree"))


@query("single_pass_copurchase", with_graph("G1w", "SELECT node AS id, cid FROM st", one_pass("assigned"), unit=False))
def _(spark, sf_dir):
    return onepass.stream_pass_exact(graph(spark, sf_dir, "G1w", False))


@query("single_pass_modularity", with_graph("G6", "SELECT k, n, CAST(two_m * k2 - vol2 AS BIGINT) AS qnum FROM t", f"{one_pass('assigned')}, asg AS MATERIALIZED (SELECT node AS id, cid FROM st), {_SUMS}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = onepass.stream_pass_exact(g)
    return measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, a)).select("k", "n", F.col("qnum").cast("long").alias("qnum"))


#: A run is held against facts of the data: nodes, total weight, the score it began from; and none of its own invariants may fail.
_FACTS = with_graph("G6", "SELECT count(*) AS nodes, CAST(sum(wdeg) AS BIGINT) AS two_m, CAST(-sum(wdeg * wdeg) AS BIGINT) AS q_singletons, CAST(0 AS BIGINT) AS violations FROM nodes")


def _facts(g, assign, extra=0):
    """Nodes in clusters, volume of clusters, score of singletons; violations: nodes lost or doubled, clusters that span components, a lower score."""
    s = measures.cluster_sums(g.arcs, g.nodes, assign)
    r = measures.modularity_num(s).first()
    q0 = -int(g.nodes.agg(F.sum(F.col("wdeg") * F.col("wdeg"))).first()[0])
    comp = components.connected_components(g.arcs, g.nodes).select("id", F.col("cid").alias("comp"))
    spans = assign.join(comp, "id").groupBy("cid").agg(F.count_distinct("comp").alias("c")).where("c > 1").count()
    bad = spans + abs(assign.select("id").distinct().count() - assign.count()) + int(int(r["qnum"]) < q0) + extra
    return g.nodes.sparkSession.createDataFrame([(int(r["n"]), int(r["two_m"]), q0, bad)], "nodes long, two_m long, q_singletons long, violations long")


@query("single_pass_batches_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, onepass.stream_pass_batches(g, 3, 3))


@query("single_pass_wavefront_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, onepass.stream_pass_wavefront(g, 4))


@query("single_pass_waves", with_graph("G6", "SELECT id, coalesce(cid, id) AS cid FROM w4", wave_pass(4)))
def _(spark, sf_dir):
    """The parallel pass over the whole stream, four waves far: its clusters, node by node."""
    return waves.stream_pass_waves(graph(spark, sf_dir, "G6"), first=0, growth=1 << 40, ready=0.9, least=0.0, max_waves=4)[0]


@query("single_pass_waves_quotient", with_graph("G6", "SELECT CAST(least(x.cid, y.cid) AS BIGINT) AS ci, CAST(greatest(x.cid, y.cid) AS BIGINT) AS cj, CAST(sum(CASE WHEN x.cid = y.cid THEN 2 * h.w ELSE h.w END) AS BIGINT) AS w FROM half h JOIN asg x ON x.id = h.u JOIN asg y ON y.id = h.v GROUP BY 1, 2", wave_pass(3) + ", asg AS MATERIALIZED (SELECT id, coalesce(cid, id) AS cid FROM w3)"))
def _(spark, sf_dir):
    """The quotient that the parallel pass keeps alongside, three waves far."""
    return waves.stream_pass_waves(graph(spark, sf_dir, "G6"), first=0, growth=1 << 40, ready=0.9, least=0.0, max_waves=3, with_quotient=True)[1]


@query("single_pass_waves_full")
def _(spark, sf_dir):
    """The parallel pass with its defaults behind a short prefix, and the sequential pass: modularity of both."""
    g = graph(spark, sf_dir, "G6")
    a, b = waves.stream_pass_waves(g, first=64)[0], onepass.stream_pass_exact(g)
    return spark.createDataFrame([(name, measures.modularity(g.arcs, g.nodes, x)) for name, x in (("waves", a), ("sequential", b))], "form string, modularity double")


# --- quotient on G6 by remainder ---

_QUOT = "q AS MATERIALIZED (SELECT least(x.cid, y.cid) AS ci, greatest(x.cid, y.cid) AS cj, CAST(sum(CASE WHEN x.cid = y.cid THEN 2 * h.w ELSE h.w END) AS BIGINT) AS w FROM half h JOIN asg x ON x.id = h.u JOIN asg y ON y.id = h.v GROUP BY 1, 2)"


@query("quotient_edges", with_graph("G6", "SELECT ci, cj, w FROM q", f"{_MOD}, {_QUOT}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return quotient.contract(g.arcs, mod_assign(g, 7))


@query("quotient_nodes", with_graph("G6", "SELECT asg.cid, count(*) AS cw, coalesce(max(q.w), 0) AS self_w, CAST(sum(wdeg) AS BIGINT) AS vol FROM asg JOIN nodes USING (id) LEFT JOIN q ON q.ci = asg.cid AND q.cj = asg.cid GROUP BY 1", f"{_MOD}, {_QUOT}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    return quotient.supernodes(quotient.contract(g.arcs, a), g.nodes, a)


@query("quotient_incremental_equals_batch", with_graph("G6", "SELECT ci, cj, w FROM q", f"{_MOD}, {_QUOT}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a, n = mod_assign(g, 7), g.nodes.count()
    step = -(-n // 3)
    return quotient.merge_quotient(*[quotient.quotient_delta(g.arcs, g.nodes, a, i, i + step) for i in range(0, n, step)])


@query("quotient_modularity_equivalence", with_graph("G6", "SELECT k, two_m, CAST(two_m * k2 - vol2 AS BIGINT) AS qnum FROM t", f"asg AS MATERIALIZED (SELECT id, (id % 7) % 3 AS cid FROM nodes), {_SUMS}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    q = quotient.contract(g.arcs, mod_assign(g, 7))
    lab = spark.range(7).select(F.col("id").alias("cid"), F.pmod("id", F.lit(3)).alias("lab"))
    return quotient.modularity_num_quotient(q, lab).select("k", "two_m", F.col("qnum").cast("long").alias("qnum"))


@query("quotient_lift", with_graph("G6", "SELECT id, (id % 7) % 3 AS cid FROM nodes"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return quotient.project(mod_assign(g, 7), spark.range(7).select(F.col("id").alias("cid"), F.pmod("id", F.lit(3)).alias("lab")))


# --- re-stream ---

_ALONE = "SELECT id, id AS cid FROM nodes"
_FIX = RestreamConfig(min_rel_gain=0.0, max_rounds=1000, time_limit_s=None)


@query("restream_fixpoint", with_graph("G8", "SELECT k AS id, com AS cid FROM st WHERE k >= 0", restream_sql(_ALONE)))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G8")
    return restream.restream_exact(g, onepass.init_singletons(g.nodes), _FIX)[0]


@query("restream_from_remainders", with_graph("G6", "SELECT k AS id, com AS cid FROM st WHERE k >= 0", restream_sql("SELECT id, id % 7 AS cid FROM nodes")))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return restream.restream_exact(g, mod_assign(g, 7), _FIX)[0]


@query("restream_worked_example", with_graph("T", "SELECT k AS id, com AS cid FROM st WHERE k >= 0", restream_sql(_ALONE)))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "T")
    return restream.restream_exact(g, onepass.init_singletons(g.nodes), _FIX)[0]


@query("restream_sync_proposals", with_graph("G6", "SELECT src, cur, arg_max(cid, (gain, -cid)) AS target, max(gain) AS gain FROM scored WHERE gain > 0 GROUP BY 1, 2", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    return restream.proposals(g.arcs, g, a, scoring.cluster_volumes(g.nodes, a)).select("src", "cur", "target", "gain")


@query("restream_independent_set", with_graph("G6", """SELECT src, target, gain FROM best b WHERE NOT EXISTS (SELECT 1 FROM arcs a JOIN best o ON o.src = a.dst WHERE a.src = b.src AND (o.gain > b.gain OR (o.gain = b.gain AND o.src < b.src)))""", f"{_MOD}, {_SCORED}, best AS MATERIALIZED (SELECT src, arg_max(cid, (gain, -cid)) AS target, max(gain) AS gain FROM scored WHERE gain > 0 GROUP BY 1)"))
def _(spark, sf_dir):
    from ..operators import rounds

    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    return rounds.independent_set(g.arcs, restream.proposals(g.arcs, g, a, scoring.cluster_volumes(g.nodes, a))).select("src", "target", "gain")


@query("restream_next_active", with_graph("G6", "SELECT DISTINCT a.dst AS id FROM arcs a JOIN (SELECT DISTINCT src FROM scored WHERE gain > 0) m ON m.src = a.src", f"{_MOD}, {_SCORED}"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7)
    return restream.next_active(g.arcs, restream.proposals(g.arcs, g, a, scoring.cluster_volumes(g.nodes, a)))


@query("restream_first_round_exact", with_graph("G6", "SELECT k AS id, com AS cid FROM st WHERE k >= 0", restream_sql("SELECT id, id % 7 AS cid FROM nodes", 1)))
def _(spark, sf_dir):
    """The first round, over all nodes."""
    g = graph(spark, sf_dir, "G6")
    return restream.restream_exact(g, mod_assign(g, 7), RestreamConfig(min_rel_gain=0.0, max_rounds=1, time_limit_s=None))[0]


@query("restream_trace", with_graph("G8", "SELECT count(*) AS nodes, CAST(0 AS BIGINT) AS violations FROM nodes"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G8")
    a, rows = restream.restream_exact(g, onepass.init_singletons(g.nodes), _FIX)
    q = measures.modularity(g.arcs, g.nodes, a)
    t = restream.trace_frame(spark, rows)
    last = t.orderBy(F.col("round").desc()).limit(1)
    off = last.select((F.abs(F.col("q") - F.lit(q)) > 1e-9).cast("long").alias("off"))
    falls = t.withColumn("was", F.lag("q").over(Window.orderBy("round"))).agg(F.count_if(F.col("q") < F.col("was")).alias("falls"))
    return g.nodes.agg(F.count("*").alias("nodes")).join(off).join(falls).select("nodes", (F.col("off") + F.col("falls")).alias("violations"))


@query("restream_parallel_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 7).select("id", F.col("id").alias("cid"))
    got, rows = restream.restream_parallel(g, a, RestreamConfig(max_rounds=2, time_limit_s=None), 4)
    falls = sum(y[5] < x[5] - 1e-12 for x, y in zip(rows, rows[1:], strict=False))
    return _facts(g, got, falls)


# --- baselines ---

for _key, _name, _cap, _sql, _order in (
    ("edge_stream_capped_10000", "G6", 10_000, "10000", "u, v"), ("edge_stream_capped_n", "G6", "n", "(SELECT n FROM tot)", "u, v"), ("edge_stream_small_cap", "G8", 4, "4", "u, v"), ("edge_stream_geo", "G3", 60, "60", "u, v"),
):

    @query(_key, with_graph(_name, "SELECT k AS id, com AS cid FROM st WHERE k >= 0", edge_stream(_sql, "least(u, v), greatest(u, v)").replace("AS seq, u, v FROM half", "AS seq, least(u, v) AS u, greatest(u, v) AS v FROM half")))
    def _(spark, sf_dir, name=_name, most=_cap):
        return baselines.edge_stream_capped(graph(spark, sf_dir, name), most)


@query("edge_stream_storage", with_graph("G8", "SELECT k AS id, com AS cid FROM st WHERE k >= 0", edge_stream("(SELECT n FROM tot)", "least(u, v), greatest(u, v)").replace("AS seq, u, v FROM half", "AS seq, least(u, v) AS u, greatest(u, v) AS v FROM half")))
def _(spark, sf_dir):
    return baselines.edge_stream_capped(graph(spark, sf_dir, "G8"), "n", materialise=True)


_SHUFFLED = "md5(least(u, v) || '-' || greatest(u, v) || '-1'), least(u, v), greatest(u, v)"


def _shuffled(cap_sql: str, body: str) -> str:
    return with_graph("G6", body, edge_stream(cap_sql, _SHUFFLED).replace("AS seq, u, v FROM half", "AS seq, least(u, v) AS u, greatest(u, v) AS v FROM half"))


@query("edge_stream_shuffled", _shuffled("(SELECT n FROM tot)", "SELECT k AS id, com AS cid FROM st WHERE k >= 0"))
def _(spark, sf_dir):
    return baselines.edge_stream_capped(graph(spark, sf_dir, "G6"), "n", "shuffle")


_CAPS = {"n": "(SELECT n FROM tot)", "sqrt": "(SELECT CAST(floor(two_m / sqrt(n)) AS BIGINT) FROM tot)", "10000": "10000"}


@query("edge_stream_sweep", " UNION ALL ".join(f"SELECT * FROM ({_shuffled(x, 'SELECT ' + repr(c) + ' AS v_max, count(DISTINCT com) AS k, count(*) AS n FROM st WHERE k >= 0')})" for c, x in _CAPS.items()))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    got = baselines.edge_stream_sweep(g, ["n", "sqrt", 10_000], "shuffle")
    return got.groupBy("v_max").agg(F.count_distinct("cid").alias("k"), F.count("*").alias("n"))


@query("edge_stream_shuffled_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, baselines.edge_stream_capped(g, "n", "shuffle"))


@query("edge_stream_batches_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, baselines.edge_stream_batches(g, "n", 3))


@query("connected_components", with_graph("G6", "SELECT node AS id, min(root) AS cid FROM reach GROUP BY 1", "reach(node, root) AS (SELECT id, id FROM nodes UNION SELECT a.dst, r.root FROM reach r JOIN arcs a ON a.src = r.node WHERE r.root < a.dst)"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return components.connected_components(g.arcs, g.nodes)


@query("label_propagation_3_rounds", with_graph("G6", "SELECT id, cid FROM l3", ", ".join(["l0 AS (SELECT id, id AS cid FROM nodes)"] + [f"l{r + 1} AS MATERIALIZED (SELECT l.id, CASE WHEN l.id % 2 = {r % 2} THEN coalesce(p.t, l.cid) ELSE l.cid END AS cid FROM l{r} l LEFT JOIN (SELECT src, arg_max(cid, (k, -cid)) AS t FROM (SELECT a.src, x.cid, sum(a.w) AS k FROM arcs a JOIN l{r} x ON x.id = a.dst GROUP BY 1, 2) GROUP BY 1) p ON p.src = l.id)" for r in range(3)])))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return louvain.label_propagation(g.arcs, g.nodes, None, 3)


@query("label_propagation_bounded", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = louvain.label_propagation(g.arcs, g.nodes, 12, 2)
    over = a.groupBy("cid").count().where("count > 12").count()
    facts = _facts(g, a)
    return facts.withColumn("violations", F.lit(over).cast("long"))


@query("louvain_fixpoint_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a, track = louvain.louvain_exact(g, 3)
    return _facts(g, a, sum(y < x for x, y in zip(track, track[1:], strict=False)))


@query("louvain_levels_monotone", _FACTS)
def _(spark, sf_dir):
    """Levels never fall, and the last one is the clustering's score."""
    g = graph(spark, sf_dir, "G6")
    a, track = louvain.louvain_exact(g, 5)
    last = int(measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, a)).first()["qnum"])
    return _facts(g, a, sum(y < x for x, y in zip(track, track[1:], strict=False)) + int(track[-1] != last))


@query("louvain_parallel_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, louvain.louvain_parallel(g, 2, 1, 4))


@query("memetic_inmemory_certificate", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    return _facts(g, baselines.memetic_inmemory(g, MemeticConfig(population=3, max_rounds=2, islands=1))[0])


# --- memetic operators on G6's quotient by remainder 40 ---

_POP = "asg AS MATERIALIZED (SELECT id, id % 40 AS cid FROM nodes), " + _QUOT


def _q40(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 40)
    return g, quotient.contract(g.arcs, a), a


def _lab(spark, k):
    return spark.range(40).select(F.col("id").alias("cid"), F.pmod("id", F.lit(k)).alias("lab"))


def _customers(spark, sf_dir, *by):
    """Clusterings of the customers, by a column each."""
    c = table(spark, sf_dir, "customer")
    return [c.select(F.col("c_custkey").alias("cid"), F.expr(x).alias("lab")) for x in by]


@query("overlay_two", "SELECT c_custkey AS cid, min(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment) AS lab FROM customer")
def _(spark, sf_dir):
    return memetic.overlay(*_customers(spark, sf_dir, "c_nationkey", "c_mktsegment"))


@query("overlay_three", "SELECT c_custkey AS cid, min(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment, c_acctbal < 0) AS lab FROM customer")
def _(spark, sf_dir):
    return memetic.overlay(*_customers(spark, sf_dir, "c_nationkey", "c_mktsegment", "c_acctbal < 0"))


@query("cut_symdiff", with_graph("G6", "SELECT CAST(sum(CASE WHEN (ci % 2 <> cj % 2) <> (ci % 3 <> cj % 3) THEN 1 ELSE 0 END) AS BIGINT) AS distance FROM q WHERE ci <> cj", _POP))
def _(spark, sf_dir):
    return memetic.cut_symdiff(_q40(spark, sf_dir)[1], _lab(spark, 2), _lab(spark, 3))


_FIT = ", fit AS MATERIALIZED (SELECT m.ind, CAST((SELECT two_m FROM tot) * sum(z.k2) - sum(z.vol * z.vol) AS BIGINT) AS qnum FROM (SELECT p.ind, i.id % p.ind AS lab, sum(i.wdeg) AS vol, coalesce(max(x.k2), 0) AS k2 FROM (SELECT unnest([2, 3, 5, 8]) AS ind) p, (SELECT (id % 40) AS id, wdeg FROM nodes) i LEFT JOIN (SELECT pp.ind, (a.src % 40) % pp.ind AS lab, sum(a.w) AS k2 FROM (SELECT unnest([2, 3, 5, 8]) AS ind) pp, arcs a WHERE (a.src % 40) % pp.ind = (a.dst % 40) % pp.ind GROUP BY 1, 2) x ON x.ind = p.ind AND x.lab = i.id % p.ind GROUP BY 1, 2) z JOIN (SELECT unnest([2, 3, 5, 8]) AS ind) m ON m.ind = z.ind GROUP BY 1)"


def _population(spark):
    out = None
    for k in (2, 3, 5, 8):
        p = _lab(spark, k).select(F.lit(k).alias("ind"), "cid", "lab")
        out = p if out is None else out.unionByName(p)
    return out


@query("population_fitness", with_graph("G6", "SELECT ind, qnum FROM fit", _POP + _FIT))
def _(spark, sf_dir):
    return memetic.fitness(_q40(spark, sf_dir)[1], _population(spark)).select("ind", F.col("qnum").cast("long").alias("qnum"))


@query("tournament_winner", with_graph("G6", "SELECT d.round, arg_max(d.ind, (f.qnum, -d.ind)) AS winner, max(f.qnum) AS qnum FROM (SELECT unnest([0, 0, 1, 1, 2, 2]) AS round, unnest([2, 3, 5, 8, 8, 2]) AS ind) d JOIN fit f USING (ind) GROUP BY 1", _POP + _FIT))
def _(spark, sf_dir):
    draws = spark.createDataFrame([(0, 2), (0, 3), (1, 5), (1, 8), (2, 8), (2, 2)], "round int, ind int")
    return memetic.tournament_winner(memetic.fitness(_q40(spark, sf_dir)[1], _population(spark)), draws).select("round", "winner", F.col("qnum").cast("long").alias("qnum"))


@query("replacement_choice", with_graph("G6", "SELECT ind, CAST(d AS BIGINT) AS distance FROM (SELECT f.ind, f.qnum, (SELECT sum(CASE WHEN (ci % f.ind <> cj % f.ind) <> (ci <> cj) THEN 1 ELSE 0 END) FROM q WHERE ci <> cj) AS d FROM fit f WHERE f.qnum <= (SELECT two_m * k2 - vol2 FROM t)) ORDER BY d, qnum, ind LIMIT 1", f"{_POP}{_FIT}, {_SUMS}"))
def _(spark, sf_dir):
    return memetic.replacement_choice(_q40(spark, sf_dir)[1], _population(spark), spark.range(40).select(F.col("id").alias("cid"), F.col("id").alias("lab"))).select("ind", "distance")


def _recombined(kind):
    def run(g, order):
        a, b = kernels.individual(g, 1), kernels.individual(g, 2)
        if kind == "mutation":
            a, b = kernels.split_all(g, a, 1), kernels.split_all(g, b, 2)
        child = (kernels.recombine_flat if kind == "flat" else kernels.recombine_multilevel)(g, a, b, 3)
        bad = int(g.qnum(child) < max(g.qnum(a), g.qnum(b)))
        if kind == "mutation":
            sizes: dict[int, int] = {}
            for c in kernels.individual(g, 1):
                sizes[c] = sizes.get(c, 0) + 1
            halves: dict[int, int] = {}
            for c in a:
                halves[c] = halves.get(c, 0) + 1
            bad += int(any(s > 1 for s in sizes.values()) and len(halves) <= len(sizes))
        return child, [bad]

    return run


for _key, _kind in (("flat_recombination_ge_parents", "flat"), ("multilevel_recombination_ge_parents", "multilevel"), ("mutation_split_balance", "mutation")):

    @query(_key, _FACTS)
    def _(spark, sf_dir, kind=_kind):
        g = graph(spark, sf_dir, "G6")
        child, told = run_local(g, _recombined(kind))
        return _facts(g, child, told[0])


@query("memetic_nonworsening", _FACTS)
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G6")
    a = mod_assign(g, 40)
    q = quotient.contract(g.arcs, a)
    best, rows = memetic.memetic(q, quotient.supernodes(q, g.nodes, a), MemeticConfig(population=4, max_rounds=4))
    seen: dict[tuple, int] = {}
    falls = 0
    for epoch, island, _r, _kind, _child, top, _at in rows:
        falls += top < seen.get((epoch, island), top)
        seen[epoch, island] = top
    got = quotient.project(a, best)
    facts = _facts(g, got)
    worse = measures.modularity(g.arcs, g.nodes, got) < measures.modularity(g.arcs, g.nodes, a) - 1e-12
    return facts.withColumn("violations", F.lit(falls + int(worse)).cast("long"))


# --- the pipeline ---

#: The defaults; without a time limit, which would make results depend on the machine.
_CFG = ClusterConfig(restream=RestreamConfig(time_limit_s=None))
#: The survey's graphs.
_ALL = [*(f"G{i}" for i in range(1, 11)), *(f"S{i}" for i in range(1, 7))]

for _mode in clustering.MODES:

    @query(f"mode_{_mode}", with_graph("G6", "SELECT node AS id, cid FROM st", one_pass("assigned")) if _mode == "single_pass" else _FACTS)
    def _(spark, sf_dir, mode=_mode):
        """single_pass: the assignment itself; the others: facts, with a lower score than the one pass's and lost nodes as violations."""
        g = graph(spark, sf_dir, "G6")
        r = clustering.cluster(g, mode, _CFG)
        if mode == "single_pass":
            return r.assign
        s = measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, r.assign)).first()
        base = onepass.stream_pass_exact(g)
        facts = _facts(g, base)
        worse = float(s["qnum"]) < float(measures.modularity_num(measures.cluster_sums(g.arcs, g.nodes, base)).first()["qnum"])
        return facts.withColumn("violations", F.lit(int(worse) + abs(int(s["n"]) - g.nodes.count())).cast("long"))


@query("mode_comparison")
def _(spark, sf_dir):
    """Modularity, clusters and NMI of every mode and baseline on all graphs, long format."""
    from ..plans import experiments

    return experiments.compare(spark, sf_dir, _ALL, _CFG)


@query("rq_quality_table")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.quality_table(experiments.compare(spark, sf_dir, _ALL, _CFG, experiments.ALGOS, False))


@query("rq_mode_profiles")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.mode_profiles(experiments.compare(spark, sf_dir, _ALL, _CFG, tuple(clustering.MODES)))


@query("rq_time_and_memory")
def _(spark, sf_dir):
    """Boxes of seconds and memory: the streaming methods on all graphs, and all methods on the graphs that all finished."""
    from ..plans import experiments

    return experiments.resource_boxes(experiments.compare(spark, sf_dir, _ALL, _CFG))


@query("rq_scaling")
def _(spark, sf_dir):
    """The growing planted graphs: seconds, state rows, bytes of state per node and scratch, by number of edges."""
    from ..plans import experiments

    return experiments.scaling(spark, (20_000, 100_000, 500_000))


@query("rq_ground_truth")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.compare(spark, sf_dir, ["G3", "G5", "G8", "G1", "G6", "G7", "S1", "S2"], _CFG, experiments.ALGOS, False).where("metric in ('nmi', 'modularity')")


@query("rq_cap_sweep")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.cap_sweep(spark, sf_dir, ["G6", "S2"])


@query("rq_edge_order")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.edge_order(spark, sf_dir, ["S2", "G9"])


@query("rq_memetic_budget")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.memetic_budget(spark, sf_dir, ["G1", "G6"], (0, 5, 20, 80))


@query("rq_restream_ablation")
def _(spark, sf_dir):
    from ..plans import experiments

    return experiments.restream_ablation(spark, sf_dir, ["G5", "G9", "S2"])


@query("synth_graph_stats")
def _(spark, sf_dir):
    """Nodes, edges and components of every synthetic family at its default size."""
    from ..operators.prep import graph_stats
    from ..sources import synth

    out = None
    for name in synth.SYNTH:
        g = graph(spark, sf_dir, name)
        x = graph_stats(g).select(F.lit(name).alias("name"), "n", "m", "max_deg")
        out = x if out is None else out.unionByName(x)
    return out


@query("synth_cliques_recovered", "SELECT i // 5 AS clique, 5 AS members, 1 AS clusters FROM range(40) t(i) GROUP BY 1")
def _(spark, sf_dir):
    """Ring of cliques: Louvain's clusters against the cliques."""
    g = graph(spark, sf_dir, "S1")
    a = louvain.louvain(g, 1).join(g.nodes.select("id", F.floor(F.col("okey").cast("long") / 5).alias("clique")), "id")
    return a.groupBy("clique").agg(F.count("*").alias("members"), F.count_distinct("cid").alias("clusters"))


@query("incremental_edges", with_graph("G8", "SELECT count(*) AS nodes, CAST(sum(wdeg) + 2 AS BIGINT) AS two_m, CAST(0 AS BIGINT) AS lost FROM nodes"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "G8")
    a = onepass.stream_pass_exact(g)
    n = g.nodes.count()
    grown, got, _ = clustering.add_edges(g, a, spark.createDataFrame([(0, n - 1, 1)], "u long, v long, w long"))
    return got.agg(F.count("*").alias("nodes")).withColumn("two_m", F.lit(grown.two_m).cast("long")).withColumn("lost", F.lit(n) - F.col("nodes")).select("nodes", "two_m", "lost")


# --- methodology on the published modularity table ---

from .published import ALGOS, scores, scores_sql  # noqa: E402

_S = f"s AS ({scores_sql()})"
_L = f"s AS ({linescores.scores_sql()})"  # the same, over lines of a given table


@query("geomean_scores", f"WITH {_L} SELECT algo, metric, count(*) FILTER (WHERE value IS NULL OR value <= 0) AS excluded, round(CASE WHEN count(*) FILTER (WHERE value IS NULL OR value <= 0) = 0 THEN exp(avg(ln(value))) END, 6) AS geomean FROM s GROUP BY 1, 2")
def _(spark, sf_dir):
    return methodology.geomean(linescores.scores(spark, sf_dir)).select("algo", "metric", "excluded", r6("geomean", "geomean"))


@query("paper_table_geomeans", f"WITH {_L} SELECT algo, round(exp(avg(ln(value))), 4) AS geomean FROM s GROUP BY 1 HAVING count(value) = count(*)")
def _(spark, sf_dir):
    return methodology.geomean(linescores.scores(spark, sf_dir)).where("geomean is not null").select("algo", F.round("geomean", 4).alias("geomean"))


@query("geomean_common_instances", f"WITH {_L}, c AS (SELECT instance FROM s GROUP BY 1 HAVING count(value) = count(*)) SELECT algo, round(exp(avg(ln(value))), 6) AS geomean FROM s JOIN c USING (instance) GROUP BY 1")
def _(spark, sf_dir):
    return methodology.geomean(methodology.common_instances(linescores.scores(spark, sf_dir), list(linescores.ALGOS))).select("algo", r6("geomean", "geomean"))


@query("improvement_pct", f"WITH {_L} SELECT x.instance, x.metric, round((x.value / y.value - 1) * 100, 6) AS improvement_pct FROM s x JOIN s y ON x.instance = y.instance WHERE x.algo = 'returned' AND y.algo = 'all'")
def _(spark, sf_dir):
    return methodology.improvement(linescores.scores(spark, sf_dir), "returned", "all").select("instance", "metric", r6("improvement_pct", "improvement_pct"))


@query("relative_value", f"WITH {_S} SELECT x.instance, x.metric, round(x.value / y.value, 6) AS relative FROM s x JOIN s y ON x.instance = y.instance WHERE x.algo = 'full' AND y.algo = 'louvain'")
def _(spark, sf_dir):
    return methodology.relative(scores(spark), "full", "louvain").select("instance", "metric", r6("relative", "relative"))


@query("within_ten_percent", f"WITH {_S} SELECT count(*) AS instances, count(*) FILTER (WHERE x.value >= 0.9 * y.value) AS within, round(avg(CASE WHEN x.value >= 0.9 * y.value THEN 1.0 ELSE 0.0 END), 6) AS share FROM s x JOIN s y ON x.instance = y.instance WHERE x.algo = 'single_pass_restream' AND y.algo = 'full'")
def _(spark, sf_dir):
    """On how many instances the re-streamed pass is within ten percent of the strongest mode."""
    return methodology.within(scores(spark), "single_pass_restream", "full", 0.1).select("instances", "within", r6("share", "share"))


for _better, _taus, _op in (("max", [1.0, 0.95, 0.9, 0.75, 0.5], ">="), ("min", [1.0, 1.1, 1.5, 2.0, 5.0], "<=")):

    @query(f"performance_profile_{_better}", f"WITH {_L if _better == 'max' else _S}, b AS (SELECT *, {_better}(value) OVER (PARTITION BY instance, metric) AS best FROM s) SELECT metric, algo, CAST(tau AS DOUBLE) AS tau, round(avg(CASE WHEN value / best {_op} tau THEN 1.0 ELSE 0.0 END), 6) AS share FROM b, (SELECT unnest({_taus}) AS tau) GROUP BY 1, 2, 3")
    def _(spark, sf_dir, better=_better, taus=_taus):
        told = linescores.scores(spark, sf_dir) if better == "max" else scores(spark)
        return methodology.performance_profile(told, taus, better).select("metric", "algo", "tau", r6("share", "share"))


@query("box_summary", f"WITH {_L} SELECT algo, metric, round(min(value), 6) AS low, round(quantile_cont(value, 0.25), 6) AS q1, round(quantile_cont(value, 0.5), 6) AS mid, round(quantile_cont(value, 0.75), 6) AS q3, round(max(value), 6) AS high, count(value) AS runs FROM s GROUP BY 1, 2")
def _(spark, sf_dir):
    return methodology.box_summary(linescores.scores(spark, sf_dir)).select("algo", "metric", *[r6(c, c) for c in ("low", "q1", "mid", "q3", "high")], "runs")
