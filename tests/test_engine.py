"""Distributed operators against the kernels and each other; plans."""

import io as _io
import random
from contextlib import redirect_stdout

import pytest
from pyspark.sql import functions as F

from modspark.config import ClusterConfig, MemeticConfig, RestreamConfig
from modspark.functions import measures, methodology, numbering, scoring
from modspark.operators import baselines, components, louvain, memetic, onepass, prep, quotient, restream, rounds, waves
from modspark.plans import clustering, experiments, state
from modspark.sources import graphs, metis, synth


@pytest.fixture(scope="session")
def cliques(spark):
    return prep.normalise_graph(synth.ring_of_cliques(spark, 6, 5))


@pytest.fixture(scope="session")
def planted(spark):
    return prep.normalise_graph(synth.planted_partition(spark, 200, 5, 12, 0.85))


def q(g, a):
    return measures.modularity(g.arcs, g.nodes, a)


def test_normalise(spark):
    e = spark.createDataFrame([("b", "a", 2), ("a", "b", 3), ("a", "a", 9), ("c", None, 1), ("c", "a", 1)], "a string, b string, w long")
    g = prep.normalise_graph(e, unit=False)
    assert {tuple(r) for r in g.arcs.collect()} == {(0, 1, 5), (1, 0, 5), (0, 2, 1), (2, 0, 1)}
    assert g.two_m == 12 and [r["okey"] for r in g.nodes.orderBy("id").collect()] == ["a", "b", "c"]
    assert prep.normalise_graph(e.where("a = 'z'")).nodes.count() == 0
    lone = prep.normalise_graph(e.select("a", "b"), spark.createDataFrame([("z",)], "okey string"))
    assert lone.nodes.where("deg = 0").count() == 1


def test_dense_ids_at_scale(spark):
    keys = spark.range(1000).select((F.col("id") * 7 % 1000).alias("okey"))
    assert {r["okey"]: r["id"] for r in prep.dense_ids(keys).collect()} == {i: i for i in range(1000)}


def test_no_order_is_made_in_one_task(spark, planted):
    """No builder and no stream or edge order sorts its rows in a window without a key."""
    frames = [prep.dense_ids(spark.range(9).select(F.col("id").alias("okey"))), baselines.edge_table(planted), baselines.edge_table(planted, "shuffle")]
    frames += [numbering.ranked(planted.nodes, [F.col("wdeg").desc(), F.col("id")], "place")]
    for name in ("reverse", "hash", "degree", "first_seen", "bfs"):
        g = prep.with_order(planted, name)
        assert sorted(r["rank"] for r in g.nodes.collect()) == list(range(planted.nodes.count()))
    assert all("Window" not in f._jdf.queryExecution().toString() for f in frames)
    hidden = [line for f in ("operators/prep.py", "operators/baselines.py", "operators/onepass.py", "operators/waves.py", "sources/graphs.py") for line in open(f"modspark/{f}") if "Window.orderBy" in line]
    assert not hidden


def test_bfs_order(spark):
    g = prep.normalise_graph(spark.createDataFrame([(0, 3), (3, 1), (1, 4), (2, 5)], "a long, b long"))
    layer = {r["id"]: r["ts"] for r in prep.bfs_layers(g).collect()}
    assert layer == {0: 0, 3: 1, 1: 2, 4: 3, 2: 0, 5: 1}


@pytest.mark.parametrize("mode", list(clustering.MODES))
def test_modes_on_cliques(cliques, mode):
    r = clustering.cluster(cliques, mode, ClusterConfig(memetic=MemeticConfig(population=3, max_rounds=3, islands=1)))
    assert r.assign.count() == 30 and r.assign.select("id").distinct().count() == 30
    assert r.stats["modularity"] >= clustering.cluster(cliques, "single_pass").stats["modularity"] - 1e-12


def test_unknown_mode(cliques):
    with pytest.raises(ValueError):
        clustering.cluster(cliques, "light")


def test_parallel_rounds_never_fall(planted):
    a = onepass.init_singletons(planted.nodes)
    was = q(planted, a)
    for _ in range(3):
        vols = scoring.cluster_volumes(planted.nodes, a)
        a, after, _n, moved, _m, gain = restream.subround(planted, a, planted.arcs, vols)
        now = q(planted, a)
        assert now >= was - 1e-12 and (moved == 0 or now > was) and abs(was + gain / planted.two_m**2 - now) < 1e-9
        assert {tuple(r) for r in after.where("vol > 0").select("cid", "vol").collect()} == {tuple(r) for r in scoring.cluster_volumes(planted.nodes, a).select("cid", "vol").collect()}
        was = now


def test_parallel_restream_reaches_the_sequential_quality(planted):
    start = onepass.init_singletons(planted.nodes)
    exact, rows = restream.restream_exact(planted, start, RestreamConfig(min_rel_gain=0.0, time_limit_s=None))
    far, _ = restream.restream_parallel(planted, start, RestreamConfig(min_rel_gain=0.05, max_rounds=2), 9)
    assert q(planted, far) >= 0.7 * q(planted, exact)
    assert rows[-1][-1] == "converged" and abs(rows[-1][5] - q(planted, exact)) < 1e-9
    assert exact.select("cid").distinct().count() <= start.count()


def test_independent_set_has_no_neighbours(planted):
    a = onepass.init_singletons(planted.nodes)
    p = restream.proposals(planted.arcs, planted, a, scoring.cluster_volumes(planted.nodes, a))
    kept = rounds.independent_set(planted.arcs, p).select("src")
    assert kept.count() and planted.arcs.join(kept, "src", "left_semi").join(kept.withColumnRenamed("src", "dst"), "dst", "left_semi").count() == 0


def test_batches_and_waves_place_all(planted):
    for a in (onepass.stream_pass_batches(planted, 2, 2), onepass.stream_pass_wavefront(planted, 3)):
        assert a.count() == planted.nodes.count() and q(planted, a) > q(planted, onepass.init_singletons(planted.nodes))


def test_batches_leave_no_gain_on_a_dense_graph(spark):
    g = prep.normalise_graph(synth.planted_partition(spark, 120, 4, 40, 0.7))
    exact = q(g, onepass.stream_pass_exact(g))
    assert q(g, onepass.stream_pass_batches(g, 1, 1)) > 0.6 * exact
    ring = prep.normalise_graph(synth.ring_of_cliques(spark, 2, 5))
    arcs = ring.arcs.where("dst < src")
    alone = onepass.stream_pass_batches(ring, 1, 1, task_arcs=0)
    late = restream.proposals(arcs, ring, alone, scoring.cluster_volumes(ring.nodes, alone)).where("src = cur")
    assert late.join(alone.groupBy("cid").count().where("count = 1"), F.col("cur") == F.col("cid")).count() == 0


def test_waves_match_the_sequential_pass(planted, cliques):
    for g, share in ((planted, 0.93), (cliques, 0.85)):  # 30 nodes are too few for chunks
        exact = onepass.stream_pass_exact(g)
        a, quot, rows = waves.stream_pass_waves(g, first=8, with_quotient=True)
        assert a.count() == a.select("id").distinct().count() == g.nodes.count()
        assert q(g, a) >= share * q(g, exact)
        assert sorted(map(tuple, quot.collect())) == sorted(map(tuple, quotient.contract(g.arcs, a).collect()))
        assert sum(r[4] for r in rows) == g.nodes.count() - 8
    whole = waves.stream_pass_waves(planted, first=None)[0]  # the prefix is all there is: the same rule
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, onepass.stream_pass_exact(planted).collect()))


def test_wave_placements_never_lower_the_score(planted):
    seen = [q(planted, waves.stream_pass_waves(planted, first=0, max_waves=k)[0]) for k in (1, 4, 9)]
    assert seen == sorted(seen)
    one = waves.stream_pass_waves(planted.__class__(planted.arcs, planted.nodes.repartition(7)), first=16)[0]
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, waves.stream_pass_waves(planted, first=16)[0].collect()))


def test_wave_cut():
    assert waves.ready_cut({1000: 5, 950: 1, 0: 4}, 0.9, 0.1) == (899, 0.0)
    assert waves.ready_cut({500: 10, 0: 90}, 0.9, 0.05) == (500, 0.5)
    assert waves.ready_cut({0: 7}, 1.0, 0.5) == (0, 0.5)
    assert waves.chunk_cuts(100, 10, 4) == [10, 64] and waves.chunk_cuts(0, 0, 4) == [] and waves.chunk_cuts(5, 0, 1 << 40) == [0]


def test_prefix_size(planted):
    deg = [r["deg"] for r in planted.nodes.orderBy("rank").collect()]
    for limit in (0, 5, 60, 10**9):
        n = waves.prefix_size(planted, limit)
        assert sum(deg[:n]) <= limit and (n == len(deg) or sum(deg[: n + 1]) > limit)


def test_admission_of_heavy_graphs(spark):
    """2m = 10^10: beyond 64-bit scores; and sums made range by range give the same order."""
    two_m, r = 10**10, random.Random(4)
    rows = [(i, 900 + i % 3, r.choice((500, 501)), r.randint(1, 10**6), r.randint(1, 9), r.randint(0, 3), r.randint(1, 10**9), r.randint(1, 10**9)) for i in range(400)]
    p = spark.createDataFrame(rows, "src long, cur long, target long, d long, k long, k_cur long, vol_can long, vol_cur long")
    p = p.withColumn("gain", scoring.move_gain_int(F.col("k"), F.col("k_cur"), F.col("d"), F.col("vol_can"), F.col("vol_cur"), two_m)).where("gain > 0")
    one, two = rounds.admit(p, two_m), rounds.admit(p, two_m, 10, 1)
    assert one.count() and sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect()))
    g = prep.normalise_graph(spark.createDataFrame([(0, 1, 3 * 10**9), (1, 2, 10**9), (3, 4, 10**9)], "a long, b long, w long"), unit=False)
    assert g.two_m == 10**10
    a, _ = restream.restream_parallel(g, onepass.init_singletons(g.nodes), RestreamConfig(min_rel_gain=0.0, time_limit_s=None))
    by = {x["id"]: x["cid"] for x in a.collect()}
    assert by[0] == by[1] and by[3] == by[4] and by[0] != by[3]
    assert waves.stream_pass_waves(g, first=0)[0].count() == 5 and onepass.stream_pass(g)[0].count() == 5


def test_quotient_equals_increments_and_keeps_modularity(planted):
    a = planted.nodes.select("id", F.pmod("id", F.lit(9)).alias("cid"))
    whole = quotient.contract(planted.arcs, a)
    n = planted.nodes.count()
    for step in (50, 77, n):
        parts = [quotient.quotient_delta(planted.arcs, planted.nodes, a, i, i + step) for i in range(0, n, step)]
        assert sorted(map(tuple, quotient.merge_quotient(*parts).collect())) == sorted(map(tuple, whole.collect()))
    lab = a.select("cid").distinct().select("cid", F.pmod("cid", F.lit(4)).alias("lab"))
    one = quotient.modularity_num_quotient(whole, lab).first()["qnum"]
    assert one == measures.modularity_num(measures.cluster_sums(planted.arcs, planted.nodes, quotient.project(a, lab))).first()["qnum"]
    again = quotient.contract(quotient.as_arcs(whole), lab.select(F.col("cid").alias("id"), F.col("lab").alias("cid")))
    assert again.agg(F.sum(F.when(F.col("ci") == F.col("cj"), F.col("w")).otherwise(2 * F.col("w")))).first()[0] == planted.two_m


def test_louvain_and_memetic_find_planted_blocks(spark, planted):
    truth = planted.nodes.join(synth.planted_truth(spark, 200, 5), "okey").select("id", "label")
    for a in (louvain.louvain(planted, 1), baselines.memetic_inmemory(planted, MemeticConfig(population=3, max_rounds=3, islands=2))[0]):
        assert measures.nmi(measures.contingency(a, truth)).first()["nmi_arithmetic"] > 0.9


def test_memetic_engine_choice():
    assert memetic.choose_engine(10, 100, MemeticConfig()) == "island"
    assert memetic.choose_engine(10**8, 100, MemeticConfig()) == "tables"
    assert memetic.choose_engine(10, 4 * 10**9, MemeticConfig()) == "tables"


def test_memetic_beyond_a_task(planted):
    a = planted.nodes.select("id", F.pmod("id", F.lit(15)).alias("cid"))
    e = quotient.contract(planted.arcs, a)
    best, rows = memetic.memetic(e, quotient.supernodes(e, planted.nodes, a), MemeticConfig(population=2, max_rounds=2, island_max_edges=1))
    assert len(rows) == 2 and q(planted, quotient.project(a, best)) >= q(planted, a)
    assert all(x[5] <= y[5] for x, y in zip(rows, rows[1:]))


def test_table_recombinations(planted):
    """Children of tables: whole, never worse than the better parent after the guard; halves are balanced and stay in their clusters."""
    a, b = (planted.nodes.select("id", F.pmod("id", F.lit(k)).alias("cid")) for k in (4, 6))
    for child in (memetic.recombine_flat_table(planted, a, b), memetic.recombine_multilevel_table(planted, a, b, a, 1, 2)):
        assert child.count() == child.select("id").distinct().count() == planted.nodes.count()
        assert q(planted, child) >= max(q(planted, a), q(planted, b))
    for most in (200_000, 0):
        halves = memetic.split_table(planted, a, 3, most).withColumnRenamed("cid", "half").join(a, "id")
        sizes = [r["n"] for r in halves.groupBy("cid", "half").agg(F.count("*").alias("n")).collect()]
        assert halves.groupBy("half").agg(F.count_distinct("cid").alias("c")).where("c > 1").count() == 0 and len(sizes) == 8 and min(sizes) >= (15 if most else 8)


def test_edge_stream_orders_and_storage(planted):
    a = {tuple(r) for r in baselines.edge_stream_capped(planted, "n").collect()}
    assert a == {tuple(r) for r in baselines.edge_stream_capped(planted, "n", materialise=True).collect()}
    assert a != {tuple(r) for r in baselines.edge_stream_capped(planted, "n", "shuffle").collect()}
    assert baselines.edge_stream_batches(planted, "n", 4).count() == planted.nodes.count()


def test_components_bound_clusters(spark):
    g = prep.normalise_graph(spark.createDataFrame([(0, 1), (1, 2), (5, 6), (6, 7), (7, 8)], "a long, b long"))
    c = {r["id"]: r["cid"] for r in components.connected_components(g.arcs, g.nodes).collect()}
    assert c == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3, 6: 3}


def test_nmi_limits(spark):
    a = spark.createDataFrame([(i, i % 3) for i in range(30)], "id long, cid long")
    t = a.select("id", F.concat(F.lit("x"), "cid").alias("label"))
    r = measures.nmi(measures.contingency(a, t)).first()
    assert all(abs(r[c] - 1) < 1e-9 for c in ("nmi_arithmetic", "nmi_geometric", "nmi_max", "nmi_min"))
    assert measures.nmi(measures.contingency(a.withColumn("cid", F.lit(0)), t)).first()["nmi_arithmetic"] == 0
    with pytest.raises(ValueError):
        measures.contingency(a, t.union(t))


def test_failed_runs_have_no_mean(spark):
    s = spark.createDataFrame([("a", "x", "q", 1.0), ("b", "x", "q", None), ("a", "y", "q", 4.0), ("b", "y", "q", 1.0)], "instance string, algo string, metric string, value double")
    m = {r["algo"]: r["geomean"] for r in methodology.geomean(s).collect()}
    assert m["x"] is None and m["y"] == pytest.approx(2.0)
    assert methodology.common_instances(s, ["x", "y"]).count() == 2


def test_metis_roundtrip(spark, cliques, tmp_path):
    metis.write_metis(cliques, f"file://{tmp_path}/m")
    assert sorted(map(tuple, metis.read_metis(spark, f"file://{tmp_path}/m").collect())) == sorted(map(tuple, cliques.arcs.collect()))


def test_snapshots(spark, cliques, tmp_path):
    p = f"file://{tmp_path}/s"
    assert state.resume(spark, p) == (-1, {})
    state.save(p, 0, assign=onepass.init_singletons(cliques.nodes))
    step, tables = state.resume(spark, p)
    assert step == 0 and tables["assign"].count() == 30


def test_grown_graph(spark, cliques):
    a = onepass.stream_pass_exact(cliques)
    grown, got, _ = clustering.add_edges(cliques, a, spark.createDataFrame([(0, 99, 1)], "u long, v long, w long"))
    assert got.count() == 31 and grown.two_m == cliques.two_m + 2


@pytest.mark.parametrize("name", ["S3", "S4", "S5", "S6"])
def test_synthetic_graphs(spark, name):
    g = prep.normalise_graph(synth.SYNTH[name](spark, *((12, 12) if name == "S3" else (200,))))
    assert g.nodes.count() > 100 and g.arcs.where("src = dst").count() == 0
    assert g.arcs.count() == g.arcs.select("src", "dst").distinct().count()


def test_hyperbolic_cells_lose_no_edge(spark):
    import math

    n, deg, alpha, seed = 150, 8.0, 0.75, 1
    got = {tuple(sorted(r)) for r in synth.random_hyperbolic(spark, n, deg, alpha, seed).collect()}
    big = 2 * math.log(8 * n * alpha * alpha / (math.pi * deg * (2 * alpha - 1) ** 2))
    p = spark.range(n).select("id", (synth._u("id", F.lit(seed)) * 2 * math.pi).alias("t"), synth._u("id", F.lit(seed + 1)).alias("u")).collect()
    pts = [(x["id"], x["t"], math.acosh(1 + (math.cosh(alpha * big) - 1) * x["u"]) / alpha) for x in p]
    want = set()
    for i, (a, t, r) in enumerate(pts):
        for b, s, o in pts[:i]:
            turn = math.pi - abs(math.pi - abs(t - s))
            if math.cosh(r) * math.cosh(o) - math.sinh(r) * math.sinh(o) * math.cos(turn) <= math.cosh(big):
                want.add(tuple(sorted((a, b))))
    assert got == want


def plan(df):
    out = _io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_plans(spark, sf, planted):
    a = onepass.init_singletons(planted.nodes)
    p = plan(restream.proposals(planted.arcs, planted, a, scoring.cluster_volumes(planted.nodes, a)))
    assert "CartesianProduct" not in p and "Python" not in p and "Pandas" not in p
    assert "SinglePartition" not in p
    act = plan(restream.active_arcs(planted.arcs, a.select("id").limit(3)))
    assert "LeftSemi" in act
    built = plan(graphs.order_part(spark, sf))
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in built


def test_result_does_not_depend_on_partitions(spark, planted):
    a = restream.restream_parallel(planted, onepass.init_singletons(planted.nodes), RestreamConfig(max_rounds=1), 3)[0]
    other = prep.Graph(planted.arcs.repartition(7), planted.nodes.repartition(3))
    b = restream.restream_parallel(other, onepass.init_singletons(other.nodes), RestreamConfig(max_rounds=1), 3)[0]
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
