"""What reviews found: each test failed before its finding was settled."""

import datetime as dt
import math
import os
import random
import threading
import tracemalloc

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from modspark import io
from modspark.config import ClusterConfig, MemeticConfig, RestreamConfig
from modspark.functions import udf
from modspark.llm import common, jaccard, pii, tokens
from modspark.operators import baselines, kernels, memetic, onepass, prep, restream
from modspark.plans import clustering, experiments
from modspark.queries import all_queries
from modspark.sources import graphs, synth
from modspark.streaming import streams


def against_sql(spark, sf_dir, name, *tables):
    """A query's rows and those of its SQL over the same tables."""
    c = duckdb.connect()
    for t in tables:
        c.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet{"/*.parquet" if os.path.isdir(f"{sf_dir}/{t}.parquet") else ""}')")
    df = all_queries.QUERIES[name](spark, sf_dir)
    r = c.execute(all_queries.ORACLES[name])
    names = [x[0] for x in r.description]
    return sorted((tuple(x) for x in df.select(*names).collect()), key=repr), sorted(r.fetchall(), key=repr)


def test_halves_differ_by_two_at_most(spark):
    r, n = random.Random(3), 600
    pairs = [(a, b) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(900)) if a != b]
    arcs = spark.createDataFrame([(a, b, 1) for a, b in pairs] + [(b, a, 1) for a, b in pairs], "src long, dst long, w long")
    assign = spark.range(n).select("id", F.pmod("id", F.lit(2)).alias("cid"))
    sizes = udf.bisect_groups(arcs, assign).groupBy("cid").agg(F.count("*").alias("n"), F.sum("half").alias("h")).collect()
    assert len(sizes) == 2 and all(abs(2 * x["h"] - x["n"]) <= 2 for x in sizes), sizes


def test_range_frame_rounds_seconds(spark, tmp_path):
    first = dt.datetime(2024, 1, 1)
    at = [0.6, 86401.4, 86401.5, 86402.5, 86403.5]
    e = spark.createDataFrame([(i, first + dt.timedelta(seconds=s), 1) for i, s in enumerate(at)], "event_id long, ts timestamp_ntz, user_id long")
    e.write.parquet(f"{tmp_path}/events.parquet")
    got, want = against_sql(spark, str(tmp_path), "window_range_frame", "events")
    assert got == want


def test_words_that_come_up_again_are_merged_once():
    made = []
    codes = tokens._AgedCodes(lambda w: made.append(w) or w.encode(), 3)
    for i in range(40):
        assert codes["the"] == b"the" and codes[f"w{i}"] == f"w{i}".encode()
    assert made.count("the") == 1 and len(codes) <= 3 and len(codes.old) <= 3


def test_forms_end_where_they_match_first(monkeypatch):
    """Tries of a long run: as many as its forms' matches have tokens, not as many as a segment may have."""
    tries = []

    class Form:
        def match(self, *a):
            return real.match(*a)

        def fullmatch(self, *a):
            tries.append(a)
            return real.fullmatch(*a)

    real = pii.FORMS[0]
    monkeypatch.setattr(pii, "FORMS", (Form(), *pii.FORMS[1:]))
    text = "a@b." * 200
    _, segments = pii.candidates(text, 0, len(text))
    assert len(segments) > 190 and len(tries) < 10 * len(text) / 4


#: Queries that once made their rows up.
ON_TABLES = [
    ("agg_pivot_scores", "lineitem"),
    ("join_theta_nested_loop", "lineitem"),
    ("box_summary", "lineitem"),
    ("geomean_common_instances", "lineitem"),
    ("geomean_scores", "lineitem"),
    ("improvement_pct", "lineitem"),
    ("paper_table_geomeans", "lineitem"),
    ("performance_profile_max", "lineitem"),
    ("overlay_two", "customer"),
    ("overlay_three", "customer"),
]


@pytest.mark.parametrize("name, source", ON_TABLES)
def test_reads_a_given_table(spark, sf, name, source):
    assert any(source in x for x in all_queries.QUERIES[name](spark, sf).inputFiles())
    got, want = against_sql(spark, sf, name, source)
    assert [pytest.approx(x) for x in got] == want


def test_sessions_leave_as_they_close(spark, tmp_path, monkeypatch):
    """No result that grows with the input is kept by the query's sink, and the last sessions are put out as well."""
    first, modes = dt.datetime(2024, 1, 1), []
    at = [(0, 0), (0, 5), (0, 11), (1, 1), (1, 7), (1, 13.5), (2, 13.6)]
    e = spark.createDataFrame([(i, first + dt.timedelta(hours=h), u, "a", 1.0) for i, (u, h) in enumerate(at)], "event_id long, ts timestamp_ntz, user_id long, event_type string, value double")
    e.write.parquet(f"{tmp_path}/events.parquet")
    run = streams.run_all
    monkeypatch.setattr(streams, "run_all", lambda df, mode="append", name=None: modes.append(mode) or run(df, mode, name))
    got, want = against_sql(spark, str(tmp_path), "stream_session", "events")
    assert got == want and len(got) == 6 and modes == ["append"]


def test_edge_stream_holds_a_batch_of_edges(spark, monkeypatch):
    """The edges reach the pass in portions, nodes without edges stay alone, and the clusters are those of the kernel."""
    g = prep.normalise_graph(synth.ring_of_cliques(spark, 8, 5), spark.range(1000, 1003).select(F.col("id").alias("okey")))
    edges = [tuple(r) for r in g.arcs.where("src < dst").select("src", "dst").orderBy("src", "dst").collect()]
    n = g.nodes.count()
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        df = baselines.edge_stream_sweep(g, ["n", 9])
        got = {(r["v_max"], r["id"]): r["cid"] for r in df.collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for name, most in (("n", n), ("9", 9)):
        assert [got[name, i] for i in range(n)] == kernels.edge_stream(edges, n, most)
    state = kernels.EdgeStream(n, 9)
    for at in range(0, len(edges), 7):
        state.feed(edges[at : at + 7])
    assert state.label.tolist() == kernels.edge_stream(edges, n, 9)


def test_jaccard_buckets_follow_the_text(spark, tmp_path, monkeypatch):
    class Dealt(Exception):
        pass

    def deal(buckets, *_):
        raise Dealt(buckets)

    spark.range(200).selectExpr("id as doc_id", "repeat('one two three ', 1400) as text", "uuid() as source", "uuid() as lang").write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr(jaccard, "_deal", deal)
    monkeypatch.setattr(jaccard, "LEAST_BUCKETS", 1)
    monkeypatch.setattr(jaccard, "BUCKET_BYTES", 1 << 16)
    with pytest.raises(Dealt) as got:
        jaccard.link_classes(common.documents(spark, tmp_path))
    assert got.value.args[0] == -(-200 * 1400 * 14 // (1 << 16))


def test_jaccard_verifies_with_few_sets_at_once():
    r, n = np.random.default_rng(1), 3000
    tokens_ = [r.integers(0, 1 << 63, 400, dtype=np.uint64) for _ in range(n // 2)]
    digest = np.arange(n)
    pdf = pd.DataFrame({"bucket": 0, "digest": [*digest, 0], "size": 400, "tokens": [t.tobytes() for t in tokens_ for _ in (0, 1)] + [None], "pairs": [None] * n + [jaccard._pack(digest[:-1], digest[1:])]})
    tracemalloc.start()
    got = jaccard._verify(pdf)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got.values.tolist() == [[i, i + 1] for i in range(0, n, 2)] and peak < 90e6, peak


def test_jaccard_long_sets_are_verified(monkeypatch):
    monkeypatch.setattr(jaccard, "LONG_SET", 50)
    a, b, c = np.arange(100, dtype=np.uint64), np.arange(10, 110, dtype=np.uint64), np.arange(30, 130, dtype=np.uint64)
    pdf = pd.DataFrame({"bucket": 0, "digest": [1, 2, 3, 0], "size": 100, "tokens": [a.tobytes(), b.tobytes(), c.tobytes(), None], "pairs": [None] * 3 + [jaccard._pack(np.array([1, 1, 2]), np.array([2, 3, 3]))]})
    assert jaccard._verify(pdf).values.tolist() == [[1, 2]]


def test_jaccard_pairs_only_where_enough_is_left():
    """Nodes of 100 shingles that share one, in front of 40 in one and last of the prefix in the other: at most 61 in common."""
    def found(first, second):
        nodes = pd.DataFrame({"digest": [1, 2], "label": [1, 2], "size": 100, "known": 100, "level": 1, "reach": 40, "tokens": [np.array(x, "<u8").tobytes() for x in (first, second)]})
        posted = pd.concat(jaccard._post(1)(iter([nodes])))
        return [x for out in jaccard._pairs(16, None)(iter([posted])) for p in out["payload"] for x in zip(*(c.tolist() for c in jaccard._unpack(p, "<i8", "<i8", "<u4", "<u4")), strict=True)]

    assert found([7, *range(1000, 1099)], [*range(2000, 2039), 7, *range(3000, 3060)]) == []
    assert found([*range(1000, 1005), 7, *range(1005, 1099)], [*range(2000, 2009), 7, *range(3000, 3090)]) == [(1, 2, 1, 1)]


def test_jaccard_short_runs():
    keys = np.repeat([5, 6, 7], [600, 1, 255])
    cuts = jaccard._short_runs(keys)
    assert np.diff(cuts).tolist() == [255, 255, 90, 1, 255] and np.repeat(keys[cuts[:-1]], np.diff(cuts)).tolist() == keys.tolist()


def test_coactivity_makes_no_table_of_pairs(spark, tmp_path, monkeypatch):
    """prep_user_coactivity: pairs are counted where they arise, and agree with the SQL; neither they nor arcs of them are written."""
    r, t0 = random.Random(5), dt.datetime(2024, 1, 1)
    rows = [(i, t0 + dt.timedelta(seconds=r.choice((7, 299, 300, 5000, r.randrange(100_000)))), r.choice((None, 9, 9, r.randrange(300)))) for i in range(2500)] + [(-1, None, 1), (-2, t0 + dt.timedelta(days=9), 7777)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long").write.parquet(f"{tmp_path}/events.parquet")
    made, settle = [], io.settle
    monkeypatch.setattr(io, "settle", lambda df, name="state", *folders: made.append(name) or settle(df, name, *folders))
    got, want = against_sql(spark, str(tmp_path), "prep_user_coactivity", "events")
    assert got == want and len(got) > 1000
    assert not {"pairs", "arcs"} & set(made), made
    e = spark.createDataFrame([(i % 7, (i * i) % 41 + 1) for i in range(900)], "win long, item long").distinct()
    both = e.join(e.select("win", F.col("item").alias("b")), "win").where("item < b").groupBy("item", "b").count()
    for most in (1, 30, 400):  # many blocks and chunks, and few
        assert sorted(map(tuple, graphs.shared_counts(e, most).collect())) == sorted(map(tuple, both.collect()))


def test_restream_settings_share_their_rounds(spark, monkeypatch):
    """rq_restream_ablation: settings that differ in the threshold alone are one task's; each has the result of its own run."""
    g = prep.normalise_graph(synth.SYNTH["S1"](spark))
    start = onepass.init_singletons(g.nodes)
    settings = [RestreamConfig(min_rel_gain=x, active=active, max_rounds=100, time_limit_s=None) for active in ("neighbours", "all") for x in (0.0, 0.05, 0.5)]
    rows = lambda a: sorted(map(tuple, a.select("id", "cid").collect()))
    got = restream.restream_settings(g, start, settings)
    for cfg, (a, trace) in zip(settings, got, strict=True):
        alone, told = restream.restream_exact(g, start, cfg)
        assert (rows(a), trace) == (rows(alone), told), cfg
    r = random.Random(2)
    ends = {(min(a, b), max(a, b)) for a, b in ((r.randrange(300), r.randrange(300)) for _ in range(1200)) if a != b}
    m, order = kernels.Mem(300, [(a, b, 1) for x, y in ends for a, b in ((x, y), (y, x))]), list(range(300))
    many = kernels.restream_many(m, order, order, [0.0, 0.02, 0.3])
    assert many == [kernels.restream(m, order, order, x) for x in (0.0, 0.02, 0.3)] and len({len(told) for _, told in many}) > 1
    asked = []
    monkeypatch.setattr(experiments, "load", lambda spark, sf_dir, name: (g, None))
    monkeypatch.setattr(restream, "restream_settings", lambda g, start, many: asked.append(len(many)) or got[:1] * len(many))
    assert len(experiments.restream_ablation(spark, "", ["S1"]).collect()) == 12 and asked == [4]


def test_modes_share_their_steps(spark, monkeypatch):
    """mode_comparison and the tables made of it: one pass and one evolution a graph, with the results of each mode's own run."""
    g = prep.normalise_graph(synth.SYNTH["S1"](spark))
    alone = {m: clustering.cluster(g, m).stats for m in clustering.MODES}
    counts, once = {}, lambda name, f: lambda *a, **k: counts.__setitem__(name, counts.get(name, 0) + 1) or f(*a, **k)
    monkeypatch.setattr(onepass, "stream_pass", once("pass", onepass.stream_pass))
    monkeypatch.setattr(memetic, "memetic", once("memetic", memetic.memetic))
    monkeypatch.setattr(experiments, "load", lambda spark, sf_dir, name: (g, None))
    got = {(r["algo"], r["metric"]): r["value"] for r in experiments.compare(spark, "", ["S1"], ClusterConfig(), tuple(clustering.MODES)).collect()}
    assert counts == {"pass": 1, "memetic": 1}
    for m, stats in alone.items():
        assert (got[m, "modularity"], got[m, "k"], got[m, "state_rows"], got[m, "arcs_read"]) == (stats["modularity"], stats["k"], stats["state_rows"], sum(stats.get("arcs_read", []))), m
        assert got[m, "memory_mb"] > 0 and got[m, "seconds"] > 0
    assert got["full", "seconds"] > got["single_pass_memetic", "seconds"] > got["single_pass", "seconds"]


def test_budgets_share_their_pass(spark, monkeypatch):
    """rq_memetic_budget: the rounds' number changes nothing of the pass before them; each budget has its own run's modularity."""
    g = prep.normalise_graph(synth.SYNTH["S1"](spark))
    want = {f"rounds={b}": clustering.cluster(g, "single_pass_memetic" if b else "single_pass", ClusterConfig(memetic=MemeticConfig(max_rounds=b))).stats["modularity"] for b in (0, 2, 4)}
    passes, own = [], onepass.stream_pass
    monkeypatch.setattr(onepass, "stream_pass", lambda *a, **k: passes.append(1) or own(*a, **k))
    monkeypatch.setattr(experiments, "load", lambda spark, sf_dir, name: (g, None))
    assert {r["algo"]: r["value"] for r in experiments.memetic_budget(spark, "", ["S1"], (0, 2, 4)).collect()} == want and len(passes) == 1


def test_hyperbolic_graph_has_all_near_pairs(spark):
    """S5 is one join for all pairs of bands (it was one for each, 78 s of building at check_s); its edges are those of a test of all pairs."""
    n, degree, alpha = 300, 6.0, 0.75
    big = 2 * math.log(8 * n * alpha * alpha / (math.pi * degree * (2 * alpha - 1) ** 2))
    u = lambda k: synth._u("id", F.lit(k))
    p = spark.range(n).select("id", (u(1) * 2 * math.pi).alias("t"), (F.acosh(1 + (math.cosh(alpha * big) - 1) * u(2)) / alpha).alias("r")).orderBy("id").collect()
    t, r = (np.array([x[c] for x in p]) for c in ("t", "r"))
    turn = math.pi - np.abs(math.pi - np.abs(t[:, None] - t[None, :]))
    near = np.cosh(r)[:, None] * np.cosh(r)[None, :] - np.sinh(r)[:, None] * np.sinh(r)[None, :] * np.cos(turn) <= math.cosh(big)
    got = synth.random_hyperbolic(spark, n, degree, alpha)
    assert got._jdf.queryExecution().optimizedPlan().toString().count("Join") <= 3
    pairs = [(min(a, b), max(a, b)) for a, b in map(tuple, got.collect())]
    assert sorted(pairs) == [(a, b) for a in range(n) for b in range(a + 1, n) if near[a, b]] and len(pairs) > 300


def test_graphs_go_side_by_side(spark, monkeypatch):
    """graphs wait for each other here, so that runs one by one would not end; no result changes."""
    g = prep.normalise_graph(synth.SYNTH["S1"](spark))
    algos = ("single_pass", "full", "louvain")
    monkeypatch.setattr(experiments, "load", lambda spark, sf_dir, name: (g, None))
    want = {tuple(r) for r in experiments.compare(spark, "", ["A", "B"], None, algos).collect() if r["metric"] in ("modularity", "k", "state_rows")}
    meet = threading.Barrier(2, timeout=60)
    monkeypatch.setattr(experiments, "load", lambda spark, sf_dir, name: meet.wait() >= 0 and (g, None))
    got = {tuple(r) for r in experiments.compare(spark, "", ["A", "B"], None, algos, False).collect()}
    assert want <= got and len(want) == 16 and not {m for _, _, m, _ in got} & {"memory_mb", "worker_mb"}
    assert [r["instance"] for r in experiments.memetic_budget(spark, "", ["A", "B"], (0, 2)).collect()] == ["A", "A", "B", "B"]
    assert len(experiments.restream_ablation(spark, "", ["A", "B"]).collect()) == 24
    with pytest.raises(ZeroDivisionError):
        experiments.side_by_side(lambda x: 1 / x, [1, 0, 2])
