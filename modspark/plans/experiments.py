"""The experiments: modes and baselines over graphs, their tables, and parameter sweeps. Rows are (instance, algo, metric, value)."""

from __future__ import annotations

import os
import resource
import threading
import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import schema
from ..config import ClusterConfig, MemeticConfig, RestreamConfig
from ..functions import measures, methodology
from ..operators import baselines, louvain, onepass, restream
from ..operators.prep import Graph, normalise_graph
from ..sources import graphs, synth
from . import clustering

ALGOS = (*clustering.MODES, "edge_stream", "louvain", "memetic_inmemory")


def load(spark: SparkSession, sf_dir: str, name: str) -> tuple[Graph, DataFrame | None]:
    if name in synth.SYNTH:
        g = normalise_graph(synth.SYNTH[name](spark))
        truth = g.nodes.join(synth.planted_truth(spark), "okey").select("id", "label") if name == "S2" else None
        return g, truth
    g = graphs.build(spark, sf_dir, name)
    return g, graphs.truth(spark, sf_dir, name, g)


#: Jobs of these many runs are given to Spark at once, where nothing is measured.
AT_ONCE = 12


def side_by_side(f, rows: list) -> list:
    """f of each row, in their order; the runs share the session's tasks. The first error is raised when the runs under way have ended."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        jobs = [pool.submit(f, x) for x in rows]
        try:
            return [j.result() for j in jobs]
        except BaseException:
            for j in jobs:
                j.cancel()
            raise


def run_one(g: Graph, algo: str, cfg: ClusterConfig, v_max="n", steps: clustering.Steps | None = None) -> tuple[DataFrame, dict]:
    """The clustering and its figures: seconds, state rows, arcs read, and the name of the mode that ran. steps: see cluster()."""
    began, figures = time.monotonic(), {}
    if algo in clustering.MODES:
        r = clustering.cluster(g, algo, cfg, steps)
        # the method's own seconds: the figures that cluster() adds (modularity, counts) are no part of it
        figures = {"modularity": r.stats["modularity"], "k": float(r.stats["k"])}
        figures |= {"mode": r.stats["mode"], "state_rows": r.stats["state_rows"], "arcs_read": sum(r.stats.get("arcs_read", [])), "seconds": r.stats["seconds"]}
        if steps is not None and steps.watch is Memory:  # the greatest of its steps
            figures |= {name: max(getattr(m, of) for m in r.seen) for name, of in (("memory_mb", "peak"), ("worker_mb", "workers"), ("added_mb", "added"))}
        return r.assign, figures
    elif algo == "edge_stream":
        assign = baselines.edge_stream_capped(g, v_max)
    elif algo == "louvain":
        assign = louvain.louvain(g, cfg.seed, cfg)
    elif algo == "memetic_inmemory":
        assign = baselines.memetic_inmemory(g, cfg.memetic)[0]
    else:
        raise ValueError(algo)
    return assign, figures | {"seconds": time.monotonic() - began}


def peak_mb() -> float:
    """Greatest resident set of this process so far."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def _resident_mb() -> dict[str, float]:
    """Resident memory of this process, its JVM and their Python workers, where there is a /proc (one machine)."""
    parent, held, name = {}, {}, {}
    for pid in filter(str.isdigit, os.listdir("/proc")):
        try:
            with open(f"/proc/{pid}/stat") as f:
                said = f.read()
            with open(f"/proc/{pid}/statm") as f:
                held[int(pid)] = int(f.read().split()[1]) * os.sysconf("SC_PAGE_SIZE") / 1e6
        except OSError:
            continue
        name[int(pid)] = said[said.index("(") + 1 : said.rindex(")")]
        parent[int(pid)] = int(said[said.rindex(")") + 2 :].split()[1])
    out = {"driver": held.get(os.getpid(), 0.0), "jvm": 0.0, "workers": 0.0}
    for pid in parent:
        up = pid
        while up > 1 and up != os.getpid():
            up = parent.get(up, 0)
        if up == os.getpid() and pid != os.getpid():
            out["jvm" if name[pid] == "java" else "workers"] += held[pid]
    return out


class Memory:
    """Peak memory while a block runs, sampled: all processes, and Python workers alone. added_mb: beyond what was there before."""

    def __init__(self, every: float = 0.1):
        self.every, self.peak, self.workers, self._stop = every, 0.0, 0.0, threading.Event()

    def __enter__(self):
        self.before = sum(_resident_mb().values())
        self._thread = threading.Thread(target=self._watch, daemon=True)
        self._thread.start()
        return self

    def _watch(self):
        while True:
            now = _resident_mb()
            self.peak, self.workers = max(self.peak, sum(now.values())), max(self.workers, now["workers"])
            if self._stop.wait(self.every):
                return

    def __exit__(self, *_):
        self._stop.set()
        self._thread.join()
        self.added = max(0.0, self.peak - self.before)


def run_measured(g: Graph, algo: str, cfg: ClusterConfig, v_max="n", steps: clustering.Steps | None = None) -> tuple[DataFrame, dict]:
    """run_one(), with peak memory of all processes and of the Python workers. steps (watched by Memory): shared by the modes on g."""
    if algo in clustering.MODES:
        return run_one(g, algo, cfg, v_max, steps or clustering.Steps(Memory))
    with Memory() as m:
        assign, figures = run_one(g, algo, cfg, v_max)
    return assign, figures | {"memory_mb": m.peak, "worker_mb": m.workers, "added_mb": m.added}


def score_rows(name: str, algo: str, g: Graph, truth: DataFrame | None, assign: DataFrame, figures: dict) -> list[tuple]:
    algo, figures = figures.get("mode", algo), dict(figures)
    q, k = (figures.pop(x) if x in figures else None for x in ("modularity", "k"))
    q, k = measures.modularity(g.arcs, g.nodes, assign) if q is None else q, float(assign.select("cid").distinct().count()) if k is None else k
    rows = [(name, algo, "modularity", q), (name, algo, "k", k)]
    rows += [(name, algo, k, float(v)) for k, v in figures.items() if k != "mode"]
    if truth is not None:
        rows.append((name, algo, "nmi", measures.nmi(measures.contingency(assign, truth)).first()["nmi_arithmetic"]))
    return rows


def compare(spark: SparkSession, sf_dir: str, names: list[str], cfg: ClusterConfig | None = None, algos: tuple = ALGOS, measured: bool = True) -> DataFrame:
    """All algos on all graphs: what the quality table, the profiles, the box plots and the ground-truth table are made of.

    Graphs are built, and clusterings scored, side by side. The runs between go one by one, so that seconds and memory are their own; side by side,
    too, and without memory, if measured is not set, for tables of quality alone.
    """
    cfg = cfg or ClusterConfig()
    loaded = side_by_side(lambda name: load(spark, sf_dir, name), names)
    steps = [clustering.Steps(Memory) if measured else clustering.Steps(keeps=True) for _ in names]
    if measured:
        runs = [(i, algo, *run_measured(g, algo, cfg, steps=steps[i])) for i, (g, _) in enumerate(loaded) for algo in algos]
    else:
        # the longest first
        asked = sorted(((i, algo) for i in range(len(names)) for algo in algos), key=lambda x: -loaded[x[0]][0].two_m)
        got = side_by_side(lambda x: (*x, *run_one(loaded[x[0]][0], x[1], cfg, "n", steps[x[0]])), asked)
        runs = sorted(got, key=lambda x: (x[0], algos.index(x[1])))
    rows = side_by_side(lambda x: score_rows(names[x[0]], x[1], *loaded[x[0]], *x[2:]), runs)
    return spark.createDataFrame([r for part in rows for r in part], schema.SCORES)


STREAMING = (*clustering.MODES, "edge_stream")


def resource_boxes(scores: DataFrame) -> DataFrame:
    """scope, algo, metric and five numbers of seconds and memory: streaming methods on all graphs; all methods on graphs that all finished."""
    own = scores.where("metric in ('seconds', 'memory_mb', 'worker_mb', 'state_rows')")
    every = methodology.box_summary(own.where(own["algo"].isin(list(STREAMING)))).withColumn("scope", F.lit("streaming, all graphs"))
    timed = own.where("metric <> 'state_rows'")
    common = methodology.box_summary(methodology.common_instances(timed, list(ALGOS))).withColumn("scope", F.lit("all, common graphs"))
    return every.unionByName(common).select("scope", "algo", "metric", "low", "q1", "mid", "q3", "high", "runs")


def scaling(spark: SparkSession, edges: tuple = (100_000, 1_000_000, 10_000_000), mode: str = "single_pass", cfg: ClusterConfig | None = None) -> DataFrame:
    """Planted graphs of growing size under one mode: seconds, modularity, state rows and peak memory per number of edges."""
    rows = []
    for m in edges:
        n = m // 5
        g = normalise_graph(synth.planted_partition(spark, n, max(10, n // 100), 10, 0.8))
        assign, figures = run_measured(g, mode, cfg or ClusterConfig())
        name = f"planted {m}"
        rows += [(name, mode, k, float(v)) for k, v in figures.items() if k not in ("mode", "modularity", "k")]
        rows += [(name, mode, "modularity", figures["modularity"]), (name, mode, "nodes", float(n)), (name, mode, "state_rows_per_node", figures["state_rows"] / n)]
    return spark.createDataFrame(rows, schema.SCORES)


def quality_table(scores: DataFrame) -> DataFrame:
    """One row per graph, one column per algo."""
    return scores.where("metric = 'modularity'").groupBy("instance").pivot("algo", list(ALGOS)).max("value")


def mode_profiles(scores: DataFrame, modes: tuple = tuple(clustering.MODES)) -> DataFrame:
    """Profiles of modularity (falling from 1), seconds and state rows."""
    own = scores.where(scores["algo"].isin(list(modes)))
    up = methodology.performance_profile(own.where("metric = 'modularity' and value > 0"), [1.0, 0.99, 0.95, 0.9, 0.8, 0.5], "max")
    down = methodology.performance_profile(own.where("metric in ('seconds', 'state_rows')"), [1.0, 1.5, 2.0, 5.0, 10.0, 20.0], "min")
    return up.unionByName(down)


def cap_sweep(spark: SparkSession, sf_dir: str, names: list[str], caps: tuple = ("n", "sqrt", 10_000)) -> DataFrame:
    """The edge stream's cap: modularity per graph and cap."""
    rows = []
    for name in names:
        g, _ = load(spark, sf_dir, name)
        got = baselines.edge_stream_sweep(g, list(caps))
        rows += [(name, f"edge_stream v_max={c}", "modularity", measures.modularity(g.arcs, g.nodes, got.where(got["v_max"] == str(c)).select("id", "cid"))) for c in caps]
    return spark.createDataFrame(rows, schema.SCORES)


def edge_order(spark: SparkSession, sf_dir: str, names: list[str]) -> DataFrame:
    """The edge stream by order and storage: modularity and seconds."""
    rows = []
    for name in names:
        g, truth = load(spark, sf_dir, name)
        for order in ("input", "shuffle", *(("intra_first",) if truth is not None else ())):
            for stored in (False, True):
                t = time.monotonic()
                a = baselines.edge_stream_capped(g, "n", order, truth=truth, materialise=stored)
                algo = f"edge_stream {order}{' loaded' if stored else ''}"
                rows += [(name, algo, "modularity", measures.modularity(g.arcs, g.nodes, a)), (name, algo, "seconds", time.monotonic() - t)]
    return spark.createDataFrame(rows, schema.SCORES)


def memetic_budget(spark: SparkSession, sf_dir: str, names: list[str], budgets: tuple = (0, 5, 20)) -> DataFrame:
    """The memetic stage's rounds against its modularity. Graphs go side by side; on each, all budgets begin with one pass, and then evolve side by side."""

    def graph(name: str) -> list[tuple]:
        g, _ = load(spark, sf_dir, name)
        steps = clustering.Steps(keeps=any(budgets))

        def run(b: int) -> tuple:
            r = clustering.cluster(g, "single_pass_memetic" if b else "single_pass", ClusterConfig(memetic=MemeticConfig(max_rounds=b)), steps)
            return name, f"rounds={b}", "modularity", r.stats["modularity"]

        return side_by_side(run, sorted(budgets, reverse=True))[::-1]

    rows = {r[:2]: r for part in side_by_side(graph, names) for r in part}
    return spark.createDataFrame([rows[name, f"rounds={b}"] for name in names for b in budgets], schema.SCORES)


def restream_ablation(spark: SparkSession, sf_dir: str, names: list[str]) -> DataFrame:
    """Active nodes or all, and the relative-gain threshold: modularity, rounds, arcs read. Graphs go side by side."""
    settings = [RestreamConfig(min_rel_gain=x, active=active, max_rounds=100, time_limit_s=None) for active in ("neighbours", "all") for x in (0.0, 0.05)]

    def graph(name: str) -> list[tuple]:
        g, _ = load(spark, sf_dir, name)
        start, _ = onepass.stream_pass(g)
        rows = []
        for cfg, (a, trace) in zip(settings, restream.restream_settings(g, start, settings), strict=True):
            algo = f"{cfg.active} X={cfg.min_rel_gain}"
            rows += [(name, algo, "modularity", measures.modularity(g.arcs, g.nodes, a)), (name, algo, "rounds", float(len(trace))), (name, algo, "arcs_read", float(sum(r[6] for r in trace)))]
        return rows

    return spark.createDataFrame([r for part in side_by_side(graph, names) for r in part], schema.SCORES)
