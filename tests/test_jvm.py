"""The loops in the JVM against those in Python: the same labels, rows and random numbers."""

import random

import pytest

from modspark.config import MemeticConfig, RestreamConfig
from modspark.operators import jvm, louvain, memetic, onepass, restream
from modspark.operators.prep import Graph, node_table


def weighted(spark, n: int, m: int, seed: int, most: int) -> Graph:
    """Weighted arcs between ids with gaps, in an order of their own; some nodes are isolated."""
    r = random.Random(seed)
    e = {(min(a, b), max(a, b)): r.randint(1, most) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}
    arcs = spark.createDataFrame([(x * 3, y * 3, w) for (a, b), w in e.items() for x, y in ((a, b), (b, a))], "src long, dst long, w long")
    nodes = node_table(arcs, spark.range(n).selectExpr("id * 3 as id")).selectExpr("id", "okey", "(id * 7) % 997 as rank", "deg", "wdeg", "1 + id % 3 as cw")
    return Graph(arcs.cache(), nodes.cache())


def results(g: Graph) -> list:
    rows = lambda a: sorted(map(tuple, a.collect()))
    one = {rule: onepass.stream_pass_exact(g, rule) for rule in ("assigned", "all")}
    out = [rows(a) for a in one.values()]
    settings = [RestreamConfig(min_rel_gain=x, active=active, include_movers=movers, max_rounds=7, time_limit_s=None) for active in ("neighbours", "all") for movers in (False, True) for x in (0.0, 0.02)]
    for a, told in [*restream.restream_settings(g, one["assigned"], settings), restream.restream_exact(g, onepass.init_singletons(g.nodes)), louvain.louvain_exact(g, 3), louvain.louvain_exact(g)]:
        out.append((rows(a), told))
    edges = g.arcs.where("src < dst").selectExpr("src as ci", "dst as cj", "w").union(g.nodes.where("id % 2 = 0").selectExpr("id", "id", "2 * cw"))
    supernodes = g.nodes.selectExpr("id as cid", "cw", "0L as self_w", "wdeg + if(id % 2 = 0, 2 * cw, 0) as vol")
    best, told = memetic.memetic(edges, supernodes, MemeticConfig(population=4, max_rounds=16, p_mutation=0.3))
    assert {row[3] for row in told} == {"mutation", "flat", "multilevel"}
    return [*out, (rows(best), told)]


@pytest.mark.parametrize(("n", "m", "most"), [(40, 60, 1), (330, 900, 1), (200, 3000, 1000)])
def test_jvm_loops_equal_python(spark, monkeypatch, n, m, most):
    """F1 to F7: passes, re-streams, Louvain and evolutions run in the JVM, and no result changes."""
    g = weighted(spark, n, m, n, most)
    monkeypatch.setattr(jvm, "run", lambda *a, _own=jvm.run: ran.append(1) or _own(*a))
    ran: list = []
    fast = results(g)
    assert len(ran) == 8
    monkeypatch.setattr(jvm, "MAX_2M", 0)
    slow = results(g)
    assert len(ran) == 8
    for a, b in zip(fast, slow, strict=True):
        assert a == b
