"""The sequential kernels: worked values, brute force on small graphs, invariants."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from modspark.operators import kernels as k

TRIANGLES = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (3, 5), (4, 5)]


def mem(n, edges):
    return k.Mem(n, [(a, b, 1) for a, b in edges] + [(b, a, 1) for a, b in edges])


def q(g, label):
    return g.qnum(label) / g.two_m**2


def partitions(n):
    if n == 1:
        yield [0]
        return
    for p in partitions(n - 1):
        for c in range(max(p) + 2):
            yield [*p, c]


@st.composite
def small_graphs(draw):
    n = draw(st.integers(2, 9))
    pairs = list(itertools.combinations(range(n), 2))
    return mem(n, draw(st.lists(st.sampled_from(pairs), min_size=1, unique=True)))


def test_worked_example():
    g = mem(6, TRIANGLES)
    assert q(g, list(range(6))) == pytest.approx(-34 / 196)
    one = k.stream_pass(g, list(range(6)))
    assert one == [0, 0, 0, 3, 3, 3] and q(g, one) == pytest.approx(5 / 14)
    every = k.stream_pass(g, list(range(6)), "all")
    assert q(g, every) == pytest.approx(38 / 196)
    quotient, to = g.contract(one)
    assert quotient.loop == [6, 6] and quotient.adj[0] == {1: 1} and quotient.deg == [7, 7] and quotient.weight == [3, 3]
    assert to == [0, 0, 0, 1, 1, 1]


@settings(max_examples=40, deadline=None)
@given(small_graphs(), st.integers(0, 99))
def test_bounds_and_equivalence(g, seed):
    best = max(g.qnum(p) for p in partitions(g.n)) if g.n <= 7 else None
    r = random.Random(seed)
    label = [r.randrange(3) for _ in range(g.n)]
    order = list(range(g.n))
    r.shuffle(order)
    found = [k.stream_pass(g, order), k.restream(g, label, order, 0.0)[0], k.louvain(g, seed)[0], k.individual(g, seed), k.evolve(g, 3, 3, seed)[0]]
    for f in found:
        assert len(f) == g.n and (best is None or g.qnum(f) <= best)
    coarse, to = g.contract(label)
    assert coarse.two_m == g.two_m
    half = [c % 2 for c in range(coarse.n)]
    assert coarse.qnum(half) == g.qnum([half[p] for p in to])


@settings(max_examples=40, deadline=None)
@given(small_graphs(), st.integers(0, 99))
def test_gains_add_up_and_end_at_a_fixpoint(g, seed):
    start = list(range(g.n))
    label, rows = k.restream(g, start, start, 0.0, 1000)
    assert g.qnum(label) - g.qnum(start) == sum(r[3] for r in rows)
    full, _ = k.restream(g, label, start, 0.0, 1000, "all")
    vol = k.volumes(g, full)
    assert all(k._best(g, v, full, vol)[0] == 0 for v in range(g.n))


@settings(max_examples=30, deadline=None)
@given(small_graphs(), st.integers(0, 99))
def test_recombination_never_worsens(g, seed):
    a, b = k.individual(g, seed), k.individual(g, seed + 1)
    top = max(g.qnum(a), g.qnum(b))
    assert g.qnum(k.recombine_flat(g, a, b, seed)) >= top
    assert g.qnum(k.recombine_multilevel(g, a, b, seed)) >= top
    o = k.overlay(a, b)
    assert all(a[i] == a[j] and b[i] == b[j] for i in range(g.n) for j in range(g.n) if o[i] == o[j])
    assert k.overlay(a, a) == [a.index(c) for c in a]


def test_replacement_evicts_the_most_similar():
    g = mem(6, TRIANGLES)
    pop = [list(range(6)), [0, 0, 1, 3, 3, 3], [0] * 6]
    child = [0, 0, 0, 3, 3, 3]
    assert k.replace(g, pop, child) == 2 and pop[2] == child  # it cuts one edge less; the second cuts two more
    assert k.replace(g, [child], list(range(6))) is None
    assert k.cut_distance(g, child, child) == 0


def test_split_is_balanced():
    g = mem(8, [(i, i + 1) for i in range(7)])
    label = k.split_all(g, [0] * 8, 1)
    assert sorted(label.count(c) for c in set(label)) == [4, 4]
    assert k.split_all(mem(2, [(0, 1)]), [0, 1], 1) == [0, 1]


def test_edge_stream_caps():
    edges = [(0, 1), (1, 2), (0, 2)]
    assert len(set(k.edge_stream(edges, 3, None))) == 1
    assert k.edge_stream(edges, 3, 0) == [0, 1, 2]
    assert k.edge_stream(edges, 3, 10_000) == k.edge_stream(edges, 3, None)


def test_empty_and_isolated():
    g = k.Mem(3, [])
    assert k.stream_pass(g, [0, 1, 2]) == [0, 1, 2]
    assert k.louvain(g)[0] == [0, 1, 2]
    assert k.restream(g, [0, 1, 2], [0, 1, 2])[1][-1][-1] == "converged"


def test_full_reaches_the_optimum_on_cliques():
    edges = [(c * 4 + i, c * 4 + j) for c in range(3) for i in range(4) for j in range(i)] + [(c * 4, (c * 4 + 5) % 12) for c in range(3)]
    g = mem(12, edges)
    label, rows, _ = k.evolve(g, 4, 6, 1)
    assert len(set(label)) == 3 and all(x[3] <= y[3] for x, y in zip(rows, rows[1:], strict=False))
