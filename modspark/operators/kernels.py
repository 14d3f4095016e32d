"""Sequential kernels over one graph in memory: exact node stream, re-stream, edge stream, Louvain, label propagation, evolution.

They run in single tasks on graphs below the configured limits (and on quotient graphs), and are what the parallel rounds are tested
against. All scores are whole numbers: a move's gain times 2m^2.
"""

from __future__ import annotations

import random
from array import array
from collections import defaultdict, deque


class Mem:
    """A graph as adjacency dictionaries. adj[v]: neighbour -> weight, loops apart in loop[v] (both directions counted)."""

    def __init__(self, n: int, arcs, weight: list[int] | None = None):
        self.n = n
        self.adj: list[dict[int, int]] = [{} for _ in range(n)]
        self.loop = [0] * n
        for u, v, w in arcs:
            if u == v:
                self.loop[u] += w
            else:
                self.adj[u][v] = self.adj[u].get(v, 0) + w
        self.deg = [sum(a.values()) + lp for a, lp in zip(self.adj, self.loop, strict=True)]
        self.two_m = sum(self.deg)
        self.weight = weight or [1] * n

    def qnum(self, label: list[int]) -> int:
        """2m * inner weight - sum of squared volumes."""
        inner, vol = sum(self.loop), defaultdict(int)
        for v, a in enumerate(self.adj):
            c = label[v]
            vol[c] += self.deg[v]
            for u, w in a.items():
                if label[u] == c:
                    inner += w
        return self.two_m * inner - sum(x * x for x in vol.values())

    def contract(self, label: list[int]) -> tuple[Mem, list[int]]:
        """The quotient graph and each node's place in it; places follow the labels' order of first use."""
        place: dict[int, int] = {}
        to = [place.setdefault(c, len(place)) for c in label]
        arcs, weight = defaultdict(int), [0] * len(place)
        for v, a in enumerate(self.adj):
            weight[to[v]] += self.weight[v]
            if self.loop[v]:
                arcs[to[v], to[v]] += self.loop[v]
            for u, w in a.items():
                arcs[to[v], to[u]] += w
        return Mem(len(place), ((u, v, w) for (u, v), w in arcs.items()), weight), to


def _best(g: Mem, v: int, label, vol, only=None) -> tuple[int, int]:
    """(gain, cluster) of v's best move; gain 0 and its own cluster if none is positive. only: a test that neighbours must pass."""
    cur, links = label[v], {}
    for u, w in g.adj[v].items():
        if only is None or only(u):
            c = label[u]
            links[c] = links.get(c, 0) + w
    d, own, vc = g.deg[v], links.get(cur, 0), vol[cur]
    best, to = 0, cur
    for c, k in links.items():
        if c != cur:
            gain = g.two_m * (k - own) - d * (d + vol[c] - vc)
            if gain > best or (gain == best and gain > 0 and c < to):
                best, to = gain, c
    return best, to


def _move(g: Mem, v: int, to: int, label, vol) -> None:
    vol[label[v]] -= g.deg[v]
    vol[to] += g.deg[v]
    label[v] = to


def volumes(g: Mem, label: list[int]) -> defaultdict:
    vol = defaultdict(int)
    for v, c in enumerate(label):
        vol[c] += g.deg[v]
    return vol


def stream_pass(g: Mem, order: list[int], candidates: str = "assigned") -> list[int]:
    """Each node, in order, joins the neighbouring cluster of the greatest gain or stays alone."""
    label = list(range(g.n))
    vol, placed = volumes(g, label), [False] * g.n
    only = placed.__getitem__ if candidates == "assigned" else None
    for v in order:
        gain, to = _best(g, v, label, vol, only)
        if gain > 0:
            _move(g, v, to, label, vol)
        placed[v] = True
    return label


def place_in_order(nodes, links: dict, label: dict, vol: dict, two_m: int) -> dict:
    """Where each of nodes (rank, node, degree) moves, in this order, by its links (neighbour, weight); label and vol are those of all that links reach."""
    moved = {}
    for _, v, d in nodes:
        cur, k = label[v], {}
        for u, w in links.get(v, ()):
            k[label[u]] = k.get(label[u], 0) + w
        own, best, to = k.get(cur, 0), 0, cur
        for c, x in k.items():
            if c != cur:
                gain = two_m * (x - own) - d * (d + vol[c] - vol[cur])
                if gain > best or (gain == best and gain > 0 and c < to):
                    best, to = gain, c
        if to != cur:
            label[v], moved[v] = to, to
            vol[cur] -= d
            vol[to] += d
    return moved


def restream(g: Mem, label: list[int], order: list[int], min_rel_gain: float = 0.05, max_rounds: int = 50, active_mode: str = "neighbours", include_movers: bool = False, deadline=None):
    """Rounds over the active nodes in stream order. Returns labels and (round, active, moves, gain, qnum, arcs read, stop) rows."""
    return restream_many(g, label, order, [min_rel_gain], max_rounds, active_mode, include_movers, deadline)[0]


def restream_many(g: Mem, label: list[int], order: list[int], gains: list[float], max_rounds: int = 50, active_mode: str = "neighbours", include_movers: bool = False, deadline=None):
    """restream()'s labels and rows for each threshold of gains: they only say where to stop, so that the rounds are made once for all."""
    label, vol, q, rows = list(label), volumes(g, label), g.qnum(label), []
    rank = {v: i for i, v in enumerate(order)}
    active, out = list(order), [None if max_rounds > 0 else (list(label), []) for _ in gains]
    for r in range(max_rounds):
        gained, moves, nxt, read = 0, 0, set(), 0
        for v in active:
            read += len(g.adj[v])
            gain, to = _best(g, v, label, vol)
            if gain > 0:
                _move(g, v, to, label, vol)
                gained, moves = gained + 2 * gain, moves + 1
                nxt.update(g.adj[v])
                if include_movers:
                    nxt.add(v)
        before, q = q, q + gained
        late = deadline is not None and deadline()
        for i, x in enumerate(gains):
            stop = ""
            if not moves or not nxt:
                stop = "converged"
            elif gained <= 0 or (before + gained > 0 and gained < x * q):
                stop = "small gain"
            elif late:
                stop = "time"
            elif r == max_rounds - 1:
                stop = "rounds"
            if stop and out[i] is None:
                out[i] = list(label), [*rows, (r, len(active), moves, gained, q, read, stop)]
        rows.append((r, len(active), moves, gained, q, read, ""))
        if None not in out:
            break
        active = list(order) if active_mode == "all" else sorted(nxt, key=rank.__getitem__)
    return out


class EdgeStream:
    """State of a volume-capped clustering of an edge stream: three whole numbers of eight bytes a node, whatever the number of edges."""

    def __init__(self, n: int, v_max: int | None):
        self.label, self.deg, self.vol, self.v_max = array("q", range(n)), array("q", bytes(8 * n)), array("q", bytes(8 * n)), v_max

    def feed(self, edges) -> None:
        """Per edge the endpoint of the lighter community joins the other, while both are light."""
        label, deg, vol, v_max = self.label, self.deg, self.vol, self.v_max
        for u, v in edges:
            deg[u] += 1
            deg[v] += 1
            a, b = label[u], label[v]
            vol[a] += 1
            vol[b] += 1
            if a != b and (v_max is None or (vol[a] <= v_max and vol[b] <= v_max)):
                if vol[a] <= vol[b]:
                    vol[a] -= deg[u]
                    vol[b] += deg[u]
                    label[u] = b
                else:
                    vol[b] -= deg[v]
                    vol[a] += deg[v]
                    label[v] = a


def edge_stream(edges, n: int, v_max: int | None) -> list[int]:
    """The clusters that an edge stream ends with."""
    state = EdgeStream(n, v_max)
    state.feed(edges)
    return state.label.tolist()


def sweeps(g: Mem, label: list[int], rng: random.Random | None, max_sweeps: int = 50) -> bool:
    """Local moves, in place, until a sweep makes none; whether any was made."""
    vol, order, any_ = volumes(g, label), list(range(g.n)), False
    for _ in range(max_sweeps):
        if rng:
            rng.shuffle(order)
        moved = False
        for v in order:
            gain, to = _best(g, v, label, vol)
            if gain > 0:
                _move(g, v, to, label, vol)
                moved = any_ = True
        if not moved:
            break
    return any_


def louvain(g: Mem, seed: int | None = None, start: list[int] | None = None, max_levels: int = 30) -> tuple[list[int], list[int]]:
    """Labels and the modularity numerator after each level. start: a clustering to begin from."""
    rng = random.Random(seed) if seed is not None else None
    label = list(range(g.n)) if start is None else list(start)
    level, to, track = g, list(range(g.n)), []
    own = label
    for _ in range(max_levels):
        changed = sweeps(level, own, rng)
        label = [own[p] for p in to]
        track.append(g.qnum(label))
        if not changed and start is None or len(set(own)) == level.n:
            break
        level, step = level.contract(own)
        to = [step[p] for p in to]
        own, start = list(range(level.n)), None
    return label, track


def label_propagation(g: Mem, bound: int, rounds: int, rng: random.Random, within: list[int] | None = None) -> list[int]:
    """Nodes take the label of the greatest link weight whose node weight stays within bound; within: labels don't leave their cells."""
    label, size = list(range(g.n)), list(g.weight)
    order = list(range(g.n))
    for _ in range(rounds):
        rng.shuffle(order)
        moved = 0
        for v in order:
            links = defaultdict(int)
            for u, w in g.adj[v].items():
                if within is None or within[u] == within[v]:
                    links[label[u]] += w
            best, to = links.get(label[v], 0), label[v]
            for c, k in links.items():
                if c != label[v] and size[c] + g.weight[v] <= bound and (k > best or (k == best and rng.random() < 0.5)):
                    best, to = k, c
            if to != label[v]:
                size[label[v]] -= g.weight[v]
                size[to] += g.weight[v]
                label[v] = to
                moved += 1
        if not moved:
            break
    return label


def individual(g: Mem, seed: int) -> list[int]:
    """A start for the population: bounded label propagation, then Louvain on what it contracts to."""
    rng = random.Random(seed)
    total = sum(g.weight)
    bound = max(max(g.weight), int(total / (2 + rng.random() * max(2, g.n // 4))))
    coarse, to = g.contract(label_propagation(g, bound, 3, rng))
    label, _ = louvain(coarse, rng.randrange(1 << 30))
    label = [label[p] for p in to]
    sweeps(g, label, rng)
    return label


def overlay(*labels: list[int]) -> list[int]:
    """Together if and only if together in all; named by the first member."""
    first: dict[tuple, int] = {}
    return [first.setdefault(key, i) for i, key in enumerate(zip(*labels, strict=True))]


def recombine_flat(g: Mem, a: list[int], b: list[int], seed: int) -> list[int]:
    coarse, to = g.contract(overlay(a, b))
    label, _ = louvain(coarse, seed)
    child = [label[p] for p in to]
    better = max((a, b), key=g.qnum)
    if g.qnum(child) < g.qnum(better):
        child = list(better)
        sweeps(g, child, random.Random(seed))
    return child


def recombine_multilevel(g: Mem, a: list[int], b: list[int], seed: int) -> list[int]:
    """Coarsens inside the overlay's cells, starts at the coarsest level from the better parent, refines on every level back."""
    rng = random.Random(seed)
    better = max((a, b), key=g.qnum)
    levels, level, cells, own = [], g, overlay(a, b), list(better)
    while level.n > 2:
        grouped = label_propagation(level, max(2, sum(level.weight) // 4), 2, rng, cells)
        if len(set(grouped)) == level.n:
            break
        coarse, to = level.contract(grouped)
        levels.append((level, to))
        c2, o2 = [0] * coarse.n, [0] * coarse.n
        for v, p in enumerate(to):
            c2[p], o2[p] = cells[v], own[v]
        level, cells, own = coarse, c2, o2
    child = list(own)
    # labels are names of the parent's clusters; sweeps move nodes among those of their neighbours
    sweeps(level, child, rng)
    for fine, to in reversed(levels):
        child = [child[p] for p in to]
        sweeps(fine, child, rng)
    return child if g.qnum(child) >= g.qnum(better) else list(better)


def bisect(g: Mem, members: list[int], rng: random.Random, eps: float = 0.03) -> list[int]:
    """One of two blocks of about equal weight of a cluster: grown by breadth, then moved towards a smaller cut."""
    if len(members) < 2:
        return []
    inside, total = set(members), sum(g.weight[v] for v in members)
    block, size, seen, queue = set(), 0, set(), deque()
    pool = list(members)
    rng.shuffle(pool)
    waiting = iter(pool)
    heaviest = max(g.weight[u] for u in members)
    while size * 2 < total:
        if not queue:
            fresh = next((v for v in waiting if v not in seen), None)
            if fresh is None:
                break
            queue.append(fresh)
            seen.add(fresh)
        v = queue.popleft()
        if size and size + g.weight[v] > (1 + eps) * total / 2 + heaviest / 2:
            continue
        block.add(v)
        size += g.weight[v]
        for u in g.adj[v]:
            if u in inside and u not in seen:
                seen.add(u)
                queue.append(u)
    limit = max((1 + eps) * total / 2, size, total - size)
    for v in pool:
        same = sum(w for u, w in g.adj[v].items() if u in inside and (u in block) == (v in block))
        other = sum(w for u, w in g.adj[v].items() if u in inside and (u in block) != (v in block))
        after = size + (g.weight[v] if v not in block else -g.weight[v])
        if other > same and 0 < after < total and max(after, total - after) <= limit:
            block ^= {v}
            size = after
    return sorted(block)


def split_all(g: Mem, label: list[int], seed: int) -> list[int]:
    """Every cluster halved; new clusters are named by their first member beyond the old names."""
    rng, members, out = random.Random(seed), defaultdict(list), list(label)
    for v, c in enumerate(label):
        members[c].append(v)
    base = max(label, default=0) + 1
    for c in sorted(members):
        for v in bisect(g, members[c], rng):
            out[v] = base + c
    return out


def cut_distance(g: Mem, a: list[int], b: list[int]) -> int:
    """Edges that one clustering cuts and the other doesn't."""
    return sum((a[u] != a[v]) != (b[u] != b[v]) for v in range(g.n) for u in g.adj[v] if u > v)


def replace(g: Mem, pop: list[list[int]], child: list[int], fit: list[int] | None = None) -> int | None:
    """The most similar member that isn't better gives way: its place, or None if the child is dropped. fit: the members' scores, kept up to date."""
    q, own = g.qnum(child), [g.qnum(p) for p in pop] if fit is None else fit
    worse = [(cut_distance(g, p, child), own[i], i) for i, p in enumerate(pop) if own[i] <= q]
    if not worse:
        return None
    i = min(worse)[2]
    pop[i] = child
    own[i] = q
    return i


def evolve(g: Mem, population: int, rounds: int, seed: int, p_mutation: float = 0.1, p_flat: float = 0.5, tournament: int = 2, start: list[list[int]] | None = None, deadline=None):
    """The best labels and (round, kind, qnum of the child, best qnum, replaced) rows."""
    rng = random.Random(seed)
    pop = list(start or []) + [individual(g, rng.randrange(1 << 30)) for _ in range(population - len(start or []))]
    rows, fit = [], [g.qnum(p) for p in pop]

    def pick():
        return max(rng.sample(range(len(pop)), min(tournament, len(pop))), key=lambda i: (fit[i], -i))

    for r in range(rounds):
        i, j = pick(), pick()
        for _ in range(8):
            if i != j or len(pop) < 2:
                break
            j = pick()
        a, b = pop[i], pop[j]
        s = rng.randrange(1 << 30)
        if rng.random() < p_mutation:
            kind, child = "mutation", recombine_multilevel(g, split_all(g, a, s), split_all(g, b, s + 1), s)
        elif rng.random() < p_flat:
            kind, child = "flat", recombine_flat(g, a, b, s)
        else:
            kind, child = "multilevel", recombine_multilevel(g, a, b, s)
        at = replace(g, pop, child, fit)
        rows.append((r, kind, g.qnum(child) if at is None else fit[at], max(fit), -1 if at is None else at))
        if deadline is not None and deadline():
            break
    best = max(range(len(pop)), key=lambda i: (fit[i], -i))
    return pop[best], rows, pop
