"""Thresholds and parameters of the clustering engine."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class MemeticConfig:
    """The evolution on the quotient graph: rounds and a time limit, whichever ends first."""

    population: int = 6
    max_rounds: int = 12
    time_limit_s: float | None = None
    p_mutation: float = 0.1
    p_flat: float = 0.5
    tournament: int = 2
    islands: int = 2
    seed: int = 1
    #: Quotient edges up to which whole populations evolve in single tasks (some 200 bytes each there); beyond, one population of tables evolves.
    island_max_edges: int = 2_000_000


@dataclass(frozen=True)
class RestreamConfig:
    """The local search: stops when nothing is active, the gain of a sweep is below a share of the modularity, or time is up."""

    min_rel_gain: float = 0.05
    max_rounds: int = 50
    max_subrounds: int = 24
    time_limit_s: float | None = 600.0
    active: str = "neighbours"  # or "all"
    include_movers: bool = False


@dataclass(frozen=True)
class ClusterConfig:
    """order: the stream's order. candidates: which neighbours' clusters a node may join in the first pass."""

    order: str = "input"
    candidates: str = "assigned"
    seed: int = 1
    #: The waves of the parallel pass: how a chunk grows over the ones before, the share of a node's earlier weight that must be placed,
    #: and the share of the waiting nodes that a wave takes at least.
    growth: int = 4
    ready: float = 0.9
    least: float = 0.1
    #: For the candidate rule "all", which goes in chunks and sub-rounds.
    n_batches: int = 32
    max_subrounds: int = 16
    #: Arcs of the stream's beginning that one task places node by node (all of a smaller graph); the rest goes in waves over all tasks.
    exact_limit_arcs: int = 2_000_000
    memetic: MemeticConfig = field(default_factory=MemeticConfig)
    restream: RestreamConfig = field(default_factory=RestreamConfig)


#: (2m)^2 must stay below 2^63 for 64-bit scores; beyond, DECIMAL(38,0) holds them.
MAX_INT_2M = 3_000_000_000
