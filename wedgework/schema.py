"""The graph value and the option records of the engine."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class Graph:
    """A simple unweighted graph: distinct arcs (src, dst) without loops; an undirected graph has both arcs of every edge."""

    arcs: DataFrame
    directed: bool = False
    name: str = ""
    #: (v, nbrs ascending) of every vertex with arcs, where the source makes whole lists anyway; the arcs are these lists' entries.
    lists: DataFrame | None = None
    #: (v) of the vertices of ``lists``, without making them.
    ends: DataFrame | None = None
    #: (ms) the groups, each of whose members is a neighbour of all its others, where the arcs are those of groups.
    groups: DataFrame | None = None

    def with_arcs(self, arcs: DataFrame) -> Graph:
        return replace(self, arcs=arcs, lists=None, ends=None, groups=None)

    @property
    def spark(self):
        return self.arcs.sparkSession


@dataclass(frozen=True)
class CostModel:
    """Read time alpha + bytes * beta (seconds); gamma for one comparison; overheads of a cache look-up and of a miss."""

    alpha: float = 2.5e-6
    beta: float = 1.0e-10
    gamma: float = 1.0e-9
    lookup: float = 0.0
    miss_extra: float = 0.0


@dataclass(frozen=True)
class CacheConfig:
    """Options of a read-cache replay.

    ``score``: 'lru', 'lru_positional' (recency less ``position_weight`` times the free bytes beside the entry) or 'app' (``score_col``;
    the smallest goes first and never makes room for a smaller one). ``mode``: 'always' (never flushed), 'transparent' (flushed
    after ``epoch_len`` reads) or 'user' (flushed before reads whose ``flush_col`` is true). ``adaptive`` doubles the slots or the
    buffer, at the price of a flush, when conflict or capacity misses among the last ``adapt_every`` reads exceed their threshold.
    """

    capacity_bytes: int
    slots: int = 0  # 0: no index conflicts
    ways: int = 1
    score: str = "lru"
    mode: str = "always"
    epoch_len: int = 0
    adaptive: bool = False
    adapt_every: int = 1000
    conflict_threshold: float = 0.2
    capacity_threshold: float = 0.5
    fragmentation: bool = False
    fit: str = "first"
    position_weight: float = 1.0
    window: str = "adj"
