"""Schemas, settings and results."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from ..session import drop_path
from .layers import Bucketed, RankTable

VERTEX = "id bigint"
EDGE = "src bigint, dst bigint"
TEDGE = "src bigint, dst bigint, seq bigint"
DELTA = "src bigint, dst bigint, op string"
RANK = "id bigint, rank double"
TRACE = "run_id string, workload string, method string, batch int, superstep int, n_affected bigint, n_expanded bigint, n_settled bigint, in_edges bigint, rows_scanned bigint, linf double, wall_ms double"


@dataclass(frozen=True)
class RankConfig:
    """Settings of a run. ``tau`` stops it, ``tau_f`` spreads a change, ``tau_p`` settles a vertex.

    norm: linf, l1 or l2 of the changes of a round. expand_by: rel (change over the larger rank),
    abs, or share (change over out-degree). dangling: self_loops, redistribute or none.
    tolerance_scale: absolute, or mean_rank, which multiplies changes by V / scale_vertices before ``tau``.
    engine: distributed, or, on request only, local (one task; refused beyond local_edges) or where_it_fits (one task up to local_edges, distributed beyond).
    direction: push runs over all edges; pull over the in-edges of vertices ever affected, fetched as they are marked;
    auto pulls until those are more than the share ``push_share`` of the edges.
    """

    alpha: float = 0.85
    tau: float = 1e-10
    tau_f: float = 1e-6
    tau_p: float = 1e-6
    max_supersteps: int = 500
    norm: str = "linf"
    expand_by: str = "rel"
    dangling: str = "self_loops"
    tolerance_scale: str = "absolute"
    scale_vertices: float = 1e6
    direction: str = "auto"
    engine: str = "distributed"
    local_edges: int = 2_000_000
    push_share: float = 0.25
    hub_degree: int = 1_000_000

    def but(self, **changes) -> RankConfig:
        return replace(self, **changes)

    def __post_init__(self) -> None:
        for name, allowed in (("norm", ("linf", "l1", "l2")), ("expand_by", ("rel", "abs", "share")), ("dangling", ("self_loops", "redistribute", "none")), ("tolerance_scale", ("absolute", "mean_rank")), ("direction", ("auto", "pull", "push")), ("engine", ("local", "distributed", "where_it_fits"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")
        if not 0 < self.alpha < 1:
            raise ValueError("alpha lies between 0 and 1")


@dataclass(frozen=True)
class MethodPlan:
    """What tells the methods apart, for the one solver that runs them all."""

    name: str
    warm: bool
    seed: str  # all, reach or neighbours
    expand: bool = False
    prune: bool = False
    formula: str = "plain"


COLD = MethodPlan("cold", False, "all")
WARM = MethodPlan("warm", True, "all")
REACH = MethodPlan("reach", True, "reach")
FRONTIER = MethodPlan("frontier", True, "neighbours", expand=True)
PRUNED = MethodPlan("pruned", True, "neighbours", expand=True, prune=True, formula="loopfree")
METHODS = {m.name: m for m in (COLD, WARM, REACH, FRONTIER, PRUNED)}


@dataclass
class RankRun:
    """Result of a run: ranks (id, rank, ever_affected) and one trace entry per superstep.

    In the trace, ``in_edges`` counts those of affected vertices, ``rows_scanned`` what the round really read: edges, states, lookups.
    """

    method: str
    ranks: DataFrame
    trace: list[dict] = field(default_factory=list)
    seconds: float = 0.0
    #: (id, rank) of the rows that the run may have changed; None where that is all of them.
    changed: DataFrame | None = None
    started_from: RankTable | None = None
    buckets: int = 16
    #: Written tables that ``ranks`` reads.
    paths: list[str] = field(default_factory=list)
    _table: RankTable | None = field(default=None, repr=False)

    @property
    def supersteps(self) -> int:
        return len(self.trace)

    @property
    def in_edges(self) -> int:
        return sum(t["in_edges"] for t in self.trace)

    @property
    def rows_scanned(self) -> int:
        return sum(t["rows_scanned"] for t in self.trace)

    def drop(self) -> None:
        """Delete what the run wrote; its ranks can't be read after that, but :meth:`table` can, if it was asked for before."""
        for path in self.paths:
            drop_path(self.ranks.sparkSession, path)
        self.paths.clear()

    def table(self, n: int, home: str | None = None) -> RankTable:
        """The ranks as a table to start the next run from; writes changed rows only, where the run touched only some."""
        if self._table is None:
            if self.changed is not None and self.started_from is not None and isinstance(self.started_from.base, Bucketed):
                self._table = self.started_from.updated(self.changed)
            else:
                self._table = RankTable.store(self.ranks, self.buckets, n, home)
        return self._table
