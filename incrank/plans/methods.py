"""The five methods, the reference run, and advice on which to use."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import Snapshot
from .layers import RankTable
from .marking import reach_set, seed_frontier
from .model import COLD, FRONTIER, METHODS, PRUNED, REACH, WARM, MethodPlan, RankConfig, RankRun
from .solver import solve

Ranks = DataFrame | RankTable

DEFAULT = RankConfig()


def cold_rank(g: Snapshot, cfg: RankConfig = DEFAULT) -> RankRun:
    """From uniform ranks, every vertex every round."""
    return solve(g, COLD, cfg)


def warm_rank(g: Snapshot, prev: Ranks, cfg: RankConfig = DEFAULT) -> RankRun:
    """From the previous ranks, every vertex every round."""
    return solve(g, WARM, cfg, prev)


def reach_rank(old: Snapshot, new: Snapshot, delta: DataFrame, prev: Ranks, cfg: RankConfig = DEFAULT, scope: str = "either", most_share: float | None = None) -> RankRun:
    """Only what a changed edge's source reaches, from the previous ranks; everything, where that is more than ``most_share`` of the vertices."""
    return solve(new, REACH, cfg, prev, reach_set(old, new, delta, scope, most_share))


def frontier_rank(old: Snapshot, new: Snapshot, delta: DataFrame, prev: Ranks, cfg: RankConfig = DEFAULT, plan: MethodPlan = FRONTIER) -> RankRun:
    """An affected set that starts at the out-neighbours of changed sources and grows where ranks change."""
    return solve(new, plan, cfg, prev, seed_frontier(old, new, delta))


def pruned_rank(old: Snapshot, new: Snapshot, delta: DataFrame, prev: Ranks, cfg: RankConfig = DEFAULT) -> RankRun:
    """As :func:`frontier_rank`, but settled vertices leave, and ranks solve their own self-loop."""
    return frontier_rank(old, new, delta, prev, cfg, PRUNED)


def reference_rank(g: Snapshot, cfg: RankConfig = DEFAULT, ref_floor: float = 0.0) -> RankRun:
    """The ranks that errors are measured against: a cold run that stops only when nothing moves by more than ``ref_floor``, or at the cap."""
    return solve(g, COLD, cfg.but(tau=max(1e-100, ref_floor), tolerance_scale="absolute"))


def run_method(name: str, old: Snapshot, new: Snapshot, delta: DataFrame, prev: Ranks, cfg: RankConfig = DEFAULT, scope: str = "either") -> RankRun:
    """A method by name. Where the new graph has more vertices than the old one, ranks are carried over to all of them, and all are marked."""
    if name not in METHODS:
        raise ValueError(f"no method {name}")
    if name != "cold" and new.n_vertices != old.n_vertices:
        grown, _ = carry_ranks(new.vertices, prev.df if isinstance(prev, RankTable) else prev, "grow", (old.n_vertices, new.n_vertices))
        return solve(new, METHODS[name], cfg, RankTable.store(grown, new.buckets, new.n_vertices, new.home))
    if name == "cold":
        return cold_rank(new, cfg)
    if name == "warm":
        return warm_rank(new, prev, cfg)
    if name == "reach":
        return reach_rank(old, new, delta, prev, cfg, scope)
    return frontier_rank(old, new, delta, prev, cfg, METHODS[name])


def carry_ranks(vertices: DataFrame, prev: DataFrame, universe: str = "fixed", sizes: tuple[int, int] | None = None) -> tuple[DataFrame, bool]:
    """Old ranks for a vertex set, and whether every vertex must be marked.

    fixed: vertices are those of the old ranks. grow: old ranks shrink to their share of the larger set, newcomers get an even
    share, and, since the teleport term changes for all, all are marked.
    """
    if universe == "fixed":
        return vertices.join(prev.select("id", "rank"), "id", "left"), False
    n_old, n_new = sizes or (prev.count(), vertices.count())
    grown = vertices.join(prev.select("id", "rank"), "id", "left").withColumn("rank", F.coalesce(F.col("rank") * (n_old / n_new), F.lit(1.0 / n_new)))
    return grown, n_old != n_new


def advise(errors: dict[str, float], kind: str = "temporal", random_batch: bool = False) -> str:
    """Pruned, unless a probe finds its error above cold's, or a web graph gets random batches: then frontier."""
    if kind == "web" and random_batch or errors.get("pruned", 0.0) > errors.get("cold", float("inf")):
        return "frontier"
    return "pruned"
