"""Choices for a run and its next superstep, from what has been counted."""

from __future__ import annotations

import math

from .model import RankConfig

#: Rounds over fewer rows are interpreted, those over more are compiled.
COMPILED_ROWS = 300_000
#: Rows of a partition aimed at in a run's tables.
PART_ROWS = 200_000


def engine(cfg: RankConfig, n_edges: int, n_vertices: int) -> str:
    """Distributed, unless one task is asked for; beyond the bound that is refused, or distributed after all if it was asked for only where it fits."""
    fits = n_edges + n_vertices <= cfg.local_edges
    if cfg.engine == "where_it_fits":
        return "local" if fits else "distributed"
    if cfg.engine == "local" and not fits:
        raise ValueError(f"{n_edges} edges and {n_vertices} vertices are more than local_edges = {cfg.local_edges}")
    return cfg.engine


#: Fetches after which a run that may do all its rounds over all edges in one job does so, once it has so many rows: each fetch takes several jobs.
MOST_FETCHES, FETCHED_ROWS = 3, 20_000


def direction(cfg: RankConfig, in_edges: int, n_edges: int, fetches: int = 0) -> str:
    """Pull fetches and keeps the in-edges of the vertices ever affected, while they, and the fetches, are few; push runs over all edges."""
    if cfg.direction != "auto":
        return cfg.direction
    return "pull" if in_edges <= cfg.push_share * n_edges and (fetches <= MOST_FETCHES or in_edges <= FETCHED_ROWS) else "push"


def partitions(rows: int, most: int, cores: int) -> int:
    """Partitions of a run's tables: by rows, and enough for all cores as soon as there is work for them; two at least, as one is dealt by no key."""
    by_rows = -(-rows // PART_ROWS)
    return min(most, max(2, by_rows, min(cores, -(-rows // 5_000))))


def hub_salts(cfg: RankConfig, max_out_degree: int) -> int:
    """Into how many parts the edges of a hub are dealt; 1 where no source has more than ``hub_degree`` edges."""
    return 1 if max_out_degree <= cfg.hub_degree else min(256, -(-max_out_degree // cfg.hub_degree))


#: A job does as many rounds as take so many seconds, at most so many.
CHAIN_SECONDS, MOST_CHAINED = 2.0, 8


def chained(before: int, seconds: float, norms: list[float], tau: float) -> int:
    """Rounds of the next job: twice those of the last one, as long as rounds are short and the stop is not expected sooner."""
    if not seconds:
        return 1
    rounds = max(1, min(MOST_CHAINED, 2 * before, int(CHAIN_SECONDS / seconds)))
    if len(norms) == 2 and 0 < norms[1] < norms[0] and norms[1] > tau > 0:
        rounds = min(rounds, max(1, math.ceil(math.log(tau / norms[1]) / math.log(norms[1] / norms[0]))))
    return rounds
