"""Which vertices a change may reach: seeds, spreading, settling, closures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import stored
from .graph import Snapshot
from .layers import Keys, Steps


def sources(delta: DataFrame) -> DataFrame:
    return delta.select(F.col("src").alias("id")).distinct()


def spread(edges: DataFrame, hot: DataFrame) -> DataFrame:
    """Out-neighbours of vertices."""
    return edges.join(hot.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()


def neighbours(g: Snapshot, keys: Keys) -> DataFrame:
    """Out-neighbours of few vertices: only their buckets are read."""
    return g.out_edges(keys).select(F.col("dst").alias("id"))


def seed_frontier(old: Snapshot, new: Snapshot, delta: DataFrame) -> DataFrame:
    """Out-neighbours, in the old graph or the new one, of every vertex whose out-edges changed."""
    before = Keys.of(sources(delta), old.buckets)
    after = before if new.buckets == old.buckets else Keys.of(before.ids, new.buckets)
    return neighbours(old, before).unionByName(neighbours(new, after)).distinct()


def settle(rel: Column, tau_p: float) -> Column:
    """Whether a vertex leaves the affected set."""
    return rel <= F.lit(tau_p)


def reachable(edges: DataFrame, start: DataFrame, most_levels: int | None = None, most_rows: int | None = None) -> DataFrame | None:
    """id, depth of everything reachable from ``start``, itself included; one level a job, cut into tables.

    None as soon as there are more than ``most_rows``.
    """
    seen = stored(start.select("id", F.lit(0).alias("depth")).distinct(), "reach")
    level, depth, total = seen.select("id"), 0, seen.count() if most_rows is not None else 0
    while most_levels is None or depth < most_levels:
        depth += 1
        fresh = stored(spread(edges, level).join(seen, "id", "left_anti").select("id", F.lit(depth).alias("depth")), "reach")
        n = fresh.count()
        if not n:
            break
        total += n
        if most_rows is not None and total > most_rows:
            return None
        seen, level = seen.unionByName(fresh), fresh.select("id")
    return seen


def reach_set(old: Snapshot, new: Snapshot, delta: DataFrame, scope: str = "either", most_share: float | None = None) -> DataFrame | None:
    """Everything reachable from a changed edge's source: in the old graph or in the new one (``either``: two closures,
    level by level at once), or in their union (``union``: a superset, one closure).

    A level reads the buckets of its vertices only. None if more than ``most_share`` of the vertices are reached: marking them
    would cost more than it saves.
    """
    limit = None if most_share is None else int(most_share * new.n_vertices) * (1 if scope == "union" else 2)
    sides = [0] if scope == "union" else [0, 1]
    begin = sources(delta)
    level = begin.select("id", F.explode(F.array(*map(F.lit, sides))).alias("side"))
    seen, total, steps = None, 0, Steps(begin.sparkSession)
    while True:
        level, got = steps.put(level, n=F.count(F.lit(1)))
        total += got["n"]
        if limit is not None and total > limit:
            return None
        if not got["n"]:
            break
        seen = level if seen is None else seen.unionByName(level)
        if scope == "union":
            keys = Keys.of(level, old.buckets, steps)
            other = keys if new.buckets == old.buckets else Keys.of(level, new.buckets, steps)
            found = neighbours(old, keys).unionByName(neighbours(new, other)).select("id", F.lit(0).alias("side"))
        else:
            found = neighbours(old, Keys.of(level.where("side = 0"), old.buckets, steps)).select("id", F.lit(0).alias("side")).unionByName(neighbours(new, Keys.of(level.where("side = 1"), new.buckets, steps)).select("id", F.lit(1).alias("side")))
        level = found.distinct().join(seen, ["id", "side"], "left_anti")
    return begin if seen is None else seen.select("id").distinct()
