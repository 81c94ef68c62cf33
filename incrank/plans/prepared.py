"""A workload, ready for one batch: old and new snapshots, the batch, and the old ranks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..session import stored
from ..sources import batches, workloads
from .graph import Snapshot, next_snapshot, normalize_delta, snapshot, vertices_of
from .layers import RankTable
from .methods import cold_rank
from .model import RankConfig

#: One slice of this share of the temporal edges, or of the edges of a static graph, is a query's batch.
FRACTION = 1e-3


@dataclass
class Prepared:
    workload: str
    old: Snapshot
    new: Snapshot
    delta: DataFrame
    table: RankTable

    @property
    def base(self) -> DataFrame:
        """Ranks of the old graph."""
        return self.table.df


_ready: dict[tuple, Prepared] = {}
_started: dict[tuple, tuple[DataFrame, int, Snapshot, RankTable]] = {}


def static_batch(vertices: DataFrame, edges: DataFrame, fraction: float, seed: int = 42) -> DataFrame:
    return batches.random_batch(vertices, edges, edges.count(), fraction, seed=seed)


def started(spark: SparkSession, sf_dir: str, workload: str, cfg: RankConfig) -> tuple[DataFrame, int, Snapshot, RankTable]:
    """A workload's edges and their number, its first snapshot and that one's ranks: the same whatever the batch."""
    key = (spark.sparkContext.applicationId, sf_dir, workload, cfg)
    if key not in _started:
        edges = stored(workloads.build(spark, sf_dir, workload), workload)
        total = edges.count()
        first = batches.preload_split(edges, total) if workload in workloads.TEMPORAL else edges.where("src <> dst").distinct()
        old = snapshot(vertices_of(edges), first, cfg.dangling == "self_loops")
        run = cold_rank(old, cfg)
        _started[key] = (edges, total, old, run.table(old.n_vertices))
        run.drop()
        old.release()
    return _started[key]


def prepared(spark: SparkSession, sf_dir: str, workload: str, fraction: float = FRACTION, cfg: RankConfig | None = None) -> Prepared:
    """Built once per application, table folder and settings: ranks of the old graph are an input of every method."""
    cfg = cfg or RankConfig()
    key = (spark.sparkContext.applicationId, sf_dir, workload, fraction, cfg)
    if key not in _ready:
        edges, total, old, table = started(spark, sf_dir, workload, cfg)
        if workload in workloads.TEMPORAL:
            raw = batches.slice_batches(edges, total, fraction, 1)
        else:
            raw = static_batch(old.vertices, old.edges.where("src <> dst"), fraction)
        delta = stored(normalize_delta(old, raw), "delta")
        _ready[key] = Prepared(workload, old, next_snapshot(old, delta), delta, table)
    return _ready[key]


def replay(spark: SparkSession, sf_dir: str, workload: str, fraction: float, n: int, seed: int = 42) -> Iterator[tuple[int, Snapshot, Snapshot, DataFrame]]:
    """(number, old snapshot, new snapshot, batch) of consecutive batches: slices of a temporal list, or random batches of a static graph."""
    edges = stored(workloads.build(spark, sf_dir, workload), workload)
    vertices = vertices_of(edges)
    temporal = workload in workloads.TEMPORAL
    total = edges.count() if temporal else 0
    first = batches.preload_split(edges, total) if temporal else edges.where("src <> dst").distinct()
    slices = stored(batches.slice_batches(edges, total, fraction, n), "slices") if temporal else None
    g = snapshot(vertices, first)
    for k in range(n):
        if temporal:
            raw = slices.where(f"batch = {k}").select("src", "dst", "op")
        else:
            raw = static_batch(vertices, g.edges.where("src <> dst"), fraction, seed + k)
        delta = stored(normalize_delta(g, raw), "delta")
        new = next_snapshot(g, delta)
        yield k, g, new, delta
        g.release()
        if new.base is not g.base:
            g.base.drop()
        g = new
    g.release()
