"""Ranks kept up to date by micro-batches of edge changes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.measures import trace_table
from ..plans.graph import Snapshot, next_snapshot, normalize_delta, snapshot
from ..plans.layers import RankTable, written
from ..plans.methods import cold_rank, run_method
from ..plans.model import RankConfig
from ..plans.store import Manifests, manifest_of, opened


class RankMaintainer:
    """Alternates update and computation, as the one writer of a versioned graph and its ranks.

    Version 0 is the first graph with a cold run's ranks; micro-batch k makes version k + 1. A step whose version is current
    does nothing, so a repeated or restarted micro-batch has its effect once; its trace overwrites its own folder. A step
    writes what the batch changed: overlays of edges and ranks, folded into their bases once they have grown with them.
    Batches have src, dst and, if there are deletions, op: those of an expiring stream, for one.

    universe: ``grow`` takes in vertices that a batch names for the first time, with a self-loop each; then all ranks are marked, as the
    teleport term changes for all. ``fixed`` refuses such a batch with an error. late: ``admit`` takes late rows as ordinary changes of the
    batch they come with; ``drop`` leaves out rows whose ``ts`` is more than ``delay`` seconds before the latest seen in earlier
    batches, and the trace says how many.
    """

    def __init__(self, spark: SparkSession, root: str, method: str = "pruned", cfg: RankConfig | None = None, universe: str = "grow", late: str = "admit", delay: int = 0) -> None:
        if universe not in ("grow", "fixed") or late not in ("admit", "drop"):
            raise ValueError("universe is grow or fixed, late is admit or drop")
        self.spark, self.method, self.cfg, self.universe, self.late, self.delay = spark, method, cfg or RankConfig(), universe, late, delay
        self.root = root.rstrip("/")
        self.versions = Manifests(spark, self.root)
        self.trace_path = f"{self.root}/trace"

    def current(self) -> int | None:
        return self.versions.current()

    def start(self, vertices: DataFrame, edges: DataFrame) -> None:
        """Load the first graph, unless the store has one."""
        if self.current() is not None:
            return
        g = snapshot(vertices, edges, home=self.root)
        run = cold_rank(g, self.cfg)
        self.versions.commit(0, manifest_of(g, run.table(g.n_vertices, self.root)))
        run.drop()
        g.release()

    def open(self, version: int | None = None) -> tuple[Snapshot, RankTable]:
        """The graph and the ranks of a version, the current one by default."""
        return opened(self.spark, self.versions.read(self.current() if version is None else version), self.root)

    def read(self, version: int | None = None) -> DataFrame:
        """id, rank."""
        return self.open(version)[1].df

    def step(self, batch: DataFrame, batch_id: int) -> None:
        version = batch_id + 1
        now = self.current()
        if now >= version:
            return
        before = self.versions.read(now)
        if "op" not in batch.columns:
            batch = batch.withColumn("op", F.lit("+"))
        ts = F.unix_micros(F.col("ts").cast("timestamp")) if "ts" in batch.columns else F.lit(None).cast("bigint")
        # A micro-batch has a session of its own, and is read several times.
        rows, path, got = written(batch.select("src", "dst", "op", ts.alias("at")), "micro-batch", latest=F.max("at"))
        rows = self.spark.read.schema("src bigint, dst bigint, op string, at bigint").parquet(path)
        latest, n_late = before.get("latest"), 0
        if self.late == "drop" and latest is not None:
            in_time = F.coalesce(F.col("at") >= latest - self.delay * 1_000_000, F.lit(True))
            n_late = rows.where(~in_time).count()
            rows = rows.where(in_time)
        old, prev = opened(self.spark, before, self.root)
        delta, _, _ = written(normalize_delta(old, rows.select("src", "dst", "op")), "delta")
        new = next_snapshot(old, delta, self.universe)
        run = run_method(self.method, old, new, delta, prev, self.cfg)
        table = run.table(new.n_vertices, self.root)
        trace_table(self.spark, [("stream", self.method, batch_id, run.trace)]).withColumn("n_late", F.lit(n_late).cast("bigint")).write.mode("overwrite").parquet(f"{self.trace_path}/batch_id={batch_id}")
        seen = [x for x in (latest, got["latest"]) if x is not None]
        self.versions.commit(version, manifest_of(new, table) | {"latest": max(seen) if seen else None})
        run.drop()
        new.release()

    def write_stream(self, changes: DataFrame, checkpoint: str, **trigger):
        """Start the streaming query that feeds :meth:`step`; by default it takes what is there and ends."""
        return changes.writeStream.foreachBatch(self.step).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
