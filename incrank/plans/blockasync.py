"""Asynchronous rounds by blocks: within a block, ranks are used as soon as they are made.

Vertices go to blocks by hash. A round ships each block its vertices, its in-edges and
the shares of sources in other blocks, summed per vertex; the block then sweeps
over its own edges several times with fresh ranks. Fixed point and stop test are
those of the synchronous rounds, but changes inside a block need no round each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..session import scratch, ship
from .graph import Snapshot
from .model import RankConfig, RankRun


def _sweeps(alpha: float, n: int, sweeps: int):
    base = (1 - alpha) / n

    def kernel(left, right):
        """left: vertices of the block (id, rank, deg, outside); right: edges inside it."""
        ids = left.column("id").to_numpy()
        order = np.argsort(ids)
        ids, rank = ids[order], left.column("rank").to_numpy()[order].copy()
        deg, outside = left.column("deg").to_numpy()[order].astype(float), left.column("outside").to_numpy()[order]
        old = rank.copy()
        s, d = (np.searchsorted(ids, right.column(c).to_numpy()) for c in ("src", "dst")) if right.num_rows else (np.zeros(0, int), np.zeros(0, int))
        half = len(ids) // 2
        for _ in range(sweeps):
            for part in (slice(0, half), slice(half, len(ids))):  # the second half already sees the first half's new ranks
                total = np.bincount(d, weights=(rank / deg)[s], minlength=len(ids)) if len(s) else np.zeros(len(ids))
                rank[part] = base + alpha * (outside[part] + total[part])
        return pa.table({"id": ids, "rank": rank, "deg": deg.astype(np.int64), "dr": np.abs(rank - old)})

    return kernel


def block_async_rank(g: Snapshot, cfg: RankConfig, prev: DataFrame | None = None, blocks: int = 8, sweeps: int = 4) -> RankRun:
    """Ranks of all vertices by block-asynchronous rounds. At most V / blocks vertices and their inner edges are in one task."""
    spark = g.edges.sparkSession
    ship(spark)
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")
    edges = g.edges.withColumn("from", block(F.col("src"))).withColumn("block", block(F.col("dst"))).repartition("src").persist(StorageLevel.MEMORY_AND_DISK)
    inner = edges.where("from = block").select("src", "dst", "block")
    state = g.degrees.select("id", F.col("out_deg").alias("deg"))
    state = state.withColumn("rank", F.lit(1.0 / g.n_vertices)) if prev is None else state.join(prev.select("id", "rank"), "id")
    trace: list[dict] = []
    schema = "id bigint, rank double, deg bigint, dr double"
    try:
        while len(trace) < cfg.max_supersteps:
            shares = state.select(F.col("id").alias("src"), (F.col("rank") / F.col("deg")).alias("share"))
            outside = edges.where("from <> block").join(shares, "src").groupBy(F.col("dst").alias("id")).agg(F.sum("share").alias("outside"))
            vertices = state.join(outside, "id", "left").select("id", "rank", "deg", F.coalesce("outside", F.lit(0.0)).alias("outside"), block(F.col("id")).alias("block"))
            seen = Observation()
            step = vertices.groupBy("block").cogroup(inner.groupBy("block")).applyInArrow(_sweeps(cfg.alpha, g.n_vertices, sweeps), schema).observe(seen, F.max("dr").alias("linf"), F.count(F.lit(1)).alias("n"))
            path = scratch(spark, "async")
            step.write.parquet(path)
            state = spark.read.schema(schema).parquet(path).select("id", "rank", "deg")
            linf = seen.get["linf"]
            trace.append({"superstep": len(trace) + 1, "n_affected": seen.get["n"], "n_expanded": 0, "n_settled": 0, "in_edges": g.n_edges, "rows_scanned": g.n_edges + g.n_vertices, "linf": linf, "wall_ms": 0.0})
            if linf <= cfg.tau:
                break
    finally:
        edges.unpersist()
    return RankRun("block_async", state.select("id", "rank", F.lit(True).alias("ever_affected")), trace)
