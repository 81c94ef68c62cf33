"""Batches of changes: slices of a temporal list, random insertions and deletions, event-time windows, expiring edges."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.graph import number_rows, static_edges

PRELOAD = 0.9


def batch_size(total: int, fraction: float) -> int:
    return max(1, round(fraction * total))


def preload_split(tedges: DataFrame, total: int, share: float = PRELOAD) -> DataFrame:
    """The first share of a temporal list, as distinct edges."""
    return static_edges(tedges.where(F.col("seq") <= math.floor(share * total)))


def slice_batches(tedges: DataFrame, total: int, fraction: float, n: int = 100, share: float = PRELOAD) -> DataFrame:
    """src, dst, op, batch (from 0): consecutive slices after the preload; the last may be short or empty."""
    first, size = math.floor(share * total), batch_size(total, fraction)
    number = F.floor((F.col("seq") - 1 - first) / size).cast("int")
    return tedges.where((F.col("seq") > first) & (F.col("seq") <= first + n * size)).select("src", "dst", F.lit("+").alias("op"), number.alias("batch"))


def md5_number(*parts) -> Column:
    """32 bits of an md5: the same integers in any engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])), 1, 8), 16, 10).cast("bigint")


def random_inserts(vertices: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """m pairs, each vertex as likely as any other in either place; what repeats an edge is dropped by normalisation."""
    index = number_rows(vertices.select("id"), ["id"], "place")
    n = index.count()
    draws = vertices.sparkSession.range(m).select("id", (md5_number(seed, "s", F.col("id").cast("string")) % n + 1).alias("ps"), (md5_number(seed, "d", F.col("id").cast("string")) % n + 1).alias("pd"))
    src, dst = index.select(F.col("id").alias("src"), F.col("place").alias("ps")), index.select(F.col("id").alias("dst"), F.col("place").alias("pd"))
    return draws.join(src, "ps").join(dst, "pd").select("src", "dst", F.lit("+").alias("op"))


def random_deletes(edges: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """m existing edges, never self-loops: those with the least hash."""
    key = md5_number(seed, "x", F.col("src").cast("string"), F.col("dst").cast("string"))
    return edges.where("src <> dst").orderBy(key, "src", "dst").limit(m).select("src", "dst", F.lit("-").alias("op"))


def random_batch(vertices: DataFrame, edges: DataFrame, n_edges: int, fraction: float, mix: float = 0.8, seed: int = 42) -> DataFrame:
    """A batch of ``fraction`` of the edges, ``mix`` of them insertions."""
    m = batch_size(n_edges, fraction)
    ins = math.ceil(mix * m)
    return random_inserts(vertices, ins, seed).unionByName(random_deletes(edges, m - ins, seed))


def window_batches(tedges: DataFrame, width: str = "1 day", ts: str = "ts") -> DataFrame:
    """src, dst, op, batch: one batch for each tumbling window of event time; batch is the window's start."""
    return tedges.groupBy(F.window(F.col(ts).cast("timestamp"), width).alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("times")).select("src", "dst", F.lit("+").alias("op"), F.col("w.start").alias("batch"), "times")


def sliding_batches(tedges: DataFrame, horizon_s: int, step_s: int, ts: str = "ts") -> DataFrame:
    """src, dst, op, batch: an edge is there while it was last seen within the horizon.

    At each step's end: insertions are edges seen in it that were not there, deletions are edges whose last sight has left the horizon.
    """
    step = F.floor(F.unix_micros(F.col(ts).cast("timestamp")) / F.lit(step_s * 1_000_000)).cast("bigint")
    keep = -(-horizon_s // step_s)
    seen = tedges.select("src", "dst", step.alias("step")).distinct()
    from pyspark.sql import Window

    order = Window.partitionBy("src", "dst").orderBy("step")
    runs = seen.withColumn("last", F.lag("step").over(order)).withColumn("then", F.lead("step").over(order))
    ins = runs.where(F.col("last").isNull() | (F.col("step") - F.col("last") > keep)).select("src", "dst", F.lit("+").alias("op"), F.col("step").alias("batch"))
    gone = runs.where(F.col("then").isNull() | (F.col("then") - F.col("step") > keep)).select("src", "dst", F.lit("-").alias("op"), (F.col("step") + keep + 1).alias("batch"))
    return ins.unionByName(gone)
