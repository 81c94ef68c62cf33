"""Accuracy, cost and scaling measures as tables."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .formulas import plain_rank


def _against(ranks: DataFrame, ref: DataFrame) -> DataFrame:
    a, b = ranks.select("id", F.col("rank").alias("x")), ref.select("id", F.col("rank").alias("y"))
    return a.join(b, "id", "full").select("id", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))


def l1_error(ranks: DataFrame, ref: DataFrame) -> DataFrame:
    """One row, l1: the sum of absolute differences over all vertices of either side."""
    return _against(ranks, ref).agg(F.coalesce(F.sum(F.abs(F.col("x") - F.col("y"))), F.lit(0.0)).alias("l1"))


def l2_error(ranks: DataFrame, ref: DataFrame) -> DataFrame:
    return _against(ranks, ref).agg(F.coalesce(F.sqrt(F.sum(F.pow(F.col("x") - F.col("y"), 2))), F.lit(0.0)).alias("l2"))


def linf_change(ranks: DataFrame, ref: DataFrame) -> DataFrame:
    return _against(ranks, ref).agg(F.coalesce(F.max(F.abs(F.col("x") - F.col("y"))), F.lit(0.0)).alias("linf"))


def timed_run(fn: Callable):
    """(result, seconds)."""
    began = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - began


def geomean(df: DataFrame, keys: list[str], column: str, name: str | None = None) -> DataFrame:
    """Geometric means by group; zeros count as the smallest positive double."""
    return df.groupBy(*keys).agg(F.exp(F.avg(F.ln(F.greatest(F.col(column), F.lit(5e-324))))).alias(name or column))


def speedup(times: DataFrame, baseline: str, keys: list[str], method: str = "method", column: str = "seconds") -> DataFrame:
    """keys, method, speedup: the baseline's time over the method's."""
    base = times.where(F.col(method) == baseline).select(*keys, F.col(column).alias("base_time"))
    joined = times.join(F.broadcast(base), keys) if keys else times.crossJoin(F.broadcast(base))
    return joined.select(*keys, method, (F.col("base_time") / F.col(column)).alias("speedup"))


def mean_speedup(speedups: DataFrame, method: str = "method") -> DataFrame:
    """Arithmetic mean over batch sizes, as headlines have it."""
    return speedups.groupBy(method).agg(F.avg("speedup").alias("mean_speedup"))


def affected_share(ranks: DataFrame) -> DataFrame:
    return ranks.agg(F.avg(F.col("ever_affected").cast("double")).alias("share"))


def residual_bound(edges: DataFrame, degrees: DataFrame, ranks: DataFrame, n: int, alpha: float) -> DataFrame:
    """One row, bound: an upper bound of the L1 distance to the fixed point, from one exact round and the map's contraction."""
    shares = ranks.join(degrees, "id").where("out_deg > 0").select(F.col("id").alias("src"), (F.col("rank") / F.col("out_deg")).alias("share"))
    sums = edges.join(shares, "src").groupBy(F.col("dst").alias("id")).agg(F.sum("share").alias("s"))
    moved = ranks.join(sums, "id", "left").select(F.abs(plain_rank(F.coalesce("s", F.lit(0.0)), n, alpha) - F.col("rank")).alias("d"))
    return moved.agg((F.sum("d") / (1 - alpha)).alias("bound"))


def mass(ranks: DataFrame) -> DataFrame:
    return ranks.agg(F.sum("rank").alias("mass"), F.min("rank").alias("least"))


def topk_overlap(ranks: DataFrame, ref: DataFrame, k: int) -> DataFrame:
    """One row, overlap: share of the k highest of ``ref`` that are among the k highest of ``ranks``; ties by id."""
    top = lambda df: df.orderBy(F.desc("rank"), "id").limit(k).select("id")
    return top(ranks).join(top(ref), "id", "left_semi").agg((F.count(F.lit(1)) / F.lit(k)).alias("overlap"))


def footrule(ranks: DataFrame, ref: DataFrame) -> DataFrame:
    """One row, footrule: the sum of how far vertices moved in order. Orders come from range-partitioned numbering."""
    from ..plans.graph import number_rows

    order = lambda df, name: number_rows(df.select("id", (-F.col("rank")).alias("key")), ["key", "id"], name).select("id", name)
    return order(ranks, "p").join(order(ref, "q"), "id").agg(F.sum(F.abs(F.col("p") - F.col("q"))).alias("footrule"))


def error_ratio(errors: DataFrame, keys: list[str], baseline: str = "cold") -> DataFrame:
    """keys, method, ratio: the method's error over the baseline's; under 1 is what is asked for."""
    base = errors.where(F.col("method") == baseline).select(*keys, F.col("l1").alias("base_l1"))
    return errors.join(F.broadcast(base), keys).select(*keys, "method", (F.col("l1") / F.col("base_l1")).alias("ratio"))


def scaling_table(times: DataFrame) -> DataFrame:
    """method, cores, seconds, speedup over one core, gain per doubling."""
    one = F.first(F.when(F.col("cores") == 1, F.col("seconds")), ignorenulls=True).over(Window.partitionBy("method").orderBy("cores").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    s = times.withColumn("speedup", one / F.col("seconds"))
    return s.withColumn("per_doubling", F.when(F.col("cores") > 1, F.pow("speedup", 1 / F.log2(F.col("cores").cast("double")))))


def trace_table(spark, runs: list[tuple[str, str, int, list[dict]]]) -> DataFrame:
    """TRACE rows of (workload, method, batch, trace) entries."""
    rows = [(f"{w}/{m}/{b}", w, m, b, t["superstep"], t["n_affected"], t["n_expanded"], t["n_settled"], t["in_edges"], t["rows_scanned"], float(t["linf"]), float(t["wall_ms"])) for w, m, b, trace in runs for t in trace]
    from ..plans.model import TRACE

    return spark.createDataFrame(rows, TRACE)


def per_doubling(speedup_at: float, cores: int) -> float:
    return speedup_at ** (1 / math.log2(cores))
