"""Queries of the methods, their traces, affected shares and errors, on all workloads."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles
from ..functions import measures
from ..functions.formulas import rank_e9
from ..plans.methods import reference_rank, run_method
from ..plans.model import METHODS, MethodPlan, RankConfig, RankRun
from ..plans.prepared import prepared
from ..plans.solver import solve
from ..sources.workloads import BUILDERS

#: The run that errors are measured against: 500 rounds, or until nothing moves at all. It is a yardstick, asked for in one task, where hundreds of
#: tiny rounds need no job each; on graphs beyond ``local_edges`` its rounds are distributed.
REFERENCE = RankConfig(tau=1e-100, max_supersteps=500, engine="where_it_fits")


_runs: dict[tuple, RankRun] = {}


def run(spark: SparkSession, sf_dir: str, workload: str, method: str, cfg: RankConfig | None = None, scope: str = "either") -> RankRun:
    """A method's run on a workload's first batch. Runs are written tables: ranks, trace, share and error of one run share it."""
    key = (spark.sparkContext.applicationId, sf_dir, workload, method, cfg, scope)
    if key not in _runs:
        p = prepared(spark, sf_dir, workload)
        _runs[key] = run_method(method, p.old, p.new, p.delta, p.table, cfg or RankConfig(), scope)
    return _runs[key]


_references: dict[tuple, RankRun] = {}


def reference(spark: SparkSession, sf_dir: str, workload: str) -> RankRun:
    key = (spark.sparkContext.applicationId, sf_dir, workload)
    if key not in _references:
        _references[key] = reference_rank(prepared(spark, sf_dir, workload).new, REFERENCE)
    return _references[key]


def result(run_: RankRun) -> DataFrame:
    return run_.ranks.select("id", rank_e9(F.col("rank")).alias("rank_e9"), "ever_affected")


def rank(spark: SparkSession, sf_dir: str, workload: str, method: str, cfg: RankConfig | None = None, scope: str = "either") -> DataFrame:
    return result(run(spark, sf_dir, workload, method, cfg, scope))


def trace(spark: SparkSession, sf_dir: str, workload: str, method: str) -> DataFrame:
    t = run(spark, sf_dir, workload, method).trace
    return spark.createDataFrame([(r["superstep"], r["n_affected"], r["n_expanded"], r["n_settled"], r["in_edges"]) for r in t], "superstep int, n_affected bigint, n_expanded bigint, n_settled bigint, in_edges bigint")


def affected(spark: SparkSession, sf_dir: str, workload: str, method: str) -> DataFrame:
    return run(spark, sf_dir, workload, method).ranks.agg(F.count_if("ever_affected").alias("affected"), F.count(F.lit(1)).alias("vertices"))


def error(spark: SparkSession, sf_dir: str, workload: str, method: str) -> DataFrame:
    ref = reference(spark, sf_dir, workload)
    return measures.l1_error(run(spark, sf_dir, workload, method).ranks, ref.ranks).select(F.floor(F.col("l1") * 1e10 + 0.5).cast("bigint").alias("l1_e10"))


#: Variants: (workload, method, settings, reach scope, plan). Each differs from the method's default in one point.
VARIANTS: dict[str, tuple[str, str, RankConfig, str, MethodPlan | None]] = {
    "expand_by_abs": ("part_flow", "pruned", RankConfig(expand_by="abs", tau_f=1e-10), "either", None),
    "expand_by_share": ("part_flow", "pruned", RankConfig(expand_by="share", tau_f=1e-11), "either", None),
    "expand_by_rel_coarse": ("part_flow", "frontier", RankConfig(tau_f=1e-3), "either", None),
    "settle_below_spread": ("part_flow", "pruned", RankConfig(tau_p=1e-8), "either", None),
    "cautious_spread_1e7": ("event_flow", "pruned", RankConfig(tau_f=1e-7), "either", None),
    "cautious_spread_1e8": ("event_flow", "frontier", RankConfig(tau_f=1e-8), "either", None),
    "damping_half": ("cust_supp", "cold", RankConfig(alpha=0.5), "either", None),
    "stop_early": ("supp_part", "warm", RankConfig(tau=1e-6), "either", None),
    "norm_l1": ("part_flow", "warm", RankConfig(norm="l1", tau=1e-8), "either", None),
    "norm_l2": ("part_flow", "cold", RankConfig(norm="l2", tau=1e-9), "either", None),
    "reach_union": ("supp_part", "reach", RankConfig(), "union", None),
    "round_cap": ("order_chain", "cold", RankConfig(max_supersteps=5), "either", None),
    "scaled_tolerance": ("order_chain", "pruned", RankConfig(tolerance_scale="mean_rank", tau=1e-9), "either", None),
    "frontier_loopfree": ("cust_supp", "frontier", RankConfig(), "either", MethodPlan("frontier_loopfree", True, "neighbours", expand=True, formula="loopfree")),
    "pruned_plain": ("part_flow", "pruned", RankConfig(), "either", MethodPlan("pruned_plain", True, "neighbours", expand=True, prune=True)),
    "no_expand": ("part_flow", "frontier", RankConfig(), "either", MethodPlan("no_expand", True, "neighbours")),
    "warm_loopfree": ("supp_part", "warm", RankConfig(), "either", MethodPlan("warm_loopfree", True, "all", formula="loopfree")),
    "dangling_redistribute": ("user_item", "cold", RankConfig(dangling="redistribute"), "either", None),
    "dangling_none": ("geo_tree", "cold", RankConfig(dangling="none"), "either", None),
}


def variant(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    workload, method, cfg, scope, plan = VARIANTS[name]
    if cfg.dangling != "self_loops":
        return result(run_method(method, *_inputs(spark, sf_dir, workload, RankConfig(dangling=cfg.dangling)), cfg, scope))
    if plan is None:
        return rank(spark, sf_dir, workload, method, cfg, scope)
    from ..plans.marking import seed_frontier

    p = prepared(spark, sf_dir, workload)
    return result(solve(p.new, plan, cfg, p.table, seed_frontier(p.old, p.new, p.delta) if plan.seed == "neighbours" else None))


def _inputs(spark: SparkSession, sf_dir: str, workload: str, cfg: RankConfig):
    p = prepared(spark, sf_dir, workload, cfg=cfg)
    return p.old, p.new, p.delta, p.table


#: The same rounds in one task, on request: what tests and yardsticks use. (workload, method)
IN_ONE_TASK = [("event_flow", "cold"), ("part_flow", "warm"), ("supp_part", "reach"), ("part_flow", "frontier"), ("cust_supp", "pruned")]
#: Runs that must pull, or push, whatever the planner would say. (workload, method, direction)
DIRECTED = [("order_chain", "pruned", "push"), ("part_flow", "pruned", "pull"), ("cust_supp", "frontier", "pull"), ("web_links", "frontier", "push"), ("turn_chain", "reach", "push")]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
    for w in BUILDERS:
        for m in METHODS:
            for name, fn in (("rank", rank), ("trace", trace), ("affected", affected), ("error", error)):
                out[f"{name}_{m}_{w}"] = partial(fn, workload=w, method=m)
    for w, m in IN_ONE_TASK:
        out[f"local_{m}_{w}"] = partial(rank, workload=w, method=m, cfg=RankConfig(engine="local"))
    for w, m, way in DIRECTED:
        out[f"{way}_{m}_{w}"] = partial(rank, workload=w, method=m, cfg=RankConfig(direction=way))
    for name in VARIANTS:
        out[f"variant_{name}"] = partial(variant, name=name)
    return out


def oracle_sql() -> dict[str, str]:
    out = {}
    for w in BUILDERS:
        for m in METHODS:
            out[f"rank_{m}_{w}"] = oracles.rank_sql(w, m)
            out[f"trace_{m}_{w}"] = oracles.trace_sql(w, m)
            out[f"affected_{m}_{w}"] = oracles.affected_sql(w, m)
            out[f"error_{m}_{w}"] = oracles.error_sql(w, m, REFERENCE)
    for w, m in IN_ONE_TASK:
        out[f"local_{m}_{w}"] = oracles.rank_sql(w, m)
    for w, m, way in DIRECTED:
        out[f"{way}_{m}_{w}"] = oracles.rank_sql(w, m)
    for name, (w, m, cfg, scope, plan) in VARIANTS.items():
        loops = cfg.dangling == "self_loops"
        base = RankConfig(dangling=cfg.dangling)
        out[f"variant_{name}"] = oracles.rank_sql(w, m, cfg=cfg, scope=scope, plan=plan, loops=loops, base_cfg=base)
    return out
