"""Experiment drivers: tolerance sweeps, replays, breakdowns, scaling, advice."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..session import stored
from ..sources import workloads
from .arrays import MOST_ROWS, parts_for, sweep
from .kernel import SWEPT, local_sweep
from .layers import RankTable, settings
from .marking import seed_frontier
from .methods import advise, cold_rank, reference_rank, run_method
from .model import FRONTIER, METHODS, PRUNED, MethodPlan, RankConfig
from .planner import engine
from .prepared import Prepared, prepared, replay
from .solver import solve, starting_state

#: The run that errors are measured against.
REFERENCE = RankConfig(tau=1e-100, max_supersteps=500)
RUNS = "workload string, method string, fraction double, batch int, seconds double, supersteps int, in_edges bigint, rows_scanned bigint, affected bigint, vertices bigint, l1 double"


def replay_runs(spark: SparkSession, sf_dir: str, names: Iterable[str], methods: Iterable[str], fractions: Iterable[float], n_batches: int, cfg: RankConfig | None = None, reference: RankConfig | None = None) -> DataFrame:
    """One row for each workload, method, batch size and batch: time, rounds, work, share affected, error.

    Each method keeps its own ranks from batch to batch; time covers marking and stop tests, not the building of snapshots.
    """
    cfg, rows = cfg or RankConfig(), []
    reference = reference or REFERENCE
    for w in names:
        for f in fractions:
            ranks: dict[str, RankTable] = {}
            for k, old, new, delta in replay(spark, sf_dir, w, f, n_batches):
                if not k:
                    first = cold_rank(old, cfg)
                    ranks = dict.fromkeys(methods, first.table(old.n_vertices))
                    first.drop()
                ref = reference_rank(new, reference)
                for m in methods:
                    run = run_method(m, old, new, delta, ranks[m], cfg)
                    ranks[m] = run.table(new.n_vertices)
                    l1 = measures.l1_error(run.ranks, ref.ranks).first()[0]
                    affected = run.ranks.where("ever_affected").count()
                    rows.append((w, m, float(f), k, run.seconds, run.supersteps, run.in_edges, run.rows_scanned, affected, new.n_vertices, l1))
                    run.drop()
                ref.drop()
    return spark.createDataFrame(rows, RUNS)


def replay_temporal(spark, sf_dir, names=workloads.TEMPORAL, methods=tuple(METHODS), fractions=(1e-5, 1e-4, 1e-3), n_batches: int = 100, cfg=None, reference=None) -> DataFrame:
    """After 90 % of the edges, consecutive slices of the rest."""
    return replay_runs(spark, sf_dir, names, methods, fractions, n_batches, cfg, reference)


def replay_random(spark, sf_dir, names=workloads.STATIC, methods=tuple(METHODS), fractions=tuple(10.0**-k for k in range(7, 0, -1)), n_batches: int = 1, cfg=None, reference=None) -> DataFrame:
    """Random batches on static graphs, four insertions to one deletion, vertices fixed."""
    return replay_runs(spark, sf_dir, names, methods, fractions, n_batches, cfg, reference)


def summary(runs: DataFrame) -> DataFrame:
    """method, fraction: geometric means of time and error over batches, then over workloads; speedup over cold; share affected; edges read over cold's."""
    per = runs.groupBy("workload", "method", "fraction").agg(F.exp(F.avg(F.ln("seconds"))).alias("seconds"), F.exp(F.avg(F.ln(F.greatest("l1", F.lit(1e-300))))).alias("l1"), F.exp(F.avg(F.ln(F.greatest(F.col("rows_scanned").cast("double"), F.lit(1.0))))).alias("rows_scanned"), F.avg(F.col("affected") / F.col("vertices")).alias("affected_share"))
    means = per.groupBy("method", "fraction").agg(*(F.exp(F.avg(F.ln(c))).alias(c) for c in ("seconds", "l1", "rows_scanned")), F.avg("affected_share").alias("affected_share"))
    cold = means.where("method = 'cold'").select("fraction", F.col("seconds").alias("s0"), F.col("rows_scanned").alias("e0"), F.col("l1").alias("l0"))
    return means.join(F.broadcast(cold), "fraction", "left").select("method", "fraction", "seconds", "l1", "affected_share", (F.col("s0") / F.col("seconds")).alias("speedup"), (F.col("e0") / F.col("rows_scanned")).alias("work_ratio"), (F.col("l1") / F.col("l0")).alias("error_ratio"))


def affected_report(runs: DataFrame) -> DataFrame:
    """fraction, and a column for each of reach, frontier and pruned: mean share of vertices ever affected."""
    return runs.groupBy("fraction").pivot("method", ["reach", "frontier", "pruned"]).agg(F.avg(F.col("affected") / F.col("vertices")))


def batch_series(runs: DataFrame) -> DataFrame:
    return runs.select("workload", "method", "fraction", "batch", "seconds", "l1", "supersteps", "in_edges", "rows_scanned")


def graph_breakdown(runs: DataFrame) -> DataFrame:
    """Geometric means by workload and method, with subtotals over workloads and in all."""
    return runs.rollup("method", "workload").agg(F.exp(F.avg(F.ln("seconds"))).alias("seconds"), F.exp(F.avg(F.ln(F.greatest("l1", F.lit(1e-300))))).alias("l1"), F.sum("rows_scanned").alias("rows_scanned"))


#: Spread tolerances of each measure, from the largest: absolute ones are multiples of the stop tolerance.
SPREAD_GRID = {"abs": [1e-10 * 10.0**-k for k in range(6)], "share": [1e-10 * 10.0**-k for k in range(6)], "rel": [10.0**-k for k in range(1, 7)]}


def _tune(spark, sf_dir, names, settings: list[tuple[str, RankConfig, str]], fraction: float, n_batches: int, reference: RankConfig | None) -> DataFrame:
    """One row for each setting, workload and batch: work and error, and cold's on the same batch."""
    rows = []
    reference = reference or REFERENCE
    for w in names:
        prev: RankTable | None = None
        for k, old, new, delta in replay(spark, sf_dir, w, fraction, n_batches):
            prev = prev if prev is not None else cold_rank(old).table(old.n_vertices)
            ref, cold = reference_rank(new, reference).ranks, cold_rank(new)
            base = (cold.seconds, cold.in_edges, cold.rows_scanned, measures.l1_error(cold.ranks, ref).first()[0])
            for label, cfg, method in settings:
                run = solve(new, {"pruned": PRUNED, "frontier": FRONTIER}[method], cfg, prev, seed_frontier(old, new, delta))
                rows.append((label, cfg.expand_by, cfg.tau_f, cfg.tau_p, w, k, run.seconds, run.supersteps, run.in_edges, run.rows_scanned, measures.l1_error(run.ranks, ref).first()[0], *base))
            prev = cold.table(new.n_vertices)
    return spark.createDataFrame(rows, "setting string, expand_by string, tau_f double, tau_p double, workload string, batch int, seconds double, supersteps int, in_edges bigint, rows_scanned bigint, l1 double, cold_seconds double, cold_in_edges bigint, cold_rows_scanned bigint, cold_l1 double")


def tuned(rows: DataFrame) -> DataFrame:
    """Per setting: mean speedup over cold in time and in edges read, mean error, and the share of graphs where the error is under cold's."""
    g = lambda c: F.exp(F.avg(F.ln(c)))
    work = F.col("cold_rows_scanned") / F.greatest(F.col("rows_scanned"), F.lit(1))
    return rows.groupBy("expand_by", "tau_f", "tau_p").agg(g(F.col("cold_seconds") / F.col("seconds")).alias("speedup"), g(work).alias("work_ratio"), g(F.greatest("l1", F.lit(1e-300))).alias("l1"), g("cold_l1").alias("cold_l1"), F.avg((F.col("l1") <= F.col("cold_l1")).cast("double")).alias("under_cold"))


def sweep_work(spark: SparkSession, sf_dir: str, names: Iterable[str], settings: list[tuple[MethodPlan, RankConfig]], fraction: float, reference: RankConfig | None = None) -> DataFrame:
    """Rounds, work, reach and error of each setting on each graph's first batch: workload, setting, supersteps, in_edges, affected, l1.

    A study of work and error: a graph is swept in one task up to ``local_edges``; beyond, in parts that all settings share, or, where these don't fit,
    each setting is a distributed run.
    """
    out, reference = None, reference or REFERENCE.but(engine="where_it_fits")
    for w in names:
        p = prepared(spark, sf_dir, w, fraction)
        ref = reference_rank(p.new, reference).ranks
        seeds = stored(seed_frontier(p.old, p.new, p.delta), "seeds")
        if engine(reference, p.new.n_edges, p.new.n_vertices) == "local":
            state = starting_state(p.new, p.base, seeds).join(ref.select("id", F.col("rank").alias("ref")), "id")
            rows = local_sweep(p.new.edges, state, p.new.n_vertices, settings)
        else:
            parts = parts_for(spark, p.new.n_edges + p.new.n_vertices)
            state = starting_state(p.new, p.base, seeds).join(ref.select("id", F.col("rank").alias("ref")), "id")
            got = sweep(p.new.edges, state, parts, p.new.n_vertices, settings) if parts and p.new.even(parts, MOST_ROWS) else None
            rows = spark.createDataFrame(_swept(p, settings, seeds, ref) if got is None else got, SWEPT)
        rows = rows.select(F.lit(w).alias("workload"), "*")
        out = rows if out is None else out.unionByName(rows)
    return out


def _swept(p: Prepared, settings: list[tuple[MethodPlan, RankConfig]], seeds: DataFrame, ref: DataFrame) -> list[tuple]:
    """What :func:`local_sweep` gives, of one distributed run after the other."""
    rows = []
    for k, (plan, cfg) in enumerate(settings):
        run = solve(p.new, plan, cfg, p.table if plan.warm else None, seeds if plan.seed != "all" else None)
        rows.append((k, run.supersteps, run.in_edges, run.ranks.where("ever_affected").count(), measures.l1_error(run.ranks, ref).first()[0]))
        run.drop()
    return rows


#: Settings of the two tolerance studies.
def spread_settings(grid=None) -> list[tuple[MethodPlan, RankConfig]]:
    return [(FRONTIER, RankConfig(expand_by=kind, tau_f=t)) for kind, ts in (grid or SPREAD_GRID).items() for t in ts]


def settle_settings(spreads=(1e-6, 1e-7, 1e-8), ratios=(1.0, 1e-1, 1e-2, 1e-3, 1e-4)) -> list[tuple[MethodPlan, RankConfig]]:
    return [(PRUNED, RankConfig(tau_f=f, tau_p=f * r)) for f in spreads for r in ratios]


def sweep_spread(spark, sf_dir, names=workloads.TEMPORAL, fraction: float = 1e-5, n_batches: int = 1, grid=None, reference=None) -> DataFrame:
    """Three measures of change, each over its tolerances, without pruning."""
    settings = [(f"{kind}/{t:.0e}", RankConfig(expand_by=kind, tau_f=t), "frontier") for kind, ts in (grid or SPREAD_GRID).items() for t in ts]
    return tuned(_tune(spark, sf_dir, names, settings, fraction, n_batches, reference))


def sweep_settle(spark, sf_dir, names=workloads.TEMPORAL, fraction: float = 1e-5, n_batches: int = 1, spreads=(1e-6, 1e-7, 1e-8), ratios=(1.0, 1e-1, 1e-2, 1e-3, 1e-4), reference=None) -> DataFrame:
    """Settle tolerances from the spread tolerance down, for three spread tolerances."""
    settings = [(f"{f:.0e}/{f * r:.0e}", RankConfig(tau_f=f, tau_p=f * r), "pruned") for f in spreads for r in ratios]
    return tuned(_tune(spark, sf_dir, names, settings, fraction, n_batches, reference))


def worked_example(spark: SparkSession) -> DataFrame:
    """step, vertex, role on the 16-vertex example: marked, hot, new mark, settled, or never reached."""
    from .graph import apply_delta, snapshot
    from .kernel import local_rounds
    from .marking import reach_set

    cfg = RankConfig(tau=1e-16, dangling="none", engine="local")
    v, edges, batch = workloads.example16(spark)
    old = snapshot(v, edges, self_loops=False)
    new = snapshot(v, apply_delta(edges, batch), self_loops=False)
    prev = {r["id"]: r["rank"] for r in cold_rank(old, cfg).ranks.collect()}
    seeds = {r["id"] for r in seed_frontier(old, new, batch).collect()}
    reached = {r["id"] for r in reach_set(old, new, batch).collect()}
    import numpy as np

    pairs = np.array([(r["src"], r["dst"]) for r in new.edges.collect()])
    ids = np.arange(1, 17)
    deg = np.array([int((pairs[:, 0] == i).sum()) for i in ids])
    rows, rank, affected = [(0, i, "marked") for i in sorted(seeds)], np.array([prev[int(i)] for i in ids]), np.isin(ids, list(seeds))
    plan = PRUNED.__class__("example", True, "neighbours", expand=True, prune=False)
    for step in (1, 2):
        _, moved, _, _ = local_rounds(pairs[:, 0], pairs[:, 1], ids, rank, deg, affected, 16, plan, cfg.but(max_supersteps=1))
        rel = np.abs(moved - rank) / np.maximum(moved, rank)
        hot = affected & (rel > cfg.tau_f)
        marks = np.isin(ids, pairs[np.isin(pairs[:, 0], ids[hot]), 1])
        rows += [(step, int(i), "hot") for i in ids[hot]] + [(step, int(i), "marked") for i in ids[marks]] + [(step, int(i), "settled") for i in ids[affected & (rel <= cfg.tau_p)]]
        rank, affected = moved, affected | marks
    rows += [(9, int(i), "never reached") for i in ids if int(i) not in reached]
    return spark.createDataFrame(rows, "step int, vertex bigint, role string")


def advise_report(runs: DataFrame) -> DataFrame:
    """workload: the fastest method by edges read among those whose error is not above cold's, and what the rules of thumb say."""
    per = runs.groupBy("workload", "method").agg(F.avg("rows_scanned").alias("work"), F.avg("l1").alias("l1"))
    cold = per.where("method = 'cold'").select("workload", F.col("l1").alias("limit"))
    best = per.join(F.broadcast(cold), "workload").where("l1 <= limit").groupBy("workload").agg(F.min_by("method", F.struct("work", "method")).alias("best"))
    errors: dict[str, dict[str, float]] = {}
    for r in per.collect():
        errors.setdefault(r["workload"], {})[r["method"]] = r["l1"]
    told = [(w, advise(e, "web" if w == "web_links" else "temporal", w in workloads.STATIC)) for w, e in errors.items()]
    return best.join(runs.sparkSession.createDataFrame(told, "workload string, advice string"), "workload")


def scaling_report(spark: SparkSession, sf_dir: str, workload: str = "part_flow", cores=(1, 2, 4), fraction: float = 1e-4, methods=("frontier", "pruned")) -> DataFrame:
    """Time by number of cores, with speedups and gains per doubling, all in the caller's session, whatever it runs on.

    On ``c`` cores scans, shuffles and rounds are cut into ``c`` tasks, so that a stage has work for no more; a second stage that is ready
    at the same time, such as the other side of a join, may still run beside it.
    """
    p = prepared(spark, sf_dir, workload, fraction)
    cfg, rows = RankConfig(), []
    for c in cores:
        n = str(c)
        with settings(spark, spark__sql__shuffle__partitions=n, spark__sql__files__minPartitionNum=n, spark__sql__files__maxPartitionNum=n):
            for m in methods:
                run_method(m, p.old, p.new, p.delta, p.table, cfg.but(max_supersteps=1)).drop()
                run = run_method(m, p.old, p.new, p.delta, p.table, cfg)
                rows.append((m, c, run.seconds))
                run.drop()
    return measures.scaling_table(spark.createDataFrame(rows, "method string, cores int, seconds double"))
