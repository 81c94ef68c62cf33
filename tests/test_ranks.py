"""Methods on hand-made graphs and on the smallest tables."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from incrank.functions.formulas import rank_e9
from incrank.functions.measures import l1_error, residual_bound
from incrank.plans import methods as M
from incrank.plans.experiments import worked_example
from incrank.plans.graph import apply_delta, diff_snapshots, next_snapshot, normalize_delta, snapshot
from incrank.plans.kernel import pull_shares, push_shares
from incrank.plans.layers import Keys, RankTable
from incrank.plans.marking import reach_set, seed_frontier
from incrank.plans.model import DELTA, EDGE, METHODS, MethodPlan, RankConfig
from incrank.plans.planner import chained, direction, engine, partitions
from incrank.plans.prepared import prepared
from incrank.plans.solver import solve
from incrank.sources import workloads

SF = "/root/testdata/sf0.001"
# Ranks of the 16-vertex example in units of 1e-9, with self-loops, before and after the batch.
BEFORE = [47707449, 99510409, 33935361, 56191132, 33935361, 145743042, 28603047, 47707449, 33935361, 76649033, 30043667, 28603047, 24959124, 78978306, 92310631, 141187578]
AFTER = [11904762, 120541133, 20703934, 37237038, 20703934, 141026239, 28603047, 76958707, 44745609, 82218036, 30043667, 46951732, 24959124, 69356488, 96009100, 148037449]


LOCAL = RankConfig(engine="local")


def graph(spark, edges, n=None, first=0, loops=True):
    ids = range(first, first + n) if n else sorted({x for e in edges for x in e})
    return snapshot(spark.createDataFrame([(i,) for i in ids], "id bigint"), spark.createDataFrame(edges, EDGE), loops)


def ranks(run):
    return {r["id"]: r["rank"] for r in run.ranks.collect()}


@pytest.fixture(scope="module")
def example(spark):
    v, e, d = workloads.example16(spark)
    old = snapshot(v, e)
    delta = normalize_delta(old.edges, d)
    return old, next_snapshot(old, delta), delta, M.cold_rank(old, LOCAL)


@pytest.mark.parametrize("cfg", [LOCAL, RankConfig(tau=1e-4)])
def test_single_vertex_cycle_and_star(spark, cfg):
    assert ranks(M.cold_rank(graph(spark, [], 1), cfg)) == {0: pytest.approx(1.0)}
    cycle = graph(spark, [(0, 1), (1, 2), (2, 0)])
    assert all(r == pytest.approx(1 / 3) for r in ranks(M.cold_rank(cycle, cfg)).values())


def test_closed_forms(spark):
    pair = ranks(M.cold_rank(graph(spark, [(0, 1)]), LOCAL))
    assert pair[0] == pytest.approx(0.130434783, abs=1e-8) and pair[1] == pytest.approx(0.869565217, abs=1e-8)
    n = 5
    star = ranks(M.cold_rank(graph(spark, [(k, 0) for k in range(1, n + 1)]), LOCAL))
    leaf = 0.15 / (n + 1) / 0.575
    assert star[1] == pytest.approx(leaf, abs=1e-9) and star[0] == pytest.approx(1 - n * leaf, abs=1e-8)


def test_example_ranks(example):
    old, new, delta, base = example
    got = [r[0] for r in base.ranks.orderBy("id").select(rank_e9(F.col("rank"))).collect()]
    assert got == BEFORE and base.supersteps == 49
    ref = M.reference_rank(new, LOCAL.but(max_supersteps=150))
    assert [r[0] for r in ref.ranks.orderBy("id").select(rank_e9(F.col("rank"))).collect()] == AFTER
    frontier = M.frontier_rank(old, new, delta, base.ranks, LOCAL)
    pruned = M.pruned_rank(old, new, delta, base.ranks, LOCAL)
    for run in (frontier, pruned):
        assert run.ranks.where("ever_affected").count() == 13
        assert {r["id"] for r in run.ranks.where("NOT ever_affected").collect()} == {7, 11, 13}
        assert run.trace[0]["n_affected"] == 6 and run.trace[0]["n_expanded"] == 6 and run.trace[1]["n_affected"] == 11
    assert frontier.supersteps == 52 and pruned.trace[1]["n_expanded"] == 8
    assert l1_error(frontier.ranks, ref.ranks).first()[0] == pytest.approx(6.4e-10, rel=0.05)
    assert l1_error(pruned.ranks, ref.ranks).first()[0] == pytest.approx(4.6e-7, rel=0.05)


def test_example_roles_without_self_loops(spark):
    roles = {}
    for r in worked_example(spark).collect():
        roles.setdefault((r["step"], r["role"]), set()).add(r["vertex"])
    assert roles[0, "marked"] == {1, 8, 12, 14}
    assert roles[1, "hot"] == {1, 8, 12, 14} and roles[1, "marked"] == {3, 5, 9, 10, 14, 15}
    assert roles[2, "hot"] == {3, 5, 9, 14, 15} and roles[2, "marked"] == {4, 6, 10, 15, 16}
    assert roles[2, "settled"] == {1, 8, 12, 10} and roles[9, "never reached"] == {7, 11, 13}


def work(run):
    return [(t["n_affected"], t["n_expanded"], t["n_settled"], t["in_edges"]) for t in run.trace]


def assert_same(a, b):
    assert work(a) == work(b)
    both = a.ranks.join(b.ranks.withColumnRenamed("rank", "q").withColumnRenamed("ever_affected", "e"), "id")
    assert both.count() == a.ranks.count() and both.where("abs(rank - q) > 1e-15 OR ever_affected <> e").count() == 0


@pytest.mark.parametrize("method,direction,rounds", [("cold", "push", 7), ("warm", "push", 7), ("reach", "pull", 7), ("reach", "push", 3), ("frontier", "pull", 500), ("frontier", "push", 3), ("pruned", "pull", 3), ("pruned", "push", 500)])
def test_distributed_rounds_are_local_rounds(example, method, direction, rounds):
    """In chains and alone, marks of the last round included; two at full length."""
    old, new, delta, base = example
    cut = RankConfig(max_supersteps=rounds)
    a = M.run_method(method, old, new, delta, base.ranks, cut.but(engine="local"))
    assert_same(a, M.run_method(method, old, new, delta, base.ranks, cut.but(direction=direction)))


@pytest.mark.parametrize("workload,method", [("part_flow", "frontier"), ("cust_supp", "pruned")])
def test_distributed_rounds_are_local_rounds_on_tables(spark, workload, method):
    p = prepared(spark, SF, workload)
    a = M.run_method(method, p.old, p.new, p.delta, p.table, RankConfig(engine="local"))
    for direction in ("pull", "push"):
        assert_same(a, M.run_method(method, p.old, p.new, p.delta, p.table, RankConfig(direction=direction)))


def test_a_small_frontier_costs_what_it_needs(spark):
    """Edges and states of what was reached are read, not the graph; the run writes what it reached, and the next batch writes what it changes."""
    p = prepared(spark, SF, "order_chain")
    run = M.run_method("pruned", p.old, p.new, p.delta, p.table)
    own = p.new.in_edges(Keys.of(run.changed, p.new.buckets)).count()
    assert run.changed.count() == run.ranks.where("ever_affected").count() < 0.01 * p.new.n_vertices
    assert own + run.changed.count() <= run.trace[-1]["rows_scanned"] + 2 and run.trace[-1]["rows_scanned"] < 0.05 * p.new.n_edges
    assert run.rows_scanned < M.cold_rank(p.new, LOCAL).rows_scanned / 10
    table = run.table(p.new.n_vertices)
    assert table.base is p.table.base and table.n_over == run.changed.count()
    assert p.new.base is p.old.base and p.new.n_net == p.delta.count()
    assert l1_error(table.df, run.ranks).first()[0] == 0


def test_lookups_open_few_buckets(spark):
    p = prepared(spark, SF, "order_chain")
    keys = Keys.of(p.new.vertices.limit(1), p.new.buckets)
    plan = p.new.base.into.of(keys)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(bucket" in plan and "Exchange hashpartitioning(dst" not in plan
    assert p.new.base.into.scanned(keys.touched) < p.new.n_edges / 4


def test_empty_batch_changes_nothing(spark, example):
    old, _, _, base = example
    none = spark.createDataFrame([], DELTA)
    for method in ("reach", "frontier", "pruned"):
        run = M.run_method(method, old, old, none, base.ranks)
        assert run.supersteps == 0 and l1_error(run.ranks, base.ranks).first()[0] == 0


def test_batches_are_sets(spark):
    old = graph(spark, [(0, 1), (1, 2), (2, 0)])
    raw = spark.createDataFrame([(0, 1, "+"), (0, 2, "+"), (0, 2, "+"), (1, 2, "-"), (2, 1, "-"), (1, 1, "-"), (2, 0, "-"), (2, 0, "+")], DELTA)
    delta = normalize_delta(old, raw)
    assert sorted(map(tuple, normalize_delta(old.edges, raw).collect())) == sorted(map(tuple, delta.collect()))
    assert sorted(map(tuple, delta.collect())) == [(0, 2, "+"), (1, 2, "-")]
    new = next_snapshot(old, delta)
    assert sorted(map(tuple, diff_snapshots(old.edges, new.edges).collect())) == [(0, 2, "+"), (1, 2, "-")]
    assert new.edges.where("src = dst").count() == 3
    assert {r["id"]: r["out_deg"] for r in new.degrees.collect()} == {0: 3, 1: 1, 2: 2}
    assert apply_delta(new.edges, spark.createDataFrame([(0, 2, "-"), (1, 2, "+")], DELTA)).exceptAll(old.edges).count() == 0


def test_bound_mass_and_reach(spark):
    p = prepared(spark, SF, "part_flow")
    cold = M.cold_rank(p.new, LOCAL)
    ref = M.reference_rank(p.new, LOCAL)
    bound = residual_bound(p.new.edges, p.new.degrees, cold.ranks, p.new.n_vertices, 0.85).first()[0]
    assert l1_error(cold.ranks, ref.ranks).first()[0] <= bound + 1e-13
    total, least = cold.ranks.agg(F.sum("rank"), F.min("rank")).first()
    assert total == pytest.approx(1, abs=1e-8) and least >= 0.15 / p.new.n_vertices - 1e-15
    reached = reach_set(p.old, p.new, p.delta, "union")
    for run in (M.frontier_rank(p.old, p.new, p.delta, p.table, LOCAL), M.pruned_rank(p.old, p.new, p.delta, p.table)):
        assert run.ranks.where("ever_affected").join(reached, "id", "left_anti").count() == 0
        seeds = seed_frontier(p.old, p.new, p.delta)
        assert seeds.join(run.ranks.where("ever_affected"), "id", "left_anti").count() == 0
    state = p.base.join(p.new.degrees.withColumnRenamed("out_deg", "deg"), "id")
    some = p.new.vertices.where("id % 3 = 0")
    a, b = pull_shares(p.new.edges, state, some), push_shares(p.new.edges, state).join(some, "id", "left_semi")
    assert a.join(b.withColumnRenamed("share_sum", "q"), "id").where("abs(share_sum - q) > 1e-15").count() == 0 and a.count() == b.count()


def test_formulas_share_the_fixed_point(spark):
    p = prepared(spark, SF, "cust_supp")
    tight = LOCAL.but(tau=1e-15)
    a = solve(p.new, METHODS["warm"], tight, p.base)
    b = solve(p.new, MethodPlan("x", True, "all", formula="loopfree"), tight, p.base)
    assert l1_error(a.ranks, b.ranks).first()[0] < 1e-11 and b.supersteps < a.supersteps


def test_pruned_reads_fewer_edges(spark):
    for w in ("cust_supp", "order_chain"):
        p = prepared(spark, SF, w)
        cold, pruned = M.cold_rank(p.new, LOCAL), M.pruned_rank(p.old, p.new, p.delta, p.table)
        assert pruned.in_edges < cold.in_edges / 3


def test_planner_and_settings():
    cfg = RankConfig(local_edges=100)
    assert engine(cfg, 90, 5) == "distributed" and engine(cfg.but(engine="local"), 90, 5) == "local"
    assert partitions(10, 200, 8) == 2 and partitions(100_000, 200, 8) == 8 and partitions(10**9, 200, 8) == 200
    assert chained(1, 0.1, [], 1e-10) == 2 and chained(8, 0.1, [1e-9, 2e-10], 1e-10) == 1 and chained(8, 60.0, [], 1e-10) == 1
    with pytest.raises(ValueError):
        engine(cfg.but(engine="local"), 1000, 5)
    assert direction(cfg, 1, 1000) == "pull" and direction(cfg, 900, 1000) == "push"
    with pytest.raises(ValueError):
        RankConfig(norm="l3")
    assert M.advise({"pruned": 2.0, "cold": 1.0}) == "frontier" and M.advise({}) == "pruned" and M.advise({}, "web", True) == "frontier"
    assert 11.5 ** (1 / math.log2(16)) == pytest.approx(1.84, abs=0.01)


def test_thresholds_are_strict():
    from incrank.plans.kernel import local_rounds

    # one vertex with a self-loop at its fixed point: no change, so it settles at tau_p = 0 and does not spread at tau_f = 0
    one = np.array([0])
    _, rank, ever, trace = local_rounds(one, one, one, np.array([1.0]), np.array([1]), np.array([True]), 1, METHODS["pruned"], RankConfig(tau_f=0.0, tau_p=0.0))
    assert rank[0] == pytest.approx(1.0) and trace[0][1] in (0, 1) and len(trace) == 1 and ever[0]


def test_plan_of_a_round(spark):
    """Neither edges nor states move in a round, only sums; and a scan reads what it needs."""
    from incrank.plans.kernel import job_sql
    from incrank.plans.solver import Rounds

    p = prepared(spark, SF, "part_flow")
    rounds = Rounds(p.new, METHODS["frontier"], RankConfig(), p.table)
    state, _ = rounds.job(rounds.push(rounds._first(p.new.vertices.limit(3))), 1)
    with rounds.planned():
        state.createOrReplaceTempView(rounds.state_view)
        plan = spark.sql(job_sql(2, rounds.edge_view, rounds.state_view, p.new.n_vertices, rounds.plan, rounds.cfg))._jdf.queryExecution().executedPlan().toString()
    lines, kept = [], None  # how kept edges were made is left out
    for line in plan.split("\n"):
        depth = len(line) - len(line.lstrip(" :+-"))
        if kept is not None and depth > kept:
            continue
        kept = depth if "InMemoryRelation" in line else None
        lines.append(line)
    moves = [line for line in lines if "Exchange" in line]
    assert len(moves) == 2 and all("hashpartitioning(dst" in line for line in moves)
    assert sum("SortMergeJoin" in line for line in lines) == 2 and sum("Sort [src" in line for line in lines) == 0
    scan = workloads.read(spark, SF, "lineitem", "l_partkey").where("l_partkey = 7")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_partkey), EqualTo(l_partkey,7)]" in scan and "ReadSchema: struct<l_partkey:bigint>" in scan


def test_hubs_are_salted(spark):
    """A source with more edges than a hub may have is dealt over several parts; results stay."""
    edges = [(0, k) for k in range(1, 40)] + [(k, (k * 7) % 40) for k in range(1, 40)]
    g = graph(spark, edges)
    cfg = RankConfig(engine="distributed", max_supersteps=4)
    a, b = M.cold_rank(g, cfg), M.cold_rank(g, cfg.but(hub_degree=10))
    assert l1_error(a.ranks, b.ranks).first()[0] < 1e-15 and [t["in_edges"] for t in a.trace] == [t["in_edges"] for t in b.trace]


def test_dead_ends_can_be_spread(spark):
    g = graph(spark, [(0, 1), (1, 2), (0, 2)], loops=False)
    cfg = RankConfig(dangling="redistribute", max_supersteps=6)
    a, b = M.cold_rank(g, cfg.but(engine="local")), M.cold_rank(g, cfg.but(engine="distributed"))
    assert l1_error(a.ranks, b.ranks).first()[0] < 1e-15 and a.ranks.agg(F.sum("rank")).first()[0] == pytest.approx(1)


def test_reach_gives_up_beyond_its_share(spark):
    p = prepared(spark, SF, "part_flow")
    assert reach_set(p.old, p.new, p.delta, most_share=0.0) is None
    run = M.reach_rank(p.old, p.new, p.delta, p.base, RankConfig(max_supersteps=2), most_share=0.0)
    assert run.trace[0]["n_affected"] == p.new.n_vertices


def test_growing_graphs_mark_everything(spark):
    from incrank.plans.methods import carry_ranks

    old = spark.createDataFrame([(1, 0.5), (2, 0.5)], "id bigint, rank double")
    ranks_, all_ = carry_ranks(spark.range(1, 5), old, "grow")
    assert all_ and {r["id"]: r["rank"] for r in ranks_.collect()} == {1: 0.25, 2: 0.25, 3: 0.25, 4: 0.25}


@pytest.mark.parametrize("method", ["cold", "warm", "pruned"])
def test_new_vertices_come_in(spark, method):
    old = graph(spark, [(0, 1), (1, 2), (2, 0)])
    delta = normalize_delta(old, spark.createDataFrame([(3, 4, "+"), (4, 1, "+"), (0, 1, "-")], DELTA))
    with pytest.raises(ValueError):
        next_snapshot(old, delta)
    new = next_snapshot(old, delta, "grow")
    assert (new.n_vertices, new.n_edges) == (5, 9) and new.edges.where("src = dst").count() == 5
    whole = graph(spark, [(1, 2), (2, 0), (3, 4), (4, 1)])
    assert sorted(map(tuple, new.degrees.collect())) == sorted(map(tuple, whole.degrees.collect()))
    run = M.run_method(method, old, new, delta, M.cold_rank(old).ranks, RankConfig(tau=1e-6, tau_f=1e-9, tau_p=1e-9))
    assert l1_error(run.ranks, M.cold_rank(whole, LOCAL).ranks).first()[0] < 1e-4 and run.ranks.count() == 5


def test_layers_fold_and_changes_cancel(spark):
    """Batches upon batches end where one graph with all their changes begins; what is taken back leaves no trace."""
    g = graph(spark, [(k, (k + 1) % 40) for k in range(40)])
    there = spark.createDataFrame([(0, 5, "+"), (7, 8, "-")], DELTA)
    back = spark.createDataFrame([(0, 5, "-"), (7, 8, "+")], DELTA)
    one = next_snapshot(g, normalize_delta(g, there))
    two = next_snapshot(one, normalize_delta(one, back))
    assert one.n_net == 2 and two.n_net == 0 and two.edges.exceptAll(g.edges).count() == 0 and two.n_edges == g.n_edges
    many = spark.createDataFrame([(k, (k + 2) % 40, "+") for k in range(12)], DELTA)
    three = next_snapshot(two, normalize_delta(two, many))
    assert three.base is not g.base and three.n_net == 0 and three.n_edges == g.n_edges + 12 and three.edges.count() == three.n_edges
    table = RankTable.store(g.vertices.selectExpr("id", "1.0D / 40 AS rank"), g.buckets, 40)
    over = table.updated(spark.createDataFrame([(1, 0.5), (2, 0.25)], "id bigint, rank double"))
    assert over.base is table.base and over.n_over == 2 and over.of(Keys.of(spark.range(1, 4), g.buckets)).agg(F.sum("rank")).first()[0] == pytest.approx(0.775)
    folded = over.updated(spark.createDataFrame([(k, 0.0) for k in range(2, 9)], "id bigint, rank double"))
    assert folded.base is not table.base and folded.over is None and folded.df.agg(F.sum("rank")).first()[0] == pytest.approx(0.5 + 32 / 40)


def test_scaling_needs_no_process_of_its_own(spark, monkeypatch):
    """Nothing but the caller's session is used: a second Spark may not be there to be had."""
    import subprocess

    from incrank.plans.experiments import scaling_report

    def refuse(*args, **more):
        raise OSError("no second process")

    monkeypatch.setattr(subprocess, "run", refuse)
    was = spark.conf.get("spark.sql.shuffle.partitions")
    got = scaling_report(spark, SF, "event_flow", (1, 2), 1e-3, ("pruned",)).collect()
    assert [(r["method"], r["cores"]) for r in sorted(got, key=lambda r: r["cores"])] == [("pruned", 1), ("pruned", 2)]
    assert spark.conf.get("spark.sql.shuffle.partitions") == was


def test_nearest_of_sparse_ids_with_ties(spark):
    """Ids may lie anywhere, and many vectors may be equal: ties go to the smaller id, whatever blocks they lie in."""
    from incrank.functions.vectors import nearest

    rng = np.random.default_rng(3)
    v = np.concatenate([np.repeat(rng.normal(size=(3, 16)), 40, axis=0), rng.normal(size=(30, 16))]).astype(np.float32)
    ids = rng.permutation(len(v)) * 10**15 + 7
    got = {(r["src"], r["place"]): r["dst"] for r in nearest(spark.createDataFrame([(int(i), x.tolist()) for i, x in zip(ids, v, strict=True)], "vec_id bigint, embedding array<float>"), 4, 20).collect()}
    u = v.astype(float) / np.linalg.norm(v.astype(float), axis=1, keepdims=True)
    far = -np.round(u @ u.T, 9)
    want = {}
    for k in range(len(v)):
        order = [j for j in np.lexsort((ids, far[k])) if j != k][:4]
        want |= {(int(ids[k]), p + 1): int(ids[j]) for p, j in enumerate(order)}
    assert got == want


def test_yardsticks_beyond_one_task(spark, monkeypatch):
    """Errors and sweeps are measured on graphs of any size; beyond ``local_edges`` their rounds are distributed, with the same results."""
    from incrank.operators import ranks
    from incrank.plans.experiments import spread_settings, sweep_work

    short = ranks.REFERENCE.but(max_supersteps=60)
    got = []
    for cfg in (short, short.but(local_edges=100)):
        monkeypatch.setattr(ranks, "REFERENCE", cfg)
        monkeypatch.setattr(ranks, "_references", {})
        swept = sweep_work(spark, SF, ["event_flow"], spread_settings({"rel": [1e-1, 1e-3]}), 1e-2, cfg)
        got.append((ranks.error(spark, SF, "event_flow", "pruned").collect(), sorted(swept.selectExpr("workload", "setting", "supersteps", "in_edges", "affected", "round(l1, 10)").collect())))
    assert got[0] == got[1] and len(got[0][1]) == 2


def test_scaling_report(spark):
    from incrank.plans.experiments import scaling_report

    got = scaling_report(spark, SF, "event_flow", (1, 2), 1e-3, ("pruned",)).toPandas()
    assert sorted(got.cores) == [1, 2] and (got.seconds > 0).all() and got[got.cores == 1].speedup.tolist() == [1.0]


@pytest.mark.parametrize("parts", [1, 5])
def test_rounds_in_parts(spark, monkeypatch, parts):
    """However many parts a graph has, one job does all rounds up to the stop or the next fetch; they are those of SQL, round by round."""
    from incrank.plans import arrays
    from incrank.plans.solver import Rounds

    def runs(cfgs):
        out = []
        for m, cfg in cfgs:
            run = M.run_method(m, p.old, p.new, p.delta, p.table, cfg)
            out.append(([{c: t[c] for c in ("superstep", "n_affected", "n_expanded", "n_settled", "in_edges", "rows_scanned")} for t in run.trace], {r["id"]: (pytest.approx(r["rank"], abs=1e-15), r["ever_affected"]) for r in run.ranks.collect()}))
        return out

    p = prepared(spark, SF, "part_flow")
    cfgs = [(m, RankConfig()) for m in METHODS] + [("frontier", RankConfig(direction="push", max_supersteps=3)), ("warm", RankConfig(dangling="redistribute", norm="l1", tau=1e-6, max_supersteps=6))]
    monkeypatch.setattr(arrays, "parts_for", lambda spark, rows: 0)
    want = runs(cfgs)
    monkeypatch.setattr(arrays, "parts_for", lambda spark, rows: parts)
    monkeypatch.setattr(Rounds, "job", lambda *args: pytest.fail("a job for each chain of rounds"))
    assert runs(cfgs) == want


def test_parts_that_do_not_fit(spark, monkeypatch):
    """Rounds stay jobs of SQL where a part would be too large, or the session deals rows otherwise than asked; a task that fails ends all."""
    from incrank.plans import arrays

    p = prepared(spark, SF, "part_flow")
    assert arrays.slots(spark) == 8 and arrays.parts_for(spark, 50 * arrays.PART_ROWS) == 8 and not arrays.parts_for(spark, 9 * arrays.MOST_ROWS)
    assert p.new.even(4, p.new.n_edges) and not p.new.even(4, 100)
    monkeypatch.setattr(arrays, "dealt", lambda *args: None)
    assert len(M.cold_rank(p.new, RankConfig(max_supersteps=2)).trace) == 2
    monkeypatch.undo()
    monkeypatch.setattr(arrays, "parts_for", lambda spark, rows: 3)
    with pytest.raises(Exception, match="division by zero|ZeroDivision"):
        arrays._tried(spark, lambda folder: spark.range(3).repartition(3).mapInArrow(arrays._guarded(folder, lambda batches: [1 / 0]), "id bigint", barrier=True).collect())


def test_sweeps_in_parts(spark, monkeypatch):
    """All settings of a sweep beyond one task share the parts: none is a run of its own."""
    from incrank.plans import arrays, experiments

    cfg = RankConfig(tau=1e-100, max_supersteps=40, engine="where_it_fits")
    settings_ = experiments.spread_settings({"rel": [1e-1, 1e-3]}) + experiments.settle_settings((1e-6,), (1.0,))
    monkeypatch.setattr(experiments, "solve", lambda *args: pytest.fail("a run of its own"))
    monkeypatch.setattr(experiments, "parts_for", lambda spark, rows: 3)
    rows = lambda c: sorted(map(tuple, experiments.sweep_work(spark, SF, ["part_flow"], settings_, 1e-2, c).selectExpr("workload", "setting", "supersteps", "in_edges", "affected", "round(l1, 10)").collect()))
    assert rows(cfg.but(local_edges=100)) == rows(cfg)


def test_long_paths_are_not_fetched_step_by_step(spark, monkeypatch):
    """A frontier that goes on along paths is fetched a few times; then, if it has enough rows, all its rounds are one job over all edges, with the same result."""
    from incrank.plans import planner
    from incrank.plans.solver import Rounds

    monkeypatch.setattr(planner, "FETCHED_ROWS", 4)

    old = graph(spark, [(k, k + 1) for k in range(60)])
    delta = normalize_delta(old, spark.createDataFrame([(0, 30, "+")], DELTA))
    new, base = next_snapshot(old, delta), M.cold_rank(old).ranks
    fetched, fetch = [], Rounds.fetch
    monkeypatch.setattr(Rounds, "fetch", lambda self, keys: (fetched.append(keys.n), fetch(self, keys)))
    run = M.frontier_rank(old, new, delta, base)
    assert 1 < len(fetched) <= 5
    one = M.frontier_rank(old, new, delta, base, LOCAL)
    assert l1_error(run.ranks, one.ranks).first()[0] < 1e-12 and [t["in_edges"] for t in run.trace] == [t["in_edges"] for t in one.trace]
    reached = lambda r: sorted(v["id"] for v in r.ranks.where("ever_affected").collect())
    assert reached(run) == reached(one)
