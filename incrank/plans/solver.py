"""The loop that all methods share.

A round reads what its vertices need. While the in-edges of the vertices ever affected are few, a run keeps just these (pull):
they are fetched from the layout by target when a vertex is first marked, with the shares of their sources, which stay as they
were until a source is affected itself. Beyond that, all edges lie by source and are joined with all ranks (push). Either way a
round is one join and one shuffle, of sums; marks come along with the sums of the next round. Short rounds are chained, so that a job
and its one write, of the state, may do several; each round has its own stop test, and a chain that ran past it is cut back.

Where tasks can keep their part of edges and states as arrays (:mod:`arrays`), a job does all rounds up to the stop, or up to the next fetch.
"""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..session import scratch, ship
from . import arrays, planner
from .graph import Snapshot
from .kernel import STATE, incoming_sql, job_sql, local_solve, measures_sql, own_rows, salted
from .layers import BROADCAST_KEYS, Keys, RankTable, Steps, bucket_of, settings
from .model import MethodPlan, RankConfig, RankRun


def starting_state(g: Snapshot, prev: DataFrame | None, frontier: DataFrame | None) -> DataFrame:
    """id, rank, deg, affected: ranks carried over, or uniform; all vertices affected, or the frontier.

    A vertex without an old rank starts at 1 / V.
    """
    state = g.degrees.select("id", F.col("out_deg").alias("deg"))
    uniform = F.lit(1.0 / g.n_vertices) if g.n_vertices else F.lit(0.0)
    state = state.withColumn("rank", uniform) if prev is None else state.join(prev.select("id", "rank"), "id", "left").withColumn("rank", F.coalesce("rank", uniform))
    if frontier is None:
        state = state.withColumn("affected", F.lit(True))
    else:
        state = state.join(frontier.select("id", F.lit(True).alias("seed")), "id", "left").withColumn("affected", F.coalesce("seed", F.lit(False)))
    return state.select("id", "rank", "deg", "affected")


def solve(g: Snapshot, plan: MethodPlan, cfg: RankConfig, prev: DataFrame | RankTable | None = None, frontier: DataFrame | None = None) -> RankRun:
    """Run supersteps until the norm of the processed vertices' changes is within ``tau``, nothing is affected, or the cap.

    ``frontier``: the vertices affected at first; None for all of them.
    """
    began = time.perf_counter()
    ship(g.spark)
    if not g.n_vertices:
        return RankRun(plan.name, g.degrees.select("id", F.lit(0.0).alias("rank"), F.lit(False).alias("ever_affected")), [], 0.0)
    table = prev if prev is None or isinstance(prev, RankTable) else RankTable(prev)
    if planner.engine(cfg, g.n_edges, g.n_vertices) == "local":
        run = _local(g, starting_state(g, None if table is None else table.df, frontier), plan, cfg)
    else:
        run = Rounds(g, plan, cfg, table).run(frontier)
    run.started_from, run.buckets = table, g.buckets
    run.seconds = time.perf_counter() - began
    return run


def _local(g: Snapshot, state: DataFrame, plan: MethodPlan, cfg: RankConfig) -> RankRun:
    spark = g.spark
    path = scratch(spark, "ranks")
    began = time.perf_counter()
    local_solve(g.edges, state, g.n_vertices, plan, cfg).write.partitionBy("kind").parquet(path)
    wall = (time.perf_counter() - began) * 1000
    got = spark.read.schema("id bigint, rank double, ever boolean, n_affected bigint, n_expanded bigint, n_settled bigint, in_edges bigint, kind int").parquet(path)
    rows = sorted((r.asDict() for r in got.where("kind = 1").collect()), key=lambda r: r["id"])
    trace = [{"superstep": r["id"], "n_affected": r["n_affected"], "n_expanded": r["n_expanded"], "n_settled": r["n_settled"], "in_edges": r["in_edges"], "rows_scanned": g.n_edges + g.n_vertices, "linf": r["rank"], "wall_ms": wall / len(rows)} for r in rows]
    return RankRun(plan.name, got.where("kind = 0").select("id", "rank", F.col("ever").alias("ever_affected")), trace)


class Rounds:
    """One distributed run."""

    def __init__(self, g: Snapshot, plan: MethodPlan, cfg: RankConfig, prev: RankTable | None) -> None:
        self.g, self.plan, self.cfg, self.prev, self.spark = g, plan, cfg, prev, g.spark
        self.steps = Steps(self.spark)
        self.most = int(self.spark.conf.get("spark.sql.shuffle.partitions", "200"))
        self.cores = self.spark.sparkContext.defaultParallelism
        self.factor = g.n_vertices / cfg.scale_vertices if cfg.tolerance_scale == "mean_rank" else 1.0
        self.near: DataFrame | None = None  # in-edges of the vertices ever affected, while pulling
        self.n_near, self.n_state, self.fetched = 0, 0, 0
        self._edge_paths: list[str] = []
        self.edges: DataFrame | None = None
        self.parts, self.salts = 1, 1
        self.sinks, self.in_parts, self.fetches = 0.0, False, 0
        name = f"incrank_{uuid.uuid4().hex}"
        self.edge_view, self.state_view = f"{name}_edges", f"{name}_state"

    # where edges and state lie

    @contextmanager
    def planned(self) -> Iterator[None]:
        """Rounds keep the layout they are given: no adaptive plan, no broadcast but those asked for, sums dealt like the state."""
        conf = {"spark__sql__adaptive__enabled": "false", "spark__sql__autoBroadcastJoinThreshold": "-1", "spark__sql__shuffle__partitions": str(self.parts)}
        if (self.n_near if self.near is not None else self.g.n_edges) < planner.COMPILED_ROWS:
            # compiling a chain's code would take longer than running it
            conf |= {"spark__sql__codegen__wholeStage": "false", "spark__sql__codegen__factoryMode": "NO_CODEGEN"}
        with settings(self.spark, **conf):
            yield

    def _dealt(self, state: DataFrame) -> DataFrame:
        return state.select(*STATE).repartition(self.parts, "id").sortWithinPartitions("id")

    def push(self, state: DataFrame) -> DataFrame:
        """All edges by source, all vertices by id."""
        g, cfg = self.g, self.cfg
        self._forget()
        self.parts = planner.partitions(g.n_edges, self.most, self.cores)
        self.salts = planner.hub_salts(cfg, g.base.max_out + g.n_net)
        with self.planned():
            if self.salts == 1:
                self.edges = g.laid(self.parts)
            else:
                rows = g.edges.select("src", "dst", F.lit(False).alias("own")).unionByName(own_rows(g.vertices))
                dealt = salted(rows, g.degrees, self.salts, cfg.hub_degree).repartition(self.parts, "src", "salt")
                self.edges = dealt.sortWithinPartitions("src", "salt").persist(StorageLevel.MEMORY_AND_DISK)
        self.edges.createOrReplaceTempView(self.edge_view)
        self.n_state = g.n_vertices
        return self._dealt(state)

    def widened(self, state: DataFrame) -> DataFrame:
        """From the vertices ever affected to all vertices."""
        mine = state.select("id", F.col("rank").alias("own"), "stays", "hot", "ever", "grown")
        both = self._first(None).drop("stays", "hot", "ever", "grown").join(mine, "id", "left")
        return both.selectExpr("id", "coalesce(own, rank) AS rank", "deg", *(f"coalesce({c}, false) AS {c}" for c in ("stays", "hot", "ever", "grown")))

    def _first(self, frontier: DataFrame | None) -> DataFrame:
        start = starting_state(self.g, None if self.prev is None else self.prev.df, frontier)
        return start.selectExpr("id", "rank", "deg", "affected AS stays", "false AS hot", "affected AS ever", "false AS grown")

    def _rows_of(self, keys: Keys) -> tuple[DataFrame, int]:
        """State rows of vertices that are marked for the first time, and the number of their in-edges."""
        ranks, degs = self.prev.of(keys), self.g.degrees_of(keys)
        self.fetched += 2 * self.g.base.degs.scanned(keys.touched)
        rows = degs.join(ranks, "id", "left").selectExpr("id", f"coalesce(rank, {1.0 / self.g.n_vertices!r}D) AS rank", "out_deg AS deg", "in_deg")
        table, got = self.steps.put(rows, in_edges=F.coalesce(F.sum("in_deg"), F.lit(0)))
        return table.selectExpr("id", "rank", "deg", "true AS stays", "false AS hot", "true AS ever", "false AS grown"), got["in_edges"]

    def fetch(self, keys: Keys) -> None:
        """Add the in-edges of some vertices, each with its source's share before the run, and their own rows."""
        g = self.g
        found, got = self.steps.put(g.in_edges(keys), n=F.count(F.lit(1)), touched=F.collect_set(bucket_of("src", g.buckets)))
        touched = tuple(sorted(got["touched"]))
        self.fetched += g.base.into.scanned(keys.touched) + 2 * g.base.degs.scanned(touched)
        wanted = found.selectExpr("src AS id").distinct()
        degs, ranks = g.degrees_in(touched), self.prev.some(touched, g.buckets)
        few = F.broadcast(wanted) if got["n"] <= BROADCAST_KEYS else wanted
        before = degs.join(few, "id", "left_semi").join(ranks, "id", "left").selectExpr("id AS src", f"coalesce(rank, {1.0 / g.n_vertices!r}D) / out_deg AS share_before")
        rows = found.join(before, "src").selectExpr("src", "dst", "false AS own", "share_before").unionByName(own_rows(keys.ids).withColumn("share_before", F.lit(0.0)))
        more, _ = self.steps.put(rows)
        self._edge_paths.append(self.steps.last)
        self.near = more if self.near is None else self.near.unionByName(more)
        self.n_near += got["n"]
        old = self.edges
        self.parts = planner.partitions(self.n_near, self.most, self.cores)
        with self.planned():
            self.edges = self.near.repartition(self.parts, "src").sortWithinPartitions("src").persist(StorageLevel.MEMORY_AND_DISK)
        self.edges.createOrReplaceTempView(self.edge_view)
        if old is not None:
            old.unpersist()

    def _forget(self) -> None:
        if self.edges is not None and (self.near is not None or self.salts > 1):
            self.edges.unpersist()
        self.near, self.edges, self._edge_paths = None, None, []

    # the run

    def run(self, frontier: DataFrame | None) -> RankRun:
        try:
            with settings(self.spark, spark__sql__shuffle__partitions=str(min(self.most, self.cores))):
                return self._run(frontier)
        finally:
            self._forget()
            for view in (self.edge_view, self.state_view):
                self.spark.catalog.dropTempView(view)

    def _run(self, frontier: DataFrame | None) -> RankRun:
        cfg, g, plan = self.cfg, self.g, self.plan
        seeds = None
        if frontier is not None:
            seeds = Keys.of(frontier, g.buckets, self.steps)
            if not seeds.n:
                return self._unchanged()
        pulls = seeds is not None and self.prev is not None and cfg.dangling != "redistribute"
        if pulls:
            state, n_in = self._rows_of(seeds)
            pulls = planner.direction(cfg, n_in, g.n_edges) == "pull"
        if pulls:
            self.fetch(seeds)
            self.n_state = seeds.n
            state = self._dealt(state)
        else:
            state = self.push(self._first(None if seeds is None else seeds.ids))
        if cfg.dangling == "redistribute":
            self.sinks = state.where("deg = 0").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
        trace: list[dict] = []
        rounds, seconds, hot, got = 1, 0.0, 0, {}
        while len(trace) < cfg.max_supersteps:
            began = time.perf_counter()
            whole = self.at_once(state, cfg.max_supersteps - len(trace))
            if whole is not None:
                state, seen = whole
                seconds = (time.perf_counter() - began) / len(seen)
                last = self._ends(seen)
                self._traced(trace, seen, seconds)
                got = seen[-1]
                hot, self.sinks = got["hot"], got["sinks"]
                self.steps.drop([self.steps.last, *self._read])
                if last is None or len(trace) >= cfg.max_supersteps or self._over(got):
                    break
                state = self.grow(state, got)
                continue
            most = 1 if cfg.dangling == "redistribute" else cfg.max_supersteps - len(trace)
            rounds = min(most, planner.chained(rounds, seconds, [t["linf"] for t in trace[-2:]], cfg.tau))
            start = state
            state, seen = self.job(start, rounds)
            last = self._ends(seen)
            if last is not None and last + 1 < len(seen) and seen[last]["was"] and (seen[last]["stays"] or seen[last]["hot"]):
                # what follows a stop would go on changing ranks
                rounds = last + 1
                state, seen = self.job(start, rounds)
                last = self._ends(seen)
            self.steps.drop([self.steps.last, *self._read])
            seen = seen if last is None else seen[: last + 1]
            seconds = (time.perf_counter() - began) / len(seen)
            self._traced(trace, seen, seconds)
            got = seen[-1]
            hot, self.sinks = got["hot"], got["sinks"]
            if last is None or len(trace) >= cfg.max_supersteps:
                continue
            if self._over(got):
                break
            rounds, state = 1, self.grow(state, got)
        marked = self.marked_last(state, got) if hot and plan.expand and not (self.in_parts and self.near is None) else None
        return self._result(state, trace, marked)

    def _traced(self, trace: list[dict], seen: list[dict], seconds: float) -> None:
        for got in seen:
            if got["was"]:
                scanned, self.fetched = self.fetched + (self.n_near if self.near is not None else self.g.n_edges) + self.n_state, 0
                trace.append({"superstep": len(trace) + 1, "n_affected": got["was"], "n_expanded": got["hot"], "n_settled": got["settled"], "in_edges": got["in_edges"], "rows_scanned": scanned, "linf": got["norm"] * self.factor, "wall_ms": 1000 * seconds})

    def at_once(self, state: DataFrame, most: int) -> tuple[DataFrame, list[dict]] | None:
        """All rounds up to the stop, or the next fetch, in one job; None where parts of the graph don't fit the tasks there are."""
        g, pulls = self.g, self.near is not None
        self.in_parts = False
        parts = arrays.parts_for(self.spark, (self.n_near if pulls else g.n_edges) + self.n_state)
        if not parts or self.salts > 1 or not g.even(parts, arrays.MOST_ROWS):
            return None
        edges = self.near.where("NOT own").select("src", "dst", "share_before") if pulls else g.edges
        done = arrays.rounds(edges, state, parts, self.plan, self.cfg, most, g.n_vertices, self.factor, pulls, g.buckets)
        if done is None:
            return None
        self.in_parts = True
        self.steps.paths.append(done[1])
        return done[0], done[2]

    def _over(self, got: dict) -> bool:
        return not got["was"] or got["norm"] * self.factor <= self.cfg.tau or not (got["stays"] or got["hot"])

    def _ends(self, seen: list[dict]) -> int | None:
        """The first round of a chain that stops the run, or has marked vertices whose in-edges are not there yet."""
        return next((k for k, got in enumerate(seen) if self._over(got) or self.near is not None and got["fresh_hot"]), None)

    def job(self, state: DataFrame, rounds: int) -> tuple[DataFrame, list[dict]]:
        """Some rounds from a state: the state after them, and what was observed of each."""
        cfg, plan, pulls = self.cfg, self.plan, self.near is not None
        extra = self.sinks / self.g.n_vertices if cfg.dangling == "redistribute" else 0.0
        measures = [F.expr(m) for m in measures_sql(rounds, plan, cfg, self.g.buckets, pulls)]
        with self.planned():
            state.createOrReplaceTempView(self.state_view)
            seen = Observation(f"rounds-{uuid.uuid4().hex}")
            step = self.spark.sql(job_sql(rounds, self.edge_view, self.state_view, self.g.n_vertices, plan, cfg, base_extra=extra, salts=self.salts, partial=pulls))
            state, _ = self.steps.put(step.observe(seen, *measures).select(*STATE))
        got = seen.get
        names = ("norm", "was", "in_edges", "hot", "settled", "fresh_hot")
        each = [{c: got.get(f"{c}{k}", 0) for c in names} for k in range(rounds)]
        for one in each:
            one |= {"stays": one["was"] - one["settled"], "touched": got.get("touched", ()), "sinks": got.get("sinks", 0.0)}
        return state, each

    @property
    def _read(self) -> list[str]:
        """Checkpoints that edges are read from again if their kept partitions are lost."""
        return self._edge_paths if self.near is not None else []

    def _fresh(self, state: DataFrame, got: dict) -> Keys:
        """Vertices that hot ones mark for the first time."""
        keys = Keys(state.where("hot AND NOT grown").select("id"), got["fresh_hot"], self.g.buckets, tuple(sorted(got["touched"])))
        self.fetched += self.g.base.out.scanned(keys.touched)
        out = self.g.out_edges(keys).selectExpr("dst AS id").distinct()
        return Keys.of(out.join(state.select("id"), "id", "left_anti"), self.g.buckets, self.steps)

    def grow(self, state: DataFrame, got: dict) -> DataFrame:
        """Take in what is marked for the first time; go over to all edges where that is cheaper."""
        fresh = self._fresh(state, got)
        state = state.selectExpr(*(c if c != "grown" else "grown OR hot AS grown" for c in STATE))
        if not fresh.n:
            return state
        rows, n_in = self._rows_of(fresh)
        state = state.unionByName(rows)
        self.fetches += 1
        if planner.direction(self.cfg, self.n_near + n_in, self.g.n_edges, self.fetches if self.in_parts else 0) == "push":
            return self.push(self.widened(state))
        self.fetch(fresh)
        self.n_state += fresh.n
        return self._dealt(state)

    def marked_last(self, state: DataFrame, got: dict) -> DataFrame:
        """Vertices that the last round's changes mark: they count as affected, though no round works on them any more."""
        if self.near is not None:
            return self._fresh(state, got).ids
        with self.planned():
            state.createOrReplaceTempView(self.state_view)
            return self.steps.put(self.spark.sql(incoming_sql(self.edge_view, self.state_view, [], self.salts, self.cfg.hub_degree)).where("marked").select("id"))[0]

    def _unchanged(self) -> RankRun:
        state = starting_state(self.g, None if self.prev is None else self.prev.df, None)
        run = RankRun(self.plan.name, state.selectExpr("id", "rank", "false AS ever_affected"), [])
        if self.prev is not None:
            run._table = self.prev
        return run

    def _result(self, state: DataFrame, trace: list[dict], marked: DataFrame | None) -> RankRun:
        if self.near is None:
            ranks, changed = state.selectExpr("id", "rank", "ever AS ever_affected"), None
        else:
            changed = state.select("id", "rank")
            first = starting_state(self.g, self.prev.df, None).select("id", "rank")
            ranks = first.join(state.selectExpr("id", "rank AS own", "ever"), "id", "left").selectExpr("id", "coalesce(own, rank) AS rank", "coalesce(ever, false) AS ever_affected")
        if marked is not None:
            ranks = ranks.join(marked.selectExpr("id", "true AS marked_last"), "id", "left").selectExpr("id", "rank", "ever_affected OR coalesce(marked_last, false) AS ever_affected")
        return RankRun(self.plan.name, ranks, trace, changed=changed, paths=list(self.steps.paths))
