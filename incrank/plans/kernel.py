"""One synchronous superstep over distributed tables, and the same rounds over a bounded graph inside one task."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import MethodPlan, RankConfig


def salted(edges: DataFrame, degrees: DataFrame, salts: int, hub_degree: int) -> DataFrame:
    """Edges with a salt: those of hubs are dealt over ``salts`` values by target, all others have 0."""
    hubs = degrees.where(F.col("out_deg") > hub_degree).select(F.col("id").alias("src"), F.lit(True).alias("hub"))
    return edges.join(F.broadcast(hubs), "src", "left").select("src", "dst", "own", F.when(F.col("hub") & ~F.col("own"), F.pmod(F.xxhash64("dst"), F.lit(salts))).otherwise(F.lit(0)).cast("int").alias("salt"))


def push_shares(edges: DataFrame, state: DataFrame) -> DataFrame:
    """dst, sum of shares: every source sends its share along its edges; sums form before the shuffle."""
    shares = state.where("deg > 0").select(F.col("id").alias("src"), (F.col("rank") / F.col("deg")).alias("share"))
    return edges.join(shares, "src").groupBy(F.col("dst").alias("id")).agg(F.sum("share").alias("share_sum"), F.count(F.lit(1)).alias("in_edges"))


def pull_shares(edges: DataFrame, state: DataFrame, frontier: DataFrame) -> DataFrame:
    """As :func:`push_shares`, for the vertices of ``frontier`` only: their in-edges are picked first."""
    return push_shares(edges.join(frontier.select(F.col("id").alias("dst")), "dst", "left_semi"), state)


#: State between rounds: was affected and has not settled (stays), passed the spread tolerance (hot), ever affected, out-neighbours fetched (grown).
STATE = ("id", "rank", "deg", "stays", "hot", "ever", "grown")


#: How a round calls the state it starts from.
OLD = {"rank": "old", "deg": "deg", "stays": "stayed", "ever": "had", "grown": "grown"}


def own_rows(vertices: DataFrame) -> DataFrame:
    """What brings a vertex its own state: a row to itself that is no edge, so that a round needs no second join."""
    return vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(True).alias("own"))


def incoming_sql(edges: str, state: str, carried: list[str], salts: int = 1, hub_degree: int = 0, partial: bool = False) -> str:
    """What reaches each vertex along its in-edges, shares and marks alike, and its own state, in one pass: one join and one shuffle, of sums.

    A vertex is marked if a source of an in-edge changed past the spread tolerance in the round before (``hot``). With ``partial``, the state
    has the vertices ever affected only, and edges bring along the shares of all others, which stay as they were.
    Edges lie by source (and salt) and state by id, so neither is shuffled; with salts, a hub's state goes to each of its parts.
    """
    share = "CASE WHEN s.deg > 0 THEN s.rank / s.deg ELSE 0.0D END"
    hot = "s.hot"
    if partial:
        share, hot = f"CASE WHEN s.id IS NULL THEN e.share_before ELSE {share} END", "coalesce(s.hot, false)"
    on = "e.src = s.id"
    if salts > 1:
        state = f"(SELECT *, explode(CASE WHEN deg > {hub_degree} THEN sequence(0, {salts - 1}) ELSE array(0) END) AS part FROM {state})"
        on += " AND e.salt = s.part"
    own = ", ".join(f"max(CASE WHEN e.own THEN s.{c} END) AS {name}" for c, name in [*OLD.items(), *zip(carried, carried, strict=True)])
    return f"""SELECT e.dst AS id, sum(CASE WHEN e.own THEN 0.0D ELSE {share} END) AS share_sum, count_if(NOT e.own) AS in_edges, max(NOT e.own AND {hot}) AS marked, {own}
        FROM {edges} e {"LEFT" if partial else ""} JOIN {state} s ON {on} GROUP BY e.dst"""


def superstep_sql(k: int, edges: str, state: str, carried: list[str], n: int, plan: MethodPlan, cfg: RankConfig, base_extra: float = 0.0, salts: int = 1, partial: bool = False) -> str:
    """State after round ``k`` of a job: whoever stayed or is marked gets a new rank; then it settles, or is hot, for the next round to spread.

    A fresh mark wins over settling. Besides the state's columns and those carried from earlier rounds: the change ``dr<k>`` of an affected
    vertex, and whether it was ``hot<k>`` or ``settled<k>``, from which the job's rounds are measured.
    """
    share = "share_sum" if not base_extra else f"(share_sum + {base_extra!r}D)"
    new = plain = f"({(1 - cfg.alpha) / n!r}D + {cfg.alpha!r}D * {share})"
    if plan.formula == "loopfree":
        new = f"CASE WHEN deg > 0 THEN ({cfg.alpha!r}D * ({share} - old / deg) + {(1 - cfg.alpha) / n!r}D) / (1.0D - {cfg.alpha!r}D / deg) ELSE {plain} END"
    size = "abs(rank - old)"
    measure = {"rel": f"{size} / greatest(old, rank)", "abs": size, "share": f"{size} / greatest(deg, 1)"}[cfg.expand_by]
    hot = f"was AND {measure} > {cfg.tau_f!r}D" if plan.expand else "false"
    settled = f"was AND {size} / greatest(old, rank) <= {cfg.tau_p!r}D" if plan.prune else "false"
    stays = f"was AND NOT settled{k}" if plan.prune else "was"
    more = "".join(f", {c}" for c in carried)
    return f"""SELECT id, stayed{" OR marked" if plan.expand else ""} AS was, CASE WHEN was THEN {new} ELSE old END AS rank, deg, {hot} AS hot, {settled} AS settled{k}, {stays} AS stays, had OR was AS ever, grown, in_edges{more},
        CASE WHEN was THEN {size} END AS dr{k}, hot AS hot{k} FROM ({incoming_sql(edges, state, carried, salts, cfg.hub_degree, partial)})"""


def job_sql(rounds: int, edges: str, state: str, n: int, plan: MethodPlan, cfg: RankConfig, **more) -> str:
    """Some rounds in a row."""
    text, carried = state, []
    for k in range(rounds):
        text = f"({superstep_sql(k, edges, text, carried, n, plan, cfg, **more)})"
        carried += [f"dr{k}", *([f"hot{k}"] if plan.expand else []), *([f"settled{k}"] if plan.prune else [])]
    return f"SELECT * FROM {text}"


def measures_sql(rounds: int, plan: MethodPlan, cfg: RankConfig, buckets: int, pulls: bool) -> list[str]:
    """What is observed of a job's rounds. ``fresh`` vertices are hot, and their out-neighbours have not been fetched yet."""
    out = []
    for k in range(rounds):
        norm = {"linf": f"max(dr{k})", "l1": f"sum(dr{k})", "l2": f"sqrt(sum(dr{k} * dr{k}))"}[cfg.norm]
        out += [f"coalesce({norm}, 0.0D) AS norm{k}", f"count(dr{k}) AS was{k}", f"coalesce(sum(CASE WHEN dr{k} IS NOT NULL THEN in_edges END), 0L) AS in_edges{k}"]
        out += [f"count_if(hot{k}) AS hot{k}"] if plan.expand else []
        out += [f"count_if(settled{k}) AS settled{k}"] if plan.prune else []
        out += [f"count_if(hot{k} AND NOT grown) AS fresh_hot{k}"] if plan.expand and pulls else []
    if plan.expand and pulls:
        fresh = " OR ".join(f"hot{k}" for k in range(rounds))
        out.append(f"collect_set(CASE WHEN ({fresh}) AND NOT grown THEN CAST(pmod(xxhash64(id), {buckets}) AS INT) END) AS touched")
    if cfg.dangling == "redistribute":
        out.append("coalesce(sum(CASE WHEN deg = 0 THEN rank END), 0.0D) AS sinks")
    return out


def norm_of(kind: str, dr: np.ndarray) -> float:
    if not len(dr):
        return 0.0
    return float({"linf": dr.max, "l1": dr.sum, "l2": lambda: np.sqrt((dr * dr).sum())}[kind]())


def local_rounds(src: np.ndarray, dst: np.ndarray, ids: np.ndarray, rank: np.ndarray, deg: np.ndarray, affected: np.ndarray, n: int, plan: MethodPlan, cfg: RankConfig) -> tuple[np.ndarray, np.ndarray, list[tuple]]:
    """All rounds of a bounded graph with arrays: ranks, ever affected, trace. The rounds are those of :func:`superstep_sql`; every round reads all edges."""
    order = np.argsort(ids)
    ids, rank, deg, affected = ids[order], rank[order].copy(), deg[order].astype(float), affected[order].copy()
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    by_dst = np.argsort(d, kind="stable")
    s, d = s[by_dst], d[by_dst]
    in_deg = np.bincount(d, minlength=len(ids))
    by_src = np.argsort(s, kind="stable")
    out_at, out_to = np.searchsorted(s[by_src], np.arange(len(ids) + 1)), d[by_src]
    ever, trace = affected.copy(), []
    base = (1 - cfg.alpha) / n
    factor = n / cfg.scale_vertices if cfg.tolerance_scale == "mean_rank" else 1.0
    whole = bool(affected.all())
    for _ in range(cfg.max_supersteps):
        if not affected.any():
            break
        share = np.divide(rank, deg, out=np.zeros_like(rank), where=deg > 0)
        if whole:
            total = np.bincount(d, weights=share[s], minlength=len(ids))
        else:
            pick = affected[d]
            total = np.bincount(d[pick], weights=share[s[pick]], minlength=len(ids))
        if cfg.dangling == "redistribute":
            total = total + rank[deg == 0].sum() / n
        new = base + cfg.alpha * total
        if plan.formula == "loopfree":
            loop = (cfg.alpha * (total - share) + base) / (1 - cfg.alpha / np.where(deg > 0, deg, np.inf))
            new = np.where(deg > 0, loop, new)
        new = np.where(affected, new, rank)
        dr = np.abs(new - rank)
        rel = dr / np.maximum(rank, new)
        was = affected
        measure = {"rel": rel, "abs": dr, "share": dr / np.where(deg > 0, deg, 1)}[cfg.expand_by]
        hot = was & (measure > cfg.tau_f) if plan.expand else np.zeros(len(ids), bool)
        settled = was & (rel <= cfg.tau_p) if plan.prune else np.zeros(len(ids), bool)
        affected = was & ~settled
        if hot.any():
            marks = np.concatenate([out_to[out_at[v] : out_at[v + 1]] for v in np.flatnonzero(hot)])
            affected[marks] = True
            ever[marks] = True
        rank = new
        size = norm_of(cfg.norm, dr[was]) * factor
        trace.append((int(was.sum()), int(hot.sum()), int(settled.sum()), int(in_deg[was].sum()), size))
        if size <= cfg.tau:
            break
    return order, rank, ever, trace


LOCAL = "kind int, id bigint, rank double, ever boolean, n_affected bigint, n_expanded bigint, n_settled bigint, in_edges bigint"


def local_solve(edges: DataFrame, state: DataFrame, n: int, plan: MethodPlan, cfg: RankConfig) -> DataFrame:
    """Run all rounds in one task. The caller has checked that the graph is within ``cfg.local_edges``.

    Rows of kind 0 are vertices; kind 1, with id the superstep and rank the norm, are the trace.
    """

    def kernel(key, left: pa.Table, right: pa.Table) -> pa.Table:
        col = lambda t, c: t.column(c).to_numpy()
        ids = col(right, "id")
        order, rank, ever, trace = local_rounds(col(left, "src"), col(left, "dst"), ids, col(right, "rank"), col(right, "deg"), col(right, "affected").astype(bool), n, plan, cfg)
        rows, steps = len(ids), len(trace)
        zeros = np.zeros(rows, np.int64)
        extra = np.array([t[:4] for t in trace], np.int64).reshape(steps, 4)
        return pa.table({
            "kind": pa.array(np.concatenate([np.zeros(rows), np.ones(steps)]).astype(np.int32)),
            "id": pa.array(np.concatenate([ids[order], np.arange(1, steps + 1)])),
            "rank": pa.array(np.concatenate([rank, np.array([t[4] for t in trace], float)])),
            "ever": pa.array(np.concatenate([ever, np.zeros(steps, bool)])),
            **{c: pa.array(np.concatenate([zeros, extra[:, k]])) for k, c in enumerate(("n_affected", "n_expanded", "n_settled", "in_edges"))},
        })

    one = F.lit(0).alias("whole")
    left = edges.select("src", "dst", one).groupBy("whole")
    right = state.select("id", "rank", "deg", "affected", one).groupBy("whole")
    return left.cogroup(right).applyInArrow(kernel, LOCAL)


SWEPT = "setting int, supersteps int, in_edges bigint, affected bigint, l1 double"


def local_sweep(edges: DataFrame, state: DataFrame, n: int, settings: list[tuple[MethodPlan, RankConfig]]) -> DataFrame:
    """Many settings on one bounded graph, one after the other in one task: rounds, work, reach and error of each.

    ``state`` has id, rank, deg, affected and ref, the ranks that errors are measured against. For studies that count work and
    error, not time; the caller has checked that the graph is within ``local_edges``.
    """

    def kernel(key, left: pa.Table, right: pa.Table) -> pa.Table:
        col = lambda t, c: t.column(c).to_numpy()
        rows = []
        for k, (plan, cfg) in enumerate(settings):
            affected = col(right, "affected").astype(bool) if plan.seed != "all" else np.ones(right.num_rows, bool)
            start = col(right, "rank") if plan.warm else np.full(right.num_rows, 1.0 / n)
            order, rank, ever, trace = local_rounds(col(left, "src"), col(left, "dst"), col(right, "id"), start, col(right, "deg"), affected, n, plan, cfg)
            rows.append((k, len(trace), sum(t[3] for t in trace), int(ever.sum()), float(np.abs(rank - col(right, "ref")[order]).sum())))
        types = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.float64())
        return pa.table({c: pa.array(v, t) for c, v, t in zip(("setting", "supersteps", "in_edges", "affected", "l1"), zip(*rows, strict=True), types, strict=True)})

    one = F.lit(0).alias("whole")
    return edges.select("src", "dst", one).groupBy("whole").cogroup(state.select("id", "rank", "deg", "affected", "ref", one).groupBy("whole")).applyInArrow(kernel, SWEPT)
