"""Many rounds in one job: each task keeps a part of the vertices and their in-edges as arrays, and tasks tell each other shares after every round.

A part is what a hash of the id deals to a task; it holds the vertices' states and all their in-edges, so a round adds up shares where they are needed, in the
same order every time. What a part needs of another is the same in every round: it is asked for once, then sent as plain numbers, and left out
where nothing has changed. Tasks start together (a barrier stage) and send by files in the shared folder. Where that is no plain folder, where there are fewer slots
or more rows than parts may have, rounds stay jobs of SQL.
"""

from __future__ import annotations

import os
import time
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import drop_path, shared_dir
from .kernel import SWEPT
from .layers import bucket_of, settings, written
from .model import MethodPlan, RankConfig

#: Rows, of edges and vertices, that a part may have, and those that are worth a part of their own.
MOST_ROWS, PART_ROWS = 8_000_000, 100_000
#: A task that has heard nothing from another for so many seconds gives up.
SILENT_SECONDS = 1800
#: What a round is measured by, over all vertices: largest change, changes, squares of changes, and numbers; rank of dead ends.
MEASURED = ("largest", "sum", "squares", "was", "in_edges", "hot", "settled", "fresh_hot", "sinks")
STAYS, HOT, EVER, GROWN = 1, 2, 4, 8
OUT = "kind int, id bigint, rank double, deg bigint, stays boolean, hot boolean, ever boolean, grown boolean, " + ", ".join(f"m_{c} double" for c in MEASURED)


def slots(spark: SparkSession) -> int:
    """Tasks that can run at once; none where executors come and go, as a barrier stage can't wait for them."""
    if spark.sparkContext.getConf().get("spark.dynamicAllocation.enabled", "false") == "true":
        return 0
    sc = spark.sparkContext._jsc.sc()
    return sc.maxNumConcurrentTasks(sc.resourceProfileManager().defaultResourceProfile())


def plain_folder(spark: SparkSession) -> str | None:
    """The shared folder as workers open it, if they can."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    whole = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(path).toUri()
    return whole.getPath() if whole.getScheme() == "file" else None


def parts_for(spark: SparkSession, rows: int) -> int:
    """Parts for so many rows; 0 where they don't fit."""
    free = slots(spark)
    parts = min(free, max(1, -(-rows // PART_ROWS)))
    return parts if rows <= parts * MOST_ROWS and plain_folder(spark) is not None else 0


def dealt(edges: DataFrame, state: DataFrame, parts: int, *more: str) -> DataFrame | None:
    """Edges and states in one table, dealt by target and by id. ``b`` tells them apart: where an edge's source lies, or, below 0, degree and flags.

    None where the session deals into other numbers than it is asked for.
    """
    zero = [F.lit(0.0).alias(c) for c in more]
    before = F.col("share_before") if "share_before" in edges.columns else F.lit(0.0)
    flags = " + ".join(f"CASE WHEN {c} THEN {v} ELSE 0 END" for c, v in (("stays", STAYS), ("hot", HOT), ("ever", EVER), ("grown", GROWN)))
    left = edges.select(F.col("dst").alias("id"), "src", before.alias("a"), F.pmod(F.hash("src"), F.lit(parts)).cast("bigint").alias("b"), *zero)
    right = state.select("id", F.col("id").alias("src"), F.col("rank").alias("a"), F.expr(f"-1L - (deg * 16 + {flags})").alias("b"), *more)
    both = left.unionByName(right).repartition(parts, "id")
    return both if both._jdf.queryExecution().executedPlan().outputPartitioning().numPartitions() == parts else None


class Post:
    """Messages between tasks. All have read a step's files before any writes those of the next but one, so two steps' files lie there at most."""

    def __init__(self, folder: str, me: int, parts: int) -> None:
        self.folder, self.me, self.parts, self.step = folder, me, parts, 0

    def _path(self, step: int, who: int) -> str:
        return f"{self.folder}/{step}-{who}"

    def swap(self, numbers: list[float], bodies: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray]]:
        """Numbers to all and a body to each; the same from all."""
        head = np.array(numbers, np.float64)
        if self.parts == 1:
            return head[None, :], [bodies[0]]
        mine = [b.view(np.uint8) if q != self.me else np.zeros(0, np.uint8) for q, b in enumerate(bodies)]
        at = np.zeros(self.parts + 1, np.int64)
        at[1:] = np.cumsum([len(b) for b in mine])
        path = self._path(self.step, self.me)
        with open(path + "~", "wb") as f:
            f.write(head.tobytes())
            f.write(at.tobytes())
            for b in mine:
                f.write(b.data)
        os.rename(path + "~", path)
        if self.step > 1:
            os.unlink(self._path(self.step - 2, self.me))
        got = [self._read(q, len(head)) if q != self.me else (head, bodies[q]) for q in range(self.parts)]
        self.step += 1
        return np.stack([h for h, _ in got]), [b for _, b in got]

    def _read(self, who: int, n: int) -> tuple[np.ndarray, np.ndarray]:
        path, began, pause, looks = self._path(self.step, who), time.monotonic(), 0.0002, 0
        while True:
            try:
                f = open(path, "rb")
                break
            except FileNotFoundError:
                time.sleep(pause)
                pause, looks = min(2 * pause, 0.005), looks + 1
                if not looks % 100 and (os.path.exists(f"{self.folder}/failed") or not os.path.exists(self.folder) or time.monotonic() - began > SILENT_SECONDS):
                    raise RuntimeError(f"part {who} has not sent step {self.step}") from None
        with f:
            head = np.frombuffer(f.read(8 * n), np.float64)
            at = np.frombuffer(f.read(8 * (self.parts + 1)), np.int64)
            start, end = int(at[self.me]), int(at[self.me + 1])
            f.seek(8 * n + 8 * (self.parts + 1) + start)
            return head, np.frombuffer(f.read(end - start), np.uint8)


class Part:
    """A task's vertices, their in-edges sorted by target and source, and what it sends to whom."""

    def __init__(self, batches: Iterator[pa.RecordBatch], post: Post, partial: bool, *more: str) -> None:
        self.post, self.partial = post, partial
        rows, edges = [], []
        for batch in batches:
            col = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in batch.schema.names}
            own = col["b"] < 0
            rows.append([col[c][own] for c in ("id", "a", "b", *more)])
            edges.append([col["src"][~own], col["id"][~own], col["b"][~own].astype(np.int32), *([col["a"][~own]] if partial else [])])
        empty = lambda kinds: [np.zeros(0, k) for k in kinds]
        state = [np.concatenate(c) for c in zip(empty([np.int64, float, np.int64, *[float] * len(more)]), *rows, strict=True)]
        src, dst, home, *before = [np.concatenate(c) for c in zip(empty([np.int64, np.int64, np.int32, *[float] * partial]), *edges, strict=True)]
        del rows, edges
        order = np.argsort(state[0], kind="stable")
        self.ids, self.rank, code, *self.more = [c[order] for c in state]
        code = -(code + 1)
        self.deg, flags = code >> 4, code & 15
        self.stays, self.hot, self.ever, self.grown = ((flags & f) > 0 for f in (STAYS, HOT, EVER, GROWN))
        need, first, slot = np.unique(src, return_index=True, return_inverse=True)
        by = np.argsort(home[first], kind="stable")
        self.cut = np.searchsorted(home[first][by], np.arange(post.parts + 1))
        place = np.empty(len(by), np.int64)
        place[by] = np.arange(len(by))
        need, self.before = need[by], before[0][first][by] if partial else None
        self.m = len(need)
        key = np.searchsorted(self.ids, dst) * max(1, self.m) + place[slot]
        del src, dst, home, before, slot
        key.sort()
        self.slot = key % max(1, self.m)
        self.in_deg = np.bincount(key // max(1, self.m), minlength=len(self.ids))
        del key
        self.has = np.flatnonzero(self.in_deg)
        self.starts = np.cumsum(self.in_deg[self.has]) - self.in_deg[self.has]
        _, asked = post.swap([], [np.ascontiguousarray(need[a:b]) for a, b in zip(self.cut[:-1], self.cut[1:], strict=True)])
        self.send, self.absent = [], []
        known = self.ids if len(self.ids) else np.array([-1])
        for wanted in asked:
            wanted = wanted.view(np.int64)
            at = np.minimum(np.searchsorted(known, wanted), len(known) - 1)
            self.send.append(at)
            self.absent.append((known[at] != wanted) | (len(self.ids) == 0))

    def _bodies(self, share: np.ndarray, hot: np.ndarray, last: list) -> list[np.ndarray]:
        """For each part the shares that it needs, unless they are those sent last, and which of them are hot, if any are."""
        if not len(share):
            share, hot = np.zeros(1), np.zeros(1, bool)
        out, any_hot = [], hot.any()
        for q, (at, absent) in enumerate(zip(self.send, self.absent, strict=True)):
            v, pieces = share[at], []
            v[absent] = np.nan
            if last[q] is None or not np.array_equal(v, last[q], equal_nan=True):
                pieces.append(v.view(np.uint8))
                last[q] = v
            if any_hot and (h := hot[at] & ~absent).any():
                pieces.append(h.view(np.uint8))
            out.append(pieces[0] if len(pieces) == 1 else np.concatenate(pieces) if pieces else np.zeros(0, np.uint8))
        return out

    def _take(self, bodies: list[np.ndarray], share: np.ndarray, hot: np.ndarray) -> None:
        hot[:] = False
        for q, body in enumerate(bodies):
            a, b = self.cut[q], self.cut[q + 1]
            n = int(b - a)
            if len(body) >= 8 * n > 0:
                v = body[: 8 * n].view(np.float64)
                share[a:b] = np.where(np.isnan(v), self.before[a:b], v) if self.partial else v
                body = body[8 * n :]
            if len(body):
                hot[a:b] = body.view(bool)

    def run(self, plan: MethodPlan, cfg: RankConfig, most: int, n: int, factor: float, pulls: bool) -> list[dict]:
        """Rounds up to the one that ends the run, or marks vertices that are not there; the rounds are those of :func:`kernel.superstep_sql`."""
        rank, stays, hot, ever = self.rank, self.stays, self.hot, self.ever
        deg, dead = self.deg.astype(float), self.deg == 0
        share_in, hot_in, last = np.zeros(self.m), np.zeros(self.m, bool), [None] * self.post.parts
        numbers, trace, rounds, base = [0.0] * len(MEASURED), [], 0, (1 - cfg.alpha) / n
        numbers[-1] = float(rank[dead].sum())
        while True:
            share = np.divide(rank, deg, out=np.zeros_like(rank), where=~dead)
            each, bodies = self.post.swap(numbers, self._bodies(share, hot, last))
            got = dict(zip(MEASURED, [each[:, 0].max(), *each[:, 1:].sum(axis=0)], strict=True))
            if rounds:
                trace.append(got)
                norm = {"linf": got["largest"], "l1": got["sum"], "l2": got["squares"] ** 0.5}[cfg.norm] * factor
                over = not got["was"] or norm <= cfg.tau or not (got["was"] > got["settled"] or got["hot"])
                if over or pulls and got["fresh_hot"] or len(trace) >= most:
                    self._take(bodies, share_in, hot_in)
                    # what the last round marks counts as affected
                    ever = ever | self._marked(hot_in)
                    break
            self._take(bodies, share_in, hot_in)
            total = np.zeros(len(self.ids))
            if len(self.slot):
                total[self.has] = np.add.reduceat(share_in[self.slot], self.starts)
            if cfg.dangling == "redistribute":
                total += got["sinks"] / n
            new = base + cfg.alpha * total
            if plan.formula == "loopfree":
                loop = (cfg.alpha * (total - share) + base) / (1 - cfg.alpha / np.where(dead, np.inf, deg))
                new = np.where(dead, new, loop)
            was = stays | self._marked(hot_in)
            new = np.where(was, new, rank)
            dr = np.abs(new - rank)
            rel = np.divide(dr, np.maximum(rank, new), out=np.zeros_like(dr), where=dr > 0)
            size = {"rel": rel, "abs": dr, "share": dr / np.maximum(deg, 1)}[cfg.expand_by]
            hot = was & (size > cfg.tau_f) if plan.expand else np.zeros(len(rank), bool)
            settled = was & (rel <= cfg.tau_p) if plan.prune else np.zeros(len(rank), bool)
            stays, ever, rank = was & ~settled, ever | was, new
            fresh = int((hot & ~self.grown).sum()) if pulls else 0
            numbers = [float(dr.max(initial=0.0)), float(dr.sum()), float((dr * dr).sum()), was.sum(), self.in_deg[was].sum(), hot.sum(), settled.sum(), fresh, float(rank[dead].sum())]
            rounds += 1
        self.rank, self.stays, self.hot, self.ever = rank, stays, hot, ever
        return trace

    def _marked(self, hot: np.ndarray) -> np.ndarray:
        """Vertices with a hot source."""
        marked = np.zeros(len(self.ids), bool)
        if hot.any():
            marked[self.has[np.searchsorted(self.starts, np.flatnonzero(hot[self.slot]), "right") - 1]] = True
        return marked


def _started(folder: str, batches: Iterator[pa.RecordBatch], partial: bool, *more: str) -> Part:
    from pyspark import BarrierTaskContext

    context = BarrierTaskContext.get()
    me, parts = context.partitionId(), len(context.getTaskInfos())
    # A stage that is tried again would find the files of the first try: the driver starts it anew, in another folder.
    with open(f"{folder}/at-{me}", "x"):
        return Part(batches, Post(folder, me, parts), partial, *more)


def _guarded(folder: str, rows):
    """Rows of a task; if it fails, the others are told."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from rows(batches)
        except GeneratorExit:
            raise
        except BaseException:
            with open(f"{folder}/failed", "w"):
                raise

    return kernel


def _tried(spark: SparkSession, job):
    """A job in a folder of its own, three times at most: what is lost with an executor is done again."""
    for left in (2, 1, 0):
        folder = f"{plain_folder(spark)}/rounds-{uuid.uuid4().hex}"
        os.makedirs(folder)
        try:
            with settings(spark, spark__sql__adaptive__enabled="false"):
                return job(folder)
        except Exception:
            if not left:
                raise
        finally:
            drop_path(spark, f"file://{folder}")


def rounds(edges: DataFrame, state: DataFrame, parts: int, plan: MethodPlan, cfg: RankConfig, most: int, n: int, factor: float, pulls: bool, buckets: int) -> tuple[DataFrame, str, list[dict]] | None:
    """State after the rounds, the path it is written to, and what was observed of each round; None where the session can't run them so."""
    spark = state.sparkSession
    with settings(spark, spark__sql__adaptive__enabled="false"):
        table = dealt(edges, state, parts)
    if table is None:
        return None

    def job(folder: str):
        def rows(batches):
            part = _started(folder, batches, pulls)
            trace = part.run(plan, cfg, most, n, factor, pulls)
            schema = pa.schema([("kind", pa.int32()), ("id", pa.int64()), ("rank", pa.float64()), ("deg", pa.int64()), *((c, pa.bool_()) for c in ("stays", "hot", "ever", "grown")), *((f"m_{c}", pa.float64()) for c in MEASURED)])
            for a in range(0, len(part.ids), 100_000):
                cols = [x[a : a + 100_000] for x in (part.ids, part.rank, part.deg, part.stays, part.hot, part.ever, part.grown)]
                k = len(cols[0])
                yield pa.RecordBatch.from_arrays([pa.array(np.zeros(k, np.int32)), *map(pa.array, cols), *[pa.nulls(k, pa.float64())] * len(MEASURED)], schema=schema)
            if part.post.me == 0:
                k = len(trace)
                yield pa.RecordBatch.from_arrays([pa.array(np.ones(k, np.int32)), pa.array(np.arange(k)), pa.nulls(k, pa.float64()), pa.nulls(k, pa.int64()), *[pa.nulls(k, pa.bool_())] * 4, *(pa.array([float(t[c]) for t in trace], pa.float64()) for c in MEASURED)], schema=schema)

        fresh = F.when(F.expr("kind = 0 AND hot AND NOT grown"), bucket_of("id", buckets)) if pulls else F.lit(None).cast("int")
        return written(table.mapInArrow(_guarded(folder, rows), OUT, barrier=True), "state", touched=F.collect_set(fresh))

    out, path, got = _tried(spark, job)
    seen = []
    for r in sorted((r.asDict() for r in out.where("kind = 1").select("id", *(f"m_{c}" for c in MEASURED)).collect()), key=lambda r: r["id"]):
        norm = {"linf": r["m_largest"], "l1": r["m_sum"], "l2": r["m_squares"] ** 0.5}[cfg.norm]
        seen.append({"norm": norm, "sinks": r["m_sinks"], "touched": got["touched"], **{c: int(r[f"m_{c}"]) for c in ("was", "in_edges", "hot", "settled", "fresh_hot")}})
        seen[-1]["stays"] = seen[-1]["was"] - seen[-1]["settled"]
    return out.where("kind = 0").select("id", "rank", "deg", "stays", "hot", "ever", "grown"), path, seen


def sweep(edges: DataFrame, state: DataFrame, parts: int, n: int, swept: list[tuple[MethodPlan, RankConfig]]) -> list[tuple] | None:
    """What :func:`kernel.local_sweep` gives, over parts that all settings share: setting, supersteps, in_edges, affected, l1. None where the session can't.

    ``state`` has id, rank, deg, affected and ref.
    """
    spark = state.sparkSession
    first = state.selectExpr("id", "rank", "deg", "affected AS stays", "false AS hot", "affected AS ever", "false AS grown", "ref")
    with settings(spark, spark__sql__adaptive__enabled="false"):
        table = dealt(edges, first, parts, "ref")
    if table is None:
        return None

    def job(folder: str):
        def rows(batches):
            part = _started(folder, batches, False, "ref")
            rank, seeds, ref, out = part.rank, part.stays, part.more[0], []
            for k, (plan, cfg) in enumerate(swept):
                part.rank = rank if plan.warm else np.full(len(rank), 1.0 / n)
                part.stays = seeds if plan.seed != "all" else np.ones(len(rank), bool)
                part.hot, part.ever = np.zeros(len(rank), bool), part.stays
                factor = n / cfg.scale_vertices if cfg.tolerance_scale == "mean_rank" else 1.0
                trace = [t for t in part.run(plan, cfg, cfg.max_supersteps, n, factor, False) if t["was"]]
                each, _ = part.post.swap([float(part.ever.sum()), float(np.abs(part.rank - ref).sum())], [np.zeros(0, np.uint8)] * part.post.parts)
                out.append((k, len(trace), int(sum(t["in_edges"] for t in trace)), int(each[:, 0].sum()), float(each[:, 1].sum())))
            if part.post.me == 0:
                types = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.float64())
                names = ("setting", "supersteps", "in_edges", "affected", "l1")
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*out, strict=True), types, strict=True)], names=list(names))

        return [tuple(r) for r in table.mapInArrow(_guarded(folder, rows), SWEPT, barrier=True).collect()]

    return sorted(_tried(spark, job))
