"""Event-time operators over the events table as a stream of files, each with the batch SQL it must agree with."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles
from ..functions.formulas import rank_e9
from ..session import scratch, ship, stored
from ..sources import batches, workloads
from ..sources.workloads import read
from .maintainer import RankMaintainer

EVENT = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double"
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(sql: str | None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return add


def event_files(spark: SparkSession, sf_dir: str, files: int = 2) -> str:
    """The events table as files in order of time, for a stream to read."""
    path = scratch(spark, "event-files")
    e = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartitionByRange(files, "ts").write.parquet(path)
    return path


def event_stream(spark: SparkSession, sf_dir: str, delay: str = "60 days") -> DataFrame:
    return spark.readStream.schema(EVENT).parquet(event_files(spark, sf_dir)).withWatermark("ts", delay)


def finished(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream until its input is used up. Append: all rows; complete: the last table."""
    spark = stream.sparkSession
    path = scratch(spark, "stream")

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/rows/batch={batch}")

    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}/offsets").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.schema(stream.schema).option("basePath", f"{path}/rows").parquet(f"{path}/rows")
    if mode == "complete":
        last = max(int(p.getPath().getName().split("=")[1]) for p in _list(spark, f"{path}/rows") if "batch=" in p.getPath().getName())
        rows = spark.read.schema(stream.schema).parquet(f"{path}/rows/batch={last}")
    return rows.select(*stream.columns)


def _list(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listStatus(p)


def e6(c):
    return F.floor(c * F.lit(1e6) + F.lit(0.5)).cast("bigint")


@op("SELECT event_type, CAST(date_trunc('day', ts) AS VARCHAR)[:10] AS day, count(*) AS n, CAST(floor(sum(value) * 1e6 + 0.5) AS BIGINT) AS total FROM events GROUP BY event_type, date_trunc('day', ts)")
def stream_tumbling(spark, sf_dir):
    agg = event_stream(spark, sf_dir).groupBy("event_type", F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return finished(agg, "complete").select("event_type", F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n", e6(F.col("total")).alias("total"))


@op("SELECT CAST(s AS BIGINT) AS start, count(*) AS n FROM (SELECT unnest([b, b - 21600, b - 43200, b - 64800]) AS s, t FROM (SELECT epoch(ts) AS t, floor(epoch(ts) / 21600)::BIGINT * 21600 AS b FROM events)) GROUP BY s")
def stream_sliding(spark, sf_dir):
    agg = event_stream(spark, sf_dir).groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finished(agg, "complete").select(F.unix_seconds("w.start").alias("start"), "n")


@op("SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR > ts THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def stream_session(spark, sf_dir):
    agg = event_stream(spark, sf_dir).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finished(agg, "complete").select("user_id", F.unix_micros("w.start").alias("start"), "n")


@op(None)
def stream_watermark_late(spark, sf_dir):
    """Counts by day in append mode under a watermark of one day; windows still open at the end are not out. Tests cover rows that come late."""
    agg = event_stream(spark, sf_dir, "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finished(agg, "append").select(F.unix_seconds("w.start").alias("start"), "n")


@op("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    once = event_stream(spark, sf_dir, "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return finished(once.select("user_id", "event_type"), "append")


_RANKS = f"WITH RECURSIVE {oracles.graph_sql('event_flow')}, {oracles.rounds_sql('base', 'eo', 'dold', oracles._UNIFORM, oracles.METHODS['cold'], oracles.RankConfig())}, base_ranks AS (SELECT id, r FROM {oracles.last('base')})"


@op(f"{_RANKS} SELECT event_id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM events JOIN base_ranks ON id = user_id WHERE event_type = 'purchase'")
def stream_static_join(spark, sf_dir):
    from ..plans.prepared import prepared

    ranks = prepared(spark, sf_dir, "event_flow").base.select(F.col("id").alias("user_id"), rank_e9(F.col("rank")).alias("rank_e9"))
    return finished(event_stream(spark, sf_dir).where("event_type = 'purchase'").join(ranks, "user_id").select("event_id", "rank_e9"), "append")


@op("SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def stream_stream_join(spark, sf_dir):
    clicks = event_stream(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("at"))
    buys = event_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", "ts")
    return finished(clicks.join(buys, F.expr("u = user_id AND ts BETWEEN at AND at + INTERVAL 1 HOUR")).select("click", "purchase"), "append")


def expiring_edges(edges: DataFrame, ttl_ms: int) -> DataFrame:
    """src, dst, op, at: an insertion when an edge is first seen, a deletion when it was not seen for ``ttl_ms`` of event time."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def follow(key, frames: Iterator[pd.DataFrame], state: GroupState):
        out = []
        if state.hasTimedOut:
            out.append((*key, "-", state.get[0] + ttl_ms))
            state.remove()
        else:
            last = state.get[0] if state.exists else None
            for frame in frames:
                times = frame["ms"]
                if last is None:
                    out.append((*key, "+", int(times.min())))
                last = max(int(times.max()), last or 0)
            state.update((last,))
            state.setTimeoutTimestamp(max(last + ttl_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["src", "dst", "op", "at"])

    timed = edges.withColumn("ms", F.unix_millis("ts"))
    return timed.groupBy("src", "dst").applyInPandasWithState(follow, "src bigint, dst bigint, op string, at bigint", "last bigint", "append", GroupStateTimeout.EventTimeTimeout)


@op(None)
def stream_edge_ttl(spark, sf_dir):
    """User to item edges that expire after two days without an event."""
    ship(spark)
    e = read(spark, sf_dir, "events", "ts", "user_id", "event_type").select(F.col("user_id").alias("src"), F.length("event_type").cast("bigint").alias("dst"), F.col("ts").cast("timestamp").alias("ts"))
    path = scratch(spark, "ttl-edges")
    e.repartitionByRange(3, "ts").write.parquet(path)
    stream = spark.readStream.schema("src bigint, dst bigint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour")
    return finished(expiring_edges(stream, 2 * 86_400_000), "append")


@op(f"SELECT id, rank_e9 FROM ({oracles.chained_sql('event_flow', 'pruned', 3)})")
def stream_rank_maintain(spark, sf_dir):
    """The first three slices after the preload, a micro-batch each: the maintainer's ranks are those of three batches of the pruned method."""
    edges = stored(workloads.event_flow(spark, sf_dir), "event-flow")
    total = edges.count()
    keeper = RankMaintainer(spark, scratch(spark, "maintained"), universe="fixed")
    keeper.start(workloads.universe(edges), batches.preload_split(edges, total))
    path = scratch(spark, "changes")
    slices = stored(batches.slice_batches(edges, total, 1e-3, 3), "slices")
    for k in range(3):  # files are read in the order of their times
        slices.where(f"batch = {k}").select("src", "dst", "op").coalesce(1).write.mode("append").parquet(path)
    changes = spark.readStream.schema("src bigint, dst bigint, op string").option("maxFilesPerTrigger", 1).parquet(path)
    keeper.write_stream(changes, scratch(spark, "offsets")).awaitTermination()
    return keeper.read().select("id", rank_e9(F.col("rank")).alias("rank_e9"))


@op(f"SELECT id, rank_e9 FROM ({oracles.grown_sql('geo_tree')})")
def stream_rank_grow(spark, sf_dir):
    """A tree without one of its regions' nations at first; a batch brings them in, as new vertices with their links: ranks by warm rounds from scaled old ones."""
    e = stored(workloads.geo_tree(spark, sf_dir), "tree")
    late = "src % 4 = 1 AND src % 3 = 0 OR dst % 4 = 1 AND dst % 3 = 0"
    keeper = RankMaintainer(spark, scratch(spark, "grown"), method="warm")
    first = e.where(f"NOT ({late})")
    keeper.start(workloads.universe(first), first)
    keeper.step(e.where(late), 0)
    return keeper.read().select("id", rank_e9(F.col("rank")).alias("rank_e9"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
