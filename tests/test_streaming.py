"""Streams end where batches end; late rows, expiry and restarts."""

import pytest
from pyspark.sql import functions as F

from incrank.functions.measures import l1_error
from incrank.plans.graph import normalize_delta, next_snapshot, snapshot
from incrank.plans.methods import cold_rank, run_method
from incrank.plans.model import RankConfig
from incrank.plans.store import RankStore
from incrank.session import scratch
from incrank.sources.random_source import RandomBatchSource
from incrank.streaming.events import expiring_edges, finished
from incrank.streaming.maintainer import RankMaintainer


def test_store_versions_overlays_and_pointer(spark):
    store = RankStore(spark, scratch(spark, "store"))
    row = lambda *xs: spark.createDataFrame(list(xs), "id bigint, rank double")
    assert store.current() is None and store.read().count() == 0
    assert store.commit(row((1, 0.5), (2, 0.5)), 0) and store.commit(row((2, 0.25)), 1, over=0)
    assert not store.commit(row((1, 9.0)), 1)
    assert sorted(map(tuple, store.read().collect())) == [(1, 0.5), (2, 0.25)]
    assert sorted(map(tuple, store.read(0).collect())) == [(1, 0.5), (2, 0.5)]
    store.compact(2)
    assert dict(store.versions())[2] is None and sorted(map(tuple, store.read().collect())) == [(1, 0.5), (2, 0.25)]


def test_store_overlays_edges(spark):
    store = RankStore(spark, scratch(spark, "store"), "src bigint, dst bigint", ("src", "dst"))
    row = lambda *xs: spark.createDataFrame(list(xs), "src bigint, dst bigint")
    store.commit(row((1, 2), (1, 3)), 0)
    store.commit(row((1, 3), (2, 1)), 1, over=0)
    assert sorted(map(tuple, store.read().collect())) == [(1, 2), (1, 3), (2, 1)]


def test_maintainer_steps_once_and_agrees_with_batches(spark):
    v = spark.range(6)
    edges = spark.createDataFrame([(0, 1), (1, 2), (2, 0), (3, 2), (4, 5)], "src bigint, dst bigint")
    one = spark.createDataFrame([(2, 4, "+"), (3, 2, "-"), (9, 1, "+"), (4, 11, "+")], "src bigint, dst bigint, op string")
    two = spark.createDataFrame([(5, 0, "+")], "src bigint, dst bigint, op string")
    keeper = RankMaintainer(spark, scratch(spark, "keeper"))
    keeper.start(v, edges)
    for _ in range(2):  # a repeated micro-batch has its effect once
        keeper.step(one, 0)
    keeper.step(two, 1)
    again = RankMaintainer(spark, keeper.root)
    again.step(two, 1)
    g = snapshot(v, edges)
    ranks = cold_rank(g, RankConfig(engine="local")).ranks
    for raw in (one, two):
        delta = normalize_delta(g, raw)
        new = next_snapshot(g, delta, "grow")
        ranks, g = run_method("pruned", g, new, delta, ranks).ranks, new
    assert again.current() == 2 and again.read().count() == 8 and l1_error(again.read(), ranks).first()[0] < 1e-14
    trace = spark.read.parquet(keeper.trace_path)
    assert trace.groupBy("batch", "superstep").count().where("count > 1").count() == 0 and trace.select("batch").distinct().count() == 2
    with pytest.raises(ValueError):
        RankMaintainer(spark, keeper.root, universe="fixed").step(one.selectExpr("src + 100 AS src", "dst", "op"), 2)


def test_a_step_writes_what_its_batch_changes(spark):
    """Ten batches upon a graph: no copies of it, and of old versions only what the last two need."""
    n = 400
    keeper = RankMaintainer(spark, scratch(spark, "keeper"), cfg=RankConfig(tau=1e-6))
    keeper.start(spark.range(n), spark.createDataFrame([(k, (k * 7 + j) % n) for k in range(n) for j in range(4)], "src bigint, dst bigint"))
    base = keeper.versions.read(0)["graph"]["base"]
    for b in range(3):
        keeper.step(spark.createDataFrame([(b, b + 50), (b + 1, b + 60)], "src bigint, dst bigint"), b)
    now = keeper.versions.read(3)
    assert now["graph"]["base"] == base and now["graph"]["n_net"] == 6 and keeper.versions.versions() == [2, 3]
    g, table = keeper.open()
    assert g.edges.count() == g.n_edges and l1_error(table.df, cold_rank(g, RankConfig(engine="local")).ranks).first()[0] < 1e-4


def test_late_rows_are_admitted_or_dropped(spark):
    row = lambda s, d, day: (s, d, f"2024-01-{day:02d}")
    batch = lambda *rows: spark.createDataFrame(list(rows), "src bigint, dst bigint, t string").selectExpr("src", "dst", "CAST(t AS timestamp) AS ts")
    for late, edges in (("admit", 4), ("drop", 3)):
        keeper = RankMaintainer(spark, scratch(spark, "late"), late=late, delay=86_400, cfg=RankConfig(tau=1e-3))
        keeper.start(spark.range(4), spark.createDataFrame([(0, 1)], "src bigint, dst bigint"))
        keeper.step(batch(row(1, 2, 20)), 0)
        keeper.step(batch(row(2, 3, 19), row(3, 0, 2)), 1)
        assert keeper.open()[0].edges.where("src <> dst").count() == edges


def test_expired_edges_leave_the_ranks(spark):
    """An expiring stream's deletions go on to the maintainer."""
    path = scratch(spark, "ttl")
    row = lambda s, d, day: (s, d, f"2024-01-{day:02d} 00:00:00")
    for batch in ([row(1, 2, 1), row(1, 2, 2)], [row(3, 4, 9)], [row(3, 4, 10)]):
        spark.createDataFrame(batch, "src bigint, dst bigint, t string").selectExpr("src", "dst", "CAST(t AS TIMESTAMP) AS ts").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema("src bigint, dst bigint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour")
    keeper = RankMaintainer(spark, scratch(spark, "keeper"), cfg=RankConfig(tau=1e-3))
    keeper.start(spark.range(1, 5), spark.createDataFrame([(1, 4)], "src bigint, dst bigint"))
    keeper.write_stream(expiring_edges(stream, 2 * 86_400_000), scratch(spark, "offsets")).awaitTermination()
    assert sorted(map(tuple, keeper.open()[0].edges.where("src <> dst").collect())) == [(1, 4), (3, 4)]


def test_late_rows_are_dropped_after_the_watermark(spark):
    path = scratch(spark, "late")
    days = lambda *d: spark.createDataFrame([(f"2024-01-{x:02d} 12:00:00",) for x in d], "t string").select(F.col("t").cast("timestamp").alias("ts"))
    days(1, 2, 9).coalesce(1).write.parquet(path)
    stream = spark.readStream.schema("ts timestamp").parquet(path).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    out = scratch(spark, "late-out")

    def run():
        stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", out + "-offsets").trigger(availableNow=True).start(out).awaitTermination()
        return sorted((str(r["window"]["start"])[:10], r["n"]) for r in spark.read.parquet(out).collect())

    assert run() == [("2024-01-01", 1), ("2024-01-02", 1)]
    days(2, 20).coalesce(1).write.mode("append").parquet(path)  # the second day is late now
    assert run() == [("2024-01-01", 1), ("2024-01-02", 1), ("2024-01-09", 1)]


def test_edges_expire(spark):
    path = scratch(spark, "ttl")
    row = lambda s, d, day: (s, d, f"2024-01-{day:02d} 00:00:00")
    for batch in ([row(1, 2, 1), row(1, 2, 2)], [row(3, 4, 9)], [row(3, 4, 10)]):
        spark.createDataFrame(batch, "src bigint, dst bigint, t string").selectExpr("src", "dst", "CAST(t AS TIMESTAMP) AS ts").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema("src bigint, dst bigint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour")
    ops = {(r["src"], r["op"]) for r in finished(expiring_edges(stream, 2 * 86_400_000), "append").collect()}
    assert (1, "+") in ops and (3, "+") in ops and (1, "-") in ops and (3, "-") not in ops


def test_random_source_streams_what_it_draws_in_batches(spark):
    spark.dataSource.register(RandomBatchSource)
    got = spark.read.format("random_pairs").option("pairs", 20).option("vertices", 7).option("slices", 3).load().collect()
    assert len(got) == 20 and all(1 <= r["ps"] <= 7 for r in got)
    source = RandomBatchSource({"pairs": "20", "vertices": "7"})
    rows, end = source.simpleStreamReader(None).read({"next": 0})
    assert sorted(rows) == sorted(map(tuple, got)) and end == {"next": 20}


@pytest.mark.parametrize("gamma", [1.0, 3.0])
def test_synthetic_graphs_scale(spark, gamma):
    from incrank.sources.workloads import synthetic

    t = synthetic(spark, 100, 1000, gamma)
    assert t.count() == 1000 and t.agg(F.max("dst")).first()[0] < 100
