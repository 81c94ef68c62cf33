"""Relational operators that feed and consume rank tables: one function for each, with its SQL beside it.

Ranks here are those of a cold run on the workload's old graph, the state every method starts from.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import oracles
from ..functions.formulas import rank_e9
from ..plans.graph import diff_snapshots, in_degrees, out_degrees
from ..plans.model import METHODS, RankConfig
from ..plans.prepared import prepared
from ..session import scratch, ship
from ..sources import batches, workloads
from ..sources.workloads import read

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(sql: str | None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return add


def e6(c: Column) -> Column:
    """Six decimals as a whole number, which engines agree on."""
    return F.floor(c * F.lit(1e6) + F.lit(0.5)).cast("bigint")


def s6(x: str) -> str:
    return f"CAST(floor(({x}) * 1e6 + 0.5) AS BIGINT)"


def base_ranks(spark: SparkSession, sf_dir: str, workload: str) -> DataFrame:
    return prepared(spark, sf_dir, workload).base


def edges_of(spark: SparkSession, sf_dir: str, workload: str) -> DataFrame:
    """Distinct edges of a workload, without self-loops."""
    return workloads.build(spark, sf_dir, workload).where("src <> dst").select("src", "dst").distinct()


def edge_sql(workload: str) -> str:
    return f"(SELECT DISTINCT src, dst FROM ({oracles.EDGES[workload]}) WHERE src <> dst)"


def with_base(workload: str, body: str) -> str:
    """SQL over ``base_ranks`` (id, r) and the graph's CTEs."""
    ctes = [oracles.graph_sql(workload), oracles.rounds_sql("base", "eo", "dold", oracles._UNIFORM, METHODS["cold"], RankConfig()), f"base_ranks AS MATERIALIZED (SELECT id, r FROM {oracles.last('base')})"]
    return f"WITH RECURSIVE {', '.join(ctes)} {body}"


# Sources and sinks


@op("SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_quantity > 49 AND l_returnflag = 'R'")
def scan_parquet_pruned(spark, sf_dir):
    schema = "l_orderkey bigint, l_suppkey bigint, l_quantity double, l_returnflag string"
    return spark.read.schema(schema).parquet(f"{sf_dir}/lineitem.parquet").where("l_quantity > 49 AND l_returnflag = 'R'").select("l_orderkey", "l_suppkey")


def _round_trip(df: DataFrame, kind: str, schema: str, **options: str) -> DataFrame:
    spark = df.sparkSession
    path = scratch(spark, kind)
    df.write.format(kind).options(**options).save(path)
    return spark.read.format(kind).options(**options).schema(schema).load(path)


@op(f"SELECT src, dst FROM ({oracles.EDGES['geo_tree']})")
def scan_edge_csv(spark, sf_dir):
    return _round_trip(workloads.geo_tree(spark, sf_dir), "csv", "src bigint, dst bigint", sep="\t")


@op(f"SELECT src, dst, seq FROM ({oracles.EDGES['event_flow']})")
def scan_edge_json(spark, sf_dir):
    return _round_trip(workloads.event_flow(spark, sf_dir), "json", "src bigint, dst bigint, seq bigint")


@op(f"SELECT src, dst FROM ({oracles.EDGES['turn_chain']}) UNION ALL SELECT src, dst FROM ({oracles.EDGES['turn_chain']})")
def scan_orc_text(spark, sf_dir):
    edges = workloads.turn_chain(spark, sf_dir)
    orc = _round_trip(edges, "orc", "src bigint, dst bigint")
    lines = _round_trip(edges.select(F.concat_ws(" ", "src", "dst").alias("value")), "text", "value string")
    parts = F.split("value", r"\s+")
    return orc.unionByName(lines.select(parts[0].cast("bigint").alias("src"), parts[1].cast("bigint").alias("dst")))


@op(f"WITH {oracles.graph_sql('geo_tree')} SELECT src, dst, op FROM raw")
def source_random_batches(spark, sf_dir):
    """A Python data source that draws a random batch; see :mod:`incrank.sources.random_source`."""
    from ..sources.random_source import RandomBatchSource

    ship(spark)
    spark.dataSource.register(RandomBatchSource)
    edges = edges_of(spark, sf_dir, "geo_tree")
    total = edges.count()
    m = batches.batch_size(total, 1e-3)
    ids = workloads.vertices_of(edges)
    from ..plans.graph import number_rows

    index = number_rows(ids, ["id"], "place")
    draws = spark.read.format("random_pairs").option("pairs", -(-8 * m // 10)).option("seed", 42).option("vertices", index.count()).load()
    src, dst = index.select(F.col("id").alias("src"), F.col("place").alias("ps")), index.select(F.col("id").alias("dst"), F.col("place").alias("pd"))
    ins = draws.join(src, "ps").join(dst, "pd").select("src", "dst", F.lit("+").alias("op"))
    return ins.unionByName(batches.random_deletes(edges, m - -(-8 * m // 10)))


@op(with_base("geo_tree", "SELECT id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9, 1 AS v FROM base_ranks"))
def sink_versioned(spark, sf_dir):
    from ..plans.store import RankStore

    store = RankStore(spark, scratch(spark, "store"))
    ranks = base_ranks(spark, sf_dir, "geo_tree")
    store.commit(ranks.limit(0), 0)
    store.commit(ranks, 1)
    return store.read().select("id", rank_e9(F.col("rank")).alias("rank_e9"), F.lit(store.current()).alias("v"))


@op(f"SELECT src, dst, 2 AS layouts FROM {edge_sql('part_flow')}")
def sink_bucketed(spark, sf_dir):
    """Two layouts of the edges, bucketed by either end: joins on that end need no exchange of edges."""
    edges = edges_of(spark, sf_dir, "part_flow")
    tag = scratch(spark, "t").rsplit("-", 1)[1]
    for end in ("src", "dst"):
        edges.write.bucketBy(8, end).sortBy(end).option("path", scratch(spark, f"by-{end}")).saveAsTable(f"edges_by_{end}_{tag}")
    both = spark.table(f"edges_by_src_{tag}").select("src", "dst").unionAll(spark.table(f"edges_by_dst_{tag}").select("src", "dst"))
    return both.groupBy("src", "dst").agg(F.count(F.lit(1)).cast("int").alias("layouts"))


# Projections and filters


@op("SELECT o_orderkey, CASE WHEN o_totalprice > 100000 THEN 'large' WHEN o_totalprice > 20000 THEN 'middle' ELSE 'small' END AS size, CAST(o_custkey AS VARCHAR) AS customer, substr(o_orderpriority, 1, 1) AS priority FROM orders")
def project_exprs(spark, sf_dir):
    o = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority")
    size = F.when(F.col("o_totalprice") > 100000, "large").when(F.col("o_totalprice") > 20000, "middle").otherwise("small")
    return o.withColumns({"size": size, "customer": F.col("o_custkey").cast("string")}).withColumnRenamed("o_orderpriority", "p").withColumn("priority", F.substring("p", 1, 1)).drop("p", "o_custkey", "o_totalprice")


@op("SELECT p_partkey FROM part WHERE (p_size IN (1, 5, 9) OR p_size BETWEEN 40 AND 45) AND p_brand LIKE 'Brand#%' AND NOT regexp_matches(p_type, '^S.*X$') AND p_name IS NOT NULL")
def filter_preds(spark, sf_dir):
    p = read(spark, sf_dir, "part", "p_partkey", "p_size", "p_brand", "p_type", "p_name")
    return p.where((F.col("p_size").isin(1, 5, 9) | F.col("p_size").between(40, 45)) & F.col("p_brand").like("Brand#%") & ~F.col("p_type").rlike("^S.*X$") & F.col("p_name").isNotNull()).select("p_partkey")


# Joins


@op(with_base("geo_tree", "SELECT n_name, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM base_ranks JOIN nation ON id = n_nationkey::BIGINT * 4 + 1"))
def join_broadcast(spark, sf_dir):
    n = read(spark, sf_dir, "nation", "n_nationkey", "n_name").withColumn("id", F.col("n_nationkey").cast("bigint") * 4 + 1)
    return base_ranks(spark, sf_dir, "geo_tree").join(n.hint("broadcast"), "id").select("n_name", rank_e9(F.col("rank")).alias("rank_e9"))


@op(with_base("part_flow", "SELECT b.id, deg, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM base_ranks b JOIN dold ON dold.id = b.id"))
def join_shuffle_hash(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return p.old.degrees.withColumnRenamed("out_deg", "deg").hint("shuffle_hash").join(p.base, "id").select("id", "deg", rank_e9(F.col("rank")).alias("rank_e9"))


@op(with_base("cust_supp", f"SELECT dst, {s6('sum(r) * 1000')} AS rank_sum FROM eo JOIN base_ranks ON id = src GROUP BY dst"))
def join_sort_merge(spark, sf_dir):
    p = prepared(spark, sf_dir, "cust_supp")
    return p.old.edges.hint("merge").join(p.base, F.col("src") == F.col("id")).groupBy("dst").agg(e6(F.sum("rank") * 1000).alias("rank_sum"))


_CS_NEW = oracles.method_ctes("cust_supp", "pruned")


@op(f"WITH {oracles.graph_sql('order_chain')}, a AS (SELECT src AS id, count(*) AS x FROM eo WHERE src <> dst GROUP BY src), b AS (SELECT src AS id, count(*) AS y FROM en WHERE src <> dst GROUP BY src) SELECT coalesce(a.id, b.id) AS id, x, y FROM a FULL JOIN b ON a.id = b.id")
def join_outer(spark, sf_dir):
    """Out-degrees before and after a batch; either may be missing."""
    p = prepared(spark, sf_dir, "order_chain")
    deg = lambda g, name: out_degrees(g.edges.where("src <> dst")).withColumnRenamed("out_deg", name)
    return deg(p.old, "x").join(deg(p.new, "y"), "id", "full")


@op(f"{oracles.method_ctes('part_flow', 'frontier')} SELECT src, dst FROM en WHERE dst IN (SELECT id FROM seed)")
def join_semi(spark, sf_dir):
    from ..plans.marking import seed_frontier

    p = prepared(spark, sf_dir, "part_flow")
    return p.new.edges.join(seed_frontier(p.old, p.new, p.delta).withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT src, dst FROM eo WHERE (src, dst) NOT IN (SELECT (src, dst) FROM delta WHERE op = '-')")
def join_anti(spark, sf_dir):
    """Edges that survive a batch's deletions."""
    p = prepared(spark, sf_dir, "order_chain")
    return p.old.edges.join(p.delta.where("op = '-'"), ["src", "dst"], "left_anti").select("src", "dst")


@op("SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) > 0.3")
def join_cross_theta(spark, sf_dir):
    """Pairs by a predicate that is no equality: all vectors in blocks against all, exactly."""
    from ..functions.vectors import pairs_above

    return pairs_above(read(spark, sf_dir, "embeddings", "vec_id", "embedding"), 0.3)


@op("SELECT event_id, band FROM events JOIN (SELECT i AS band, i * 7.5 AS lo, i * 7.5 + 11.0 AS hi FROM (SELECT unnest(range(40)) AS i)) ON value >= lo AND value < hi")
def join_range(spark, sf_dir):
    """Events in overlapping value bands: both sides go to bins of width 10, equal bins join, then the bounds decide."""
    e = read(spark, sf_dir, "events", "event_id", "value").withColumn("bin", F.floor(F.col("value") / 10))
    bands = spark.range(40).select(F.col("id").alias("band"), (F.col("id") * 7.5).alias("lo"), (F.col("id") * 7.5 + 11.0).alias("hi"))
    bands = bands.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 10), F.floor(F.col("hi") / 10))))
    return e.join(bands, "bin").where("value >= lo AND value < hi").select("event_id", "band")


_VERSIONS = "SELECT event_id AS version, ts FROM events WHERE event_type = 'signup'"


@op(f"SELECT e.event_id, v.version FROM events e ASOF LEFT JOIN ({_VERSIONS}) v ON e.ts >= v.ts")
def join_asof(spark, sf_dir):
    """The last version not after each event: both in one order, the last version seen carried on. Range partitions are
    sorted and each carries on within itself; the last version of each partition, one row, is carried over on the driver."""
    e = read(spark, sf_dir, "events", "event_id", "ts", "event_type")
    both = e.select("ts", "event_id", F.lit(None).cast("bigint").alias("version")).unionByName(e.where("event_type = 'signup'").select("ts", F.lit(None).cast("bigint").alias("event_id"), F.col("event_id").alias("version")))
    from ..session import stored

    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = stored(both.repartitionByRange(n, "ts").withColumn("part", F.spark_partition_id()), "asof")
    order = [F.col("ts"), F.col("version").asc_nulls_last()]
    lasts = {r["part"]: r["v"] for r in parts.where("version IS NOT NULL").groupBy("part").agg(F.max_by("version", F.struct("ts", "version")).alias("v")).collect()}
    carried, run = [], None
    for p in range(max([n - 1, *lasts]) + 1):
        if run is not None:
            carried.append((p, run))
        run = lasts.get(p, run)
    before = spark.createDataFrame(carried or [(-1, None)], "part int, before bigint")
    within = F.last("version", ignorenulls=True).over(Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return parts.withColumn("v", within).join(F.broadcast(before), "part", "left").where("event_id IS NOT NULL").select("event_id", F.coalesce("v", "before").alias("version"))


@op("SELECT p.event_id AS purchase, e.event_id AS near FROM events p JOIN events e ON p.user_id = e.user_id AND e.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts AND e.event_id <> p.event_id WHERE p.event_type = 'purchase'")
def join_interval(spark, sf_dir):
    e = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("ts").alias("at"), "user_id")
    return p.join(e, "user_id").where("ts BETWEEN at - INTERVAL 1 HOUR AND at AND event_id <> purchase").select("purchase", F.col("event_id").alias("near"))


@op(f"WITH e AS {edge_sql('event_flow')} SELECT a.src, b.dst, count(*) AS paths FROM e a JOIN e b ON a.dst = b.src WHERE a.src <> b.dst GROUP BY a.src, b.dst")
def two_hop(spark, sf_dir):
    e = edges_of(spark, sf_dir, "event_flow")
    return e.select("src", F.col("dst").alias("mid")).join(e.select(F.col("src").alias("mid"), "dst"), "mid").where("src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("paths"))


@op("SELECT src, dst, n FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY n DESC, dst) AS k FROM (SELECT src, dst, count(*) AS n FROM (" + oracles.EDGES["cust_supp"] + ") GROUP BY src, dst)) WHERE k <= 2")
def lateral_topk(spark, sf_dir):
    """The two targets each source meets most often."""
    n = workloads.cust_supp(spark, sf_dir).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("k", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("n"), "dst"))).where("k <= 2").select("src", "dst", "n")


# Aggregates


@op(f"SELECT d AS out_degree, count(*) AS vertices FROM (SELECT src, count(*) AS d FROM {edge_sql('part_flow')} GROUP BY src) GROUP BY d")
def agg_degree_hist(spark, sf_dir):
    return out_degrees(edges_of(spark, sf_dir, "part_flow")).groupBy(F.col("out_deg").alias("out_degree")).agg(F.count(F.lit(1)).alias("vertices"))


@op(f"SELECT src, count(DISTINCT dst) AS targets FROM ({oracles.EDGES['cust_supp']}) GROUP BY src")
def agg_distinct(spark, sf_dir):
    return workloads.cust_supp(spark, sf_dir).groupBy("src").agg(F.count_distinct("dst").alias("targets"))


@op(None)
def agg_approx(spark, sf_dir):
    """Approximate distinct targets (within 5 %) and percentiles of sequence numbers; tests hold them against exact ones."""
    return workloads.cust_supp(spark, sf_dir).groupBy("src").agg(F.approx_count_distinct("dst", 0.05).alias("targets"), F.approx_percentile("seq", [0.5, 0.9], 1000).alias("percentiles"))


@op(with_base("part_flow", f", ind AS (SELECT dst AS id, count(*) AS k FROM eo GROUP BY dst) SELECT {s6('avg(r) * 1000')} AS mean, {s6('stddev_samp(r) * 1000')} AS spread, {s6('corr(r, k)')} AS corr, {s6('quantile_cont(r, 0.5) * 1000')} AS median, count(*) FILTER (r > 0.0005) AS high FROM base_ranks b JOIN ind ON ind.id = b.id"))
def agg_stats(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    both = p.base.join(in_degrees(p.old.edges), "id")
    return both.agg(e6(F.avg("rank") * 1000).alias("mean"), e6(F.stddev("rank") * 1000).alias("spread"), e6(F.corr("rank", F.col("in_deg").cast("double"))).alias("corr"), e6(F.percentile("rank", 0.5) * 1000).alias("median"), F.count_if(F.col("rank") > 0.0005).alias("high"))


_GEO = "SELECT n_regionkey AS region, n_nationkey AS nation, n_name, id, r FROM base_ranks JOIN nation ON id = n_nationkey::BIGINT * 4 + 1"


def _nation_ranks(spark, sf_dir):
    n = read(spark, sf_dir, "nation", "n_nationkey", "n_name", "n_regionkey").withColumn("id", F.col("n_nationkey").cast("bigint") * 4 + 1)
    return base_ranks(spark, sf_dir, "geo_tree").join(F.broadcast(n), "id").select(F.col("n_regionkey").alias("region"), F.col("n_nationkey").alias("nation"), "n_name", "id", "rank")


@op(with_base("geo_tree", f"SELECT region, arg_max(n_name, k) AS highest, arg_min(n_name, k) AS lowest FROM (SELECT *, CAST(floor(r * 1e9 + 0.5) AS BIGINT) * 1000 + nation AS k FROM ({_GEO})) GROUP BY region"))
def agg_arg(spark, sf_dir):
    key = rank_e9(F.col("rank")) * 1000 + F.col("nation")  # ties go by nation
    return _nation_ranks(spark, sf_dir).withColumn("k", key).groupBy("region").agg(F.max_by("n_name", "k").alias("highest"), F.min_by("n_name", "k").alias("lowest"))


@op(with_base("geo_tree", f"SELECT region, nation, {s6('sum(r) * 1000')} AS mass, CAST(grouping(region) * 2 + grouping(nation) AS BIGINT) AS level FROM ({_GEO}) GROUP BY ROLLUP (region, nation)"))
def agg_rollup(spark, sf_dir):
    return _nation_ranks(spark, sf_dir).rollup("region", "nation").agg(e6(F.sum("rank") * 1000).alias("mass"), F.grouping_id().cast("bigint").alias("level"))


@op("SELECT event_type, CAST(date_trunc('day', ts) AS DATE) AS day, count(*) AS n FROM events GROUP BY CUBE (event_type, day)")
def agg_cube(spark, sf_dir):
    return read(spark, sf_dir, "events", "event_type", "ts").withColumn("day", F.to_date("ts")).cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark, sf_dir):
    read(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority").createOrReplaceTempView("orders_for_sets")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders_for_sets GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@op("SELECT day, unnest(['click', 'view']) AS kind, unnest([count(*) FILTER (event_type = 'click'), count(*) FILTER (event_type = 'view')]) AS n FROM (SELECT CAST(ts AS DATE) AS day, event_type FROM events) GROUP BY day")
def agg_pivot(spark, sf_dir):
    """Types as columns, and back again."""
    e = read(spark, sf_dir, "events", "event_type", "ts").withColumn("day", F.to_date("ts"))
    wide = e.groupBy("day").pivot("event_type", ["click", "view"]).count().fillna(0)
    return wide.unpivot("day", ["click", "view"], "kind", "n")


@op(f"SELECT src, array_to_string(list_sort(list(dst)), ',') AS targets FROM {edge_sql('event_flow')} GROUP BY src")
def agg_collect(spark, sf_dir):
    return edges_of(spark, sf_dir, "event_flow").groupBy("src").agg(F.concat_ws(",", F.transform(F.array_sort(F.collect_set("dst")), lambda x: x.cast("string"))).alias("targets"))


@op(f"SELECT dst, count(*) AS in_deg FROM {edge_sql('cust_supp')} GROUP BY dst HAVING count(*) > 400")
def agg_having(spark, sf_dir):
    return in_degrees(edges_of(spark, sf_dir, "cust_supp")).where("in_deg > 400").select(F.col("id").alias("dst"), "in_deg")


# Windows, order, sets


@op(with_base("geo_tree", f"SELECT id, row_number() OVER w AS rn, rank() OVER w2 AS rk, dense_rank() OVER w2 AS dr, {s6('percent_rank() OVER w')} AS pr, {s6('cume_dist() OVER w')} AS cd, CAST(ntile(3) OVER w AS INTEGER) AS nt FROM (SELECT *, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS x FROM ({_GEO})) WINDOW w AS (PARTITION BY region ORDER BY x DESC, id), w2 AS (PARTITION BY region ORDER BY x // 100000)"))
def win_ranking(spark, sf_dir):
    x = _nation_ranks(spark, sf_dir).withColumn("x", rank_e9(F.col("rank")))
    w, w2 = Window.partitionBy("region").orderBy(F.desc("x"), "id"), Window.partitionBy("region").orderBy(F.floor(F.col("x") / 100000))
    big = lambda c: c.cast("bigint")
    return x.select("id", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(w2)).alias("rk"), big(F.dense_rank().over(w2)).alias("dr"), e6(F.percent_rank().over(w)).alias("pr"), e6(F.cume_dist().over(w)).alias("cd"), F.ntile(3).over(w).alias("nt"))


@op("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_analytic(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(spark, sf_dir, "events", "event_id", "user_id", "ts").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.last("event_id").over(whole).alias("last"), F.nth_value("event_id", 2).over(whole).alias("second"))


@op(f"SELECT event_id, {s6('sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)')} AS running, {s6('avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)')} AS moving, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS hour FROM events")
def win_frames(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    by_time = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    e = read(spark, sf_dir, "events", "event_id", "user_id", "ts", "value").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", e6(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("running"), e6(F.avg("value").over(w.rowsBetween(-2, 0))).alias("moving"), F.count(F.lit(1)).over(by_time).alias("hour"))


@op("SELECT o_orderkey, o_custkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
def sort_limit(spark, sf_dir):
    return read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20).select("o_orderkey", "o_custkey")


@op(with_base("cust_supp", "SELECT id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM base_ranks ORDER BY 2 DESC, id LIMIT 10"))
def topk_rank(spark, sf_dir):
    return base_ranks(spark, sf_dir, "cust_supp").select("id", rank_e9(F.col("rank")).alias("rank_e9")).orderBy(F.desc("rank_e9"), "id").limit(10)


@op(with_base("geo_tree", f"SELECT region, nation, k FROM (SELECT region, nation, row_number() OVER (PARTITION BY region ORDER BY CAST(floor(r * 1e9 + 0.5) AS BIGINT) DESC, nation) AS k FROM ({_GEO})) WHERE k <= 2"))
def topk_per_group(spark, sf_dir):
    w = Window.partitionBy("region").orderBy(F.desc(rank_e9(F.col("rank"))), "nation")
    return _nation_ranks(spark, sf_dir).withColumn("k", F.row_number().over(w).cast("bigint")).where("k <= 2").select("region", "nation", "k")


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT src, dst, CAST(NULL AS VARCHAR) AS op FROM eo UNION ALL SELECT src, dst, op FROM delta")
def set_union(spark, sf_dir):
    p = prepared(spark, sf_dir, "order_chain")
    return p.old.edges.unionByName(p.delta, allowMissingColumns=True)


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT src, dst FROM eo WHERE (src, dst) IN (SELECT (src, dst) FROM en)")
def set_intersect(spark, sf_dir):
    p = prepared(spark, sf_dir, "order_chain")
    return p.old.edges.intersectAll(p.new.edges)


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT src, dst, op FROM delta")
def set_except(spark, sf_dir):
    """Deletions and insertions between two snapshots."""
    p = prepared(spark, sf_dir, "order_chain")
    gone = p.old.edges.exceptAll(p.new.edges).withColumn("op", F.lit("-"))
    return gone.unionByName(diff_snapshots(p.old.edges, p.new.edges).where("op = '+'"))


# Functions


@op("SELECT page_id, substr(url, 1, 12) AS head, len(string_split(url, '/')) AS parts, len(regexp_extract_all(html, '<p>')) AS paragraphs, lower(trim(substr(html, 1, 15))) AS doctype, concat_ws('|', page_id::VARCHAR, 'x') AS tag, md5(url) AS h FROM pages")
def fn_string(spark, sf_dir):
    return read(spark, sf_dir, "pages", "page_id", "url", "html").select("page_id", F.substring("url", 1, 12).alias("head"), F.size(F.split("url", "/")).cast("bigint").alias("parts"), F.size(F.regexp_extract_all("html", F.lit("<p>"), 0)).cast("bigint").alias("paragraphs"), F.lower(F.trim(F.substring("html", 1, 15))).alias("doctype"), F.concat_ws("|", F.col("page_id").cast("string"), F.lit("x")).alias("tag"), F.md5("url").alias("h"))


@op("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def fn_url(spark, sf_dir):
    return read(spark, sf_dir, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/?#]+([^?#]*)", 1).alias("path"))


@op("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(o_orderdate AS DATE) + 7 AS week_later, year(o_orderdate) AS y, CAST(epoch(o_orderdate) AS BIGINT) AS unix FROM orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return read(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.trunc(d.cast("date"), "month").alias("month"), F.datediff(d, F.lit("1992-01-01")).cast("bigint").alias("days"), F.date_add(d.cast("date"), 7).alias("week_later"), F.year(d).cast("bigint").alias("y"), F.unix_seconds(d.cast("timestamp")).alias("unix"))


@op(f"SELECT event_id, {s6('abs(value - 20)')} AS a, {s6('greatest(value, 10)')} AS g, {s6('ln(value + 1)')} AS l, {s6('exp(-value)')} AS e, {s6('pow(value, 0.5)')} AS p, CAST(floor(value) AS BIGINT) AS f, CAST(sign(value - 20) AS BIGINT) AS s FROM events")
def fn_math(spark, sf_dir):
    v = F.col("value")
    return read(spark, sf_dir, "events", "event_id", "value").select("event_id", e6(F.abs(v - 20)).alias("a"), e6(F.greatest(v, F.lit(10.0))).alias("g"), e6(F.ln(v + 1)).alias("l"), e6(F.exp(-v)).alias("e"), e6(F.pow(v, F.lit(0.5))).alias("p"), F.floor(v).alias("f"), F.signum(v - 20).cast("bigint").alias("s"))


@op("SELECT vec_id, len(embedding) AS n, " + s6("list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x))") + " AS squares, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def fn_array(spark, sf_dir):
    from ..functions.vectors import dot

    v = F.col("embedding")
    return read(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.size(v).cast("bigint").alias("n"), e6(dot(v, v)).alias("squares"), F.size(F.filter(v, lambda x: x > 0)).cast("bigint").alias("positive"))


@op("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def fn_map(spark, sf_dir):
    """Counts by type as a map, read back by key."""
    n = read(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("bigint").alias("clicks"), F.size(F.map_keys("m")).cast("bigint").alias("kinds"))


@op("SELECT event_id, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k, '{\"k\":' || regexp_extract(props, '\"k\": *([0-9]+)', 1) || ',\"t\":\"' || event_type || '\"}' AS j FROM events")
def fn_json(spark, sf_dir):
    k = F.from_json("props", "k bigint")["k"]
    return read(spark, sf_dir, "events", "event_id", "props", "event_type").select("event_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.to_json(F.struct(k.alias("k"), F.col("event_type").alias("t"))).alias("j"))


@op("SELECT d.doc_id, coalesce(quality, -1) AS quality, nullif(toxic, 0) AS toxic, CASE WHEN quality IS NULL THEN 'unknown' WHEN quality = 1 THEN 'good' ELSE 'bad' END AS word FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def fn_null_cond(spark, sf_dir):
    d, labels = read(spark, sf_dir, "documents", "doc_id"), read(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    q = F.col("quality")
    return d.join(labels, "doc_id", "left").select("doc_id", F.coalesce(q, F.lit(-1)).alias("quality"), F.nullif("toxic", F.lit(0)).alias("toxic"), F.when(q.isNull(), "unknown").when(q == 1, "good").otherwise("bad").alias("word"))


@op("SELECT vec_id, " + s6("sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)))") + " AS length FROM embeddings")
def udf_arrow(spark, sf_dir):
    """A scalar function over Arrow batches."""

    @F.pandas_udf("double")
    def length(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float((x.astype("float64") ** 2).sum() ** 0.5))

    return read(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", e6(length("embedding")).alias("length"))


@op(f"SELECT event_type, {s6('sum(abs(value))')} AS l1, {s6('exp(avg(ln(value + 1)))')} AS geomean FROM events GROUP BY event_type")
def udaf_norm(spark, sf_dir):
    """Grouped aggregates over Arrow batches; each group is one batch, so groups must be bounded, as event types are per bench table."""
    import numpy as np

    @F.pandas_udf("double")
    def l1(v: pd.Series) -> float:
        return float(v.abs().sum())

    @F.pandas_udf("double")
    def geo(v: pd.Series) -> float:
        return float(np.exp(np.log(v + 1).mean()))

    return read(spark, sf_dir, "events", "event_type", "value").groupBy("event_type").agg(l1("value").alias("l1"), geo("value").alias("geomean")).select("event_type", e6(F.col("l1")).alias("l1"), e6(F.col("geomean")).alias("geomean"))


@op("SELECT page_id, unnest(regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)) AS url FROM pages")
def udtf_edges(spark, sf_dir):
    """A table function that unpacks a page's links."""
    import re

    @F.udtf(returnType="url string")
    class Links:
        def eval(self, html: str):
            for url in re.findall(r'<a href="([^"]*)"', html or ""):
                yield (url,)

    spark.udtf.register("links_of", Links)
    read(spark, sf_dir, "pages", "page_id", "html").createOrReplaceTempView("pages_for_links")
    return spark.sql("SELECT page_id, url FROM pages_for_links, LATERAL links_of(html)")


@op(with_base("part_flow", f"SELECT b.id, {s6('r / deg * 1000')} AS share, {s6('abs(r - 0.0005) / greatest(r, 0.0005)')} AS rel FROM base_ranks b JOIN dold d ON d.id = b.id"))
def sql_fn(spark, sf_dir):
    """Share and relative change as SQL functions."""
    p = prepared(spark, sf_dir, "part_flow")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rank_share(r DOUBLE, d BIGINT) RETURNS DOUBLE RETURN r / d")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION relative_change(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN abs(a - b) / greatest(a, b)")
    p.base.join(p.old.degrees, "id").createOrReplaceTempView("ranks_and_degrees")
    got = spark.sql("SELECT id, rank_share(rank, out_deg) * 1000 AS share, relative_change(rank, CAST(0.0005 AS DOUBLE)) AS rel FROM ranks_and_degrees")
    return got.select("id", e6(F.col("share")).alias("share"), e6(F.col("rel")).alias("rel"))


@op(f"SELECT src // 1000 AS conv, count(*) AS links, max(dst % 1000) AS furthest FROM ({oracles.EDGES['turn_chain']}) GROUP BY conv")
def map_arrow(spark, sf_dir):
    """A kernel over Arrow tables, one for each conversation."""
    import pyarrow.compute as pc

    def kernel(key, t):
        return pa.table({"conv": pa.array([key[0].as_py()]), "links": pa.array([t.num_rows]), "furthest": pa.array([max(x % 1000 for x in t.column("dst").to_pylist())] if pc.count(t.column("dst")).as_py() else [None], pa.int64())})

    edges = workloads.turn_chain(spark, sf_dir).withColumn("conv", F.floor(F.col("src") / 1000))
    return edges.groupBy("conv").applyInArrow(kernel, "conv bigint, links bigint, furthest bigint")


@op(f"WITH RECURSIVE e AS {edge_sql('turn_chain')}, r(id) AS (SELECT min(src) FROM e UNION SELECT dst FROM r JOIN e ON src = id) SELECT id FROM r")
def sql_recursive_reach(spark, sf_dir):
    """A closure in plain SQL, for small graphs."""
    edges_of(spark, sf_dir, "turn_chain").createOrReplaceTempView("chain_edges")
    return spark.sql("WITH RECURSIVE r(id) AS (SELECT min(src) FROM chain_edges UNION ALL SELECT dst FROM r JOIN chain_edges ON src = id) SELECT DISTINCT id FROM r")


# Ranks in use


@op(f"{_CS_NEW} SELECT a.id, CAST(floor(abs(a.r - b.r) * 1e9 + 0.5) AS BIGINT) AS moved FROM {oracles.last('run')} a JOIN base_ranks b ON a.id = b.id ORDER BY 2 DESC, 1 LIMIT 10")
def movers(spark, sf_dir):
    from .ranks import run

    new = run(spark, sf_dir, "cust_supp", "pruned").ranks.select("id", F.col("rank").alias("new"))
    both = base_ranks(spark, sf_dir, "cust_supp").join(new, "id")
    return both.select("id", rank_e9(F.abs(F.col("new") - F.col("rank"))).alias("moved")).orderBy(F.desc("moved"), "id").limit(10)


@op(with_base("cust_supp", f"SELECT c_mktsegment, {s6('quantile_cont(r, 0.5) * 1000')} AS median, {s6('quantile_cont(r, 0.9) * 1000')} AS p90 FROM base_ranks JOIN customer ON id = c_custkey * 2 GROUP BY c_mktsegment"))
def rank_percentile_by_segment(spark, sf_dir):
    c = read(spark, sf_dir, "customer", "c_custkey", "c_mktsegment").select((F.col("c_custkey") * 2).alias("id"), "c_mktsegment")
    p = base_ranks(spark, sf_dir, "cust_supp").join(c, "id").groupBy("c_mktsegment").agg(F.percentile("rank", F.array(F.lit(0.5), F.lit(0.9))).alias("p"))
    return p.select("c_mktsegment", e6(F.col("p")[0] * 1000).alias("median"), e6(F.col("p")[1] * 1000).alias("p90"))


@op(with_base("part_flow", f"SELECT dst AS id, {s6('avg(r) * 1000')} AS mean FROM eo JOIN base_ranks ON id = src WHERE src <> dst GROUP BY dst"))
def neighbour_rank(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return p.old.edges.where("src <> dst").join(p.base, F.col("src") == F.col("id")).groupBy("dst").agg(e6(F.avg("rank") * 1000).alias("mean")).select(F.col("dst").alias("id"), "mean")


@op(f"SELECT src, dst FROM {edge_sql('part_flow')} WHERE {oracles.number(chr(39) + '9' + chr(39), 'src::VARCHAR', 'dst::VARCHAR')} < 42949672")
def sample_edges(spark, sf_dir):
    """One edge in a hundred, the same in any engine."""
    return edges_of(spark, sf_dir, "part_flow").where(batches.md5_number(9, F.col("src").cast("string"), F.col("dst").cast("string")) < 42949672)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
