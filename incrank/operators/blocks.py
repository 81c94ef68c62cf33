"""Queries of the methods' building blocks, of batch construction, and of measures; each has its SQL beside it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles
from ..functions import measures
from ..functions.formulas import loopfree_rank, plain_rank, rank_e9, relative_change, spread_measure, teleport
from ..plans import graph, marking
from ..plans.experiments import settle_settings, spread_settings
from ..plans.kernel import pull_shares, push_shares
from ..plans.methods import carry_ranks
from ..plans.model import METHODS, RankConfig
from ..plans.prepared import prepared
from ..session import stored
from ..sources import batches, workloads
from . import ranks

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
E9 = "CAST(floor(({}) * 1e9 + 0.5) AS BIGINT)"


def op(sql: str | None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return add


def base_ctes(workload: str) -> str:
    parts = [oracles.graph_sql(workload), oracles.rounds_sql("base", "eo", "dold", oracles._UNIFORM, METHODS["cold"], RankConfig()), f"base_ranks AS MATERIALIZED (SELECT id, r FROM {oracles.last('base')})"]
    return f"WITH RECURSIVE {', '.join(parts)}"


def e9(c: Column) -> Column:
    return rank_e9(c)


def state_of(p) -> DataFrame:
    return p.base.join(p.new.degrees.withColumnRenamed("out_deg", "deg"), "id")


def _runs_sql(names) -> str:
    return " UNION ALL ".join(f"SELECT '{w}' AS workload, '{m}' AS method, * FROM ({oracles.run_sql(w, m, ranks.REFERENCE)})" for w in names for m in METHODS)


def measured(spark, sf_dir, names) -> DataFrame:
    """workload, method, supersteps, in_edges, affected, vertices, l1 of the methods' runs on each graph's first batch of 1e-3 of its edges."""
    rows = []
    for w in names:
        for m in METHODS:
            run = ranks.run(spark, sf_dir, w, m)
            one = measures.l1_error(run.ranks, ranks.reference(spark, sf_dir, w).ranks).first()[0]
            rows.append((w, m, run.supersteps, run.in_edges, run.ranks.where("ever_affected").count(), prepared(spark, sf_dir, w).new.n_vertices, one))
    return spark.createDataFrame(rows, "workload string, method string, supersteps int, in_edges bigint, affected bigint, vertices bigint, l1 double")


# Blocks of the methods


_SUMS = "sh AS (SELECT e.dst AS id, sum(b.r / d.deg) AS s FROM en e JOIN base_ranks b ON b.id = e.src JOIN dn d ON d.id = e.src GROUP BY e.dst)"


@op(f"{base_ctes('part_flow')}, {_SUMS} SELECT id, {E9.format('0.15 / (SELECT n FROM cnt) + 0.85 * s')} AS rank_e9 FROM sh")
def b_plain_formula(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return push_shares(p.new.edges, state_of(p)).select("id", e9(plain_rank(F.col("share_sum"), p.new.n_vertices, 0.85)).alias("rank_e9"))


@op(f"{base_ctes('cust_supp')}, {_SUMS} SELECT sh.id, {E9.format('(0.85 * (s - r / deg) + 0.15 / (SELECT n FROM cnt)) / (1 - 0.85 / deg)')} AS rank_e9 FROM sh JOIN base_ranks b ON b.id = sh.id JOIN dn ON dn.id = sh.id")
def b_loopfree_formula(spark, sf_dir):
    p = prepared(spark, sf_dir, "cust_supp")
    both = push_shares(p.new.edges, state_of(p)).join(state_of(p), "id")
    return both.select("id", e9(loopfree_rank(F.col("share_sum"), F.col("rank") / F.col("deg"), F.col("deg"), p.new.n_vertices, 0.85)).alias("rank_e9"))


@op(f"WITH {oracles.graph_sql('geo_tree')} SELECT n AS vertices, {E9.format('0.15 / n * 1000')} AS teleport, {E9.format('1.0 / n * 1000')} AS uniform FROM cnt")
def b_teleport_and_uniform(spark, sf_dir):
    n = prepared(spark, sf_dir, "geo_tree").new.n_vertices
    return spark.range(1).select(F.lit(n).cast("bigint").alias("vertices"), e9(teleport(n, 0.85) * 1000).alias("teleport"), e9(F.lit(1.0 / n) * 1000).alias("uniform"))


@op(f"{base_ctes('geo_tree')}, b AS (SELECT * FROM base_ranks WHERE id IN (SELECT src FROM eo WHERE src <> dst)) SELECT v.id, {E9.format('coalesce(r * (SELECT count(*) FROM b) / (SELECT n FROM cnt), 1.0 / (SELECT n FROM cnt))')} AS rank_e9 FROM v LEFT JOIN b ON b.id = v.id")
def b_carry_over_grown(spark, sf_dir):
    p = prepared(spark, sf_dir, "geo_tree")
    had = p.base.join(p.old.edges.where("src <> dst").select(F.col("src").alias("id")), "id", "left_semi")
    return carry_ranks(p.new.vertices, had, "grow")[0].select("id", e9(F.col("rank")).alias("rank_e9"))


@op(f"WITH {oracles.graph_sql('turn_chain')} SELECT src, dst FROM en")
def b_self_loops(spark, sf_dir):
    return prepared(spark, sf_dir, "turn_chain").new.edges


@op(f"WITH {oracles.graph_sql('part_flow')}, i AS (SELECT dst AS id, count(*) AS k FROM en GROUP BY dst) SELECT dn.id, deg AS out_deg, k AS in_deg FROM dn JOIN i ON i.id = dn.id")
def b_degrees(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return graph.out_degrees(p.new.edges).join(graph.in_degrees(p.new.edges), "id")


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT id, deg AS out_deg FROM dn")
def b_incremental_degrees(spark, sf_dir):
    p = prepared(spark, sf_dir, "order_chain")
    return graph.update_degrees(p.old.degrees, p.delta)


@op(f"WITH {oracles.graph_sql('order_chain')} SELECT src, dst, op FROM delta")
def b_normalized_batch(spark, sf_dir):
    return prepared(spark, sf_dir, "order_chain").delta


@op(f"WITH {oracles.graph_sql('geo_tree')} SELECT src, dst FROM en WHERE src <> dst")
def b_applied_batch(spark, sf_dir):
    p = prepared(spark, sf_dir, "geo_tree")
    return graph.apply_delta(p.old.edges, p.delta).where("src <> dst")


@op(f"WITH {oracles.graph_sql('geo_tree')} SELECT src, dst, '-' AS op FROM eo WHERE (src, dst) NOT IN (SELECT (src, dst) FROM en) UNION ALL SELECT src, dst, '+' FROM en WHERE (src, dst) NOT IN (SELECT (src, dst) FROM eo)")
def b_diff_snapshots(spark, sf_dir):
    p = prepared(spark, sf_dir, "geo_tree")
    return graph.diff_snapshots(p.old.edges, p.new.edges)


@op(f"WITH {oracles.graph_sql('part_flow')} SELECT dst AS id FROM eo WHERE src IN (SELECT src FROM delta) UNION SELECT dst FROM en WHERE src IN (SELECT src FROM delta)")
def b_seed_marks(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return marking.seed_frontier(p.old, p.new, p.delta)


@op(f"WITH {oracles.graph_sql('part_flow')} SELECT DISTINCT dst AS id FROM en WHERE src IN (SELECT src FROM delta)")
def b_spread(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return marking.spread(p.new.edges, marking.sources(p.delta))


_MOVED = f"{base_ctes('part_flow')}, {_SUMS}, c AS (SELECT b.id, r AS old, 0.15 / (SELECT n FROM cnt) + 0.85 * s AS new, deg FROM base_ranks b JOIN sh ON sh.id = b.id JOIN dn ON dn.id = b.id)"


@op(f"{_MOVED} SELECT id, abs(new - old) / greatest(old, new) > 1e-6 AS spreads_rel, abs(new - old) > 1e-9 AS spreads_abs, abs(new - old) / deg > 1e-10 AS spreads_share, abs(new - old) / greatest(old, new) <= 1e-6 AS settles FROM c")
def b_spread_and_settle(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    both = push_shares(p.new.edges, state_of(p)).join(state_of(p), "id").withColumn("new", plain_rank(F.col("share_sum"), p.new.n_vertices, 0.85))
    old, new, deg = F.col("rank"), F.col("new"), F.col("deg")
    return both.select("id", (spread_measure("rel", old, new, deg) > 1e-6).alias("spreads_rel"), (spread_measure("abs", old, new, deg) > 1e-9).alias("spreads_abs"), (spread_measure("share", old, new, deg) > 1e-10).alias("spreads_share"), marking.settle(relative_change(old, new), 1e-6).alias("settles"))


@op(f"WITH RECURSIVE {oracles.graph_sql('order_chain')}, r(id) AS (SELECT DISTINCT src FROM delta UNION SELECT e.dst FROM r JOIN en e ON e.src = r.id) SELECT id FROM r")
def b_reachable(spark, sf_dir):
    p = prepared(spark, sf_dir, "order_chain")
    return marking.reachable(p.new.edges, marking.sources(p.delta)).select("id")


def _reach_sql(scope: str) -> str:
    return oracles.method_ctes("supp_part", "reach", scope=scope) + " SELECT id FROM seed"


@op(_reach_sql("either"))
def b_reach_either(spark, sf_dir):
    p = prepared(spark, sf_dir, "supp_part")
    return marking.reach_set(p.old, p.new, p.delta, "either")


@op(_reach_sql("union"))
def b_reach_union(spark, sf_dir):
    p = prepared(spark, sf_dir, "supp_part")
    return marking.reach_set(p.old, p.new, p.delta, "union")


@op(f"{base_ctes('part_flow')}, {_SUMS} SELECT id, {E9.format('s')} AS s FROM sh WHERE id IN (SELECT dst FROM eo WHERE src IN (SELECT src FROM delta) UNION SELECT dst FROM en WHERE src IN (SELECT src FROM delta))")
def b_pull_shares(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return pull_shares(p.new.edges, state_of(p), marking.seed_frontier(p.old, p.new, p.delta)).select("id", e9(F.col("share_sum")).alias("s"))


@op(f"{base_ctes('part_flow')}, {_SUMS} SELECT id, {E9.format('s')} AS s FROM sh")
def b_push_shares(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return push_shares(p.new.edges, state_of(p)).select("id", e9(F.col("share_sum")).alias("s"))


# Batches and graphs


def _temporal(spark, sf_dir, name: str) -> tuple[DataFrame, int]:
    t = stored(workloads.build(spark, sf_dir, name), name)
    return t, t.count()


_TE = f"WITH te AS ({oracles.EDGES['event_flow']}), k AS (SELECT count(*) AS n, CAST(floor(0.9 * count(*)) AS BIGINT) AS k0, greatest(1, CAST(round(1e-3 * count(*)) AS BIGINT)) AS b FROM te)"


@op(f"{_TE} SELECT DISTINCT src, dst FROM te, k WHERE seq <= k0 AND src <> dst")
def c_preload_split(spark, sf_dir):
    t, n = _temporal(spark, sf_dir, "event_flow")
    return batches.preload_split(t, n)


@op(f"{_TE} SELECT src, dst, '+' AS op, CAST((seq - 1 - k0) // b AS INTEGER) AS batch FROM te, k WHERE seq > k0 AND seq <= k0 + 100 * b")
def c_slice_batches(spark, sf_dir):
    t, n = _temporal(spark, sf_dir, "event_flow")
    return batches.slice_batches(t, n, 1e-3)


_IX = f"WITH e AS (SELECT DISTINCT src, dst FROM ({oracles.EDGES['geo_tree']}) WHERE src <> dst), ix AS (SELECT id, row_number() OVER (ORDER BY id) AS place FROM (SELECT src AS id FROM e UNION SELECT dst FROM e))"


@op(f"""{_IX}, d AS (SELECT {oracles.number("'7'", "'s'", "i::VARCHAR")} % (SELECT count(*) FROM ix) + 1 AS ps, {oracles.number("'7'", "'d'", "i::VARCHAR")} % (SELECT count(*) FROM ix) + 1 AS pd FROM (SELECT unnest(range(200)) AS i))
    SELECT a.id AS src, b.id AS dst, '+' AS op FROM d JOIN ix a ON a.place = ps JOIN ix b ON b.place = pd""")
def c_random_inserts(spark, sf_dir):
    e = workloads.geo_tree(spark, sf_dir)
    return batches.random_inserts(workloads.universe(e), 200, 7)


@op(f"""{_IX} SELECT src, dst, '-' AS op FROM e ORDER BY {oracles.number("'7'", "'x'", "src::VARCHAR", "dst::VARCHAR")}, src, dst LIMIT 50""")
def c_random_deletes(spark, sf_dir):
    return batches.random_deletes(workloads.geo_tree(spark, sf_dir).distinct(), 50, 7)


@op(f"WITH {oracles.graph_sql('turn_chain', 1e-1)} SELECT src, dst, op FROM raw")
def c_random_batch(spark, sf_dir):
    e = stored(workloads.turn_chain(spark, sf_dir).where("src <> dst").distinct(), "turns")
    return batches.random_batch(workloads.universe(e), e, e.count(), 1e-1)


_USER_TYPE = "SELECT user_id AS src, length(event_type)::BIGINT AS dst, ts FROM events"


def _user_type(spark, sf_dir):
    return workloads.read(spark, sf_dir, "events", "user_id", "event_type", "ts").select(F.col("user_id").alias("src"), F.length("event_type").cast("bigint").alias("dst"), "ts")


@op(f"SELECT src, dst, '+' AS op, CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS batch, count(*) AS times FROM ({_USER_TYPE}) GROUP BY ALL")
def c_window_batches(spark, sf_dir):
    return batches.window_batches(_user_type(spark, sf_dir)).withColumn("batch", F.unix_seconds("batch"))


@op(f"""WITH s AS (SELECT DISTINCT src, dst, CAST(floor(epoch_us(ts) / 86400000000) AS BIGINT) AS step FROM ({_USER_TYPE})),
    r AS (SELECT *, lag(step) OVER w AS l, lead(step) OVER w AS n FROM s WINDOW w AS (PARTITION BY src, dst ORDER BY step))
    SELECT src, dst, '+' AS op, step AS batch FROM r WHERE l IS NULL OR step - l > 2 UNION ALL SELECT src, dst, '-', step + 3 FROM r WHERE n IS NULL OR n - step > 2""")
def c_sliding_batches(spark, sf_dir):
    return batches.sliding_batches(_user_type(spark, sf_dir), 2 * 86400, 86400)


@op(f"SELECT DISTINCT src, dst FROM ({oracles.EDGES['user_item']}) WHERE src <> dst")
def c_static_edges(spark, sf_dir):
    return graph.static_edges(workloads.user_item(spark, sf_dir))


@op("SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM (SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS key FROM pages)")
def c_encode_vertices(spark, sf_dir):
    hosts = workloads.read(spark, sf_dir, "pages", "url").select(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"))
    return graph.encode_vertices(hosts, ["host"])


def _profile_sql(name: str) -> str:
    return f"""WITH te AS ({oracles.EDGES[name]}), e AS (SELECT DISTINCT src, dst FROM te WHERE src <> dst), v AS (SELECT src AS id FROM te UNION SELECT dst FROM te)
        SELECT '{name}' AS workload, (SELECT count(*) FROM v) AS vertices, (SELECT count(*) FROM te) AS temporal_edges, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM v WHERE id NOT IN (SELECT src FROM e)) AS sinks, (SELECT max(k) FROM (SELECT count(*) AS k FROM e GROUP BY dst)) AS max_in_degree"""


@op(" UNION ALL ".join(f"SELECT * FROM ({_profile_sql(n)})" for n in oracles.EDGES))
def c_profiles(spark, sf_dir):
    """Sizes of all workloads."""
    out = None
    for name in workloads.BUILDERS:
        t = stored(workloads.build(spark, sf_dir, name), name)
        row = graph.profile(t).select(F.lit(name).alias("workload"), "vertices", "temporal_edges", "edges", "sinks", "max_in_degree")
        out = row if out is None else out.unionByName(row)
    return out


@op(f"SELECT src, dst FROM (SELECT src, dst FROM ({oracles.EDGES['order_chain']}) UNION SELECT dst, src FROM ({oracles.EDGES['order_chain']}))")
def c_symmetrize(spark, sf_dir):
    return graph.symmetrize(workloads.order_chain(spark, sf_dir))


# Measures


def _two_runs(workload: str, body: str) -> str:
    ref = oracles.rounds_sql("ref", "en", "dn", oracles._UNIFORM, METHODS["cold"], ranks.REFERENCE)
    return f"{oracles.method_ctes(workload, 'pruned')}, {ref}, x AS (SELECT id, r FROM {oracles.last('run')}), y AS (SELECT id, r FROM {oracles.last('ref')}) {body}"


def _pruned_and_reference(spark, sf_dir, workload: str):
    p = prepared(spark, sf_dir, workload)
    return ranks.run(spark, sf_dir, workload, "pruned").ranks, ranks.reference(spark, sf_dir, workload).ranks, p


@op(_two_runs("supp_part", f"SELECT {E9.format('sum(abs(x.r - y.r)) * 10')} AS l1, {E9.format('sqrt(sum((x.r - y.r) * (x.r - y.r))) * 10')} AS l2, {E9.format('max(abs(x.r - y.r)) * 10')} AS linf FROM x JOIN y ON x.id = y.id"))
def a_error_norms(spark, sf_dir):
    a, b, _ = _pruned_and_reference(spark, sf_dir, "supp_part")
    one = measures.l1_error(a, b).join(F.broadcast(measures.l2_error(a, b))).join(F.broadcast(measures.linf_change(a, b)))  # one row each
    return one.select(*(e9(F.col(c) * 10).alias(c) for c in ("l1", "l2", "linf")))


@op(f"{base_ctes('part_flow')}, {_SUMS} SELECT {E9.format('sum(abs(0.15 / (SELECT n FROM cnt) + 0.85 * coalesce(s, 0) - r)) / 0.15')} AS bound FROM base_ranks b LEFT JOIN sh ON sh.id = b.id")
def a_residual_bound(spark, sf_dir):
    p = prepared(spark, sf_dir, "part_flow")
    return measures.residual_bound(p.new.edges, p.new.degrees, p.base, p.new.n_vertices, 0.85).select(e9(F.col("bound")).alias("bound"))


@op(f"{base_ctes('web_links')} SELECT {E9.format('sum(r)')} AS mass, {E9.format('min(r)')} AS least FROM base_ranks")
def a_rank_mass(spark, sf_dir):
    return measures.mass(prepared(spark, sf_dir, "web_links").base).select(e9(F.col("mass")).alias("mass"), e9(F.col("least")).alias("least"))


@op(_two_runs("part_flow", f"SELECT {E9.format('count(*) / 100.0')} AS overlap FROM (SELECT id FROM x ORDER BY r DESC, id LIMIT 100) JOIN (SELECT id FROM y ORDER BY r DESC, id LIMIT 100) USING (id)"))
def a_topk_overlap(spark, sf_dir):
    a, b, _ = _pruned_and_reference(spark, sf_dir, "part_flow")
    return measures.topk_overlap(a, b, 100).select(e9(F.col("overlap")).alias("overlap"))


@op(_two_runs("part_flow", "SELECT CAST(sum(abs(p - q)) AS BIGINT) AS footrule FROM (SELECT id, row_number() OVER (ORDER BY -r, id) AS p FROM x) JOIN (SELECT id, row_number() OVER (ORDER BY -r, id) AS q FROM y) USING (id)"))
def a_footrule(spark, sf_dir):
    a, b, _ = _pruned_and_reference(spark, sf_dir, "part_flow")
    return measures.footrule(a, b)


_WORK = ("event_flow", "part_flow", "order_chain")


@op(f"WITH w AS ({_runs_sql(_WORK)}), g AS (SELECT method, exp(avg(ln(greatest(in_edges, 1)))) AS x FROM w GROUP BY method) SELECT method, {E9.format("(SELECT x FROM g WHERE method = 'cold') / x")} AS speedup FROM g")
def a_geomean_speedup(spark, sf_dir):
    """Ratio of the geometric means over graphs, of the edges that three graphs' runs needed."""
    g = measures.geomean(measured(spark, sf_dir, _WORK).withColumn("in_edges", F.greatest("in_edges", F.lit(1)).cast("double")), ["method"], "in_edges").withColumn("all", F.lit(1))
    return measures.speedup(g, "cold", ["all"], column="in_edges").select("method", e9(F.col("speedup")).alias("speedup"))


@op(f"WITH w AS ({_runs_sql(_WORK)}) SELECT w.method, {E9.format('avg(greatest(c.in_edges, 1) / greatest(w.in_edges, 1))')} AS mean_speedup FROM w JOIN w c ON c.workload = w.workload AND c.method = 'cold' GROUP BY w.method")
def a_mean_speedup(spark, sf_dir):
    """The arithmetic mean of ratios to cold, of the same runs."""
    ratios = measures.speedup(measured(spark, sf_dir, _WORK).withColumn("in_edges", F.greatest("in_edges", F.lit(1))), "cold", ["workload"], column="in_edges")
    return measures.mean_speedup(ratios).select("method", e9(F.col("mean_speedup")).alias("mean_speedup"))


_SPEEDUP = "one.seconds / t.seconds"


@op(f"""WITH n AS (SELECT event_type AS method, cores, user_id % cores AS core, count(*) AS n FROM events, (VALUES (1), (4), (16)) c(cores) GROUP BY ALL), t AS (SELECT method, cores, CAST(max(n) AS DOUBLE) AS seconds FROM n GROUP BY method, cores)
    SELECT t.method, t.cores, {E9.format(_SPEEDUP)} AS speedup, CASE WHEN t.cores > 1 THEN {E9.format(f"pow({_SPEEDUP}, 1 / log2(t.cores))")} END AS per_doubling FROM t JOIN t one ON one.method = t.method AND one.cores = 1""")
def a_scaling_table(spark, sf_dir):
    """How much faster each type's events can be taken in if users are dealt over more cores, at one second an event: the fullest core decides."""
    events = workloads.read(spark, sf_dir, "events", "event_type", "user_id")
    dealt = events.select(F.col("event_type").alias("method"), "user_id", F.explode(F.array(*map(F.lit, (1, 4, 16)))).alias("cores"))
    loads = dealt.groupBy("method", "cores", F.pmod("user_id", "cores").alias("core")).count()
    t = measures.scaling_table(loads.groupBy("method", "cores").agg(F.max("count").cast("double").alias("seconds")))
    return t.select("method", "cores", e9(F.col("speedup")).alias("speedup"), e9(F.col("per_doubling")).alias("per_doubling"))


@op(f"WITH w AS ({_runs_sql(('part_flow',))}) SELECT w.workload, w.method, CAST(floor(w.l1 / c.l1 * 100 + 0.5) AS BIGINT) AS ratio_e2 FROM w JOIN w c ON c.workload = w.workload AND c.method = 'cold'")
def a_error_ratio(spark, sf_dir):
    """Errors over cold's; under 1 is what is asked for."""
    return measures.error_ratio(measured(spark, sf_dir, ("part_flow",)), ["workload"]).select("workload", "method", F.floor(F.col("ratio") * 100 + 0.5).cast("bigint").alias("ratio_e2"))


# Experiments


@op(None)
def e_worked_example(spark, sf_dir):
    from ..plans.experiments import worked_example

    return worked_example(spark)


_RUN = "workload, method, CAST(supersteps AS INTEGER) AS supersteps, in_edges, affected, vertices, CAST(floor(l1 * 1e10 + 0.5) AS BIGINT) AS l1_e10"


def _runs(spark, sf_dir, names) -> DataFrame:
    return measured(spark, sf_dir, names).withColumn("l1_e10", F.floor(F.col("l1") * 1e10 + 0.5).cast("bigint")).drop("l1")


@op(f"SELECT {_RUN} FROM ({_runs_sql(workloads.TEMPORAL)})")
def e_replay_temporal(spark, sf_dir):
    """All temporal graphs and methods on the first slice after the preload: rounds, work, reach, error. ``replay_temporal`` has all sizes and 100 slices, with times."""
    return _runs(spark, sf_dir, workloads.TEMPORAL)


@op(f"SELECT {_RUN} FROM ({_runs_sql(workloads.STATIC)})")
def e_replay_random(spark, sf_dir):
    """All static graphs and methods on a random batch. ``replay_random`` has all sizes, with times."""
    return _runs(spark, sf_dir, workloads.STATIC)


_ALL = (*workloads.TEMPORAL, *workloads.STATIC)


@op(f"SELECT workload, {', '.join(f'max(CASE WHEN method = {chr(39)}{m}{chr(39)} THEN affected END) AS {m}' for m in ('reach', 'frontier', 'pruned'))}, max(vertices) AS vertices FROM ({_runs_sql(_ALL)}) GROUP BY workload")
def e_affected_report(spark, sf_dir):
    """Vertices ever affected, by graph and method."""
    return measured(spark, sf_dir, _ALL).groupBy("workload").pivot("method", ["reach", "frontier", "pruned"]).agg(F.max("affected")).join(F.broadcast(measured(spark, sf_dir, _ALL).groupBy("workload").agg(F.max("vertices").alias("vertices"))), "workload")


@op(f"SELECT method, workload, count(*) AS graphs, CAST(sum(in_edges) AS BIGINT) AS in_edges, CAST(sum(supersteps) AS BIGINT) AS supersteps FROM ({_runs_sql(_ALL)}) GROUP BY ROLLUP (method, workload)")
def e_graph_breakdown(spark, sf_dir):
    """Work by method and graph, with subtotals."""
    return measured(spark, sf_dir, _ALL).rollup("method", "workload").agg(F.count(F.lit(1)).alias("graphs"), F.sum("in_edges").alias("in_edges"), F.sum("supersteps").alias("supersteps"))


@op(None)
def e_advise_report(spark, sf_dir):
    """The least work among methods that are no less accurate than cold, and what the rules of thumb say, for each graph."""
    from ..plans import experiments as x

    return x.advise_report(measured(spark, sf_dir, _ALL).withColumn("rows_scanned", F.col("in_edges")))


@op(None)
def e_batch_series(spark, sf_dir):
    """Time, error and work of three consecutive batches, for all methods, on the smallest temporal graph."""
    from ..plans import experiments as x

    return x.batch_series(x.replay_temporal(spark, sf_dir, ("event_flow",), fractions=(1e-3,), n_batches=3, reference=ranks.REFERENCE))


@op(None)
def e_scaling(spark, sf_dir):
    """Seconds of frontier and pruned on one, two and four cores, with speedups and gains per doubling."""
    from ..plans import experiments as x

    return x.scaling_report(spark, sf_dir, "event_flow", (1, 2, 4), 1e-3)


def _sweep_sql(settings) -> str:
    return " UNION ALL ".join(f"SELECT '{w}' AS workload, {k} AS setting, {_SWEPT} FROM ({oracles.run_sql(w, plan.name, ranks.REFERENCE, cfg=cfg, fraction=1e-5)})" for w in workloads.TEMPORAL for k, (plan, cfg) in enumerate(settings))


_SWEPT = "CAST(supersteps AS INTEGER) AS supersteps, in_edges, affected, CAST(floor(l1 * 1e10 + 0.5) AS BIGINT) AS l1_e10"


def _sweep(spark, sf_dir, settings) -> DataFrame:
    from ..plans import experiments as x

    return x.sweep_work(spark, sf_dir, workloads.TEMPORAL, settings, 1e-5).selectExpr("workload", "setting", "supersteps", "in_edges", "affected", "CAST(floor(l1 * 1e10 + 0.5) AS BIGINT) AS l1_e10")


@op(_sweep_sql(spread_settings()))
def e_sweep_spread(spark, sf_dir):
    """Three measures of change over all their tolerances, on all temporal graphs, at a batch of 1e-5 of the edges."""
    return _sweep(spark, sf_dir, spread_settings())


@op(_sweep_sql(settle_settings()))
def e_sweep_settle(spark, sf_dir):
    """All settle tolerances of all three spread tolerances, likewise."""
    return _sweep(spark, sf_dir, settle_settings())


@op(oracles.rank_sql("part_flow", "cold").replace("ever AS ever_affected", "true AS ever_affected").replace("r * 1e9 + 0.5", "r * 1e8 + 0.5").replace("rank_e9", "rank_e8"))
def variant_block_async(spark, sf_dir):
    """Block-asynchronous rounds end at the synchronous fixed point, to the eighth digit."""
    from ..plans.blockasync import block_async_rank

    p = prepared(spark, sf_dir, "part_flow")
    got = block_async_rank(p.new, RankConfig(tau=1e-12), p.base).ranks
    return got.select("id", F.floor(F.col("rank") * 1e8 + 0.5).cast("bigint").alias("rank_e8"), "ever_affected")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
