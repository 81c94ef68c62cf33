"""SQL, for DuckDB, that computes what the queries compute: graphs, batches and all rounds of all methods."""

from __future__ import annotations

from .plans.model import METHODS, MethodPlan, RankConfig
from .sources.workloads import EXAMPLE_BATCH, EXAMPLE_EDGES, TEMPORAL

_LINES = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey"

#: src, dst, seq of temporal graphs; src, dst of static ones.
EDGES = {
    "event_flow": "SELECT src, dst, row_number() OVER (ORDER BY ts, event_id) AS seq FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst, ts, event_id FROM events) WHERE dst IS NOT NULL",
    "user_item": "SELECT src, dst, row_number() OVER (ORDER BY ts, event_id) AS seq FROM (SELECT user_id * 2 AS src, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) * 2 + 1 AS dst, ts, event_id FROM events)",
    "part_flow": f"SELECT src, dst, row_number() OVER (ORDER BY {_LINES}) AS seq FROM (SELECT *, l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY {_LINES}) AS dst FROM lineitem) WHERE dst IS NOT NULL",
    "cust_supp": f"SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst, row_number() OVER (ORDER BY o_orderdate, {_LINES}) AS seq FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "supp_part": f"SELECT l_suppkey * 2 AS src, l_partkey * 2 + 1 AS dst, row_number() OVER (ORDER BY {_LINES}) AS seq FROM lineitem",
    "order_chain": "SELECT * FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst FROM orders) WHERE dst IS NOT NULL",
    "turn_chain": "SELECT * FROM (SELECT conv_id * 1000 + turn AS src, lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL",
    "web_links": """SELECT a.id AS src, b.id AS dst FROM (SELECT DISTINCT page, target FROM (SELECT 'p:' || page_id AS page, 'u:' || unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) AS target FROM pages)) l
        JOIN (SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM (SELECT 'p:' || page_id AS key FROM pages WHERE len(regexp_extract_all(html, '<a href="([^"]*)"', 1)) > 0 UNION SELECT 'u:' || unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) FROM pages)) a ON a.key = l.page
        JOIN (SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM (SELECT 'p:' || page_id AS key FROM pages WHERE len(regexp_extract_all(html, '<a href="([^"]*)"', 1)) > 0 UNION SELECT 'u:' || unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) FROM pages)) b ON b.key = l.target""",
    "knn": """SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 12) DESC, b.vec_id) AS place
        FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE place <= 8""",
    "geo_tree": "SELECT c_custkey * 4 AS src, c_nationkey::BIGINT * 4 + 1 AS dst FROM customer UNION ALL SELECT s_suppkey * 4 + 2, s_nationkey::BIGINT * 4 + 1 FROM supplier UNION ALL SELECT n_nationkey::BIGINT * 4 + 1, n_regionkey::BIGINT * 4 + 3 FROM nation",
}


def number(*parts: str) -> str:
    """32 bits of an md5."""
    return f"('0x' || substr(md5({' || chr(58) || '.join(parts)}), 1, 8))::UBIGINT::BIGINT"


def graph_sql(workload: str, fraction: float = 1e-3, seed: int = 42, loops: bool = True) -> str:
    """CTEs: v (id), cnt (n), eo and en (src, dst; old and new), dn and dold (id, deg), delta (src, dst, op)."""
    if workload == "example16":
        values = lambda rows: ", ".join(str(r).replace("'", "'") for r in rows)
        head = f"""te AS (SELECT * FROM (VALUES {values(EXAMPLE_EDGES)}) t(src, dst)), v AS (SELECT unnest(range(1, 17)) AS id), e0 AS (SELECT * FROM te),
            raw AS (SELECT * FROM (VALUES {values(EXAMPLE_BATCH)}) t(src, dst, op))"""
    elif workload in TEMPORAL:
        head = f"""te AS MATERIALIZED ({EDGES[workload]}), v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM te UNION ALL SELECT dst FROM te)),
            tot AS (SELECT count(*) AS n, CAST(floor(0.9 * count(*)) AS BIGINT) AS k0, greatest(1, CAST(round({fraction!r} * count(*)) AS BIGINT)) AS b FROM te),
            e0 AS MATERIALIZED (SELECT DISTINCT src, dst FROM te, tot WHERE seq <= k0 AND src <> dst),
            raw AS (SELECT src, dst, '+' AS op FROM te, tot WHERE seq > k0 AND seq <= k0 + b)"""
    else:
        head = f"""te AS MATERIALIZED ({EDGES[workload]}), v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM te UNION ALL SELECT dst FROM te)),
            e0 AS MATERIALIZED (SELECT DISTINCT src, dst FROM te WHERE src <> dst),
            ix AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY id) AS place FROM v),
            tot AS (SELECT greatest(1, CAST(round({fraction!r} * count(*)) AS BIGINT)) AS m, CAST(ceil(0.8 * greatest(1, CAST(round({fraction!r} * count(*)) AS BIGINT))) AS BIGINT) AS ins FROM e0),
            dr AS (SELECT {number(f"'{seed}'", "'s'", "i::VARCHAR")} % (SELECT count(*) FROM v) + 1 AS ps, {number(f"'{seed}'", "'d'", "i::VARCHAR")} % (SELECT count(*) FROM v) + 1 AS pd FROM (SELECT unnest(range((SELECT ins FROM tot))) AS i)),
            raw AS (SELECT a.id AS src, b.id AS dst, '+' AS op FROM dr JOIN ix a ON a.place = ps JOIN ix b ON b.place = pd
                UNION ALL SELECT src, dst, '-' FROM (SELECT src, dst, row_number() OVER (ORDER BY {number(f"'{seed}'", "'x'", "src::VARCHAR", "dst::VARCHAR")}, src, dst) AS k FROM e0) , tot WHERE k <= m - ins)"""
    own = " UNION ALL SELECT id, id FROM v" if loops else ""
    return f"""{head},
        one AS (SELECT src, dst, min(op) AS op FROM raw WHERE src <> dst GROUP BY src, dst),
        delta AS MATERIALIZED (SELECT * FROM one WHERE op = '+' AND (src, dst) NOT IN (SELECT (src, dst) FROM e0) UNION ALL SELECT * FROM one WHERE op = '-' AND (src, dst) IN (SELECT (src, dst) FROM e0)),
        cnt AS MATERIALIZED (SELECT count(*) AS n FROM v),
        eo AS MATERIALIZED (SELECT src, dst FROM e0{own}),
        en AS MATERIALIZED (SELECT src, dst FROM e0 WHERE (src, dst) NOT IN (SELECT (src, dst) FROM delta WHERE op = '-') UNION ALL SELECT src, dst FROM delta WHERE op = '+'{own}),
        dold AS MATERIALIZED (SELECT v.id, count(src) AS deg FROM v LEFT JOIN eo ON eo.src = v.id GROUP BY v.id),
        dn AS MATERIALIZED (SELECT v.id, count(src) AS deg FROM v LEFT JOIN en ON en.src = v.id GROUP BY v.id)"""


def rounds_sql(name: str, edges: str, degrees: str, start: str, plan: MethodPlan, cfg: RankConfig) -> str:
    """A recursive CTE of all rounds. ``start`` gives id, r, aff."""
    a, base = repr(cfg.alpha), f"({1 - cfg.alpha!r} / (SELECT n FROM cnt))"
    sinks = f" + (SELECT coalesce(sum(q.r), 0) FROM {name} q JOIN {degrees} dq ON dq.id = q.id WHERE dq.deg = 0) / (SELECT n FROM cnt)" if cfg.dangling == "redistribute" else ""
    share = f"(coalesce(k, 0){sinks})"
    plain = f"{base} + {a} * {share}"
    new = f"CASE WHEN d.deg > 0 THEN ({a} * ({share} - p.r / d.deg) + {base}) / (1.0 - {a} / d.deg) ELSE {plain} END" if plan.formula == "loopfree" else plain
    measure = {"rel": "rel", "abs": "dr", "share": "dr / greatest(deg, 1)"}[cfg.expand_by]
    hot = f"was AND {measure} > {cfg.tau_f!r}" if plan.expand else "false"
    settled = f"was AND rel <= {cfg.tau_p!r}" if plan.prune else "false"
    norm = {"linf": "max(dr)", "l1": "sum(dr)", "l2": "sqrt(sum(dr * dr))"}[cfg.norm]
    factor = f" * (SELECT n FROM cnt) / {cfg.scale_vertices!r}" if cfg.tolerance_scale == "mean_rank" else ""
    return f"""{name}(it, id, r, aff, was, dr, ever, hot, settled) AS (
        SELECT 0, id, CAST(r AS DOUBLE), aff, true, 1e300::DOUBLE, aff, false, false FROM ({start})
        UNION ALL
        (WITH sh AS (SELECT e.dst AS id, sum(p.r / d.deg) AS k FROM {edges} e JOIN {name} p ON p.id = e.src JOIN {degrees} d ON d.id = e.src GROUP BY e.dst),
            ch AS (SELECT p.it, p.id, p.r AS old, p.aff AS was, p.ever, d.deg, CASE WHEN p.aff THEN {new} ELSE p.r END AS new FROM {name} p JOIN {degrees} d ON d.id = p.id LEFT JOIN sh ON sh.id = p.id),
            me AS (SELECT *, abs(new - old) AS dr, abs(new - old) / greatest(old, new) AS rel FROM ch),
            mh AS (SELECT *, ({hot}) AS hot, ({settled}) AS settled FROM me),
            mk AS (SELECT DISTINCT e.dst AS id FROM mh JOIN {edges} e ON e.src = mh.id WHERE mh.hot)
        SELECT mh.it + 1, mh.id, mh.new, (mh.was AND NOT mh.settled) OR mk.id IS NOT NULL, mh.was, CASE WHEN mh.was THEN mh.dr ELSE 0 END, mh.ever OR mk.id IS NOT NULL, mh.hot, mh.settled
        FROM mh LEFT JOIN mk ON mk.id = mh.id
        WHERE (SELECT {norm} FROM {name} WHERE was){factor} > {cfg.tau!r} AND (SELECT bool_or(aff) FROM {name}) AND mh.it < {cfg.max_supersteps}))"""


def last(name: str) -> str:
    return f"(SELECT * FROM {name} WHERE it = (SELECT max(it) FROM {name}))"


_UNIFORM = "SELECT id, 1.0::DOUBLE / (SELECT n FROM cnt) AS r, true AS aff FROM v"
_CARRIED = "SELECT id, r, true AS aff FROM base_ranks"


def method_ctes(workload: str, method: str, cfg: RankConfig | None = None, fraction: float = 1e-3, base_cfg: RankConfig | None = None, scope: str = "either", loops: bool = True, plan: MethodPlan | None = None) -> str:
    """All CTEs up to ``run``, the rounds of one method after one batch, from old ranks made by a cold run."""
    cfg, base_cfg, plan = cfg or RankConfig(), base_cfg or RankConfig(), plan or METHODS[method]
    parts = [graph_sql(workload, fraction, loops=loops), rounds_sql("base", "eo", "dold", _UNIFORM, METHODS["cold"], base_cfg), f"base_ranks AS MATERIALIZED (SELECT id, r FROM {last('base')})"]
    if plan.seed == "reach":
        if scope == "union":
            parts += ["eu AS (SELECT * FROM eo UNION SELECT * FROM en)", "seed(id) AS (SELECT DISTINCT src FROM delta UNION SELECT e.dst FROM seed JOIN eu e ON e.src = seed.id)"]
        else:
            parts += [f"reach_{x}(id) AS (SELECT DISTINCT src FROM delta UNION SELECT e.dst FROM reach_{x} r JOIN {x} e ON e.src = r.id)" for x in ("eo", "en")]
            parts += ["seed AS MATERIALIZED (SELECT id FROM reach_eo UNION SELECT id FROM reach_en)"]
    elif plan.seed == "neighbours":
        parts += ["seed AS MATERIALIZED (SELECT dst AS id FROM eo WHERE src IN (SELECT src FROM delta) UNION SELECT dst FROM en WHERE src IN (SELECT src FROM delta))"]
    start = {"all": _CARRIED if plan.warm else _UNIFORM}.get(plan.seed, "SELECT id, r, id IN (SELECT id FROM seed) AS aff FROM base_ranks")
    parts.append(rounds_sql("run", "en", "dn", start, plan, cfg))
    return "WITH RECURSIVE " + ", ".join(parts)


def rank_sql(workload: str, method: str, **kw) -> str:
    return f"{method_ctes(workload, method, **kw)} SELECT id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9, ever AS ever_affected FROM {last('run')}"


def chained_sql(workload: str, method: str, n: int, fraction: float = 1e-3) -> str:
    """Ranks after the first ``n`` slices of a temporal graph, each run from the ranks of the one before."""
    cfg, plan = RankConfig(), METHODS[method]
    parts = [f"""te AS MATERIALIZED ({EDGES[workload]}), v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM te UNION ALL SELECT dst FROM te)), cnt AS MATERIALIZED (SELECT count(*) AS n FROM v),
        tot AS (SELECT CAST(floor(0.9 * count(*)) AS BIGINT) AS k0, greatest(1, CAST(round({fraction!r} * count(*)) AS BIGINT)) AS b FROM te)"""]
    for k in range(n + 1):
        parts += [f"e_{k} AS MATERIALIZED (SELECT DISTINCT src, dst FROM te, tot WHERE seq <= k0 + {k} * b AND src <> dst UNION ALL SELECT id, id FROM v)", f"d_{k} AS MATERIALIZED (SELECT src AS id, count(*) AS deg FROM e_{k} GROUP BY src)"]
        if not k:
            parts.append(rounds_sql("run_0", "e_0", "d_0", _UNIFORM, METHODS["cold"], cfg))
            continue
        came = f"(SELECT src FROM e_{k} WHERE (src, dst) NOT IN (SELECT (src, dst) FROM e_{k - 1}))"
        parts.append(f"s_{k} AS MATERIALIZED (SELECT dst AS id FROM e_{k} WHERE src IN {came})")
        parts.append(rounds_sql(f"run_{k}", f"e_{k}", f"d_{k}", f"SELECT id, r, id IN (SELECT id FROM s_{k}) AS aff FROM {last(f'run_{k - 1}')}", plan, cfg))
    return f"WITH RECURSIVE {', '.join(parts)} SELECT id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM {last(f'run_{n}')}"


def grown_sql(workload: str) -> str:
    """Warm ranks after a batch that brings in vertices: old ranks shrink to their share, new ones get an even share."""
    late = "(src % 4 = 1 AND src % 3 = 0 OR dst % 4 = 1 AND dst % 3 = 0)"
    ids = lambda e: f"SELECT DISTINCT id FROM (SELECT src AS id FROM {e} UNION ALL SELECT dst FROM {e})"
    looped = lambda e, v: f"SELECT DISTINCT src, dst FROM {e} WHERE src <> dst UNION ALL SELECT id, id FROM {v}"
    degrees = lambda e: f"SELECT src AS id, count(*) AS deg FROM {e} GROUP BY src"
    first = rounds_sql("first", "e_0", "d_0", "SELECT id, 1.0::DOUBLE / (SELECT n FROM c_0) AS r, true AS aff FROM v_0", METHODS["cold"], RankConfig()).replace("FROM cnt", "FROM c_0")
    start = f"SELECT v.id, coalesce(f.r * (SELECT n FROM c_0) / (SELECT n FROM cnt), 1.0 / (SELECT n FROM cnt)) AS r, true AS aff FROM v LEFT JOIN {last('first')} f ON f.id = v.id"
    return f"""WITH RECURSIVE te AS MATERIALIZED ({EDGES[workload]}), t_0 AS MATERIALIZED (SELECT * FROM te WHERE NOT {late}), v_0 AS MATERIALIZED ({ids('t_0')}), c_0 AS MATERIALIZED (SELECT count(*) AS n FROM v_0),
        e_0 AS MATERIALIZED ({looped('t_0', 'v_0')}), d_0 AS MATERIALIZED ({degrees('e_0')}), {first},
        v AS MATERIALIZED ({ids('te')}), cnt AS MATERIALIZED (SELECT count(*) AS n FROM v), e_1 AS MATERIALIZED ({looped('te', 'v')}), d_1 AS MATERIALIZED ({degrees('e_1')}),
        {rounds_sql('run', 'e_1', 'd_1', start, METHODS['warm'], RankConfig())} SELECT id, CAST(floor(r * 1e9 + 0.5) AS BIGINT) AS rank_e9 FROM {last('run')}"""


def trace_sql(workload: str, method: str, **kw) -> str:
    return f"""{method_ctes(workload, method, **kw)}, ind AS (SELECT dst AS id, count(*) AS k FROM en GROUP BY dst)
        SELECT it AS superstep, count(*) FILTER (was) AS n_affected, count(*) FILTER (hot) AS n_expanded, count(*) FILTER (settled) AS n_settled, CAST(coalesce(sum(ind.k) FILTER (was), 0) AS BIGINT) AS in_edges
        FROM run LEFT JOIN ind ON ind.id = run.id WHERE it > 0 GROUP BY it"""


def run_sql(workload: str, method: str, ref_cfg: RankConfig, **kw) -> str:
    """One row of a run: rounds, in-edges of affected vertices, vertices ever affected and in all, L1 error to the reference run."""
    ref = rounds_sql("ref", "en", "dn", _UNIFORM, METHODS["cold"], ref_cfg)
    return f"""{method_ctes(workload, method, **kw)}, {ref}, ind AS (SELECT dst AS id, count(*) AS k FROM en GROUP BY dst)
        SELECT (SELECT max(it) FROM run) AS supersteps, (SELECT CAST(coalesce(sum(ind.k), 0) AS BIGINT) FROM run JOIN ind ON ind.id = run.id WHERE it > 0 AND was) AS in_edges,
            (SELECT count(*) FILTER (ever) FROM {last('run')}) AS affected, (SELECT n FROM cnt) AS vertices, (SELECT sum(abs(a.r - b.r)) FROM {last('run')} a JOIN {last('ref')} b ON a.id = b.id) AS l1"""


def affected_sql(workload: str, method: str, **kw) -> str:
    return f"{method_ctes(workload, method, **kw)} SELECT count(*) FILTER (ever) AS affected, count(*) AS vertices FROM {last('run')}"


def error_sql(workload: str, method: str, ref_cfg: RankConfig, **kw) -> str:
    """L1 error to the reference run, in units of 1e-10."""
    ref = rounds_sql("ref", "en", "dn", _UNIFORM, METHODS["cold"], ref_cfg)
    return f"{method_ctes(workload, method, **kw)}, {ref} SELECT CAST(floor(sum(abs(a.r - b.r)) * 1e10 + 0.5) AS BIGINT) AS l1_e10 FROM {last('run')} a JOIN {last('ref')} b ON a.id = b.id"
