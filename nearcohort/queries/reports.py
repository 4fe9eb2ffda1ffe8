"""Measures, case studies and workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from nearcohort.model import make_queries
from nearcohort.operators import graph as G
from nearcohort.operators.truss import min_trussness
from nearcohort.plans import comparators, explain, metrics, workloads
from nearcohort.plans.runtime import Workspace
from nearcohort.plans.solve import solve
from nearcohort.queries.searches import _ALL_SEG, _TYPES, BATCH, Q1, Q4, q
from nearcohort.queries.sqlgen import good_cte, label_cte, prepared_ctes, search_sql
from nearcohort.sources.graphs import load

QUERIES, ORACLES = {}, {}


def add(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f
    return put


_TEAM = """SELECT a.qid, a.group_id, a.size, a.d, a.keywords, b.edges, b.mean_support, round(2 * b.edges / (a.size * (a.size - 1)), 6) AS density FROM
(SELECT qid, group_id, count(*) AS size, max(dist) AS d, count(DISTINCT kw) AS keywords FROM answer GROUP BY 1, 2) a JOIN
(SELECT qid, group_id, count(*) AS edges, round(avg(s), 6) AS mean_support FROM (
  SELECT x.qid, x.group_id, p.src, p.dst, (SELECT count(*) FROM pr_end u JOIN pr_end t ON t.qid = u.qid AND t.r = u.r WHERE u.qid = p.qid AND u.r = p.r
    AND p.src IN (u.src, u.dst) AND p.dst IN (t.src, t.dst) AND (u.src + u.dst - p.src) = (t.src + t.dst - p.dst) AND NOT (u.src = p.src AND u.dst = p.dst) AND NOT (t.src = p.src AND t.dst = p.dst)) AS s
  FROM answer x JOIN pr_end p ON p.qid = x.qid AND p.r = x.d AND p.src = x.member) GROUP BY 1, 2) b USING (qid, group_id)"""


@add("team_report", search_sql("buyers", [Q1], select=_TEAM))
def team_report(s, d):
    return metrics.team_report(solve(load(s, d, "buyers"), make_queries(s, [Q1])))


# the edges of the groups, and the least number of triangles on one of them
_TRUSS = """, ge AS MATERIALIZED (SELECT DISTINCT p.qid, x.group_id, p.src, p.dst FROM answer x JOIN pr_end p ON p.qid = x.qid AND p.r = x.d AND p.src = x.member),
gt AS MATERIALIZED (SELECT a.qid, a.group_id, a.src AS a, a.dst AS b, b.dst AS w FROM ge a JOIN ge b ON a.qid = b.qid AND a.group_id = b.group_id AND a.src = b.src AND a.dst < b.dst
  JOIN ge c ON c.qid = a.qid AND c.group_id = a.group_id AND c.src = a.dst AND c.dst = b.dst),
gs AS (SELECT qid, group_id, a AS src, b AS dst FROM gt UNION ALL SELECT qid, group_id, a, w FROM gt UNION ALL SELECT qid, group_id, b, w FROM gt)
SELECT qid, group_id, min(k) + 2 AS trussness FROM (SELECT ge.qid, ge.group_id, ge.src, ge.dst, count(gs.src) AS k FROM ge LEFT JOIN gs USING (qid, group_id, src, dst)
  GROUP BY 1, 2, 3, 4) GROUP BY 1, 2"""


@add("group_trussness", search_sql("buyers", BATCH, select=_TRUSS))
def group_trussness(s, d):
    """Every group of an answer has at least the trussness asked for."""
    return min_trussness(solve(load(s, d, "buyers"), make_queries(s, BATCH)).group_edges)


@add("group_distance", search_sql("buyers", BATCH, select="SELECT qid, group_id, max(dist) AS d FROM answer GROUP BY 1, 2"))
def group_distance(s, d):
    return G.group_distance(solve(load(s, d, "buyers"), make_queries(s, BATCH)).groups)


@add("coverage_open", search_sql("buyers", BATCH, select="SELECT a.qid, a.group_id AS comp, len(list_filter(phi, lambda x: NOT list_contains(have, x))) = 0 AS covered "
     "FROM (SELECT qid, group_id, list(DISTINCT kw) AS have FROM answer GROUP BY 1, 2) a JOIN fl USING (qid)"))
def coverage_open(s, d):
    return _coverage(s, d, "open")


@add("coverage_closed", search_sql("buyers", BATCH, select="SELECT a.qid, a.group_id AS comp, len(list_filter(phi, lambda x: NOT list_contains(have, x))) = 0 "
     "AND len(list_filter(have, lambda x: NOT list_contains(phi, x))) = 0 AS covered FROM (SELECT qid, group_id, list(DISTINCT kw) AS have FROM answer GROUP BY 1, 2) a JOIN fl USING (qid)"))
def coverage_closed(s, d):
    return _coverage(s, d, "closed")


def _coverage(s, d, mode):
    qs = make_queries(s, BATCH)
    return G.covers(solve(load(s, d, "buyers"), qs).groups.withColumnRenamed("group_id", "comp"), qs, mode)


_SHARE = f"""WITH RECURSIVE {prepared_ctes('buyers', BATCH)}, {label_cte('hl', 'pg_end', ['qid'])}, {good_cte('hl_end', ['qid'], 'hgood')},
g AS (SELECT count(DISTINCT id) AS n FROM (SELECT src AS id FROM e UNION SELECT dst FROM e))
SELECT qid, round(count(DISTINCT hl_end.id) / max(g.n), 6) AS h_g FROM hl_end JOIN hgood USING (qid, comp), g GROUP BY qid"""


@add("pruned_share", _SHARE)
def pruned_share(s, d):
    """Vertices that the maximal trusses of each query leave, of those with an edge."""
    g = load(s, d, "buyers")
    return metrics.pruning_ratios(g, solve(g, make_queries(s, BATCH), nearest=False)).select("qid", "h_g")


@add("stage_cost")
def stage_cost(s, d):
    return metrics.stage_cost(solve(load(s, d, "buyers"), make_queries(s, BATCH), seed="none", check="full", nearest=False), 2.0)


@add("spark_measures")
def spark_measures(s, d):
    """Jobs, stages, tasks and bytes of each solver on one batch."""
    g, qs = load(s, d, "buyers"), make_queries(s, BATCH)
    rows = [(m, *metrics.spark_measures(s, lambda m=m: solve(g, qs, m)).values()) for m in workloads.SOLVERS]
    return s.createDataFrame(rows, "method string, seconds double, jobs long, stages long, tasks long, shuffle_bytes long, spill_bytes long")


@add("response_time")
def response_time(s, d):
    """Mean, median and p95 seconds of a query of each solver, after a run that is not counted."""
    g, qs, rows = workloads.cached(load(s, d, "active"), Workspace(s, "time")), make_queries(s, [Q4]), []
    for m in workloads.SOLVERS:
        t = metrics.time_runs(lambda m=m: solve(g, qs, m), 3, warm=1)
        rows.append((m, t["runs"], t["mean"], t["median"], t["p95"]))
    return s.createDataFrame(rows, "method string, runs long, mean double, median double, p95 double")


@add("validator", search_sql("buyers", BATCH, select="SELECT DISTINCT qid, group_id, true AS cohesive, true AS connected, true AS covered, true AS within FROM answer"))
def validator(s, d):
    qs = make_queries(s, BATCH)
    return metrics.check_group(solve(load(s, d, "buyers"), qs), qs)


@add("pruning_ratios")
def pruning_ratios(s, d):
    g = load(s, d, "baskets")
    _, r = workloads.batch(g, 200, 3, 6, nearest=False)
    return metrics.pruning_ratios(g, r)


@add("pruning_ratios_buyers")
def pruning_ratios_buyers(s, d):
    g = load(s, d, "buyers")
    _, r = workloads.batch(g, 200, 1, 4, nearest=False)
    return metrics.pruning_ratios(g, r)


@add("round_bounds")
def round_bounds(s, d):
    return metrics.round_bounds(solve(load(s, d, "buyers"), make_queries(s, BATCH), nearest=False), 2.0)


@add("kernel_counters")
def kernel_counters(s, d):
    return solve(load(s, d, "buyers"), make_queries(s, BATCH), nearest=False).counters


def _rows(s, rows):
    return s.createDataFrame([(r["graph"], r["parameter"], float(r["value"]), r["method"], r["seconds"], r["per_query"], r["found"], r["tested"]) for r in rows],
                             "graph string, parameter string, value double, method string, seconds double, per_query double, found long, tested long")


def _team(s, d, graph, rows):
    g, qs = load(s, d, graph), make_queries(s, rows)
    ours = solve(g, qs, only_first=True).groups.select("qid", "member", "dist")
    theirs = comparators.nearest_by_role(g, qs).select("qid", "member", "dist")
    return (metrics.team_ties(ours, g).withColumn("team", F.lit("found")).unionByName(
        metrics.team_ties(theirs, g).withColumn("team", F.lit("by_role"))))


def _team_sql(graph, rows, band=None):
    """Ties of the found team of least id and of the nearest holders of each keyword."""
    return search_sql(graph, rows, band, select=""", m AS MATERIALIZED (
  SELECT 'found' AS team, qid, member, dist FROM answer WHERE group_id = (SELECT min(x.group_id) FROM answer x WHERE x.qid = answer.qid)
  UNION ALL SELECT 'by_role', qid, id, dist FROM (SELECT vd.qid, vd.id, vd.dist, w.least, row_number() OVER (PARTITION BY vd.qid, vd.kw ORDER BY vd.dist, vd.id) AS k
    FROM vd JOIN w ON w.qid = vd.qid AND w.kw = vd.kw) WHERE k <= least)
SELECT t.team, t.qid, t.size, t.d, coalesce(k.edges, 0) AS edges, round(2 * coalesce(k.edges, 0) / (t.size * (t.size - 1)), 6) AS density
FROM (SELECT team, qid, count(*) AS size, max(dist) AS d FROM m GROUP BY 1, 2) t LEFT JOIN
  (SELECT a.team, a.qid, count(*) AS edges FROM m a JOIN e ON e.src = a.member JOIN m b ON b.team = a.team AND b.qid = a.qid AND b.member = e.dst GROUP BY 1, 2) k
  USING (team, qid)""")


def workload_share(s, d):
    """Time by the share of vertices: all shares, all solvers."""
    return _rows(s, workloads.sweep(load(s, d, "buyers"), "share", workloads.SHARES, n=10, base={"c": 3, "rho": 1}))


def workload_keywords(s, d):
    """Time by the number of keywords; insertion is left out here, as it tests every distance of a graph of
    tens of thousands of edges (its own query: ``group_insert``)."""
    return _rows(s, workloads.sweep(load(s, d, "baskets_brand"), "n_keywords", workloads.RANGES["n_keywords"], workloads.SOLVERS[:4], n=5))


def workload_c(s, d):
    """Time by cohesion on the graph where all levels exist."""
    return _rows(s, workloads.sweep(load(s, d, "active10"), "c", workloads.RANGES["c"], n=10))


def workload_rho(s, d):
    """Time by the minimum of each keyword."""
    return _rows(s, workloads.sweep(load(s, d, "active10"), "rho", workloads.RANGES["rho"], n=10))


add("case_small_team", _team_sql("buyers", [q(_ALL_SEG, 1, 4)]))(lambda s, d: _team(s, d, "buyers", [q(_ALL_SEG, 1, 4)]))
add("case_large_team", _team_sql("baskets", [q(_TYPES, 5, 6)], (30.4, 30.5)))(lambda s, d: _team(s, d, "baskets", [q(_TYPES, 5, 6)]))
for _f in (workload_share, workload_keywords, workload_c, workload_rho):
    add(_f.__name__)(_f)
add("workload_delta")(lambda s, d: _rows(s, workloads.sweep(load(s, d, "buyers"), "delta", workloads.DELTAS, ("two_phase",), n=10, base={"c": 3, "rho": 1})))
add("ablation")(lambda s, d: workloads.ablation(load(s, d, "active"), make_queries(s, [Q4]), workloads.SEEDS))
add("explain_strategy")(lambda s, d: s.createDataFrame([(explain.explain_strategy(load(s, d, "buyers"), make_queries(s, BATCH)),)], "plan string"))
