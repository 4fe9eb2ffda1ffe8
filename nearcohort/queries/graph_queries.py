"""Graphs, building blocks and fixpoints."""

from __future__ import annotations

from pyspark.sql import functions as F

from nearcohort.model import Constraints, check_queries, demands, make_queries, push_vertices
from nearcohort.operators import graph as G
from nearcohort.operators import space as S
from nearcohort.operators.components import components
from nearcohort.operators.qualify import prune, social_peel
from nearcohort.operators.truss import truss_decompose, truss_drops, truss_peel
from nearcohort.plans.runtime import Workspace, small
from nearcohort.plans.solve import _Job, _ledger, merge_components, seed_radius, spanning_forest
from nearcohort.queries.searches import _SEG, BATCH, Q1
from nearcohort.queries.sqlgen import (
    edges_sql,
    good_cte,
    label_cte,
    peel_cte,
    prepared_ctes,
    vertices_sql,
)
from nearcohort.sources.graphs import load
from nearcohort.sources.tables import table

QUERIES, ORACLES = {}, {}


def add(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f
    return put


for _g in ("buyers", "baskets", "active", "active10", "vectors", "suppliers", "articles"):
    add(f"graph_{_g}", edges_sql(_g))(lambda s, d, g=_g: load(s, d, g).edges)
    _round = "round(x, 6) AS x, round(y, 6) AS y"
    add(f"vertices_{_g}", f"SELECT id, kw, {_round} FROM ({vertices_sql(_g)})")(
        lambda s, d, g=_g: load(s, d, g).vertices.select("id", "kw", F.round("x", 6).alias("x"), F.round("y", 6).alias("y")))


@add("latest_checkin", "SELECT user_id AS user, event_id AS seq, event_type FROM events "
     "QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) = 1")
def latest_checkin(s, d):
    ev = table(s, d, "events").select(F.col("user_id").alias("user"), "ts", F.col("event_id").alias("seq"), "event_type")
    return G.latest_checkin(ev).select("user", "seq", "event_type")


@add("assign_keywords", "SELECT c_custkey AS id, ['a', 'b', 'c', 'd', 'e'][CAST((c_custkey * 2654435761 + 7) % 5 AS INT) + 1] AS kw FROM customer")
def assign_keywords(s, d):
    v = table(s, d, "customer").select(F.col("c_custkey").alias("id"))
    return G.assign_keywords(v, ["a", "b", "c", "d", "e"], 7).select("id", "kw")


_PICK = "SELECT id FROM ({v}) WHERE (id * 2654435761 + 3) % 100 < 60"


@add("sample_vertices", f"WITH p AS ({_PICK.format(v=vertices_sql('buyers'))}) SELECT src, dst FROM ({edges_sql('buyers')}) "
     "WHERE src IN (SELECT id FROM p) AND dst IN (SELECT id FROM p)")
def sample_vertices(s, d):
    return G.sample_vertices(load(s, d, "buyers"), 60, 3).edges


@add("vertex_degree", f"SELECT id, count(*) AS degree FROM (SELECT src AS id FROM ({edges_sql('baskets')}) UNION ALL SELECT dst FROM ({edges_sql('baskets')})) GROUP BY id")
def vertex_degree(s, d):
    return G.degrees(load(s, d, "baskets").edges)


_TRI = ("WITH e AS MATERIALIZED ({e}) SELECT a.src AS a, a.dst AS b, b.dst AS w FROM e a JOIN e b ON a.src = b.src AND a.dst < b.dst "
        "JOIN e c ON c.src = a.dst AND c.dst = b.dst")


@add("triangles_buyers", _TRI.format(e=edges_sql("buyers")))
def triangles(s, d):
    return G.triangles(load(s, d, "buyers").edges)


@add("triangle_count", f"SELECT count(*) AS n FROM ({_TRI.format(e=edges_sql('baskets'))})")
def triangle_count(s, d):
    return G.triangles(load(s, d, "baskets").edges).agg(F.count("*").alias("n"))


@add("edge_support", f"WITH t AS ({_TRI.format(e=edges_sql('buyers'))}), e2 AS ({edges_sql('buyers')}), s AS (SELECT a AS src, b AS dst FROM t "
     "UNION ALL SELECT a, w FROM t UNION ALL SELECT b, w FROM t) SELECT e2.src, e2.dst, count(s.src) AS sup FROM e2 LEFT JOIN s USING (src, dst) GROUP BY 1, 2")
def edge_support(s, d):
    return G.support(load(s, d, "buyers").edges)


_PREP = prepared_ctes("buyers", [Q1])


@add("edge_distance", f"WITH RECURSIVE {_PREP} SELECT q.qid, e.src, e.dst, greatest(a.dist, b.dist) AS ed FROM e, q "
     "JOIN vd a ON a.qid = q.qid JOIN vd b ON b.qid = q.qid WHERE a.id = e.src AND b.id = e.dst")
def edge_distance(s, d):
    g = load(s, d, "buyers")
    return S.with_edge_distance(g.edges, S.with_distance(g.vertices, make_queries(s, [Q1])))


@add("vertex_distance", f"WITH RECURSIVE {prepared_ctes('buyers', BATCH)} SELECT qid, id, kw, dist FROM vd")
def vertex_distance(s, d):
    return S.with_distance(load(s, d, "buyers").vertices, make_queries(s, BATCH))


def _job(s, d, graph="buyers", rows=(Q1,)) -> _Job:
    """A pruned job with its ledger."""
    from nearcohort.plans.solve import _prepare

    job = _prepare(load(s, d, graph), make_queries(s, rows), Constraints(), Workspace(s, "job"), 2_000_000, True, None)
    _ledger(job)
    job.steps = job.work.save(S.radius_steps(job.ledger), "steps")
    return job


# the pruned graph of a query and its edge distances
_H = (f"WITH RECURSIVE {prepared_ctes('buyers', [Q1])}, {label_cte('hl', 'pg_end', ['qid'])}, {good_cte('hl_end', ['qid'], 'hgood')}, "
      "hh AS MATERIALIZED (SELECT hed.qid, hed.src, hed.dst, hed.ed, hl_end.comp FROM hed JOIN hl_end ON hl_end.qid = hed.qid AND hl_end.id = hed.src "
      "JOIN hgood ON hgood.qid = hed.qid AND hgood.comp = hl_end.comp)")


@add("maximal_trusses_H", _H + " SELECT qid, src, dst, comp FROM hh")
def maximal_trusses(s, d):
    return _job(s, d).pruned.select("qid", "src", "dst", "comp")


@add("ledger_rank", _H + ", n AS (SELECT qid, ed, count(*) AS k FROM hh GROUP BY 1, 2) SELECT qid, ed, row_number() OVER (PARTITION BY qid ORDER BY ed) - 1 AS step, "
     "CAST(sum(k) OVER (PARTITION BY qid ORDER BY ed) AS BIGINT) AS upto FROM n")
def ledger_rank(s, d):
    return _job(s, d).steps


@add("next_radius", _H + ", n AS (SELECT ed, count(*) AS k FROM hh GROUP BY 1), c AS (SELECT ed, row_number() OVER (ORDER BY ed) - 1 AS step, "
     "CAST(sum(k) OVER (ORDER BY ed) AS BIGINT) AS upto FROM n) SELECT CAST(1 AS BIGINT) AS qid, ed, step, upto FROM c WHERE upto >= 50 ORDER BY step LIMIT 1")
def next_radius(s, d):
    return S.next_radius(_job(s, d).steps, s.createDataFrame([(1, 25)], "qid long, upto long"), 2.0)


@add("radius_band", _H + " SELECT qid, src, dst, ed FROM hh WHERE ed > 20 AND ed <= 40")
def radius_band(s, d):
    return S.band(_job(s, d).ledger, 20.0, 40.0).select("qid", "src", "dst", "ed")


@add("radius_graph", _H + " SELECT qid, src, dst, ed FROM hh WHERE ed <= 35.5")
def radius_graph(s, d):
    return S.within(_job(s, d).ledger, 35.5).select("qid", "src", "dst", "ed")


@add("spanning_forest", _H + " SELECT qid, CAST(count(*) - count(DISTINCT comp) AS BIGINT) AS n_edges FROM (SELECT DISTINCT qid, comp, id FROM "
     "(SELECT qid, comp, src AS id FROM hh UNION SELECT qid, comp, dst FROM hh)) GROUP BY qid")
def forest_size(s, d):
    job = _job(s, d)
    return spanning_forest(job.ledger, job.work).groupBy("qid").agg(F.count("*").alias("n_edges"))


# least radius at which a connected part holds the keywords: tested at every radius
_SEED = (_H + ", sr AS (SELECT DISTINCT qid, ed AS r FROM hh), se AS MATERIALIZED (SELECT hh.qid, sr.r, hh.src, hh.dst FROM hh JOIN sr ON sr.qid = hh.qid AND hh.ed <= sr.r), "
         + label_cte("sl", "se", ["qid", "r"]) + ", " + good_cte("sl_end", ["qid", "r"], "sgood", 2) + " SELECT qid, min(r) AS d FROM sgood GROUP BY qid")
for _m in ("kruskal", "forest", "bisect"):
    add(f"seed_radius_{_m}", _SEED)(lambda s, d, m=_m: seed_radius(_job(s, d), m))
# only vertices with c - 1 neighbours within the radius may unite
_RIPE = (_H + ", sr AS (SELECT DISTINCT qid, ed AS r FROM hh), s0 AS MATERIALIZED (SELECT hh.qid, sr.r, hh.src, hh.dst FROM hh JOIN sr ON sr.qid = hh.qid AND hh.ed <= sr.r), "
         f"ripe AS MATERIALIZED (SELECT qid, r, id FROM (SELECT qid, r, src AS id FROM s0 UNION ALL SELECT qid, r, dst FROM s0) GROUP BY 1, 2, 3 HAVING count(*) >= {Q1[5] - 1}), "
         "se AS MATERIALIZED (SELECT s0.* FROM s0 JOIN ripe a ON a.qid = s0.qid AND a.r = s0.r AND a.id = s0.src JOIN ripe b ON b.qid = s0.qid AND b.r = s0.r AND b.id = s0.dst), "
         + label_cte("sl", "se", ["qid", "r"]) + ", " + good_cte("sl_end", ["qid", "r"], "sgood", 2) + " SELECT qid, min(r) AS d FROM sgood GROUP BY qid")
add("seed_radius_degree", _RIPE)(lambda s, d: seed_radius(_job(s, d), "degree"))
# the nearest truss of the pruned graph whatever its keywords
_LOOSE = (_H + ", sr AS (SELECT DISTINCT qid, ed AS r FROM hh), "
          + peel_cte("px", f"SELECT hh.qid, sr.r, hh.src, hh.dst, {Q1[5] - 2} AS need FROM hh JOIN sr ON sr.qid = hh.qid AND hh.ed <= sr.r", ["qid", "r"])
          + " SELECT qid, min(r) AS d FROM px_end GROUP BY qid")
add("seed_radius_relax", _LOOSE)(lambda s, d: seed_radius(_job(s, d), "relax_keyword"))
# weight of the forest: at each radius, what the number of its edges grows by
_WEIGHT = (_SEED[:_SEED.index(", sgood AS")] + ", fn AS (SELECT qid, r, count(*) - count(DISTINCT comp) AS k FROM sl_end GROUP BY 1, 2), "
           "fd AS (SELECT qid, r, k - coalesce(lag(k) OVER (PARTITION BY qid ORDER BY r), 0) AS k FROM fn) "
           "SELECT qid, CAST(sum(k) AS BIGINT) AS n_edges, round(sum(k * r), 4) AS weight FROM fd GROUP BY qid")
for _n, _o in (("spanning_forest_weight", {}), ("spanning_forest_parts", {"part_edges": 64, "fan_in": 2})):
    add(_n, _WEIGHT)(lambda s, d, o=_o: _forest_weight(s, d, o))


def _forest_weight(s, d, options):
    job = _job(s, d)
    return spanning_forest(job.ledger, job.work, **options).groupBy("qid").agg(F.count("*").alias("n_edges"), F.round(F.sum("ed"), 4).alias("weight"))


@add("keyword_census", f"WITH RECURSIVE {_PREP}, {label_cte('cl', 'pg_end', ['qid'])} SELECT cl_end.qid, cl_end.comp, w.kw, count(*) AS n FROM cl_end "
     "JOIN vd ON vd.qid = cl_end.qid AND vd.id = cl_end.id JOIN w ON w.qid = vd.qid AND w.kw = vd.kw GROUP BY 1, 2, 3")
def keyword_census(s, d):
    g, q, cons, work = load(s, d, "buyers"), check_queries(make_queries(s, [Q1])), Constraints(), Workspace(s, "census")
    e = social_peel(g.edges.crossJoin(F.broadcast(q.select("qid", "c"))), ["qid"], "truss", work)
    return G.census(components(e, ["qid"], work=work), push_vertices(g, q, cons), demands(q, cons))


@add("components_active", f"WITH RECURSIVE ce AS ({edges_sql('active')}), {label_cte('ca', 'ce', [])} SELECT id, comp FROM ca_end")
def components_active(s, d):
    return components(load(s, d, "active").edges)


@add("merge_components", f"WITH RECURSIVE ce AS (SELECT CAST(1 AS BIGINT) AS qid, src, dst FROM ({edges_sql('vectors')})), {label_cte('ca', 'ce', ['qid'])} SELECT qid, id, comp FROM ca_end")
def merged(s, d):
    e = load(s, d, "vectors").edges.withColumn("qid", F.lit(1).cast("long"))
    work = Workspace(s, "merge")
    first = work.save(components(e.where("src % 3 = 0"), ["qid"], work=work), "first")
    return merge_components(first, e.where("src % 3 <> 0").select("qid", "src", "dst"), work)


@add("nearest_k", f"WITH v AS ({vertices_sql('baskets')}), d AS (SELECT id, kw, round(sqrt(pow(x - 50, 2) + pow(y - 50, 2)), 6) AS dist FROM v) "
     "SELECT CAST(1 AS BIGINT) AS qid, id, kw, dist, row_number() OVER (ORDER BY dist, id) AS rank FROM d QUALIFY rank <= 25")
def nearest_k(s, d):
    return S.nearest_vertices(S.with_distance(load(s, d, "baskets").vertices, make_queries(s, [Q1])), 25).withColumn("rank", F.col("rank").cast("long"))


@add("cells_in_range", f"WITH v AS ({vertices_sql('baskets')}), q(qid, qx, qy) AS (VALUES (1, 50.0, 50.0), (2, 10.0, 80.0)) "
     "SELECT CAST(qid AS BIGINT) AS qid, id, round(sqrt(pow(x - qx, 2) + pow(y - qy, 2)), 6) AS dist FROM v, q WHERE round(sqrt(pow(x - qx, 2) + pow(y - qy, 2)), 6) <= 12.5")
def cells_in_range(s, d):
    q = s.createDataFrame([(1, 50.0, 50.0, 12.5), (2, 10.0, 80.0, 12.5)], "qid long, qx double, qy double, r double")
    return S.in_range(S.cell_index(load(s, d, "baskets").vertices), q)


def _peel_sql(graph, c, social="truss", less=2):
    return f"WITH RECURSIVE {peel_cte('p', f'SELECT src, dst, {c - less} AS need FROM ({edges_sql(graph)})', [], social)} SELECT src, dst FROM p_end"


for _c in (3, 4, 5):
    add(f"truss_c{_c}", _peel_sql("buyers", _c))(
        lambda s, d, c=_c: truss_peel(load(s, d, "buyers").edges.withColumn("need", F.lit(c - 2)), []).select("src", "dst"))
add("truss_c4_rounds", _peel_sql("active", 4))(
    lambda s, d: truss_peel(load(s, d, "active").edges.withColumn("need", F.lit(2)), [], kernel_edges=0).select("src", "dst"))
add("core_k3", _peel_sql("active", 4, "core", 1))(
    lambda s, d: social_peel(load(s, d, "active").edges.withColumns({"qid": F.lit(1), "c": F.lit(4)}), ["qid"], "core").select("src", "dst"))


@add("truss_index", "WITH RECURSIVE " + ", ".join(
    [f"e AS MATERIALIZED ({edges_sql('buyers')})"]
    + [peel_cte(f"p{c}", f"SELECT src, dst, {c - 2} AS need FROM e", []) for c in (3, 4, 5, 6, 7)])
    + " SELECT src, dst, CAST(max(t) AS INT) AS truss FROM (SELECT src, dst, 2 AS t FROM e "
    + " ".join(f"UNION ALL SELECT src, dst, {c} FROM p{c}_end" for c in (3, 4, 5, 6, 7)) + ") GROUP BY 1, 2")
def truss_index(s, d):
    return truss_decompose(load(s, d, "buyers").edges)


add("truss_index_rounds", ORACLES["truss_index"])(lambda s, d: truss_decompose(load(s, d, "buyers").edges, kernel_edges=0))


@add("anchored_peel", _peel_sql("active", 4))
def anchored_peel(s, d):
    """A part peeled first is locked while the rest is peeled: together the whole answer."""
    work = Workspace(s, "anchored")
    e = work.save(load(s, d, "active").edges, "edges").withColumn("need", F.lit(2))
    first = F.expr("src % 2 = 0 or dst % 3 = 0")
    gone, n = truss_drops(e.where(first), [], work, stored=True)
    lost = small(gone.withColumn("lost", F.lit(True)), n)
    e = e.join(lost, ["src", "dst"], "left").withColumn("pool", first & F.col("lost").isNull()).drop("lost")
    return e.where("pool").select("src", "dst").unionByName(truss_peel(e, [], "pool", work, stored=True).select("src", "dst"))


# triangles that lie in four-cliques, peeled to a fixpoint
ORACLES["nucleus_34"] = f"""WITH RECURSIVE t0 AS MATERIALIZED ({_TRI.format(e=edges_sql('active'))}), e AS ({edges_sql('active')}),
p(it, a, b, w, n, pn) AS (
  SELECT 0, a, b, w, count(*) OVER (), CAST(-1 AS BIGINT) FROM t0
  UNION ALL
  SELECT it + 1, a, b, w, count(*) OVER (), n FROM (
    SELECT p.it, p.a, p.b, p.w, p.n FROM p JOIN (
      SELECT f.a AS a, f.b AS b, f.w AS w, count(*) AS k FROM (
        SELECT unnest([{{'a': x.a, 'b': x.b, 'w': x.w}}, {{'a': x.a, 'b': x.b, 'w': y.w}}, {{'a': x.a, 'b': x.w, 'w': y.w}}, {{'a': x.b, 'b': x.w, 'w': y.w}}]) AS f
        FROM p x JOIN p y ON x.a = y.a AND x.b = y.b AND x.w < y.w JOIN p z ON z.a = x.a AND z.b = x.w AND z.w = y.w
        JOIN p u ON u.a = x.b AND u.b = x.w AND u.w = y.w) GROUP BY 1, 2, 3) c
    ON c.a = p.a AND c.b = p.b AND c.w = p.w WHERE p.n <> p.pn AND c.k >= 1))
SELECT DISTINCT src, dst FROM (SELECT a AS src, b AS dst FROM p WHERE n = pn UNION ALL SELECT a, w FROM p WHERE n = pn UNION ALL SELECT b, w FROM p WHERE n = pn)"""


@add("nucleus_34", ORACLES["nucleus_34"])
def nucleus_34(s, d):
    e = load(s, d, "active").edges.withColumns({"qid": F.lit(1), "c": F.lit(4)})
    return social_peel(e, ["qid"], "nucleus").select("src", "dst")
