"""DuckDB SQL for the oracles: graphs, fixpoints and the whole search by testing radii."""

from __future__ import annotations

_PAIR = "SELECT DISTINCT a.u AS src, b.u AS dst FROM d a JOIN d b ON {on} AND a.u < b.u"

GRAPH_SQL = {
    "buyers": (
        "SELECT c_custkey AS id, c_mktsegment AS kw, c_acctbal / 100 AS x, o_totalprice / 5000 AS y, t AS influence FROM customer JOIN "
        "(SELECT o_custkey, o_totalprice FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey DESC) = 1) o "
        "ON o_custkey = c_custkey JOIN (SELECT o_custkey AS k, round(sum(o_totalprice), 2) AS t FROM orders GROUP BY 1) s ON k = c_custkey",
        "WITH d AS (SELECT DISTINCT o_custkey AS u, l_partkey AS p, date_trunc('month', o_orderdate) AS m FROM orders JOIN lineitem "
        "ON l_orderkey = o_orderkey) " + _PAIR.format(on="a.p = b.p AND a.m = b.m")),
    "active": (
        "SELECT user_id AS id, event_type AS kw, value AS x, CAST(json_extract(props, '$.k') AS DOUBLE) AS y, 0.0 AS influence FROM events "
        "QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) = 1",
        "WITH d AS (SELECT DISTINCT user_id AS u, date_trunc('minute', ts) AS m FROM events) " + _PAIR.format(on="a.m = b.m")),
    "active10": (
        "SELECT user_id AS id, event_type AS kw, value AS x, CAST(json_extract(props, '$.k') AS DOUBLE) AS y, 0.0 AS influence FROM events "
        "QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) = 1",
        "WITH d AS (SELECT DISTINCT user_id AS u, epoch_us(ts) // 600000000 AS m FROM events) " + _PAIR.format(on="a.m = b.m")),
    "vectors": (
        "SELECT vec_id AS id, CAST(label AS VARCHAR) AS kw, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, 0.0 AS influence FROM embeddings",
        "SELECT a.vec_id AS src, b.vec_id AS dst FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) a JOIN "
        "(SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) b ON a.vec_id < b.vec_id "
        "WHERE round(list_cosine_similarity(a.e, b.e), 6) >= 0.35"),
    "suppliers": (
        "SELECT s_suppkey AS id, r_name AS kw, s_acctbal / 100 AS x, y, 0.0 AS influence FROM supplier JOIN nation ON s_nationkey = n_nationkey "
        "JOIN region ON n_regionkey = r_regionkey JOIN (SELECT l_suppkey, round(100 * avg(l_discount), 6) AS y FROM lineitem GROUP BY 1) m ON l_suppkey = s_suppkey",
        "WITH d AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS u FROM lineitem) SELECT a.u AS src, b.u AS dst FROM d a JOIN d b "
        "ON a.o = b.o AND a.u < b.u GROUP BY 1, 2 HAVING count(*) >= 3"),
    "articles": (
        "SELECT doc_id AS id, lang AS kw, round(ln(n_chars), 6) AS x, CAST(doc_id % 100 AS DOUBLE) AS y, coalesce(f, 0.0) AS influence FROM documents "
        "LEFT JOIN (SELECT doc_id AS k, avg(quality) AS f FROM labels GROUP BY 1) l ON k = doc_id",
        "WITH d AS (SELECT DISTINCT doc_id AS u, trim(line, ' ') AS l FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) "
        "WHERE length(trim(line, ' ')) >= 40) " + _PAIR.format(on="a.l = b.l")),
}


def _baskets(least: int, kw: str) -> tuple[str, str]:
    keep = f" WHERE l_orderkey IN (SELECT l_orderkey FROM lineitem GROUP BY 1 HAVING count(DISTINCT l_partkey) >= {least})" if least > 1 else ""
    return (f"SELECT p_partkey AS id, {kw} AS kw, p_retailprice - 900 AS x, 2.0 * p_size AS y, 0.0 AS influence, [p_type, p_brand] AS attrs FROM part",
            f"WITH d AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS u FROM lineitem{keep}) " + _PAIR.format(on="a.o = b.o"))


GRAPH_SQL |= {"baskets": _baskets(6, "p_type"), "baskets_all": _baskets(1, "p_type"), "baskets_brand": _baskets(6, "p_brand"),
              "baskets_attrs": _baskets(6, "p_type")}


def vertices_sql(graph: str) -> str:
    return GRAPH_SQL[graph][0]


def edges_sql(graph: str) -> str:
    return GRAPH_SQL[graph][1]


def peel_cte(name: str, start: str, keys: list[str], social: str = "truss") -> str:
    """Recursive CTE ``name`` and ``name_end`` (keys, src, dst, need): the greatest fixpoint.

    ``start`` yields keys, src, dst, need.  A round carries the whole surviving set and its
    size per key; a key leaves when its size no longer falls.
    """
    if social == "nucleus":
        return _nucleus_cte(name, start, keys)
    k = "".join(f"{x}, " for x in keys)
    part = f"PARTITION BY {', '.join(keys)}" if keys else ""
    on = lambda a, b: "".join(f"{a}.{x} = {b}.{x} AND " for x in keys)
    if social == "truss":
        count = f"""SELECT {k}f.a AS a, f.b AS b, count(*) AS s FROM (
        SELECT {''.join(f'e1.{x}, ' for x in keys)}unnest([{{'a': e1.src, 'b': e1.dst}}, {{'a': e1.src, 'b': e2.dst}}, {{'a': e1.dst, 'b': e2.dst}}]) AS f
        FROM {name} e1 JOIN {name} e2 ON {on('e1', 'e2')}e1.src = e2.src AND e1.dst < e2.dst
        JOIN {name} e3 ON {on('e1', 'e3')}e3.src = e1.dst AND e3.dst = e2.dst) GROUP BY {k}f.a, f.b"""
        ok = f"LEFT JOIN ({count}) t ON {on('p', 't')}t.a = p.src AND t.b = p.dst WHERE p.n <> p.pn AND coalesce(t.s, 0) >= p.need"
    else:
        deg = f"SELECT {k}id, count(*) AS s FROM (SELECT {k}src AS id FROM {name} UNION ALL SELECT {k}dst FROM {name}) GROUP BY {k}id"
        ok = (f"JOIN ({deg}) t ON {on('p', 't')}t.id = p.src JOIN ({deg}) u ON {on('p', 'u')}u.id = p.dst "
              f"WHERE p.n <> p.pn AND least(t.s, u.s) >= p.need")
    return f"""{name}(it, {k}src, dst, need, n, pn) AS (
  SELECT 0, {k}src, dst, need, count(*) OVER ({part}), CAST(-1 AS BIGINT) FROM ({start})
  UNION ALL
  SELECT it + 1, {k}src, dst, need, count(*) OVER ({part}), n FROM (
    SELECT p.it, {''.join(f'p.{x}, ' for x in keys)}p.src, p.dst, p.need, p.n FROM {name} p {ok})),
{name}_end AS MATERIALIZED (SELECT {k}src, dst, need FROM {name} WHERE n = pn)"""


def _nucleus_cte(name: str, start: str, keys: list[str]) -> str:
    """The same for triangles that each lie in ``need`` four-cliques; the edges of what is left."""
    k = "".join(f"{x}, " for x in keys)
    part = f"PARTITION BY {', '.join(keys)}" if keys else ""
    on = lambda a, b: "".join(f"{a}.{x} = {b}.{x} AND " for x in keys)
    faces = "[{'a': x.a, 'b': x.b, 'w': x.w}, {'a': x.a, 'b': x.b, 'w': y.w}, {'a': x.a, 'b': x.w, 'w': y.w}, {'a': x.b, 'b': x.w, 'w': y.w}]"
    quads = f"""SELECT {k}f.a AS a, f.b AS b, f.w AS w, count(*) AS s FROM (
        SELECT {''.join(f'x.{c}, ' for c in keys)}unnest({faces}) AS f FROM {name} x JOIN {name} y ON {on('x', 'y')}x.a = y.a AND x.b = y.b AND x.w < y.w
        JOIN {name} z ON {on('x', 'z')}z.a = x.a AND z.b = x.w AND z.w = y.w JOIN {name} u ON {on('x', 'u')}u.a = x.b AND u.b = x.w AND u.w = y.w)
        GROUP BY {k}f.a, f.b, f.w"""
    return f"""{name}_start AS MATERIALIZED ({start}),
{name}_tri AS MATERIALIZED (SELECT {''.join(f'e1.{c}, ' for c in keys)}e1.src AS a, e1.dst AS b, e2.dst AS w, e1.need FROM {name}_start e1
  JOIN {name}_start e2 ON {on('e1', 'e2')}e1.src = e2.src AND e1.dst < e2.dst JOIN {name}_start e3 ON {on('e1', 'e3')}e3.src = e1.dst AND e3.dst = e2.dst),
{name}(it, {k}a, b, w, need, n, pn) AS (
  SELECT 0, {k}a, b, w, need, count(*) OVER ({part}), CAST(-1 AS BIGINT) FROM {name}_tri
  UNION ALL
  SELECT it + 1, {k}a, b, w, need, count(*) OVER ({part}), n FROM (
    SELECT p.it, {''.join(f'p.{c}, ' for c in keys)}p.a, p.b, p.w, p.need, p.n FROM {name} p LEFT JOIN ({quads}) t
    ON {on('p', 't')}t.a = p.a AND t.b = p.b AND t.w = p.w WHERE p.n <> p.pn AND coalesce(t.s, 0) >= p.need)),
{name}_end AS MATERIALIZED (SELECT {k}a AS src, b AS dst, need FROM {name} WHERE n = pn UNION SELECT {k}a, w, need FROM {name} WHERE n = pn
  UNION SELECT {k}b, w, need FROM {name} WHERE n = pn)"""


def label_cte(name: str, edges: str, keys: list[str]) -> str:
    """Recursive CTE ``name`` and ``name_end`` (keys, id, comp): least reachable vertex."""
    k = "".join(f"{x}, " for x in keys)
    part = f"PARTITION BY {', '.join(keys)}" if keys else ""
    on = lambda a, b: "".join(f"{a}.{x} = {b}.{x} AND " for x in keys)
    return f"""{name}_adj AS MATERIALIZED (SELECT {k}src AS id, dst AS o FROM {edges} UNION SELECT {k}dst, src FROM {edges}),
{name}(it, {k}id, comp, live) AS (
  SELECT 0, {k}id, id, 1 FROM (SELECT DISTINCT {k}id FROM {name}_adj)
  UNION ALL
  SELECT it + 1, {k}id, m, max(CAST(m <> comp AS INT)) OVER ({part}) FROM (
    SELECT l.it, {''.join(f'l.{x}, ' for x in keys)}l.id, l.comp, least(l.comp, min(o.comp)) AS m FROM {name} l
    JOIN {name}_adj a ON {on('l', 'a')}a.id = l.id JOIN {name} o ON {on('l', 'o')}o.id = a.o
    WHERE l.live = 1 GROUP BY l.it, {''.join(f'l.{x}, ' for x in keys)}l.id, l.comp)),
{name}_end AS MATERIALIZED (SELECT {k}id, comp FROM {name} WHERE live = 0)"""


def _values(rows, columns: str, kinds: list[str]) -> str:
    name = columns.split("(")[1].rstrip(")").split(", ")
    if not rows:
        return f"{columns} AS (SELECT " + ", ".join(f"CAST(NULL AS {t}) AS {n}" for n, t in zip(name, kinds, strict=True)) + " WHERE false)"
    one = lambda r: "(" + ", ".join(f"CAST({repr(v) if isinstance(v, str) else v} AS {t})" for v, t in zip(r, kinds, strict=True)) + ")"
    return f"{columns} AS (VALUES {', '.join(map(one, rows))})"


def prepared_ctes(graph: str, queries, social: str = "truss", coverage: str = "open", jaccard: float | None = None,
                  per_keyword: dict | None = None, min_influence: float | None = None, attrs: bool = False) -> str:
    """CTEs v, e, q, w, vd (located vertices per query), h (cohesive part), hed (with distance)."""
    less = {"truss": 2, "core": 1, "nucleus": 3}[social]
    own = per_keyword or {}
    want = [] if jaccard is not None else [(q[0], k, own.get(k, q[4])) for q in queries for k in q[3] if own.get(k, q[4]) > 0]
    phi = [(q[0], k) for q in queries for k in q[3]]
    held = "v.attrs" if attrs else "CASE WHEN v.kw IS NULL THEN [] ELSE [v.kw] END"
    local = []
    if coverage == "closed":
        local.append("len(list_intersect(held, phi)) > 0")
    if jaccard is not None:
        local.append(f"len(list_intersect(held, phi)) >= {jaccard} * len(list_distinct(list_concat(held, phi)))")
    if min_influence is not None:
        local.append(f"influence >= {min_influence}")
    where = " AND ".join(["x IS NOT NULL", "y IS NOT NULL", *local])
    return f"""v AS MATERIALIZED ({vertices_sql(graph)}),
e AS MATERIALIZED ({edges_sql(graph)}),
{_values([(q[0], q[1], q[2], q[5]) for q in queries], "q(qid, qx, qy, c)", ["BIGINT", "DOUBLE", "DOUBLE", "INT"])},
{_values(want, "w(qid, kw, least)", ["BIGINT", "VARCHAR", "BIGINT"])},
{_values(phi, "f(qid, kw)", ["BIGINT", "VARCHAR"])},
fl AS (SELECT q.qid, coalesce(list(f.kw) FILTER (f.kw IS NOT NULL), []) AS phi FROM q LEFT JOIN f USING (qid) GROUP BY q.qid),
vd AS MATERIALIZED (SELECT qid, id, kw, held, influence, round(sqrt(pow(x - qx, 2) + pow(y - qy, 2)), 6) AS dist FROM (
  SELECT q.qid, q.qx, q.qy, fl.phi, v.id, v.kw, v.x, v.y, v.influence, {held} AS held FROM v, q JOIN fl USING (qid)) WHERE {where}),
{peel_cte("pg", f"SELECT q.qid, e.src, e.dst, greatest(q.c - {less}, 0) AS need FROM e, q WHERE EXISTS (SELECT 1 FROM vd WHERE vd.qid = q.qid AND vd.id = e.src) AND EXISTS (SELECT 1 FROM vd WHERE vd.qid = q.qid AND vd.id = e.dst)", ["qid"], social)},
hed AS MATERIALIZED (SELECT g.qid, g.src, g.dst, g.need, greatest(a.dist, b.dist) AS ed FROM pg_end g
  JOIN vd a ON a.qid = g.qid AND a.id = g.src JOIN vd b ON b.qid = g.qid AND b.id = g.dst)"""


def good_cte(labels: str, keys: list[str], name: str = "good", min_size: int = 0, min_total: float | None = None) -> str:
    """CTE ``name`` (keys, comp): components that meet the demands of w."""
    k = ", ".join(f"l.{x}" for x in keys)
    more = f" AND total >= {min_total}" if min_total is not None else ""
    return f"""{name} AS MATERIALIZED (
  SELECT {', '.join(keys)}, comp FROM (
    SELECT {k}, l.comp, l.size, l.total, count(CASE WHEN n >= least THEN 1 END) AS met, (SELECT count(*) FROM w WHERE w.qid = l.qid) AS want FROM
      (SELECT {k}, comp, count(*) AS size, sum(coalesce(vd.influence, 0)) AS total FROM {labels} l LEFT JOIN vd ON vd.qid = l.qid AND vd.id = l.id
       GROUP BY {k}, comp) l LEFT JOIN
      (SELECT {k}, l.comp, w.kw, w.least, count(*) AS n FROM {labels} l JOIN vd ON vd.qid = l.qid AND vd.id = l.id
       JOIN w ON w.qid = l.qid AND list_contains(vd.held, w.kw) GROUP BY {k}, l.comp, w.kw, w.least) c
      ON {' AND '.join(f'c.{x} = l.{x}' for x in keys)} AND c.comp = l.comp
    GROUP BY {k}, l.comp, l.size, l.total) WHERE met = want AND size >= {min_size}{more})"""


def search_sql(graph: str, queries, band: tuple[float, float] | None = None, min_size: int = 0, social: str = "truss", select: str | None = None,
               min_total: float | None = None, **local) -> str:
    """All groups at the optimum radius, by testing every radius (or those of ``band``) at once.

    With a band the answer is right if its first radius fails, since feasibility is monotone.
    """
    window = f" WHERE ed BETWEEN {band[0]} AND {band[1]}" if band else ""
    return f"""WITH RECURSIVE {prepared_ctes(graph, queries, social, **local)},
radii AS (SELECT DISTINCT qid, ed AS r FROM hed{window}),
{peel_cte("pr", "SELECT hed.qid, radii.r, hed.src, hed.dst, hed.need FROM hed JOIN radii ON radii.qid = hed.qid AND hed.ed <= radii.r", ["qid", "r"], social)},
{label_cte("lab", "pr_end", ["qid", "r"])},
{good_cte("lab_end", ["qid", "r"], min_size=min_size, min_total=min_total)},
best AS (SELECT qid, min(r) AS r FROM good GROUP BY qid),
answer AS (SELECT b.qid, b.r AS d, g.comp AS group_id, l.id AS member, vd.kw, vd.dist FROM best b
  JOIN good g ON g.qid = b.qid AND g.r = b.r JOIN lab_end l ON l.qid = g.qid AND l.r = g.r AND l.comp = g.comp
  JOIN vd ON vd.qid = l.qid AND vd.id = l.id)
{select or "SELECT qid, d, group_id, member, kw, dist FROM answer"}"""
