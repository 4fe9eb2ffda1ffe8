"""Relational operators around the methods, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.functions import geo, udfs
from nearcohort.model import make_queries
from nearcohort.operators.truss import read_truss_index, truss_decompose, write_truss_index
from nearcohort.plans.runtime import Workspace
from nearcohort.plans.solve import solve
from nearcohort.queries.searches import Q1
from nearcohort.queries.sqlgen import edges_sql, peel_cte, search_sql, vertices_sql
from nearcohort.sources.graphs import load
from nearcohort.sources.tables import event_attributes, table

QUERIES, ORACLES = {}, {}


def add(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f
    return put


@add("proj_filter", "SELECT c_custkey, c_mktsegment, c_acctbal FROM customer WHERE c_acctbal BETWEEN 1000 AND 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_name LIKE '%1%'")
def proj_filter(s, d):
    return (table(s, d, "customer").where(F.col("c_acctbal").between(1000, 5000) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_name").like("%1%"))
            .select("c_custkey", "c_mktsegment", "c_acctbal"))


@add("join_inner", "SELECT c_mktsegment, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_inner(s, d):
    return (table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")))


@add("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(s, d):
    return (table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))


@add("join_full", "SELECT n_nationkey, c_custkey FROM nation FULL JOIN (SELECT * FROM customer WHERE c_acctbal < 0) c ON n_nationkey = c_nationkey")
def join_full(s, d):
    c = table(s, d, "customer").where("c_acctbal < 0")
    return table(s, d, "nation").join(c, F.col("n_nationkey") == F.col("c_nationkey"), "full").select("n_nationkey", "c_custkey")


_BIG = "SELECT l_partkey FROM lineitem WHERE l_quantity >= 49"


@add("join_semi", f"SELECT p_partkey FROM part WHERE p_partkey IN ({_BIG})")
def join_semi(s, d):
    big = table(s, d, "lineitem").where("l_quantity >= 49").select(F.col("l_partkey").alias("p_partkey"))
    return table(s, d, "part").select("p_partkey").join(big, "p_partkey", "left_semi")


@add("join_anti", f"SELECT p_partkey FROM part WHERE p_partkey NOT IN ({_BIG})")
def join_anti(s, d):
    big = table(s, d, "lineitem").where("l_quantity >= 49").select(F.col("l_partkey").alias("p_partkey"))
    return table(s, d, "part").select("p_partkey").join(big, "p_partkey", "left_anti")


@add("join_broadcast", "SELECT s_suppkey, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(s, d):
    # nation and region have 25 and 5 rows at every scale
    r = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(s, d, "supplier").join(F.broadcast(r), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "r_name")


@add("join_theta", f"SELECT CAST(qid AS BIGINT) AS qid, id FROM ({vertices_sql('buyers')}) v JOIN (VALUES (1, 50.0, 50.0, 20.0), (2, 10.0, 30.0, 15.0)) q(qid, qx, qy, r) "
     "ON round(sqrt(pow(x - qx, 2) + pow(y - qy, 2)), 6) <= r")
def join_theta(s, d):
    q = s.createDataFrame([(1, 50.0, 50.0, 20.0), (2, 10.0, 30.0, 15.0)], "qid long, qx double, qy double, r double")
    return load(s, d, "buyers").vertices.join(F.broadcast(q), geo.distance("euclid") <= F.col("r")).select("qid", "id")


@add("join_range", "SELECT band, count(*) AS n FROM orders JOIN (VALUES (1, 0, 50000), (2, 50000, 200000), (3, 200000, 1e9)) b(band, lo, hi) ON lo < o_totalprice AND o_totalprice <= hi GROUP BY 1")
def join_range(s, d):
    b = s.createDataFrame([(1, 0.0, 5e4), (2, 5e4, 2e5), (3, 2e5, 1e9)], "band int, lo double, hi double")
    return table(s, d, "orders").join(F.broadcast(b), (F.col("lo") < F.col("o_totalprice")) & (F.col("o_totalprice") <= F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@add("join_asof", "SELECT event_id, (SELECT max_by(o_orderkey, (o_orderdate, o_orderkey)) FROM orders WHERE o_custkey = user_id AND o_orderdate <= ts) AS o_orderkey FROM events")
def join_asof(s, d):
    """The last order before each event: one union, sorted by user and time, no range join."""
    ev = table(s, d, "events").select(F.col("user_id").alias("u"), "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("long").alias("o"))
    od = table(s, d, "orders").select(F.col("o_custkey").alias("u"), F.col("o_orderdate").alias("ts"), F.lit(0).alias("side"),
                                      F.lit(None).cast("long").alias("event_id"), F.col("o_orderkey").alias("o"))
    w = W.partitionBy("u").orderBy("ts", "side", "o").rowsBetween(W.unboundedPreceding, 0)
    return ev.unionByName(od).withColumn("o_orderkey", F.last("o", ignorenulls=True).over(w)).where("side = 1").select("event_id", "o_orderkey")


@add("join_interval", "SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 30000000")
def join_interval(s, d):
    """Users active within 30 seconds: equal or neighbouring buckets, then the exact condition."""
    e = table(s, d, "events").select(F.col("user_id").alias("src"), F.unix_micros("ts").alias("t")).withColumn("k", F.floor(F.col("t") / 30_000_000))
    b = e.select(F.col("src").alias("dst"), F.col("t").alias("t2"), F.explode(F.array(F.col("k") - 1, F.col("k"), F.col("k") + 1)).alias("k"))
    return e.join(b, "k").where("src < dst and abs(t - t2) <= 30000000").select("src", "dst").distinct()


@add("agg_basic", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, round(avg(value), 4) AS mean, min(value) AS low, max(value) AS high FROM events GROUP BY 1")
def agg_basic(s, d):
    v = F.col("value")
    return table(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum(v), 4).alias("total"), F.round(F.avg(v), 4).alias("mean"), F.min(v).alias("low"), F.max(v).alias("high"))


@add("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@add("agg_filter", "SELECT event_type, count(*) FILTER (value > 50) AS high FROM events GROUP BY 1")
def agg_filter(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"))


_CNR = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _cnr(s, d):
    r = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(s, d, "customer").join(F.broadcast(r), F.col("c_nationkey") == F.col("n_nationkey"))


@add("agg_rollup", f"SELECT r_name, n_name, count(*) AS n FROM {_CNR} GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(s, d):
    return _cnr(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@add("agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_CNR} GROUP BY CUBE (r_name, c_mktsegment)")
def agg_cube(s, d):
    return _cnr(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@add("agg_sets", f"SELECT r_name, c_mktsegment, grouping(r_name) AS g, count(*) AS n FROM {_CNR} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def agg_sets(s, d):
    return _cnr(s, d).groupingSets([["r_name"], ["c_mktsegment"]], "r_name", "c_mktsegment").agg(F.grouping("r_name").cast("long").alias("g"), F.count("*").alias("n"))


_SEGS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


@add("agg_pivot", "SELECT c_nationkey, " + ", ".join(f"nullif(count(*) FILTER (c_mktsegment = '{x}'), 0) AS {x}" for x in _SEGS) + " FROM customer GROUP BY 1")
def agg_pivot(s, d):
    return table(s, d, "customer").groupBy("c_nationkey").pivot("c_mktsegment", list(_SEGS)).agg(F.count("c_custkey"))


@add("agg_collect", "SELECT p_brand, array_to_string(list_sort(list(DISTINCT p_type)), ',') AS types FROM part GROUP BY 1")
def agg_collect(s, d):
    return table(s, d, "part").groupBy("p_brand").agg(F.array_join(F.array_sort(F.collect_set("p_type")), ",").alias("types"))


@add("agg_percentile", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders GROUP BY 1")
def agg_percentile(s, d):
    return table(s, d, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"))


@add("agg_approx")
def agg_approx(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


_VD = f"WITH v AS (SELECT id, kw, round(sqrt(pow(x - 50, 2) + pow(y - 50, 2)), 6) AS dist FROM ({vertices_sql('buyers')}))"


def _dist(s, d):
    v = load(s, d, "buyers").vertices.withColumns({"qx": F.lit(50.0), "qy": F.lit(50.0)})
    return v.select("id", "kw", geo.distance("euclid").alias("dist"))


@add("win_rank", _VD + " SELECT id, row_number() OVER (PARTITION BY kw ORDER BY dist, id) AS rn, rank() OVER (PARTITION BY kw ORDER BY floor(dist)) AS rk, dense_rank() OVER (PARTITION BY kw ORDER BY floor(dist)) AS dr FROM v")
def win_rank(s, d):
    a, b = W.partitionBy("kw").orderBy("dist", "id"), W.partitionBy("kw").orderBy(F.floor("dist"))
    return _dist(s, d).select("id", F.row_number().over(a).cast("long").alias("rn"), F.rank().over(b).cast("long").alias("rk"), F.dense_rank().over(b).cast("long").alias("dr"))


@add("win_ntile", _VD + " SELECT id, ntile(4) OVER (PARTITION BY kw ORDER BY dist, id) AS quarter, round(percent_rank() OVER (PARTITION BY kw ORDER BY dist, id), 6) AS pr FROM v")
def win_ntile(s, d):
    a = W.partitionBy("kw").orderBy("dist", "id")
    return _dist(s, d).select("id", F.ntile(4).over(a).cast("long").alias("quarter"), F.round(F.percent_rank().over(a), 6).alias("pr"))


@add("win_lag_lead", "SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS since, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS until FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_lead(s, d):
    w, t = W.partitionBy("user_id").orderBy("ts", "event_id"), F.unix_micros("ts")
    return table(s, d, "events").select("event_id", (t - F.lag(t).over(w)).alias("since"), (F.lead(t).over(w) - t).alias("until"))


@add("win_running", _VD + " SELECT id, count(*) OVER (PARTITION BY kw ORDER BY dist, id ROWS UNBOUNDED PRECEDING) AS upto FROM v")
def win_running(s, d):
    return _dist(s, d).select("id", F.count("*").over(W.partitionBy("kw").orderBy("dist", "id").rowsBetween(W.unboundedPreceding, 0)).alias("upto"))


@add("win_range", _VD + " SELECT id, count(*) OVER (PARTITION BY kw ORDER BY dist RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS near FROM v")
def win_range(s, d):
    return _dist(s, d).select("id", F.count("*").over(W.partitionBy("kw").orderBy("dist").rangeBetween(-5, 0)).alias("near"))


@add("topk_global", _VD + " SELECT id, dist FROM v ORDER BY dist, id LIMIT 10")
def topk_global(s, d):
    return _dist(s, d).orderBy("dist", "id").limit(10).select("id", "dist")


@add("topk_group", _VD + " SELECT kw, id FROM v QUALIFY row_number() OVER (PARTITION BY kw ORDER BY dist, id) <= 3")
def topk_group(s, d):
    return _dist(s, d).withColumn("rn", F.row_number().over(W.partitionBy("kw").orderBy("dist", "id"))).where("rn <= 3").select("kw", "id")


def _two(s, d):
    o = table(s, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderstatus")
    return o.where("o_orderstatus = 'F'").select("k"), o.where("o_orderstatus = 'O'").select("k")


_F, _O = (f"SELECT o_custkey AS k FROM orders WHERE o_orderstatus = '{x}'" for x in "FO")
add("set_union", f"{_F} UNION {_O}")(lambda s, d: _two(s, d)[0].unionByName(_two(s, d)[1]).distinct())
add("set_intersect", f"{_F} INTERSECT ALL {_O}")(lambda s, d: _two(s, d)[0].intersectAll(_two(s, d)[1]))
add("set_except", f"{_F} EXCEPT ALL {_O}")(lambda s, d: _two(s, d)[0].exceptAll(_two(s, d)[1]))


@add("fn_string", "SELECT p_partkey, len(string_split(p_name, ' ')) AS words, lower(p_brand) AS brand, levenshtein(p_type, p_brand) AS dist FROM part")
def fn_string(s, d):
    return table(s, d, "part").select("p_partkey", F.size(F.split("p_name", " ")).cast("long").alias("words"), F.lower("p_brand").alias("brand"), F.levenshtein("p_type", "p_brand").cast("long").alias("dist"))


@add("fn_date", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY 1, 2")
def fn_date(s, d):
    o = s.read.parquet(f"{d}/orders.parquet")
    return o.groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"))


@add("fn_math", "SELECT o_orderkey, round(sqrt(o_totalprice), 4) AS r, round(log2(o_totalprice + 1), 4) AS l, CAST(ceil(o_totalprice) AS BIGINT) AS c FROM orders")
def fn_math(s, d):
    p = F.col("o_totalprice")
    return table(s, d, "orders").select("o_orderkey", F.round(F.sqrt(p), 4).alias("r"), F.round(F.log2(p + 1), 4).alias("l"), F.ceil(p).alias("c"))


@add("fn_array", "SELECT p_partkey, len(list_intersect(w, ['a', 'b', p_type])) AS common, list_contains(w, p_type) AS has FROM (SELECT p_partkey, p_type, [p_type, p_brand] AS w FROM part)")
def fn_array(s, d):
    w = F.array("p_type", "p_brand")
    return table(s, d, "part").select("p_partkey", F.size(F.array_intersect(w, F.array(F.lit("a"), F.lit("b"), F.col("p_type")))).cast("long").alias("common"), F.array_contains(w, F.col("p_type")).alias("has"))


@add("fn_map", "SELECT c_nationkey, coalesce(count(*) FILTER (c_mktsegment = 'BUILDING'), 0) AS building FROM customer GROUP BY 1")
def fn_map(s, d):
    n = table(s, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    m = n.groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("census"))
    return m.select("c_nationkey", F.coalesce(F.try_element_at("census", F.lit("BUILDING")), F.lit(0)).alias("building"))


@add("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS DOUBLE) AS k FROM events")
def fn_json(s, d):
    return event_attributes(table(s, d, "events")).select("event_id", "k")


@add("fn_vector", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cos FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def fn_vector(s, d):
    e = table(s, d, "embeddings")
    b = e.select((F.col("vec_id") - 1).alias("a"), F.col("vec_id").alias("b"), F.col("embedding").alias("eb"))
    return e.select(F.col("vec_id").alias("a"), "embedding").join(b, "a").select("a", "b", F.round(geo.cosine(F.col("embedding"), F.col("eb")), 6).alias("cos"))


@add("fn_struct_nested", search_sql("buyers", [Q1], select="SELECT qid, member, dist FROM answer"))
def fn_struct_nested(s, d):
    """Groups as one nested record each, exploded again."""
    g = solve(load(s, d, "buyers"), make_queries(s, [Q1])).groups
    n = g.groupBy("qid", "group_id").agg(F.struct(F.max("d").alias("d"), F.collect_list(F.struct("member", "kw", "dist")).alias("members")).alias("team"))
    return n.select("qid", F.explode("team.members").alias("m")).select("qid", "m.member", "m.dist")


@add("tumble_batch", "SELECT event_type, epoch_us(ts) // 600000000 AS bucket, count(*) AS n FROM events GROUP BY 1, 2")
def tumble_batch(s, d):
    e = table(s, d, "events").groupBy(F.window("ts", "10 minutes").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return e.select("event_type", F.floor(F.unix_micros("w.start") / 600_000_000).alias("bucket"), "n")


@add("slide_batch", "SELECT b AS bucket, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 300000000, epoch_us(ts) // 300000000 - 1]) AS b FROM events) GROUP BY 1")
def slide_batch(s, d):
    e = table(s, d, "events").groupBy(F.window("ts", "10 minutes", "5 minutes").alias("w")).agg(F.count("*").alias("n"))
    return e.select(F.floor(F.unix_micros("w.start") / 300_000_000).alias("bucket"), "n")


@add("session_batch", "SELECT user_id AS user, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN p IS NULL OR epoch_us(ts) - p >= 900000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k "
     "FROM (SELECT user_id, event_id, ts, epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS p FROM events)) GROUP BY user_id, k")
def session_batch(s, d):
    return (table(s, d, "events").groupBy(F.session_window("ts", "15 minutes"), F.col("user_id").alias("user")).agg(F.count("*").alias("n")).select("user", "n"))


@add("recursive_components", f"WITH RECURSIVE g AS ({edges_sql('vectors')}), e AS (SELECT src, dst FROM g UNION SELECT dst, src FROM g), "
     "r(id, c) AS (SELECT src, src FROM e UNION SELECT e.dst, r.c FROM r JOIN e ON e.src = r.id WHERE r.c < e.dst) SELECT id, min(c) AS comp FROM r GROUP BY id")
def recursive_components(s, d):
    """Components of a graph by recursive queries in Spark SQL, see ``recursive_labels``."""
    return recursive_labels(load(s, d, "vectors").edges, Workspace(s, "recursive"))


def recursive_labels(edges: DataFrame, work: Workspace) -> DataFrame:
    """(id, comp) of every vertex of ``edges`` (src, dst): the least vertex that it can reach.

    Every vertex hangs below its neighbour of least hash, if that is less than its own.  Hashes fall
    along these links, so they are a forest, and a recursion from its roots meets each vertex once:
    as many rows as vertices, at the depth of a falling chain.  The trees are contracted until no edge
    is left between two; in two steps every root with such an edge hangs below another.
    """
    s = edges.sparkSession
    left = work.save(edges.select("src", "dst").where("src <> dst"), "edges")
    label = work.save(left.select(F.explode(F.array("src", "dst")).alias("id")).distinct().withColumn("tree", F.col("id")), "labels")
    rank = lambda c: F.struct(F.xxhash64(c).alias("h"), F.col(c).alias("id"))
    while not left.isEmpty():
        both = left.unionByName(left.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        near = both.groupBy("src").agg(F.min(rank("dst")).alias("low"))
        links = work.save(near.select(F.col("src").alias("id"), F.when(F.col("low") < rank("src"), F.col("low.id")).alias("up")), "links")
        tree = work.save(s.sql("""WITH RECURSIVE r(id, tree) MAX RECURSION LEVEL 1000000 AS (
            SELECT id, id FROM {links} WHERE up IS NULL
            UNION ALL SELECT l.id, r.tree FROM r JOIN {links} l ON l.up = r.id)
          SELECT id, tree FROM r LIMIT ALL""", links=links), "trees")
        root = lambda c: tree.select(F.col("id").alias(c), F.col("tree").alias(f"{c}_root"))  # noqa: E731, B023
        label = work.save(label.join(root("tree"), "tree", "left").select("id", F.coalesce("tree_root", "tree").alias("tree")), "labels")
        ends = left.join(root("src"), "src").join(root("dst"), "dst").where("src_root <> dst_root")
        left = work.save(ends.select(F.least("src_root", "dst_root").alias("src"), F.greatest("src_root", "dst_root").alias("dst")).distinct(), "edges")
    least = label.groupBy("tree").agg(F.min("id").alias("comp"))
    return label.join(least, "tree").select("id", "comp")


_SETS = "[p_type, p_brand] AS a, ['PROMO', 'LARGE', p_brand] AS b"


@add("udf_jaccard", f"SELECT p_partkey, round(len(list_intersect(a, b)) / CAST(len(list_distinct(list_concat(a, b))) AS DOUBLE), 6) AS j, round(len(list_intersect(a, b)) / CAST(len(list_distinct(list_concat(a, b))) AS DOUBLE), 6) AS j2 FROM (SELECT p_partkey, {_SETS} FROM part)")
def udf_jaccard(s, d):
    a, b = F.array("p_type", "p_brand"), F.array(F.lit("PROMO"), F.lit("LARGE"), F.col("p_brand"))
    return table(s, d, "part").select("p_partkey", F.round(geo.jaccard(a, b), 6).alias("j"), F.round(udfs.jaccard_udf(a, b), 6).alias("j2"))


@add("udaf_spread", f"SELECT kw, round(greatest(max(x) - min(x), max(y) - min(y)), 6) AS spread FROM ({vertices_sql('baskets')}) GROUP BY kw")
def udaf_spread(s, d):
    return load(s, d, "baskets").vertices.groupBy("kw").agg(udfs.spread_udaf("x", "y").alias("spread"))


@add("udtf_group", search_sql("buyers", [Q1], select="SELECT qid, d, group_id, member, dist FROM answer"))
def udtf_group(s, d):
    """The search as a table function in SQL."""
    udfs.register(s)
    g = load(s, d, "buyers")
    udfs.tagged_relation(g.vertices, g.edges, make_queries(s, [Q1])).createOrReplaceTempView("nearcohort_tagged")
    return s.sql("SELECT * FROM nearest_group(TABLE(nearcohort_tagged) PARTITION BY qid)")


@add("sink_roundtrip", f"WITH RECURSIVE {peel_cte('p', f'SELECT src, dst, 2 AS need FROM ({edges_sql('buyers')})', [])} SELECT src, dst FROM p_end")
def sink_roundtrip(s, d):
    """The truss index written by trussness and read with a filter that prunes partitions."""
    path = Workspace(s, "index").place("truss-index")
    write_truss_index(truss_decompose(load(s, d, "buyers").edges), path)
    return read_truss_index(s, path, 4).select("src", "dst")
