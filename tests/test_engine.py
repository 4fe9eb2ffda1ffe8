import os

import duckdb
import pytest
from pyspark.sql import functions as F

from nearcohort.model import Constraints, Graph, check_queries, make_queries
from nearcohort.operators.components import components
from nearcohort.operators.graph import canonical_edges, covers, sample_vertices, triangles
from nearcohort.operators.truss import nucleus_peel, truss_decompose, truss_peel
from nearcohort.plans import comparators, explain, metrics, workloads
from nearcohort.plans.solve import nearest_group, solve
from nearcohort.queries.sqlgen import search_sql
from nearcohort.sources import tables
from nearcohort.sources.graphs import load

SF = "/root/testdata/sf0.001"
Q3 = (1, 50.0, 50.0, ["BUILDING", "MACHINERY", "FURNITURE"], 2, 4)


@pytest.fixture(scope="module")
def buyers(spark):
    g = load(spark, SF, "buyers")
    return Graph(g.vertices.cache(), g.edges.cache(), "buyers")


@pytest.fixture(scope="module")
def truth():
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con.sql(search_sql("buyers", [Q3])).fetchall()


def rows(df):
    return sorted((r["qid"], r["d"], r["group_id"], r["member"]) for r in df.collect())


@pytest.mark.parametrize("method,options", [
    ("two_phase", {}), ("two_phase_plain", {}), ("nearest_insert", {}), ("farthest_peel", {}), ("radius_bisect", {}), ("all_radii", {}),
    ("two_phase", {"engine": "rounds"}), ("two_phase", {"engine": "rounds", "trim": "banded", "seed": "none", "check": "full"})])
def test_solvers_equal_sql(spark, buyers, truth, method, options):
    got = rows(solve(buyers, make_queries(spark, [Q3]), method, **options).groups)
    assert got == sorted(tuple(t[:4]) for t in truth) and len(got) == 19 and got[0][1] == 47.633341


@pytest.mark.parametrize("method,options", [
    ("nearest_insert", {}), ("farthest_peel", {})])
def test_nothing_is_held_in_one_task(spark, buyers, truth, method, options):
    r = solve(buyers, make_queries(spark, [Q3]), method, engine="rounds", kernel_edges=0, **options)
    assert rows(r.groups) == sorted(tuple(t[:4]) for t in truth)
    assert r.plan["method"] == method and r.plan["engine"] == "rounds"


def test_each_query_has_its_engine(spark, buyers):
    qs = make_queries(spark, [Q3, (2, 10.0, 20.0, ["BUILDING"], 1, 3), (3, 0.0, 0.0, ["NONE"], 1, 3)])
    whole = solve(buyers, qs)
    size = {r["qid"]: r["count"] for r in whole.pruned.groupBy("qid").count().collect()}
    assert size[1] < size[2]
    split = solve(buyers, qs, "radius_bisect", kernel_edges=size[1])
    assert split.plan["engine"] == "both" and rows(split.groups) == rows(whole.groups) and whole.plan["engine"] == "kernel"
    assert {r["qid"] for r in split.rounds.collect()} == {1, 2}


def test_rules_of_the_callers_own(spark, buyers):
    class Few:
        """At most the edges between ids that differ by less than 60, and three members at least."""

        def peel(self, edges):
            return {e for e in edges if abs(e[0] - e[1]) < 60}

        def accept(self, members):
            return len(members) >= 3

    qs = make_queries(spark, [(1, 50.0, 50.0, ["BUILDING"], 1, 3)])
    cons = Constraints(rules=(Few(),))
    got = [rows(solve(buyers, qs, m, constraints=cons).groups) for m in ("two_phase", "radius_bisect")]
    assert got[0] == got[1] and got[0]
    near = Graph(buyers.vertices, buyers.edges.where("dst - src < 60"))
    assert got[0] == rows(solve(near, qs).groups)
    for options in ({"engine": "rounds"}, {"kernel_edges": 0}):
        with pytest.raises(ValueError):
            solve(buyers, qs, constraints=cons, **options)


def test_trussness_has_no_greatest_level(spark):
    e = spark.createDataFrame([(i, j) for i in range(6) for j in range(i + 1, 6)] + [(5, 6), (5, 7), (6, 7), (7, 8)], "src long, dst long")
    for kernel_edges in (0, 1000):
        got = {(r["src"], r["dst"]): r["truss"] for r in truss_decompose(e, kernel_edges=kernel_edges).collect()}
        assert len(got) == 19 and got[0, 1] == 6 and got[6, 7] == 3 and got[7, 8] == 2
    assert truss_decompose(e.limit(0), kernel_edges=0).isEmpty()


def test_vocabulary_takes_every_keyword(spark):
    v = spark.range(1500).select("id", F.concat(F.lit("k"), "id").alias("kw"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))
    assert len(workloads.vocabulary(Graph(v, spark.createDataFrame([], "src long, dst long")))) == 1500


def test_aggregate_objective_against_every_level(spark, buyers):
    qs = make_queries(spark, [(1, 50.0, 50.0, [], 0, 2)])
    far = max(((r["x"] - 50) ** 2 + (r["y"] - 50) ** 2) ** 0.5 for r in buyers.vertices.collect())
    d = {c: solve(buyers, make_queries(spark, [(1, 50.0, 50.0, [], 0, c)])).groups.first()["d"] for c in (2, 3, 4, 5)}
    for w in (0.1, 0.9):
        got = comparators.aggregate_group(buyers, qs, w).first()
        cost = {c: w * x / far - (1 - w) * c / 5 for c, x in d.items()}
        best = min(cost, key=cost.get)
        assert got["c"] == best and got["d"] == d[best] and got["cost"] == pytest.approx(cost[best], abs=1e-5)


def test_spark_measures_count_what_ran(spark):
    m = metrics.spark_measures(spark, lambda: spark.range(1000).repartition(3, "id").groupBy("id").count().count())
    assert m["jobs"] >= 1 and m["tasks"] >= 1 and m["shuffle_bytes"] > 0 and m["seconds"] > 0
    assert metrics.time_runs(lambda: None, 3, warm=1)["runs"] == 3


def test_no_answer_and_absent_keyword(spark, buyers):
    assert solve(buyers, make_queries(spark, [(1, 50.0, 50.0, ["NONE"], 1, 3)])).groups.isEmpty()
    assert solve(buyers, make_queries(spark, [(1, 50.0, 50.0, ["NONE"], 1, 3)]), engine="rounds").groups.isEmpty()


def test_mixed_batch_and_validator(spark, buyers):
    qs = make_queries(spark, [Q3, (2, 10.0, 20.0, ["BUILDING"], 1, 3), (3, 0.0, 0.0, [], 0, 4), (4, 90.0, 9.0, ["HOUSEHOLD"], 99, 3)])
    res = solve(buyers, qs)
    bad = metrics.check_group(res, qs).where("not (cohesive and connected and covered and within)")
    assert bad.isEmpty() and {r["qid"] for r in res.groups.collect()} == {1, 2, 3}


def test_bad_arguments(spark, buyers):
    good = make_queries(spark, [Q3])
    for bad in ([(1, 0.0, 0.0, [], 1, 1)], [(1, 0.0, 0.0, [], -1, 3)], [Q3, Q3], [(None, 0.0, 0.0, [], 1, 3)]):
        with pytest.raises(ValueError):
            check_queries(make_queries(spark, bad))
    for options in ({"delta": 1.0}, {"seed": "x"}, {"method": "x"}, {"pool": "x"}):
        with pytest.raises(ValueError):
            solve(buyers, good, **options)
    with pytest.raises(ValueError):
        Graph(buyers.vertices.drop("kw"), buyers.edges)
    with pytest.raises(ValueError):
        Constraints(social="x")


def test_dirty_edges_and_null_places(spark):
    e = canonical_edges(spark.createDataFrame([(1, 2), (2, 1), (3, 3), (None, 1), (2, 3), (1, 3)], "src long, dst long"))
    assert sorted(map(tuple, e.collect())) == [(1, 2), (1, 3), (2, 3)]
    v = spark.createDataFrame([(1, "a", 0.0, 0.0), (2, None, 1.0, 0.0), (3, "b", None, 0.0)], "id long, kw string, x double, y double")
    g = Graph(v, e)
    assert nearest_group(g, (0.0, 0.0), [], 0, 3).groups.isEmpty()  # the third has no place
    got = nearest_group(g, (0.0, 0.0), ["a"], 1, 2).groups.collect()
    assert {r["member"] for r in got} == {1, 2}


def test_truss_rounds_equal_kernel(spark, buyers):
    e = buyers.edges.withColumn("need", F.lit(2))
    a = set(map(tuple, truss_peel(e, []).select("src", "dst").collect()))
    assert a == set(map(tuple, truss_peel(e, [], kernel_edges=0).select("src", "dst").collect())) and len(a) == 348
    assert dict(map(tuple, truss_decompose(buyers.edges).groupBy("truss").count().collect())) == {2: 155, 3: 494, 4: 328, 5: 20}
    assert dict(map(tuple, truss_decompose(buyers.edges, kernel_edges=0).groupBy("truss").count().collect())) == {2: 155, 3: 494, 4: 328, 5: 20}


def test_nuclei_of_other_orders(spark):
    from itertools import combinations

    e = spark.createDataFrame([(a, b, 1) for a, b in combinations(range(5), 2)] + [(4, 5, 1), (3, 5, 1), (2, 5, 1), (5, 6, 1)], "src long, dst long, need int")
    for r, s, n in ((2, 3, 13), (2, 4, 13), (3, 5, 10), (2, 5, 10)):
        for limit in (0, 1000):
            assert nucleus_peel(e, [], r=r, s=s, kernel_edges=limit).count() == n, (r, s, limit)


def test_nucleus_of_a_clique(spark):
    clique = [(a, b, 1) for a in range(4) for b in range(a + 1, 4)] + [(3, 4, 1), (3, 5, 1), (4, 5, 1)]
    e = spark.createDataFrame(clique, "src long, dst long, need int")
    assert nucleus_peel(e, []).count() == 6


def test_components_both_ways(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (101, 102)], "src long, dst long")
    a = dict(map(tuple, components(e).collect()))
    assert set(a.values()) == {0, 100} and len(a) == 44
    k = e.withColumn("qid", F.lit(1))
    assert {(r["id"], r["comp"]) for r in components(k, ["qid"], kernel_edges=1000).collect()} == set(a.items())
    assert components(e.limit(0)).count() == 0


def test_far_vertices_and_shifts_change_nothing(spark, buyers):
    base = rows(nearest_group(buyers, (50.0, 50.0), Q3[3], 2, 4).groups)
    moved = Graph(buyers.vertices.withColumns({"x": F.col("x") + 64, "y": F.col("y") - 32}), buyers.edges)
    assert [(r[3]) for r in rows(nearest_group(moved, (114.0, 18.0), Q3[3], 2, 4).groups)] == [r[3] for r in base]
    far = spark.createDataFrame([(10_000 + i, "BUILDING", 1e6, 1e6) for i in range(5)], buyers.vertices.select("id", "kw", "x", "y").schema)
    ring = spark.createDataFrame([(10_000 + i, 10_000 + j) for i in range(5) for j in range(i + 1, 5)], "src long, dst long")
    more = Graph(buyers.vertices.select("id", "kw", "x", "y").unionByName(far), buyers.edges.unionByName(ring))
    assert rows(nearest_group(more, (50.0, 50.0), Q3[3], 2, 4).groups) == base


def test_measures_and_comparators(spark, buyers):
    qs = make_queries(spark, [Q3])
    res = solve(buyers, qs)
    p = metrics.pruning_ratios(buyers, res).first().asDict()
    assert all(0 < p[k] <= 1 for k in ("h_g", "dh_h", "p_dh", "c_p"))
    assert metrics.round_bounds(res, 2.0).where("not ok").isEmpty()
    cost = metrics.stage_cost(solve(buyers, qs, seed="none", check="full"), 2.0)
    assert cost.where("not ok or factor > bound").isEmpty() and cost.count() == 1
    t = metrics.team_report(res).first()
    assert t["size"] == 19 and t["edges"] == 45 and t["mean_support"] >= 2
    assert comparators.nearest_by_role(buyers, qs).count() == 6
    assert not comparators.social_only(buyers, qs).groups.isEmpty()
    six = comparators.fixed_size_group(buyers, make_queries(spark, [(1, 50.0, 50.0, [], 0, 3)]), 3).collect()
    assert six and all(r["reached"] == (len(six) == 3) for r in six)
    assert "query 1: 348 edges after pruning; one task" in explain.explain_strategy(buyers, qs)
    assert "distributed rounds" in explain.explain_strategy(buyers, qs, 100)
    assert workloads.random_queries(spark, 5, ["a", "b", "c", "d"], 3, 1, 4).count() == 5
    m = spark.createDataFrame([(1, "a"), (1, "b")], "qid long, kw string").withColumn("comp", F.lit(1))
    q = make_queries(spark, [(1, 0.0, 0.0, ["a"], 1, 3)])
    assert covers(m, q).first()["covered"] and not covers(m, q, "closed").first()["covered"]


def test_sample_shares_are_nested(spark, buyers):
    small, large = (set(map(tuple, sample_vertices(buyers, p).edges.collect())) for p in (40, 80))
    assert small < large


def test_triangles_of_a_hub(spark):
    star = [(0, i) for i in range(1, 50)] + [(1, 2)]
    assert triangles(spark.createDataFrame(star, "src long, dst long")).collect() == [(0, 1, 2)]


def test_plans(spark):
    df = tables.table(spark, SF, "customer").where("c_acctbal > 100").select("c_custkey")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "GreaterThan(c_acctbal" in plan and "c_name" not in plan


def test_text_sources(spark, tmp_path):
    from nearcohort.sources.geosocial import GeoSocialSource

    (tmp_path / "e.txt").write_text("# c\n1\t2\n2\tx\n3\t1\n")
    assert tables.read_edge_list(spark, str(tmp_path / "e.txt")).count() == 2
    (tmp_path / "c.txt").write_text("5\t2010-10-19T23:55:27Z\t30.2\t-97.7\tplace\n")
    row = tables.read_checkins(spark, str(tmp_path / "c.txt")).first()
    assert row["user"] == 5 and row["y"] == 30.2
    spark.dataSource.register(GeoSocialSource)
    assert spark.read.format("geosocial").option("path", str(tmp_path / "e.txt")).option("kind", "edges").load().count() == 2


def test_sinks(spark, buyers, tmp_path):
    res = solve(buyers, make_queries(spark, [Q3]))
    g = res.groups
    for method in ("two_phase", "other"):
        tables.write_rounds(res.rounds, str(tmp_path / "rounds"), "buyers", method)
    back = spark.read.parquet(str(tmp_path / "rounds"))
    assert back.count() == 2 * res.rounds.count() and {r["method"] for r in back.select("method").distinct().collect()} == {"two_phase", "other"}
    name = f"edges_{os.getpid()}"
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    tables.write_bucketed(buyers.edges, name, 4)
    both = spark.table(name).groupBy("src").count()
    assert "Exchange" not in both._jdf.queryExecution().executedPlan().toString() and spark.table(name).count() == 997
    spark.sql(f"DROP TABLE {name}")
    for fmt in ("parquet", "json", "csv"):
        tables.write_groups(g, str(tmp_path / fmt), "buyers", fmt)
        r = spark.read.format(fmt)
        assert (r.option("header", True) if fmt == "csv" else r).load(str(tmp_path / fmt)).count() == 19
    assert os.path.isdir(tmp_path / "parquet" / "graph=buyers")


def test_vectors_of_many_rows_are_compared_all_with_all(spark, tmp_path):
    import numpy as np
    import pyarrow as pa
    import pyarrow.parquet as pq

    n, dim = 20_050, 128  # more rows than one block holds
    x = np.random.default_rng(3).standard_normal((n, dim)).astype(np.float32)
    rows = [*x[:-3].tolist(), [0.0] * dim, None, [1.0, None]]
    pq.write_table(pa.table({"vec_id": pa.array(range(n), pa.int64()), "embedding": pa.array(rows, pa.list_(pa.float32())),
                             "label": pa.array([0] * n, pa.int32())}), tmp_path / "embeddings.parquet")
    u = x[:-3].astype(np.float64)
    u /= np.linalg.norm(u, axis=1)[:, None]
    want = set()
    for at in range(0, n, 2000):
        i, j = np.nonzero(np.round(u[at:at + 2000] @ u.T, 6) >= 0.35)
        want |= {(a, b) for a, b in zip((i + at).tolist(), j.tolist(), strict=True) if a < b}
    got = [tuple(e) for e in load(spark, str(tmp_path), "vectors").edges.collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 1000
