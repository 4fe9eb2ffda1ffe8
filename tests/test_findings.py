"""Small forms of what failed on larger tables."""

import os
import random
import threading

import pytest
from pyspark.sql import functions as F

from nearcohort.kernels import local_search as L
from nearcohort.kernels.local_search import peel
from nearcohort.model import Constraints, Graph, make_queries
from nearcohort.operators import truss
from nearcohort.plans import solve as S
from nearcohort.plans import workloads
from nearcohort.plans.runtime import Workspace, checkpoint_root, few_rows
from nearcohort.plans.solve import solve
from nearcohort.queries import reports
from nearcohort.queries.gallery import recursive_labels
from nearcohort.sources.graphs import _meetings


def test_recursion_has_no_limit_of_rows(spark):
    # a part of 1,500 vertices: walks between all of its pairs are more rows than a recursion may have
    edges = [((i * 7919) % 1499 + 1, 0 if i < 2 else (i * 31 % i * 7919) % 1499 + 1) for i in range(1, 1499)]
    edges = [(min(e), max(e)) for e in edges if e[0] != e[1]] + [(5000, 5001), (5001, 5002), (5000, 5002)]
    df = spark.createDataFrame(edges, "src long, dst long")
    up = {}

    def find(v):
        while up.setdefault(v, v) != v:
            v = up[v]
        return v

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    want = {v: find(v) for v in list(up)}
    before = spark.conf.get("spark.sql.cteRecursionRowLimit")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "500")
    try:
        assert {r["id"]: r["comp"] for r in recursive_labels(df, Workspace(spark, "test")).collect()} == want
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", before)
    assert recursive_labels(df.limit(0), Workspace(spark, "test")).isEmpty()


def test_meetings_shuffle_no_pairs(spark):
    rows = [(k, (k * k + i * 37) % 90) for k in range(40) for i in range(k % 12)] + [(None, 1), (3, None), (7, 90), (7, 90)]
    df = spark.createDataFrame(rows, "bucket long, user long")
    want = {(a, b) for k, a in rows for m, b in rows if k is not None and k == m and a is not None and b is not None and a < b}
    for members in (10, 8192):
        e = _meetings(df, "bucket", "user", members)
        assert sorted((r["src"], r["dst"]) for r in e.collect()) == sorted(want)
    # the last step is the task that finds the pairs: nothing is shuffled after it
    plan = e._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan[:plan.index("FlatMapGroupsInArrow")]


def test_peel_without_a_list_of_triangles(spark, monkeypatch):
    dice, rows, want, locked = random.Random(5), [], set(), []
    for qid, need in ((1, 3), (2, 0)):
        e = sorted({(min(p), max(p)) for p in ((dice.randrange(66), dice.randrange(66)) for _ in range(500)) if p[0] != p[1]})
        rows += [(qid, a, b, need) for a, b in e]
        sure = peel([x for x in e if x[0] % 3 or x[1] % 2], need + 2) if qid == 1 else set()
        locked += [(qid, a, b) for a, b in sure]
        want |= {(qid, a, b) for a, b in peel(e, need + 2, frozenset(sure))}
    df = spark.createDataFrame(rows, "qid long, src long, dst long, need int")
    pool = spark.createDataFrame(locked, "qid long, src long, dst long")
    monkeypatch.setattr(truss, "triangles", None)  # all triangles are never listed
    monkeypatch.setattr(truss, "WORDS", 1)
    for wedges in (0, 1 << 40):
        monkeypatch.setattr(truss, "WEDGES", wedges)
        got = truss.truss_peel(df, ["qid"], pool, kernel_edges=0, dense=0).collect()
        assert {(r["qid"], r["src"], r["dst"]) for r in got} == want and len(got) == len(want)
    assert len(rows) > len(want) > 400


def test_far_peel_walks_only_parts_that_lose(spark):
    # 40 cliques of six at growing distances: one part loses at a time
    ids = list(range(240))
    edges = [(a, b) for a in ids for b in range(a + 1, 240) if a // 6 == b // 6]
    p = L.Problem(ids, [float(i) for i in ids], [(0,)] * 240, edges, [1], 4)
    out = L.farthest_peel(p)
    # two members of each clique can go before it falls as a whole
    assert out.d == 3.0 and sorted({v for e in out.edges for v in e}) == [0, 1, 2, 3]
    assert out.counters["visited"] <= 40 * (5 + 4)
    rows = [(i, "a", float(i), 0.0) for i in ids]
    g = Graph(spark.createDataFrame(rows, "id long, kw string, x double, y double"), spark.createDataFrame(edges, "src long, dst long"))
    r = solve(g, make_queries(spark, [(1, 0.0, 0.0, ["a"], 1, 4)]), "farthest_peel", engine="rounds", preprune=False)
    assert sorted(x["member"] for x in r.groups.collect()) == [0, 1, 2, 3]
    # one whole check, then the task
    assert r.rounds.count() == 1 and r.counters.where("counter = 'deletions'").first()["n"] > 0


def test_rules_beyond_the_limit_of_a_task(spark):
    class Any:
        def peel(self, edges):
            return edges

        def accept(self, members):
            return len(members) > 1

    ids = range(60)
    edges = [(a, b) for a in ids for b in range(a + 1, 60) if a // 6 == b // 6]
    rows = [(i, "a", float(i), 0.0) for i in ids]
    g = Graph(spark.createDataFrame(rows, "id long, kw string, x double, y double"), spark.createDataFrame(edges, "src long, dst long"))
    near = make_queries(spark, [(1, 0.0, 0.0, ["a"], 1, 4)])
    cons = Constraints(rules=(Any(),))
    r = solve(g, near, constraints=cons, kernel_edges=40)
    assert sorted((x["member"], x["d"]) for x in r.groups.collect()) == [(i, 3.0) for i in range(4)]
    with pytest.raises(ValueError):  # the first clique alone holds more edges than the task may
        solve(g, near, constraints=cons, kernel_edges=5)
    with pytest.raises(ValueError):
        solve(g, near, "all_radii", constraints=cons)


def test_nearest_part_spares_the_whole_graph(spark, monkeypatch):
    # ten cliques of six at growing distances; only edges among given vertices can be had
    ids, asked = range(60), []
    edges = spark.createDataFrame([(a, b) for a in ids for b in range(a + 1, 60) if a // 6 == b // 6], "src long, dst long")
    v = spark.createDataFrame([(i, "ab"[i % 2], float(i), 0.0) for i in ids], "id long, kw string, x double, y double")

    def among(some):
        asked.append(some.count())
        return edges.join(some.withColumnRenamed("id", "src"), "src", "left_semi").join(some.withColumnRenamed("id", "dst"), "dst", "left_semi")

    never = edges.where(F.raise_error(F.lit("the whole graph")).isNull())
    qs = make_queries(spark, [(1, 0.0, 0.0, ["a", "b"], 2, 4), (2, 59.0, 0.0, ["b"], 3, 6)])
    rows = lambda r: sorted(tuple(x) for x in r.groups.collect())
    want = rows(solve(Graph(v, edges), qs, nearest=False))
    assert {x[0] for x in want} == {1, 2}
    for name, value in (("NEAR_VERTICES", 20), ("FIRST_NEAR", 3), ("LEAST_NEAR", 1), ("NEAR_EDGES", 4), ("NEAR_GROWTH", 4)):
        monkeypatch.setattr(S, name, value)
    # parts without an answer are left for larger ones, whose rounds are numbered on
    r = solve(Graph(v, never, "far", among), qs, "nearest_insert")
    assert rows(r) == want and len(r.plan["nearest"]) > 1 and max(asked) < 60
    n = r.rounds.groupBy("qid").agg(F.count("*").alias("n"), F.count_distinct("round").alias("k"), F.max("round").alias("m")).collect()
    assert all(x["n"] == x["k"] == x["m"] + 1 for x in n)
    # a query without any answer goes through the whole graph
    none = make_queries(spark, [(1, 0.0, 0.0, ["a"], 5, 4), (2, 0.0, 0.0, ["a"], 1, 4)])
    r = solve(Graph(v, edges), none)
    assert rows(r) == rows(solve(Graph(v, edges), none, nearest=False)) and {x[0] for x in rows(r)} == {2}


def test_ablation_searches_at_once(spark, monkeypatch):
    under_way, most, begun, lock, meet = 0, 0, 0, threading.Lock(), threading.Barrier(3, timeout=20)

    class Found:
        groups = spark.createDataFrame([(1, 2.0, 3)], "qid long, d double, member long")

    def search(graph, queries, method, **options):
        nonlocal under_way, most, begun
        with lock:
            under_way, begun = under_way + 1, begun + 1
            most, early = max(most, under_way), begun <= 3
        if early:  # the first three wait for each other
            meet.wait()
        with lock:
            under_way -= 1
        return Found

    monkeypatch.setattr(workloads, "solve", search)
    monkeypatch.setattr(workloads, "AT_ONCE", 3)
    g = Graph(spark.createDataFrame([(1, "a", 0.0, 0.0)], "id long, kw string, x double, y double"), spark.createDataFrame([(1, 2)], "src long, dst long"))
    out = workloads.ablation(g, make_queries(spark, [(1, 0.0, 0.0, ["a"], 1, 4)]))
    runs = {tuple(x) for x in out.select("seed", "check", "pool", "trim", "engine").collect()}
    assert most == 3 and len(runs) == 6 * 5 * 2 + 5


def test_dense_parts_are_trimmed_by_bits(monkeypatch):
    # farthest ends go from a dense graph: the answer of the plain form, and few counts of triangles
    dice, cases = random.Random(7), 0
    for _ in range(80):
        n, share = dice.randrange(3, 40), dice.choice((0.15, 0.3, 0.5, 0.8))
        edges = [(a, b) for a in range(n) for b in range(a + 1, n) if dice.random() < share]
        hold = [tuple(k for k in range(2) if dice.random() < 0.5) for _ in range(n)]
        dist, c, got = sorted(float(dice.randrange(n)) for _ in range(n)), dice.choice((2, 3, 4, 5)), []
        sure = peel([e for e in edges if sum(e) % 3], c)
        for vertices in (L.MASK_VERTICES, -1):
            with monkeypatch.context() as m:
                m.setattr(L, "MASK_VERTICES", vertices)
                p = L.Problem(list(range(n)), dist, hold, edges, [1, 2], c)
                far, small = L.farthest_peel(p), L.prune(p)
                again = L.farthest_peel(small).d if small.edges else None
                got.append((far.d, sorted(far.edges), again, sorted(L.peel(edges, c, frozenset(sure)))))
        assert got[0] == got[1] and got[0][0] == got[0][2]
        cases += got[0][0] is not None
    assert cases > 20


def test_a_workload_holds_one_search_at_a_time(spark):
    ids = range(12)
    g = Graph(spark.createDataFrame([(i, "ab"[i % 2], float(i), 0.0) for i in ids], "id long, kw string, x double, y double"),
              spark.createDataFrame([(a, b) for a in ids for b in range(a + 1, 12)], "src long, dst long"))
    root = checkpoint_root(spark).removeprefix("file:").replace("//", "/")
    before = set(os.listdir(root)) if os.path.isdir(root) else set()
    rows = workloads.sweep(g, "rho", (1, 2), ("radius_bisect",), n=2, base={"c": 3, "n_keywords": 1})
    assert len(rows) == 2 and all(r["found"] == 2 for r in rows)
    assert [x for x in set(os.listdir(root)) - before if "radius_bisect" in x] == []


def test_a_dense_peel_writes_no_copy_of_the_edges(spark, monkeypatch):
    dice = random.Random(9)
    e = sorted({(min(p), max(p)) for p in ((dice.randrange(66), dice.randrange(66)) for _ in range(520)) if p[0] != p[1]})
    df = spark.createDataFrame([(a, b, 3) for a, b in e], "src long, dst long, need int")
    first, written, save = F.expr("src % 3 = 0 or dst % 2 = 0"), [], Workspace.save
    monkeypatch.setattr(Workspace, "save", lambda self, d, name: written.append(name) or save(self, d, name))
    options = {"kernel_edges": 0, "dense": 0, "stored": True}
    gone, n = truss.truss_drops(df.where(first), [], **options)
    part = [x for x in e if x[0] % 3 == 0 or x[1] % 2 == 0]
    lost = {(r["src"], r["dst"]) for r in gone.collect()}
    assert lost == set(part) - peel(part, 5) and n == len(lost) > 0
    locked = df.join(gone.withColumn("lost", F.lit(True)), ["src", "dst"], "left").withColumn("pool", first & F.col("lost").isNull())
    got = truss.truss_peel(locked, [], "pool", **options).collect()
    assert {(r["src"], r["dst"]) for r in got} == peel(e, 5, frozenset(set(part) - lost))
    assert not {"peel-input", "peeled", "pool"} & set(written)


def test_the_ablation_combines_every_seed_with_every_trim(spark, monkeypatch):
    class Found:
        groups = spark.createDataFrame([(1, 2.0, 3)], "qid long, d double, member long")

    g = Graph(spark.createDataFrame([(1, "a", 0.0, 0.0)], "id long, kw string, x double, y double"), spark.createDataFrame([(1, 2)], "src long, dst long"))
    monkeypatch.setattr(reports, "load", lambda *a: g)
    monkeypatch.setattr(workloads, "solve", lambda *a, **k: Found)
    rows = reports.QUERIES["ablation"](spark, "nowhere").collect()
    checks = {("full", "anchored"), ("update", "anchored"), ("lazy", "anchored"), ("incremental", "anchored"), ("incremental", "induced")}
    want = {(seed, *check, trim) for seed in S.SEEDS for check in checks for trim in ("forest", "traverse", "banded")}
    assert {tuple(r)[1:5] for r in rows} == want and len(rows) == len(want) == 90


def test_few_rows_start_no_python(spark):
    rows = [(1, ["a", None], 2.5, True, None), (2, [], 3.0, False, "x")]
    kind = "qid long, phi array<string>, r double, found boolean, kw string"
    assert [(r["qid"], r["phi"], r["r"], r["found"], r["kw"]) for r in few_rows(spark, rows, kind).orderBy("qid").collect()] == rows
    none = few_rows(spark, [], kind)
    assert none.isEmpty() and none.dtypes == spark.createDataFrame([], kind).dtypes
    assert few_rows(spark, rows, kind)._jdf.queryExecution().executedPlan().toString().startswith("LocalTableScan")


def test_a_dense_nucleus_lists_no_cliques(spark, monkeypatch):
    dice, rows, want = random.Random(11), [], set()
    for qid, many in ((1, 420), (2, 900)):
        e = sorted({(min(p), max(p)) for p in ((dice.randrange(90), dice.randrange(90)) for _ in range(many)) if p[0] != p[1]})
        rows += [(qid, a, b, 1) for a, b in e]
        want |= {(qid, a, b) for a, b in L.nucleus(e, 1, 3, 4)}
    df = spark.createDataFrame(rows, "qid long, src long, dst long, need int")
    monkeypatch.setattr(truss, "cliques", None)
    monkeypatch.setattr(truss, "WORDS", 1)  # two blocks of vertices
    for wedges in (0, 1 << 40):  # all pairs of blocks, or the last edges by their triangles
        monkeypatch.setattr(truss, "WEDGES", wedges)
        got = truss.nucleus_peel(df, ["qid"], dense=0).collect()
        assert {tuple(r)[:3] for r in got} == want and len(got) == len(want)
        one = truss.nucleus_peel(df.where("qid = 2").drop("qid"), [], r=2, dense=0).collect()
        assert {(2, r["src"], r["dst"]) for r in one} == {x for x in want if x[0] == 2}
    assert len(rows) - 100 > len(want) > 300


def test_the_vertices_of_a_batch_are_spread_over_tasks(spark, monkeypatch):
    v = spark.createDataFrame([(i, "a", float(i), 0.0) for i in range(50)], "id long, kw string, x double, y double").coalesce(1)
    g, tasks = Graph(v, spark.createDataFrame([(1, 2)], "src long, dst long")), []
    monkeypatch.setattr(Workspace, "save", lambda self, d, name: tasks.append(d.rdd.getNumPartitions()) or d)
    for n in (1, 6):
        qs = make_queries(spark, [(i, 0.0, 0.0, ["a"], 1, 3) for i in range(n)])
        assert S._located(g, qs, Constraints(), Workspace(spark, "test")).count() == 50 * n
    assert tasks == [1, 6]
