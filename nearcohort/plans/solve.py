"""Nearest qualifying groups for a batch of queries.

Every step carries ``qid``, so a workload costs the rounds of its slowest query.  A query
whose pruned graph is small is searched whole inside one grouped task; a larger one of the same
batch goes through distributed rounds until its candidate is small.  Every method has both forms.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.functions.geo import distance
from nearcohort.kernels import local_search as L
from nearcohort.model import GROUP_EDGES, GROUPS, ROUNDS, Constraints, Graph, check_queries, demands, push_vertices
from nearcohort.operators.components import components
from nearcohort.operators.graph import census, induce, meets_minimum, merge_census
from nearcohort.operators.qualify import prune, prune_own, qualify, social_peel
from nearcohort.operators.space import cell_index, in_range, next_radius, radius_steps
from nearcohort.operators.truss import KERNEL_EDGES, truss_peel
from nearcohort.plans.runtime import Workspace, few_rows, ship

METHODS = ("two_phase", "two_phase_plain", "nearest_insert", "farthest_peel", "radius_bisect", "all_radii")
SEEDS = ("kruskal", "forest", "bisect", "degree", "relax_keyword", "none")
CHECKS = ("full", "update", "lazy", "incremental")
#: Radii that one round of a distributed bisection or sweep tests at once: a round's latency
#: counts more than the smaller ones of its tests.
FAN = 8
#: Tasks of a batch that is searched in tasks, eight for each query up to this: few queries share one.
MOST_TASKS = 256
#: Edges of one part of a query's spanning forest.
FOREST_EDGES = 200_000
#: A graph of more vertices is searched among those nearest to each query before it is built whole.
NEAR_VERTICES = 4_000
#: So many vertices at first; if these have fewer than LEAST_NEAR edges, as many as should have NEAR_EDGES.
FIRST_NEAR, LEAST_NEAR, NEAR_EDGES = 400, 4_000, 250_000
#: Growth of these edges for queries that find nothing among them.
NEAR_GROWTH = 16


@dataclass
class Result:
    """groups, group_edges, rounds and counters of a batch; ``seconds`` of wall time."""

    groups: DataFrame
    group_edges: DataFrame
    rounds: DataFrame
    counters: DataFrame
    pruned: DataFrame
    seconds: float = 0.0
    plan: dict = field(default_factory=dict)


@dataclass
class _Near:
    """The vertices (as ``_located`` gives them) and edges (qid, src, dst) nearest to each query, and the edges of each."""

    held: DataFrame
    edges: DataFrame
    size: dict[int, int]


@dataclass
class _Job:
    """What all steps of one run share."""

    graph: Graph
    queries: DataFrame
    cons: Constraints
    work: Workspace
    kernel_edges: int
    held: DataFrame = None
    wanted: DataFrame = None
    vdist: DataFrame = None
    ledger: DataFrame = None
    pruned: DataFrame = None
    steps: DataFrame = None
    spatial: str = "none"
    cells: DataFrame = None
    grid: dict = None
    log: list = field(default_factory=list)

    def only(self, qids: list[int]) -> _Job:
        """The same job for some of its queries."""
        keep = lambda df: df if df is None else df.where(F.col("qid").isin(qids))
        return replace(self, queries=keep(self.queries), held=keep(self.held), wanted=keep(self.wanted), vdist=keep(self.vdist),
                       pruned=keep(self.pruned), ledger=None, steps=None, log=[])


def _prepare(graph, queries, cons, work, kernel_edges, preprune, index, own: _Near | None = None, in_task: bool = False) -> _Job:
    """``own``: the part that each query has of its own; ``in_task``: it is left to be pruned in the query's task."""
    q = check_queries(queries)
    job = _Job(graph, q, cons, work, kernel_edges)
    job.wanted = demands(q, cons)
    if own is not None:
        job.held, job.vdist = own.held, own.held.select("qid", "id", "dist")
        e = own.edges.join(F.broadcast(q.select("qid", "c")), "qid")
        if in_task:
            job.pruned = e.withColumn("comp", F.lit(-1).cast("long"))
        else:
            job.pruned = (prune_own(e, job.held, job.wanted, work, cons, kernel_edges) if preprune
                          else work.save(e.withColumn("comp", F.lit(-1).cast("long")), "unpruned"))
        return job
    restricted = (cons.coverage == "closed" or cons.jaccard is not None or cons.min_influence is not None
                  or not graph.vertices.where("x is null or y is null").isEmpty())
    job.held = _located(graph, q, cons, work)
    job.vdist = job.held.select("qid", "id", "dist")
    if preprune:
        job.pruned = prune(graph.edges, q, job.held, job.wanted, work, cons, index, kernel_edges, restricted)
    else:
        e = graph.edges.crossJoin(F.broadcast(q.select("qid", "c")))
        for end in ("src", "dst"):
            e = e.join(job.held.select("qid", F.col("id").alias(end)), ["qid", end], "left_semi")
        job.pruned = work.save(e.withColumn("comp", F.lit(-1).cast("long")), "unpruned")
    return job


def _located(graph: Graph, q: DataFrame, cons: Constraints, work: Workspace) -> DataFrame:
    """(qid, id, kw, held, influence, dist): distances are born rounded, and only once."""
    # a table of one small file is one task, whatever the queries make of it
    if (tasks := min(MOST_TASKS, q.count())) > 1:
        graph = graph.with_(vertices=graph.vertices.repartition(tasks, "id"))
    own = push_vertices(graph, q, cons)
    return work.save(own.select("qid", "id", "kw", "held", "influence", distance(cons.metric).alias("dist")), "vertices")


def _ledger(job: _Job) -> None:
    """Edges with their distance, range-partitioned and sorted by (qid, ed)."""
    a = job.vdist.select("qid", F.col("id").alias("src"), F.col("dist").alias("ds"))
    b = job.vdist.select("qid", F.col("id").alias("dst"), F.col("dist").alias("dd"))
    ed = job.pruned.join(a, ["qid", "src"]).join(b, ["qid", "dst"]).select("qid", "src", "dst", "c", F.greatest("ds", "dd").alias("ed"))
    job.ledger = job.work.save(ed.repartitionByRange("qid", "ed").sortWithinPartitions("qid", "ed"), "ledger")


# -- one task per query -------------------------------------------------------------------
_ROWS = "kind string, qid long, d double, a long, b long, group_id long, text string, nums array<double>"


def _kernel(job: _Job, edges: DataFrame, start: str, method: str, options: dict, preprune: bool = False) -> DataFrame:
    """Run a local solver per query over ``edges`` (qid, src, dst, c); tagged result rows.

    ``preprune``: the task first leaves the maximal cohesive parts that meet the demands; with ``start`` "prune" it lists
    their edges and no more, and nothing runs before these rows are asked for.
    """
    ship(job.work.spark)
    cons = job.cons
    ends = edges.select("qid", F.explode(F.array("src", "dst")).alias("id")).distinct()
    v = job.held.join(ends, ["qid", "id"], "left_semi").select(
        "qid", F.lit("v").alias("t"), F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), "dist",
        F.col("held").alias("words"), "influence", F.lit(0).alias("c"))
    e = edges.select("qid", F.lit("e").alias("t"), F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(0.0).alias("dist"),
                     F.lit(None).cast("array<string>").alias("words"), F.lit(0.0).alias("influence"), F.col("c").cast("int").alias("c"))
    w = job.wanted.select("qid", F.lit("w").alias("t"), F.col("least").cast("long").alias("a"), F.lit(0).cast("long").alias("b"),
                          F.lit(0.0).alias("dist"), F.array("kw").alias("words"), F.lit(0.0).alias("influence"), F.lit(0).alias("c"))
    tagged = v.unionByName(e).unionByName(w)
    min_size, sum_influence, social, rules = cons.min_size, cons.sum_influence, cons.social, cons.rules

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        columns = [x.split()[0] for x in _ROWS.split(", ")]
        qid = int(pdf["qid"].iloc[0])
        ver = pdf[pdf["t"] == "v"].sort_values(["dist", "a"])
        edg = pdf[pdf["t"] == "e"]
        if edg.empty:
            return pd.DataFrame([], columns=columns)
        want = pdf[pdf["t"] == "w"].sort_values("a")
        words = {x[0]: i for i, x in enumerate(want["words"])}
        ids = ver["a"].tolist()
        at = {x: i for i, x in enumerate(ids)}
        hold = [tuple({words[k] for k in h if k in words}) if h is not None else () for h in ver["words"]]
        pairs = [(min(at[a], at[b]), max(at[a], at[b])) for a, b in zip(edg["a"].tolist(), edg["b"].tolist(), strict=True)]
        weight = ver["influence"].tolist() if sum_influence is not None else None
        p = L.Problem(ids, ver["dist"].tolist(), hold, pairs, [int(x) for x in want["a"]], int(edg["c"].iloc[0]), min_size,
                      weight, sum_influence or 0.0, social, rules)
        rows = []
        if preprune:
            p = L.prune(p)
        if start == "prune":
            ans = L.Answer()
            rows = [("pruned", qid, 0.0, min(p.ids[a], p.ids[b]), max(p.ids[a], p.ids[b]), comp, "", [])
                    for comp, _, es in L.groups(p, L.Answer(edges=p.edges)) for a, b in es]
        elif start == "trim":
            ans = L.Answer()
            ans.d, ans.edges = L.trim(p, p.edges, ans, options.get("trim", "forest"))
        else:
            ans = L.SOLVERS[method](p, **options) if p.edges else L.Answer()
        for gid, members, es in L.groups(p, ans):
            rows += [("member", qid, ans.d, p.ids[m], 0, gid, "", [p.dist[m]]) for m in members]
            rows += [("edge", qid, ans.d, min(p.ids[x], p.ids[y]), max(p.ids[x], p.ids[y]), gid, "", []) for x, y in es]
        rows += [("round", qid, r[1], r[0], int(r[-1]), 0, "", [float(x) for x in r[2:-1]]) for r in ans.rounds]
        rows += [("counter", qid, 0.0, n, 0, 0, k, []) for k, n in ans.counters.items()]
        return pd.DataFrame(rows, columns=columns)

    # by number, or the queries of a batch, whose rows are few, would be put into one task
    tagged = tagged.repartition(min(MOST_TASKS, 8 * job.queries.count()), "qid")
    rows = tagged.groupBy("qid").applyInPandas(run, _ROWS)
    return rows if start == "prune" else job.work.save(rows, "kernel")


def _split(job: _Job, rows: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    kw = job.held.select("qid", F.col("id").alias("member"), "kw")
    groups = (rows.where("kind = 'member'").select("qid", "d", "group_id", F.col("a").alias("member"), F.col("nums")[0].alias("dist"))
              .join(kw, ["qid", "member"]).select("qid", "d", "group_id", "member", "kw", "dist"))
    edges = rows.where("kind = 'edge'").select("qid", "group_id", F.col("a").alias("src"), F.col("b").alias("dst"))
    n = lambda i: F.col("nums")[i].cast("long")
    rounds = rows.where("kind = 'round'").select(
        "qid", F.col("a").cast("int").alias("round"), "d", n(0).alias("edges"), n(1).alias("potential"), n(2).alias("peeled"),
        n(3).alias("v_edges"), n(4).alias("v_potential"), n(5).alias("v_peeled"), (F.col("b") == 1).alias("found"))
    counters = rows.where("kind = 'counter'").select("qid", F.col("text").alias("counter"), F.col("a").alias("n"))
    return groups, edges, rounds, counters


# -- distributed rounds ---------------------------------------------------------------------
def _feasible(job: _Job, edges: DataFrame, keys=("qid",)) -> DataFrame:
    """The whole check: qualifying cohesive parts of ``edges`` (keys, src, dst, c), with comp."""
    left = social_peel(edges, keys, job.cons.social, job.work, job.kernel_edges)
    return job.work.save(qualify(left, job.held, job.wanted, keys, job.work, job.cons, job.kernel_edges), "feasible")


def spanning_forest(ledger: DataFrame, work: Workspace, fan_in: int = 8, part_edges: int = FOREST_EDGES) -> DataFrame:
    """(qid, src, dst, ed) of the minimum spanning forests by distance.

    Each task reduces its edges to a forest, then the forests of a query are merged part by part:
    an edge that is the farthest of a cycle within a part is dispensable in the whole.  The
    number of parts falls by ``fan_in`` until every query has one; a forest has fewer edges than
    the query has vertices.
    """
    ship(work.spark)
    kind = "qid long, part long, src long, dst long, ed double"

    def reduced(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["ed", "src", "dst"], ignore_index=True)
        return pdf[_forest_mask(pdf["src"].to_numpy(), pdf["dst"].to_numpy())]

    def first(batches):
        for pdf in batches:
            for _, one in pdf.groupby("qid"):
                yield reduced(one)

    edges = ledger.select("qid", F.lit(0).cast("long").alias("part"), "src", "dst", "ed")
    part = work.save(edges.mapInPandas(first, kind), "forest")
    most = part.groupBy("qid").count().agg(F.max("count")).first()[0] or 0
    n = -(-most // part_edges)
    while True:
        n = max(1, n)
        dealt = part.withColumn("part", F.pmod(F.xxhash64("src", "dst"), F.lit(n)))
        part = work.save(dealt.groupBy("qid", "part").applyInPandas(reduced, kind), "forest")
        if n == 1:
            return part.drop("part")
        n = -(-n // fan_in)


def _forest_mask(src, dst) -> list[bool]:
    """Which of the sorted edges join two trees."""
    up: dict = {}

    def find(v):
        while up.setdefault(v, v) != v:
            up[v] = v = up[up[v]]
        return v

    out = []
    for s, t in zip(src.tolist(), dst.tolist(), strict=True):
        a, b = find(s), find(t)
        if a != b:
            up[a] = b
        out.append(a != b)
    return out


def seed_radius(job: _Job, method: str = "forest") -> DataFrame:
    """(qid, d): a radius that no answer undercuts.

    kruskal and forest unite edges nearest first until a set meets the demands, the latter
    on the spanning forest.  degree unites vertices only once they have c-1 neighbours within
    the radius.  bisect tests connected parts of the forest at bisected radii, without any
    task that holds a query.  relax_keyword asks for the nearest cohesive part without its
    keywords.  none starts at the least radius with c(c-1)/2 edges.
    """
    if method not in SEEDS:
        raise ValueError(f"unknown seed {method}")
    if method == "none":
        steps = job.steps.join(job.queries.select("qid", "c"), "qid")
        return (steps.groupBy("qid").agg(F.min(F.when(F.col("upto") >= F.col("c") * (F.col("c") - 1) / 2, F.col("ed"))).alias("d"),
                                         F.max("ed").alias("top")).select("qid", F.coalesce("d", "top").alias("d")))
    if method == "relax_keyword":
        free = _Job(job.graph, job.queries, Constraints(social=job.cons.social), job.work, job.kernel_edges, job.held,
                    job.wanted.limit(0), job.vdist, job.ledger, job.pruned, job.steps)
        return _bisect(free)[1].select("qid", "d")
    edges = spanning_forest(job.ledger, job.work) if method in ("forest", "bisect") else job.ledger
    edges = edges.join(job.queries.select("qid", "c"), "qid") if "c" not in edges.columns else edges
    if method == "bisect":
        part = _Job(job.graph, job.queries.withColumn("c", F.lit(2)), Constraints(min_size=job.cons.min_size), job.work,
                    job.kernel_edges, job.held, job.wanted, job.vdist, edges.withColumn("c", F.lit(2)), job.pruned,
                    job.work.save(radius_steps(edges), "steps"))
        return _bisect(part)[1].select("qid", "d")
    rows = _seed_kernel(job, edges, method)
    return rows.select("qid", "d")


def _seed_kernel(job: _Job, edges: DataFrame, method: str) -> DataFrame:
    ends = edges.select("qid", F.explode(F.array("src", "dst")).alias("id")).distinct()
    ship(job.work.spark)
    v = job.held.join(ends, ["qid", "id"], "left_semi").select(
        "qid", F.lit("v").alias("t"), F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), "dist", F.col("held").alias("words"),
        F.lit(0).alias("c"))
    e = edges.select("qid", F.lit("e").alias("t"), F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(0.0).alias("dist"),
                     F.lit(None).cast("array<string>").alias("words"), F.col("c").cast("int").alias("c"))
    w = job.wanted.select("qid", F.lit("w").alias("t"), F.col("least").cast("long").alias("a"), F.lit(0).cast("long").alias("b"),
                          F.lit(0.0).alias("dist"), F.array("kw").alias("words"), F.lit(0).alias("c"))
    min_size = job.cons.min_size

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ver, edg = pdf[pdf["t"] == "v"].sort_values(["dist", "a"]), pdf[pdf["t"] == "e"]
        want = pdf[pdf["t"] == "w"]
        words = {x[0]: i for i, x in enumerate(want["words"])}
        at = {x: i for i, x in enumerate(ver["a"].tolist())}
        hold = [tuple({words[k] for k in h if k in words}) if h is not None else () for h in ver["words"]]
        pairs = [(min(at[a], at[b]), max(at[a], at[b])) for a, b in zip(edg["a"].tolist(), edg["b"].tolist(), strict=True)]
        c = int(edg["c"].iloc[0]) if len(edg) else 2
        p = L.Problem(list(at), ver["dist"].tolist(), hold, pairs, [int(x) for x in want["a"]], c, min_size)
        d = L.seed_radius(p, "degree" if method == "degree" else "kruskal")
        return pd.DataFrame([(int(pdf["qid"].iloc[0]), d)] if d is not None else [], columns=["qid", "d"])

    return job.work.save(v.unionByName(e).unionByName(w).groupBy("qid").applyInPandas(run, "qid long, d double"), "seeds")


def _probe(job: _Job, at: DataFrame) -> DataFrame:
    """(qid, step, src, dst, c): the edges within each radius of ``at`` (qid, step, r)."""
    if job.spatial == "none":
        return job.ledger.join(F.broadcast(at), "qid").where("ed <= r").select("qid", "step", "src", "dst", "c")
    # by the spatial index: cells that touch a circle, exact distances, induced edges
    if job.cells is None:
        job.grid = _grid(job)
        job.cells = job.work.save(cell_index(job.graph.vertices.select("id", "x", "y"), **job.grid), "cells")
    near = in_range(job.cells, at.join(job.queries.select("qid", "qx", "qy"), "qid"), metric=job.cons.metric, keys=("qid", "step"), **job.grid)
    ids = job.work.save(near.join(job.held.select("qid", "id"), ["qid", "id"], "left_semi").select("qid", "step", "id"), "in-range")
    edges = job.pruned.select("qid", "src", "dst", "c").join(F.broadcast(at.select("qid", "step")), "qid")
    return induce(edges, ids, ["qid", "step"])


def _grid(job: _Job) -> dict:
    """The square that the cells divide."""
    x = job.graph.vertices.agg(F.min(F.least("x", "y")), F.max(F.greatest("x", "y"))).first()
    low, high = x[0] if x[0] is not None else 0.0, x[1] if x[1] is not None else 1.0
    return {"low": float(low), "high": float(max(high, low + 1e-6))}


def _test(job: _Job, wanted: dict[int, list[int]], number: int) -> tuple[DataFrame, dict[int, set[int]]]:
    """Check the given steps of every query at once: (qualifying edges with step and comp, steps that hold)."""
    rows = [(q, s) for q, steps in wanted.items() for s in steps]
    at = F.broadcast(few_rows(job.work.spark, rows, "qid long, step long"))
    r = job.work.save(job.steps.join(at, ["qid", "step"]).select("qid", F.col("step").cast("long").alias("step"), F.col("ed").alias("r"), "upto"), "radii")
    ok = _feasible(job, _probe(job, r.select("qid", "step", "r")), ("qid", "step"))
    held: dict[int, set[int]] = {}
    for x in ok.select("qid", "step").distinct().collect():
        held.setdefault(x["qid"], set()).add(x["step"])
    for x in r.orderBy("qid", "step").collect():
        job.log.append((x["qid"], number, x["r"], x["upto"], x["upto"], x["upto"], 0, 0, 0, x["step"] in held.get(x["qid"], ())))
    return ok, held


class _Best:
    """The nearest step known to hold for each query, with its edges."""

    def __init__(self, job: _Job):
        self.job, self.at, self.edges = job, {}, []

    def note(self, ok: DataFrame, held: dict[int, set[int]]) -> None:
        new = [(q, min(steps)) for q, steps in held.items() if min(steps) < self.at.get(q, 1 << 62)]
        if new:
            self.at.update(new)
            self.edges = [e.where(~F.col("qid").isin([q for q, _ in new])) for e in self.edges]
            mine = few_rows(self.job.work.spark, new, "qid long, step long")
            self.edges.append(ok.join(F.broadcast(mine), ["qid", "step"], "left_semi"))

    def result(self) -> tuple[DataFrame, DataFrame]:
        """(edges with comp, (qid, d)) of all queries that have an answer."""
        job, out = self.job, None
        for e in self.edges:
            e = e.select("qid", "src", "dst", "c", "comp")
            out = e if out is None else out.unionByName(e)
        if out is None:
            out = few_rows(job.work.spark, [], "qid long, src long, dst long, c int, comp long")
        at = F.broadcast(few_rows(job.work.spark, list(self.at.items()), "qid long, step long"))
        radius = job.work.save(job.steps.join(at, ["qid", "step"]).select("qid", F.col("ed").alias("d")), "optimum")
        return job.work.save(out, "found"), radius


def _ends(job: _Job) -> dict[int, int]:
    """The number of steps of each query."""
    return {r["qid"]: r["n"] for r in work_steps(job).groupBy("qid").agg(F.count("*").alias("n")).collect()}


def _bisect(job: _Job, low: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Least feasible radius per query by division of its steps; (edges with comp, (qid, d)).

    Each round tests ``FAN`` - 1 steps of every open query at once.  ``low`` (qid, lo, hi) bounds the
    steps: hi is known to be feasible or one past the last.
    """
    ends, best, number = _ends(job), _Best(job), 0
    state = {r["qid"]: (r["lo"], r["hi"]) for r in low.collect()} if low is not None else {q: (0, n) for q, n in ends.items()}
    while open_ := {q: (lo, hi) for q, (lo, hi) in state.items() if lo < hi}:
        ask = {}
        for q, (lo, hi) in open_.items():
            n = min(FAN - 1, hi - lo)
            ask[q] = sorted({lo + (hi - lo) * (i + 1) // (n + 1) for i in range(n)} if hi - lo > n else set(range(lo, hi)))
        ok, held = _test(job, ask, number)
        best.note(ok, held)
        for q, (lo, hi) in open_.items():
            good = held.get(q, set())
            failed = [x for x in ask[q] if x not in good]
            state[q] = (max([lo, *(x + 1 for x in failed)]), min([hi, *good]))
        number += 1
    rest = {q: [lo] for q, (lo, _) in state.items() if q not in best.at and lo < ends.get(q, 0)}
    if rest:  # known to be feasible from before
        best.note(*_test(job, rest, number))
    return best.result()


def _far_peel(job: _Job):
    """Farthest peel from distributed rounds: the whole check first, then as much in tasks as these hold.

    (groups, edges, counters).  The whole is what is left of a query at its last radius.  If that has at
    most ``kernel_edges`` edges for every query, the far ends are peeled in tasks; otherwise in rounds.
    """
    whole, held = _test(job, {q: [n - 1] for q, n in _ends(job).items()}, 0)
    if (whole.groupBy("qid").count().agg(F.max("count")).first()[0] or 0) > job.kernel_edges:
        return *_finish(job, *_sweep(job, False, (whole, held))), None
    rows = _kernel(job, whole.select("qid", "src", "dst", "c"), "trim", "farthest_peel", {"trim": "traverse"})
    groups, edges, _, counters = _split(job, rows)
    return groups, edges, counters


def _sweep(job: _Job, outward: bool, first: tuple[DataFrame, dict[int, set[int]]] | None = None) -> tuple[DataFrame, DataFrame]:
    """The single-vertex baselines over distributed rounds; (edges with comp, (qid, d)).  ``first``: the check of the whole, if known.

    Outward, vertices enter one distance at a time, nearest first, and each radius has a whole
    check until one holds.  Inward, the farthest distance goes from what is left of the whole
    until nothing qualifies.  A round does this for ``FAN`` consecutive distances of every query.
    """
    ends, best, number = _ends(job), _Best(job), 0
    if outward:
        at = dict.fromkeys(ends, 0)
        while open_ := {q: list(range(i, min(i + FAN, ends[q]))) for q, i in at.items() if i < ends[q] and q not in best.at}:
            best.note(*_test(job, open_, number))
            at, number = {q: i + FAN for q, i in at.items()}, number + 1
        return best.result()
    whole, held = first or _test(job, {q: [n - 1] for q, n in ends.items()}, number)
    best.note(whole, held)
    at = {q: ends[q] - 1 for q in held}
    while at := {q: i for q, i in at.items() if i > 0}:
        number += 1
        # what fell with a farther distance never comes back
        left = best.result()[0].select("qid", "src", "dst")
        job.ledger = job.work.save(job.ledger.join(left, ["qid", "src", "dst"], "left_semi"), "left")
        ask = {q: list(range(max(0, i - FAN), i)) for q, i in at.items()}
        ok, held = _test(job, ask, number)
        best.note(ok, held)
        # a query goes on if all of its distances could be dropped
        at = {q: ask[q][0] for q in at if len(held.get(q, ())) == len(ask[q])}
    return best.result()


def work_steps(job: _Job) -> DataFrame:
    if job.steps is None:
        job.steps = job.work.save(radius_steps(job.ledger), "steps")
    return job.steps


class _Parts:
    """Connected parts of growing edge sets with their keyword counts, both kept up to date:
    new edges contract the labels that they join, and the counts of these parts are added up."""

    def __init__(self, job: _Job):
        self.job, self.label, self.counts = job, None, None

    def add(self, new: DataFrame) -> None:
        """Take in edges (qid, src, dst)."""
        job, work = self.job, self.job.work
        if self.label is None:
            self.label = work.save(components(new, ["qid"], work=work, kernel_edges=job.kernel_edges), "labels")
            self.counts = work.save(census(self.label, job.held, job.wanted), "census")
            return
        label, root, fresh = contract(self.label, new, work, job.kernel_edges)
        self.label = work.save(label, "labels")
        moved = lambda c: c.join(root, ["qid", "comp"], "left").withColumn("comp", F.coalesce("root", "comp")).drop("root")
        self.counts = work.save(merge_census(moved(self.counts), moved(census(fresh, job.held, job.wanted))), "census")

    def good(self) -> DataFrame:
        """(qid, comp) of the parts that hold the keywords; of queries that want none, all."""
        job = self.job
        free = job.queries.select("qid").join(F.broadcast(job.wanted.select("qid").distinct()), "qid", "left_anti")
        return meets_minimum(self.counts, job.wanted).unionByName(self.label.join(F.broadcast(free), "qid", "left_semi").select("qid", "comp").distinct())

    def keep(self, edges: DataFrame) -> DataFrame:
        """Those of ``edges`` that lie in such parts, with ``comp``."""
        at = self.label.join(self.good(), ["qid", "comp"], "left_semi")
        return edges.join(at.withColumnRenamed("id", "src"), ["qid", "src"])


def _sizes(frames: dict[str, DataFrame]) -> dict[tuple[str, int], tuple[int, int]]:
    """Edges and vertices of each query in each frame, by one job."""
    both = None
    for name, df in frames.items():
        e = df.select(F.lit(name).alias("name"), "qid", F.explode(F.array("src", "dst")).alias("id"))
        both = e if both is None else both.unionByName(e)
    got = both.groupBy("name", "qid", "id").agg(F.count("*").alias("k")).groupBy("name", "qid").agg(F.sum("k").alias("k"), F.count("*").alias("v"))
    return {(r["name"], r["qid"]): (r["k"] // 2, r["v"]) for r in got.collect()}


def grow(job: _Job, delta: float, seed: str, check: str, pool: str) -> tuple[DataFrame, dict[int, tuple[int, int]]]:
    """Distributed growth: edges of the first qualifying trusses per query, and the steps
    (last that failed + 1, first that held) that bracket the optimum."""
    work, steps, spark = job.work, work_steps(job), job.work.spark
    seeds = work.save(seed_radius(job, seed), "seeds")
    now = steps.join(F.broadcast(seeds), "qid").where("ed = d").select("qid", "ed", "step", "upto", F.lit(-1.0).alias("before"))
    now, number, found_all, bracket = work.save(now, "radius"), 0, None, {}
    pool_edges = few_rows(spark, [], "qid long, src long, dst long")
    parts, known = _Parts(job), _Parts(job)
    counted_only = job.cons.min_size <= 2 and job.cons.sum_influence is None
    last: dict[int, int] = {}
    while rows := now.collect():
        r = F.broadcast(now.select("qid", F.col("ed").alias("r"), "before"))
        edges = work.save(job.ledger.join(r, "qid").where("ed <= r").select("qid", "src", "dst", "c", (F.col("ed") > F.col("before")).alias("new")), "within")
        part = edges
        if check in ("lazy", "incremental"):
            parts.add(edges.where("new").select("qid", "src", "dst"))
            part = work.save(parts.keep(edges).select("qid", "src", "dst", "c"), "potential")
        todo = part
        if check in ("full", "lazy"):
            found = _feasible(job, part.select("qid", "src", "dst", "c"))
        else:
            todo = part.join(pool_edges, ["qid", "src", "dst"], "left_anti")
            own = pool_edges.join(part, ["qid", "src", "dst"], "left_semi")
            base = part.select("qid", "src", "dst", (F.col("c") - 2).alias("need"))
            if pool == "induced" and check == "incremental":
                ends = todo.select("qid", F.explode(F.array("src", "dst")).alias("id")).distinct()
                peeled = truss_peel(induce(base, ends, ["qid"]), ["qid"], None, work, job.kernel_edges)
                peeled = peeled.join(pool_edges, ["qid", "src", "dst"], "left_anti")
            else:
                peeled = truss_peel(base, ["qid"], own, work, job.kernel_edges)
            new = work.save(peeled.select("qid", "src", "dst"), "new-in-pool")
            pool_edges = work.save(pool_edges.unionByName(new), "pool")
            mine = pool_edges.join(F.broadcast(now.select("qid")), "qid", "left_semi").join(F.broadcast(job.queries.select("qid", "c")), "qid")
            if check == "incremental" and counted_only:
                known.add(new)
                found = work.save(known.keep(mine), "found")
            else:
                found = work.save(qualify(mine, job.held, job.wanted, ["qid"], work, job.cons, job.kernel_edges), "found")
            if pool == "induced":  # a last no of this pool is not believed
                ended = work.save(now.join(steps.groupBy("qid").agg(F.max("step").alias("end")), "qid").where("step = end").select("qid"), "ended")
                again = ended.join(found.select("qid").distinct(), "qid", "left_anti")
                if not again.isEmpty():
                    found = found.unionByName(_feasible(job, part.join(F.broadcast(again), "qid", "left_semi").select("qid", "src", "dst", "c"))
                                              .select(*found.columns))
        sizes = _sizes({"edges": edges, "potential": part, "peeled": todo})
        done = {x["qid"] for x in found.select("qid").distinct().collect()}
        for x in rows:
            q = x["qid"]
            e, p, t = (sizes.get((k, q), (0, 0)) for k in ("edges", "potential", "peeled"))
            job.log.append((q, number, x["ed"], e[0], p[0], t[0], e[1], p[1], t[1], q in done))
            if q in done:
                bracket[q] = (last.get(q, 0), x["step"])
            last[q] = x["step"] + 1
        hit = found.select("qid", "src", "dst", "c")
        found_all = hit if found_all is None else found_all.unionByName(hit)
        open_ = [(x["qid"], x["upto"], x["ed"]) for x in rows if x["qid"] not in done]
        if not open_:
            break
        state = few_rows(spark, open_, "qid long, upto long, before double")
        now = work.save(next_radius(steps, state, delta).join(F.broadcast(state.select("qid", "before")), "qid"), "radius")
        number += 1
    if found_all is None:
        found_all = few_rows(spark, [], "qid long, src long, dst long, c int")
    return found_all, bracket


def contract(label: DataFrame, new: DataFrame, work: Workspace, kernel_edges: int = KERNEL_EDGES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Unite labels (qid, id, comp) along ``new`` (qid, src, dst): (labels, (qid, comp, root), labels of new vertices)."""
    ends = new
    for end in ("src", "dst"):
        ends = (ends.join(label.select("qid", F.col("id").alias(end), F.col("comp").alias(f"c_{end}")), ["qid", end], "left")
                .withColumn(f"c_{end}", F.coalesce(f"c_{end}", end)))
    ends = work.save(ends, "new-ends")
    root = components(ends.select("qid", F.col("c_src").alias("src"), F.col("c_dst").alias("dst")), ["qid"], work=work, kernel_edges=kernel_edges)
    root = work.save(root.select("qid", F.col("id").alias("comp"), F.col("comp").alias("root")), "roots")
    fresh = (ends.select("qid", F.explode(F.array("src", "dst")).alias("id")).distinct()
             .join(label.select("qid", "id"), ["qid", "id"], "left_anti").withColumn("comp", F.col("id")).select("qid", "id", "comp"))
    both = (label.unionByName(fresh).join(root, ["qid", "comp"], "left")
            .select("qid", "id", F.coalesce("root", "comp").alias("comp")))
    return both, root, fresh


def merge_components(label: DataFrame, new: DataFrame, work: Workspace, kernel_edges: int = KERNEL_EDGES) -> DataFrame:
    """Labels (qid, id, comp) after uniting along ``new`` (qid, src, dst)."""
    return contract(label, new, work, kernel_edges)[0]


def _finish(job: _Job, edges: DataFrame, radius: DataFrame):
    """Groups and group edges from qualifying edges (qid, src, dst, comp) at the optimum."""
    e = edges.select("qid", F.col("comp").alias("group_id"), "src", "dst")
    m = e.select("qid", "group_id", F.explode(F.array("src", "dst")).alias("member")).distinct()
    g = (m.join(job.held.select("qid", F.col("id").alias("member"), "kw", "dist"), ["qid", "member"])
         .join(radius, "qid").select("qid", "d", "group_id", "member", "kw", "dist"))
    return g, e


def solve(graph: Graph, queries: DataFrame, method: str = "two_phase", *, delta: float = 2.0, seed: str = "forest",
          check: str = "incremental", pool: str = "anchored", trim: str = "auto", preprune: bool = True,
          constraints: Constraints | None = None, index: DataFrame | None = None, spatial: str = "none", engine: str = "auto",
          kernel_edges: int = KERNEL_EDGES, only_first: bool = False, work: Workspace | None = None, nearest: bool = True) -> Result:
    """All nearest qualifying groups of every query.

    Queries without an answer have no rows in ``groups``.  ``engine``: ``kernel`` searches each
    query in one task, ``rounds`` over distributed rounds, ``auto`` decides for each query by the
    edges of its pruned graph.  ``trim``: forest and traverse in a task, banded by division of the
    radii in rounds, auto by size.  ``index`` is a truss index (src, dst, truss); ``spatial='cells'``
    lets distributed bisection find the vertices within a radius by grid cells.  ``only_first`` keeps
    the group of least id.  Constraints other than trusses have no pools of known parts: ``update``
    and ``incremental`` check them whole, and ``plan`` says so.  Rules of the caller's own are checked
    in tasks, beyond ``kernel_edges`` among a query's nearest edges.  ``nearest`` searches a graph of more than
    ``NEAR_VERTICES`` vertices, unless it has an index, among the vertices nearest to each query first
    (``_nearest_first``); ``pruned``, ``rounds`` and ``counters`` are then those of these parts.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    if delta <= 1:
        raise ValueError("delta must exceed 1")
    for name, value, known in (("seed", seed, SEEDS), ("check", check, CHECKS), ("pool", pool, ("anchored", "induced")),
                               ("trim", trim, ("auto", "forest", "traverse", "banded")), ("engine", engine, ("auto", "kernel", "rounds")),
                               ("spatial", spatial, ("none", "cells"))):
        if value not in known:
            raise ValueError(f"unknown {name} {value}")
    began = time.perf_counter()
    cons = constraints or Constraints()
    if spatial == "cells" and method != "radius_bisect":
        raise ValueError("only radius_bisect searches by cells")
    if cons.rules and (engine == "rounds" or method == "all_radii" or spatial == "cells"):
        raise ValueError("rules of the caller's own are checked in tasks: engine='kernel'")
    work = work or Workspace(graph.edges.sparkSession, f"solve-{method}")
    if nearest and index is None:
        v, n = work.save_count(graph.vertices, "graph-vertices")  # read again and again
        graph = graph.with_(vertices=v)
        nearest = n > NEAR_VERTICES
    if nearest and index is None:
        options = {"delta": delta, "seed": seed, "check": check, "pool": pool, "trim": trim, "preprune": preprune, "spatial": spatial,
                   "engine": engine, "kernel_edges": kernel_edges, "only_first": only_first}
        return _nearest_first(graph, check_queries(queries), method, cons, work, options, began)
    return _solve(graph, queries, method, cons, work, began, delta, seed, check, pool, trim, preprune, index, spatial, engine, kernel_edges, only_first)


def _solve(graph, queries, method, cons, work, began, delta, seed, check, pool, trim, preprune, index, spatial, engine, kernel_edges,
           only_first, own: _Near | None = None) -> Result:
    """``solve`` over the whole graph, or over the part that each query has of its own."""
    in_task = (own is not None and engine != "rounds" and method != "all_radii" and spatial != "cells"
               and (engine == "kernel" or max(own.size.values(), default=0) <= kernel_edges))
    job = _prepare(graph, queries, cons, work, kernel_edges, preprune, index, own, in_task)
    job.spatial = spatial
    if method == "two_phase_plain":
        seed, check, trim = "none", "full", "traverse" if trim == "auto" else trim
    if cons.social != "truss" or cons.rules:
        check = {"update": "full", "incremental": "lazy"}.get(check, check)
    size = own.size if in_task else {r["qid"]: r["count"] for r in job.pruned.groupBy("qid").count().collect()}
    if engine == "kernel" and method != "all_radii":
        local = list(size)
    elif engine == "rounds" or method == "all_radii" or spatial == "cells":
        local = []
    else:
        local = [q for q, n in size.items() if n <= kernel_edges]
    far = [q for q in size if q not in set(local)]
    got = []
    options = {}
    if method == "two_phase":
        options = {"delta": delta, "seed": seed, "check": check, "pool": pool, "trim": "traverse" if trim == "traverse" else "forest"}
    elif method == "two_phase_plain":
        options = {"delta": delta}
    if local or not far:
        one = job.only(local) if far else job
        rows = _kernel(one, one.pruned, "search", "radius_bisect" if method == "all_radii" else method, options, in_task and preprune)
        got.append(_split(one, rows))
        if in_task and preprune:
            left = _kernel(one, one.pruned, "prune", method, options, True).select("qid", F.col("a").alias("src"), F.col("b").alias("dst"), F.col("group_id").alias("comp"))
            job.pruned = left.join(F.broadcast(job.queries.select("qid", "c")), "qid").select("qid", "src", "dst", "c", "comp")
    if far and cons.rules:
        got.append(_nearest_edges(job.only(far), far, method, options))
    elif far:
        got.append(_rounds(job.only(far) if local else job, method, delta, seed, check, pool, trim))
    groups, edges, rounds, counters = got[0]
    if len(got) > 1:
        groups, edges, rounds, counters = (a.unionByName(b) for a, b in zip(*got, strict=True))
    if only_first:
        first = groups.groupBy("qid").agg(F.min("group_id").alias("group_id"))
        groups, edges = (x.join(F.broadcast(first), ["qid", "group_id"], "left_semi") for x in (groups, edges))
    groups = work.save(_typed(groups, GROUPS), "groups")
    return Result(groups, _typed(edges, GROUP_EDGES), _typed(rounds, ROUNDS), counters, job.pruned, time.perf_counter() - began,
                  {"method": method, "engine": "rounds" if not local and far else "kernel" if not far else "both", "seed": seed, "check": check,
                   "trim": trim, "largest": max(size.values(), default=0)})


def _near_part(graph: Graph, held: DataFrame, qids: list[int], share: float, work: Workspace) -> _Near:
    """The vertices of each query within the radius that holds ``share`` of its vertices, with the edges among them."""
    mine = held.where(F.col("qid").isin(qids))
    r = mine.groupBy("qid").agg(F.percentile_approx("dist", share).alias("r"))
    near = work.save(mine.join(F.broadcast(r), "qid").where("dist <= r").drop("r"), "near")
    ids = near.select("id") if len(qids) == 1 else work.save(near.select("id").distinct(), "near-ids")
    e = graph.among(ids) if graph.among is not None else induce(graph.edges, ids)
    if len(qids) == 1:
        e = e.select(F.lit(qids[0]).cast("long").alias("qid"), "src", "dst")
    else:
        e = e.join(near.select("qid", F.col("id").alias("src")), "src").join(near.select("qid", F.col("id").alias("dst")), ["qid", "dst"], "left_semi")
    e = work.save(e.select("qid", "src", "dst"), "near-edges")
    return _Near(near, e, {r["qid"]: r["count"] for r in e.groupBy("qid").count().collect()})


def _nearest_first(graph: Graph, q: DataFrame, method: str, cons: Constraints, work: Workspace, options: dict, began: float) -> Result:
    """Every query among its nearest vertices first, the rest among more, and the last over the whole graph.

    Whether a radius holds is decided by the edges within it alone, and if it holds so does every larger one.
    So a part of the graph that is whole up to some radius has the optimum and all of its groups, or no
    group at all; then a larger part is searched.
    """
    held = _located(graph, q, cons, work)
    open_, got, parts, log, n, goal = [r["qid"] for r in q.collect()], [], [], {}, FIRST_NEAR, None
    most = held.groupBy("qid").count().agg(F.max("count")).first()[0] or 0
    while open_ and n < most:
        near = _near_part(graph, held, open_, n / most, work)
        k = max(near.size.values(), default=0)
        if goal is None:
            goal = NEAR_EDGES if k < LEAST_NEAR else k
        if k < goal / 2 and n * 2 < most:  # edges grow with the square of the vertices
            n = max(2 * n, min(32 * n, int(n * (goal / max(k, 1)) ** 0.5)))
            continue
        part = graph.with_(vertices=graph.vertices.join(near.held.select("id").distinct(), "id", "left_semi"), edges=near.edges.select("src", "dst").distinct())
        r = _solve(part, q.where(F.col("qid").isin(open_)), method, cons, work, began, index=None, own=near, **options)
        got.append(_after(r, log, work))
        done = {x["qid"] for x in r.groups.select("qid").distinct().collect()}
        parts.append((n, k, len(done)))
        open_ = [x for x in open_ if x not in done]
        goal = NEAR_GROWTH * max(k, goal)
        n = max(2 * n, int(n * (goal / max(k, 1)) ** 0.5))
    if open_ or not got:
        r = _solve(graph, q.where(F.col("qid").isin(open_)), method, cons, work, began, index=None, **options)
        got.append(_after(r, log, work))
    out = got[0]
    for r in got[1:]:
        out = replace(out, plan=r.plan, **{x: getattr(out, x).unionByName(getattr(r, x)) for x in ("groups", "group_edges", "rounds", "counters", "pruned")})
    return replace(out, seconds=time.perf_counter() - began, plan=out.plan | {"largest": max(r.plan["largest"] for r in got), "nearest": parts})


def _after(r: Result, log: dict[int, int], work: Workspace) -> Result:
    """The result with its rounds numbered on from those of smaller parts; ``log`` counts them."""
    rounds = r.rounds
    if any(log.values()):
        before = F.broadcast(few_rows(work.spark, list(log.items()), "qid long, earlier int"))
        rounds = rounds.join(before, "qid", "left").withColumn("round", F.col("round") + F.coalesce("earlier", F.lit(0))).select(*r.rounds.columns)
    for x in r.rounds.groupBy("qid").agg((F.max("round") + 1).alias("n")).collect():
        log[x["qid"]] = log.get(x["qid"], 0) + x["n"]
    return replace(r, rounds=rounds)


def _nearest_edges(job: _Job, qids: list[int], method: str, options: dict):
    """(groups, edges, rounds, counters) by tasks that hold the nearest ``kernel_edges`` edges of each query.

    A radius is judged by the edges within it alone, so what is found among these is the optimum; a
    query without an answer there is refused.
    """
    _ledger(job)
    limit = work_steps(job).where(F.col("upto") <= job.kernel_edges).groupBy("qid").agg(F.max("ed").alias("r"))
    near = job.work.save(job.ledger.join(F.broadcast(limit), "qid").where("ed <= r").select("qid", "src", "dst", "c"), "nearest")
    out = _split(job, _kernel(job, near, "search", method, options))
    if set(qids) - {r["qid"] for r in out[0].select("qid").distinct().collect()}:
        raise ValueError(f"no answer within the nearest {job.kernel_edges} edges of a query: rules of the caller's own are checked in tasks, "
                         "engine='kernel' takes all edges into one")
    return out


def _rounds(job: _Job, method: str, delta: float, seed: str, check: str, pool: str, trim: str):
    """(groups, edges, rounds, counters) by distributed rounds."""
    work, cons = job.work, job.cons
    _ledger(job)
    work_steps(job)
    counters = few_rows(work.spark, [], "qid long, counter string, n long")
    if method == "radius_bisect":
        found = _finish(job, *_bisect(job))
    elif method == "nearest_insert":
        found = _finish(job, *_sweep(job, True))
    elif method == "farthest_peel":
        *found, seen = _far_peel(job)
        counters = counters if seen is None else seen
    elif method == "all_radii":
        found = _all_radii(job)
    else:
        cand, bracket = grow(job, delta, seed, check, pool)
        cand = work.save(cand, "candidates")
        big = (cand.groupBy("qid").count().agg(F.max("count")).first()[0] or 0) > job.kernel_edges
        if trim == "banded" or (trim == "auto" and big) or cons.social != "truss":
            low = few_rows(work.spark, [(q, lo, hi) for q, (lo, hi) in bracket.items()], "qid long, lo long, hi long")
            ledger = job.ledger.join(cand.drop("c"), ["qid", "src", "dst"], "left_semi")
            job.ledger = work.save(ledger, "candidate-ledger")
            found = _finish(job, *_bisect(job, low))
        else:
            rows = _kernel(job, cand, "trim", method, {"trim": "traverse" if trim == "traverse" else "forest"})
            groups, edges, _, counters = _split(job, rows)
            found = groups, edges
    return *found, few_rows(work.spark, job.log, ROUNDS), counters


def _typed(df: DataFrame, kinds: str) -> DataFrame:
    return df.select(*[F.col(n).cast(t).alias(n) for n, t in (x.split() for x in kinds.split(", "))])


def _all_radii(job: _Job):
    """Ground truth: every radius of a query is tested, all at once, keyed by (qid, step)."""
    steps = work_steps(job)
    keyed = (job.ledger.join(steps.select("qid", "step", F.col("ed").alias("r")), "qid").where("ed <= r")
             .select("qid", "step", "src", "dst", "c"))
    ok = _feasible(job, keyed, ("qid", "step"))
    first = ok.groupBy("qid").agg(F.min("step").alias("step"))
    radius = job.work.save(steps.join(first, ["qid", "step"]).select("qid", F.col("ed").alias("d")), "optimum")
    return _finish(job, ok.join(first, ["qid", "step"], "left_semi"), radius)


def nearest_group(graph: Graph, at: tuple[float, float], keywords, rho: int, c: int, **options) -> Result:
    """The search of a single query."""
    from nearcohort.model import make_queries

    return solve(graph, make_queries(graph.edges.sparkSession, [(0, float(at[0]), float(at[1]), list(keywords), rho, c)]), **options)
