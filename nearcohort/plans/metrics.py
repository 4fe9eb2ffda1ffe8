"""Cost and quality measures."""

from __future__ import annotations

import statistics
import time
import uuid
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearcohort.model import Graph, check_queries
from nearcohort.operators.graph import support
from nearcohort.plans.solve import Result


def spark_measures(spark: SparkSession, fn: Callable[[], object]) -> dict[str, float]:
    """What Spark did while ``fn`` ran: seconds, jobs, stages, tasks, bytes shuffled and spilled.

    The jobs are those of a job group of their own; stages that were skipped count as none.
    """
    sc, group = spark.sparkContext, f"measure-{uuid.uuid4().hex}"
    began = time.perf_counter()
    sc.setJobGroup(group, "measured")
    try:
        fn()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    took = time.perf_counter() - began
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    jobs = tracker.getJobIdsForGroup(group)
    out = {"seconds": round(took, 3), "jobs": len(jobs), "stages": 0, "tasks": 0, "shuffle_bytes": 0, "spill_bytes": 0}
    stages = {s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    for s in stages:
        try:
            data = store.lastStageAttempt(s)
        except Py4JJavaError:
            continue  # no longer kept
        if data.numCompleteTasks():
            out["stages"] += 1
            out["tasks"] += data.numCompleteTasks()
            out["shuffle_bytes"] += data.shuffleWriteBytes()
            out["spill_bytes"] += data.diskBytesSpilled()
    return out


def stage_cost(result: Result, delta: float) -> DataFrame:
    """(qid, cost, last, factor, bound, ok): cost of growth against one check of its last radius.

    A check of E edges costs E^1.5.  Radii that grow by delta in edges make the sum at most
    1 + 1/(delta^1.5 - 1) times the last check (``ok``), and the last holds less than delta times the
    edges of the optimum (more by its class of ties), hence ``bound`` = 1 + delta^1.5 + 1/(delta^1.5 - 1)
    over a check at the optimum.
    """
    r = result.rounds.withColumn("one", F.pow("edges", F.lit(1.5)))
    f = delta**1.5
    g = r.groupBy("qid").agg(F.round(F.sum("one"), 6).alias("cost"), F.round(F.max("one"), 6).alias("last"), F.count("*").alias("n"))
    return g.select("qid", "cost", "last", F.round(F.col("cost") / F.col("last"), 6).alias("factor"),
                    F.lit(round(1 + f + 1 / (f - 1), 6)).alias("bound"), (F.col("cost") <= (1 + 1 / (f - 1)) * F.col("last") + 1e-6).alias("ok"))


def time_runs(fn: Callable[[], object], n: int = 3, warm: int = 0) -> dict[str, float]:
    """Seconds of ``n`` runs: mean, median, p95; ``warm`` runs before them are not counted."""
    took = []
    for _ in range(warm):
        fn()
    for _ in range(n):
        a = time.perf_counter()
        fn()
        took.append(time.perf_counter() - a)
    took.sort()
    return {"runs": n, "mean": statistics.mean(took), "median": statistics.median(took), "p95": took[min(n - 1, int(0.95 * n))]}


def pruning_ratios(graph: Graph, result: Result) -> DataFrame:
    """(qid, h_g, dh_h, p_dh, c_p and the edge forms) of the last growth round of each query.

    h_g: vertices left by the maximal-truss pruning; dh_h: of these within the last radius;
    p_dh: of these in parts that hold the keywords; c_p: of these not in a known truss.
    """
    if "nearest" in result.plan:
        raise ValueError("ratios are those of the whole graph: solve(..., nearest=False)")
    n = graph.edges.select(F.explode(F.array("src", "dst")).alias("id")).agg(F.count_distinct("id")).first()[0]
    h = (result.pruned.select("qid", F.explode(F.array("src", "dst")).alias("id")).groupBy("qid")
         .agg(F.count_distinct("id").alias("h")))
    he = result.pruned.groupBy("qid").agg(F.count("*").alias("he"))
    last = result.rounds.groupBy("qid").agg(F.max_by(F.struct("edges", "potential", "peeled", "v_edges", "v_potential", "v_peeled"), "round").alias("r")).select("qid", "r.*")
    share = lambda a, b: F.round(F.when(b > 0, a / b), 6)
    return (h.join(he, "qid").join(last, "qid").select(
        "qid", share(F.col("h"), F.lit(n)).alias("h_g"), share(F.col("v_edges"), F.col("h")).alias("dh_h"),
        share(F.col("v_potential"), F.col("v_edges")).alias("p_dh"), share(F.col("v_peeled"), F.col("v_potential")).alias("c_p"),
        share(F.col("edges"), F.col("he")).alias("dh_h_edges"), share(F.col("potential"), F.col("edges")).alias("p_dh_edges"),
        share(F.col("peeled"), F.col("potential")).alias("c_p_edges")))


def round_bounds(result: Result, delta: float) -> DataFrame:
    """(qid, rounds, tested, last, bound, ok): edges tested in all rounds against the geometric bound.

    The sum is at most delta/(delta-1) times the last round; distances that tie may add a
    class of ties, which ``ok`` allows for by the looser factor 1 + delta/(delta-1).
    """
    r = result.rounds.groupBy("qid").agg(F.count("*").alias("rounds"), F.sum("edges").alias("tested"), F.max("edges").alias("last"))
    f = delta / (delta - 1)
    return r.withColumn("bound", F.round(F.lit(f) * F.col("last"), 6)).withColumn("ok", F.col("tested") <= (1 + f) * F.col("last"))


def team_report(result: Result) -> DataFrame:
    """(qid, group_id, size, d, keywords, edges, density, mean_support) of every group."""
    m = result.groups.groupBy("qid", "group_id").agg(
        F.count("*").alias("size"), F.max("dist").alias("d"), F.count_distinct("kw").alias("keywords"))
    s = support(result.group_edges, ["qid", "group_id"]).groupBy("qid", "group_id").agg(
        F.count("*").alias("edges"), F.round(F.avg("sup"), 6).alias("mean_support"))
    return m.join(s, ["qid", "group_id"]).withColumn("density", F.round(2 * F.col("edges") / (F.col("size") * (F.col("size") - 1)), 6))


def team_ties(members: DataFrame, graph: Graph) -> DataFrame:
    """(qid, size, d, edges, density) of any team (qid, member, dist) in the social graph."""
    a, b = (members.select("qid", F.col("member").alias(x)) for x in ("src", "dst"))
    e = a.join(graph.edges, "src").join(b, ["qid", "dst"]).groupBy("qid").agg(F.count("*").alias("edges"))
    return (members.groupBy("qid").agg(F.count("*").alias("size"), F.max("dist").alias("d")).join(e, "qid", "left")
            .withColumn("edges", F.coalesce("edges", F.lit(0)))
            .withColumn("density", F.round(2 * F.col("edges") / (F.col("size") * (F.col("size") - 1)), 6)))


def check_group(result: Result, queries: DataFrame) -> DataFrame:
    """(qid, group_id, cohesive, connected, covered, within): each condition of a group, tested anew."""
    from nearcohort.operators.components import components

    q = check_queries(queries)
    keys = ["qid", "group_id"]
    sup = support(result.group_edges, keys).groupBy(*keys).agg(F.min("sup").alias("least"))
    parts = components(result.group_edges, keys).groupBy(*keys).agg(F.count_distinct("comp").alias("parts"))
    n = result.groups.groupBy(*keys).agg(F.collect_list("kw").alias("kws"), F.max("dist").alias("far"), F.first("d").alias("d"))
    enough = F.forall("phi", lambda k: F.size(F.filter("kws", lambda x: x == k)) >= F.col("rho"))
    return (n.join(sup, keys).join(parts, keys).join(F.broadcast(q), "qid").select(
        *keys, (F.col("least") >= F.col("c") - 2).alias("cohesive"), (F.col("parts") == 1).alias("connected"),
        enough.alias("covered"), (F.col("far") <= F.col("d")).alias("within")))
