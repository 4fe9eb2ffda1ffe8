"""The models that the search is compared with."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.kernels import local_search as L
from nearcohort.model import Constraints, Graph, check_queries
from nearcohort.operators.space import with_distance
from nearcohort.operators.truss import truss_decompose
from nearcohort.plans.runtime import ship
from nearcohort.plans.solve import Result, solve


def nearest_by_role(graph: Graph, queries: DataFrame, metric: str = "euclid") -> DataFrame:
    """(qid, member, kw, dist): for each keyword its rho nearest holders; no social condition."""
    q = check_queries(queries)
    near = with_distance(graph.vertices, q, metric).join(F.broadcast(q.select("qid", "phi", "rho")), "qid").where("array_contains(phi, kw)")
    rank = F.row_number().over(W.partitionBy("qid", "kw").orderBy("dist", "id"))
    return near.withColumn("rank", rank).where("rank <= rho").select("qid", F.col("id").alias("member"), "kw", "dist")


def social_only(graph: Graph, queries: DataFrame, social: str = "core", **options) -> Result:
    """The nearest cohesive group whatever its keywords."""
    free = queries.withColumn("phi", F.array().cast("array<string>"))
    return solve(graph, free, constraints=Constraints(social=social), **options)


def fixed_size_group(graph: Graph, queries: DataFrame, size: int, **options) -> DataFrame:
    """(qid, member, dist, reached): a cohesive group of exactly ``size``, if the heuristic finds one.

    An exact size is not monotone in the radius and hard in general.  From the first radius
    with a cohesive group of at least ``size`` members the farthest members are dropped,
    those that break the group excepted, until the size is met or nobody can go.
    """
    res = solve(graph, queries, constraints=Constraints(min_size=size), **options)
    ship(graph.edges.sparkSession)
    q = check_queries(queries).select("qid", "c")
    g = res.groups.join(res.group_edges.withColumnRenamed("src", "member"), ["qid", "group_id", "member"], "left").join(F.broadcast(q), "qid")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        c, qid = int(pdf["c"].iloc[0]), int(pdf["qid"].iloc[0])
        dist = dict(zip(pdf["member"].tolist(), pdf["dist"].tolist(), strict=True))
        pairs = pdf.dropna(subset=["dst"])
        edges = {(int(a), int(b)) for a, b in zip(pairs["member"], pairs["dst"], strict=True)}
        members, stuck = set(dist), set()
        while len(members) > size and len(stuck) < len(members):
            v = max((m for m in members if m not in stuck), key=lambda m: (dist[m], m))
            left = L.peel([e for e in edges if v not in e], c)
            uf = L.UnionCensus({m: () for m in members}, 0)
            for a, b in left:
                uf.union(a, b)
            parts = [[m for m in uf.up if uf.find(m) == r] for r in uf.roots()]
            fit = [p for p in parts if len(p) >= size]
            if not fit:
                stuck.add(v)
                continue
            best = min(fit, key=lambda p: (max(dist[m] for m in p), min(p)))
            members = set(best)
            edges = {e for e in left if e[0] in members}
            stuck &= members
        rows = [(qid, m, dist[m], len(members) == size) for m in sorted(members)]
        return pd.DataFrame(rows, columns=["qid", "member", "dist", "reached"])

    return g.groupBy("qid", "group_id").applyInPandas(run, "qid long, member long, dist double, reached boolean")


def aggregate_group(graph: Graph, queries: DataFrame, weight: float = 0.5, **options) -> DataFrame:
    """(qid, c, d, cost, group_id, member, dist): the optimum of one objective over nearness and cohesion.

    The model of works that weigh several aims instead of constraining them: cost is
    weight * d / (distance of the farthest vertex) - (1 - weight) * c / (greatest trussness).  For a given
    cohesion c the nearest group is best, so every level of the graph is searched (one batch,
    keyed by query and level) and the least cost taken, ties by the greater c.
    """
    q = check_queries(queries)
    index = options.pop("index", None)
    index = truss_decompose(graph.edges) if index is None else index
    top = index.agg(F.max("truss")).first()[0] or 2
    levels = F.explode(F.sequence(F.lit(2), F.lit(top))).alias("level")
    asked = q.select("qid", "qx", "qy", levels).select(
        (F.col("qid") * (top + 1) + F.col("level")).alias("qid"), "qx", "qy", F.array().cast("array<string>").alias("phi"), F.lit(0).alias("rho"),
        F.col("level").cast("int").alias("c"))
    found = solve(graph, asked, index=index, only_first=True, **options).groups
    far = with_distance(graph.vertices, q, (options.get("constraints") or Constraints()).metric).groupBy("qid").agg(F.max("dist").alias("far"))
    by = found.withColumns({"c": F.pmod("qid", F.lit(top + 1)).cast("int"), "qid": F.floor(F.col("qid") / (top + 1)).cast("long")}).join(F.broadcast(far), "qid")
    near = F.when(F.col("far") > 0, F.col("d") / F.col("far")).otherwise(F.lit(0.0))
    by = by.withColumn("cost", F.round(weight * near - (1 - weight) * F.col("c") / top, 6))
    best = by.groupBy("qid").agg(F.min_by("c", F.struct("cost", -F.col("c"))).alias("c"))
    return by.join(F.broadcast(best), ["qid", "c"]).select("qid", "c", "d", "cost", "group_id", "member", "dist")
