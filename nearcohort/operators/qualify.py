"""Connected parts that meet the demands of their queries, and the pruning built on them."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.kernels.local_search import nucleus_levels
from nearcohort.model import Constraints
from nearcohort.operators.components import components
from nearcohort.operators.graph import census, meets_minimum
from nearcohort.operators.truss import KERNEL_EDGES, core_peel, nucleus_peel, truss_peel
from nearcohort.plans.runtime import Workspace


def social_peel(edges: DataFrame, keys: Sequence[str], social: str = "truss", work: Workspace | None = None,
                kernel_edges: int = KERNEL_EDGES) -> DataFrame:
    """Maximal part of ``edges`` (keys, src, dst, c) that is cohesive at level c; keeps c.

    truss: c-2 triangles per edge.  core: c-1 edges per vertex.  nucleus: c-3 four-cliques per
    triangle.  nucleus-r-s: comb(c-r, s-r) s-cliques per r-clique.  The levels agree in that a
    clique of c vertices satisfies each.
    """
    keys = list(keys)
    work = work or Workspace(edges.sparkSession, "social-peel")
    if social.startswith("nucleus"):
        r, s = nucleus_levels(social)
        need, room = F.lit(1), F.greatest(F.col("c") - r, F.lit(0))
        for i in range(s - r):  # a binomial coefficient, factor by factor
            need = F.floor(need * F.greatest(room - i, F.lit(0)) / (i + 1))
        own = work.save(edges.select(*keys, "src", "dst", "c", need.cast("int").alias("need")), "nucleus-input")
        out = nucleus_peel(own, keys, work, kernel_edges=kernel_edges, r=r, s=s, stored=True)
        return out.drop("need").join(own.drop("need"), [*keys, "src", "dst"])
    less = {"truss": 2, "core": 1}[social]
    e = edges.select(*keys, "src", "dst", F.greatest(F.col("c") - less, F.lit(0)).alias("need"))
    peel = truss_peel if social == "truss" else core_peel
    return peel(e, keys, work=work, kernel_edges=kernel_edges).withColumn("c", F.col("need") + less).drop("need")


def label(edges: DataFrame, keys: Sequence[str], work: Workspace, kernel_edges: int = KERNEL_EDGES) -> DataFrame:
    """Edges with the component (least vertex) of their ends."""
    keys = list(keys)
    comp = components(edges, keys, work=work, kernel_edges=kernel_edges)
    return edges.join(comp.withColumnRenamed("id", "src"), [*keys, "src"])


def qualify(edges: DataFrame, held: DataFrame, wanted: DataFrame, keys: Sequence[str], work: Workspace,
            cons: Constraints | None = None, kernel_edges: int = KERNEL_EDGES) -> DataFrame:
    """Edges (keys with qid, src, dst, …) of the components that meet the demands, with ``comp``.

    ``held`` is (qid, id, held, influence), ``wanted`` (qid, kw, least).  A query without
    wanted keywords takes every component of the least size.
    """
    cons, keys = cons or Constraints(), list(keys)
    marked = work.save(label(edges, keys, work, kernel_edges), "labelled")
    ids = (marked.select(*keys, "comp", F.explode(F.array("src", "dst")).alias("id")).distinct())
    good = meets_minimum(census(ids, held, wanted, keys), wanted, keys)
    free = marked.select(*keys, "comp").distinct().join(F.broadcast(wanted.select("qid").distinct()), "qid", "left_anti")
    good = good.unionByName(free.select(*keys, "comp"))
    if cons.min_size > 2 or cons.sum_influence is not None:
        size = ids.join(held.select("qid", "id", "influence"), ["qid", "id"], "left").groupBy(*keys, "comp").agg(
            F.count("*").alias("size"), F.sum(F.coalesce("influence", F.lit(0.0))).alias("total"))
        ok = F.col("size") >= cons.min_size
        if cons.sum_influence is not None:
            ok = ok & (F.col("total") >= cons.sum_influence)
        good = good.join(size.where(ok), [*keys, "comp"], "left_semi")
    return marked.join(good, [*keys, "comp"], "left_semi")


def prune_own(edges: DataFrame, held: DataFrame, wanted: DataFrame, work: Workspace, cons: Constraints,
              kernel_edges: int = KERNEL_EDGES) -> DataFrame:
    """The same as ``prune`` where each query has its own edges (qid, src, dst, c)."""
    left = social_peel(edges, ["qid"], cons.social, work, kernel_edges)
    return work.save(qualify(left.select("qid", "src", "dst", "c"), held, wanted, ["qid"], work, cons, kernel_edges), "pruned")


def prune(edges: DataFrame, queries: DataFrame, held: DataFrame, wanted: DataFrame, work: Workspace,
          cons: Constraints | None = None, index: DataFrame | None = None,
          kernel_edges: int = KERNEL_EDGES, restricted: bool = False) -> DataFrame:
    """(qid, src, dst, c, comp): for each query its maximal cohesive parts that meet the demands.

    Without vertex-local constraints the cohesive parts, their components and their keyword
    counts depend on c only and are found once per distinct c (or read from a truss ``index``: src,
    dst, truss); a query then only picks its components.  With them (``restricted``) each query
    has its own vertices.
    """
    cons = cons or Constraints()
    if restricted:
        own = held.select("qid", "id")
        e = edges.crossJoin(F.broadcast(queries.select("qid", "c")))
        for end in ("src", "dst"):
            e = e.join(own.withColumnRenamed("id", end), ["qid", end], "left_semi")
        return prune_own(e, held, wanted, work, cons, kernel_edges)
    if index is not None and cons.social == "truss":
        by_c = index.join(F.broadcast(queries.select("c").distinct()), F.col("truss") >= F.col("c")).select("src", "dst", "c")
    else:
        e = edges.crossJoin(F.broadcast(queries.select("c").distinct())).withColumn("level", F.col("c"))
        by_c = social_peel(e, ["level"], cons.social, work, kernel_edges).drop("level")
    marked = work.save(label(work.save(by_c, "cohesive"), ["c"], work, kernel_edges), "labelled")
    ids = marked.select("c", "comp", F.explode(F.array("src", "dst")).alias("id")).distinct()
    one = held.join(F.broadcast(queries.agg(F.min("qid").alias("qid"))), "qid", "left_semi")  # all queries have the same vertices
    size = ids.join(one.select("id", "influence"), "id", "left").groupBy("c", "comp").agg(
        F.count("*").alias("size"), F.sum(F.coalesce("influence", F.lit(0.0))).alias("total"))
    words = F.broadcast(wanted.select("kw").distinct())
    counts = (ids.join(one.select("id", F.explode("held").alias("kw")).join(words, "kw"), "id")
              .groupBy("c", "comp", "kw").agg(F.count("*").alias("n")))
    ok = F.col("size") >= cons.min_size
    if cons.sum_influence is not None:
        ok = ok & (F.col("total") >= cons.sum_influence)
    cand = size.where(ok).select("c", "comp").join(F.broadcast(queries.select("qid", "c")), "c")
    met = (counts.join(F.broadcast(wanted.join(queries.select("qid", "c"), "qid")), ["c", "kw"]).where("n >= least")
           .groupBy("qid", "comp").agg(F.count("*").alias("n_met")))
    want = wanted.groupBy("qid").agg(F.count("*").alias("n_wanted"))
    good = (cand.join(F.broadcast(want), "qid", "left").join(met, ["qid", "comp"], "left")
            .where("coalesce(n_met, 0) = coalesce(n_wanted, 0)").select("qid", "c", "comp"))
    return work.save(marked.join(good, ["c", "comp"]).select("qid", "src", "dst", "c", "comp"), "pruned")
