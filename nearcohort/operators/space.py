"""Distances of vertices and edges, the edge ledger, cells and nearest vertices."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.functions.geo import distance, z_cell


def with_distance(vertices: DataFrame, queries: DataFrame, metric: str = "euclid") -> DataFrame:
    """(qid, id, kw, dist) of every located vertex for every query (queries are few: broadcast)."""
    both = vertices.where("x is not null and y is not null").crossJoin(F.broadcast(queries.select("qid", "qx", "qy")))
    return both.select("qid", "id", "kw", distance(metric).alias("dist"))


def with_edge_distance(edges: DataFrame, vdist: DataFrame) -> DataFrame:
    """(qid, src, dst, ed): an edge is as far as its farther end; ``edges`` may carry a qid."""
    keyed = ["qid"] if "qid" in edges.columns else []
    a = vdist.select("qid", F.col("id").alias("src"), F.col("dist").alias("ds"))
    b = vdist.select("qid", F.col("id").alias("dst"), F.col("dist").alias("dd"))
    return (edges.join(a, [*keyed, "src"]).join(b, ["qid", "dst"])
            .select("qid", "src", "dst", F.greatest("ds", "dd").alias("ed")))


def build_ledger(edges: DataFrame, vdist: DataFrame) -> DataFrame:
    """Edges with their distance, range-partitioned and sorted by (qid, ed): a band is a range."""
    return with_edge_distance(edges, vdist).repartitionByRange("qid", "ed").sortWithinPartitions("qid", "ed", "src", "dst")


def within(ledger: DataFrame, radius) -> DataFrame:
    """Edges within a radius (a number, or a column of ``ledger``)."""
    return ledger.where(F.col("ed") <= radius)


def band(ledger: DataFrame, low, high) -> DataFrame:
    """Edges beyond ``low`` and within ``high``."""
    return ledger.where((F.col("ed") > low) & (F.col("ed") <= high))


def radius_steps(ledger: DataFrame) -> DataFrame:
    """(qid, ed, step, upto): the distinct radii of a query and the edges within each."""
    w = W.partitionBy("qid").orderBy("ed")
    return (ledger.groupBy("qid", "ed").agg(F.count("*").alias("n"))
            .select("qid", "ed", (F.row_number().over(w) - 1).alias("step"),
                    F.sum("n").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("upto")))


def next_radius(steps: DataFrame, state: DataFrame, delta: float) -> DataFrame:
    """(qid, ed, step, upto) of the next radius: delta times as many edges, one more step at least.

    ``state`` is (qid, upto) of the present radius; queries at their last radius drop out.
    """
    if delta <= 1:
        raise ValueError("delta must exceed 1")
    s = state.select("qid", F.col("upto").alias("have"))
    top = steps.groupBy("qid").agg(F.max("upto").alias("all"))
    goal = F.least(F.col("all"), F.greatest(F.col("have") + 1, F.ceil(F.lit(delta) * F.col("have"))))
    s = s.join(top, "qid").withColumn("goal", goal)
    return (steps.join(F.broadcast(s), "qid").where("upto > have and upto >= goal")
            .groupBy("qid").agg(F.min_by(F.struct("ed", "step", "upto"), "step").alias("s")).select("qid", "s.*"))


def cell_index(vertices: DataFrame, low: float = 0.0, high: float = 128.0, bits: int = 6) -> DataFrame:
    """Vertices with their Z-order cell, laid out by it: range predicates prune row groups."""
    cell = z_cell(F.col("x"), F.col("y"), low, high, bits)
    return vertices.where("x is not null and y is not null").withColumn("cell", cell).repartitionByRange("cell").sortWithinPartitions("cell")


def range_cells(queries: DataFrame, radius: str = "r", low: float = 0.0, high: float = 128.0, bits: int = 6,
                keys: Sequence[str] = ("qid",)) -> DataFrame:
    """keys + cell: grid cells that the square about each query's circle touches."""
    side, width = 1 << bits, (high - low) / (1 << bits)
    edge = lambda v: F.least(F.greatest(F.floor((v - low) / (high - low) * side), F.lit(0)), F.lit(side - 1))
    r = F.col(radius)
    q = queries.withColumn("cx", F.explode(F.sequence(edge(F.col("qx") - r), edge(F.col("qx") + r)))) \
        .withColumn("cy", F.explode(F.sequence(edge(F.col("qy") - r), edge(F.col("qy") + r))))
    return q.select(*keys, z_cell(low + (F.col("cx") + 0.5) * width, low + (F.col("cy") + 0.5) * width, low, high, bits).alias("cell"))


def in_range(indexed: DataFrame, queries: DataFrame, radius: str = "r", metric: str = "euclid", keys: Sequence[str] = ("qid",),
             **grid) -> DataFrame:
    """keys + (id, dist) of the vertices within each query's radius: cells first, then exactly.

    ``keys`` tell the rows of ``queries`` apart.  Degrees are no plane, so haversine takes every cell.
    """
    if metric == "euclid":
        hit = indexed.join(F.broadcast(range_cells(queries, radius, keys=keys, **grid)), "cell")
        both = hit.join(F.broadcast(queries.select(*keys, "qx", "qy", radius)), list(keys))
    else:
        both = indexed.crossJoin(F.broadcast(queries.select(*keys, "qx", "qy", radius)))
    return both.withColumn("dist", distance(metric)).where(F.col("dist") <= F.col(radius)).select(*keys, "id", "dist")


def nearest_vertices(vdist: DataFrame, k: int) -> DataFrame:
    """The k nearest vertices of each query, ties by id."""
    w = W.partitionBy("qid").orderBy("dist", "id")
    return vdist.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
