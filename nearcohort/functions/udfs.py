"""UDF surface: the same functions for SQL users, and grouped forms."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

GROUP_COLUMNS = "qid long, d double, group_id long, member long, dist double"


@F.pandas_udf(DoubleType())
def jaccard_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Similarity of two arrays as sets (the expression in ``geo`` is the default)."""
    def one(x, y):
        x, y = set(x), set(y)
        return len(x & y) / len(x | y) if x | y else 1.0
    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype=float)


@F.pandas_udf(DoubleType())
def haversine_udf(x1: pd.Series, y1: pd.Series, x2: pd.Series, y2: pd.Series) -> pd.Series:
    """Great-circle kilometres."""
    import numpy as np

    p = np.pi / 180
    a = np.sin((y2 - y1) * p / 2) ** 2 + np.cos(y1 * p) * np.cos(y2 * p) * np.sin((x2 - x1) * p / 2) ** 2
    return (2 * 6371.0088 * np.arcsin(np.sqrt(np.minimum(a, 1.0)))).round(6)


@F.pandas_udf(DoubleType())
def spread_udaf(x: pd.Series, y: pd.Series) -> float:
    """Greatest side of the bounding box of a group's places."""
    return float(round(max(x.max() - x.min(), y.max() - y.min()), 6)) if len(x) else 0.0


class NearestGroup:
    """Table function over one tagged relation, partitioned by qid.

    Rows: kind 'vertex' (a = id, x, y, words), 'edge' (a, b), 'query' (x, y, words = phi,
    a = rho, b = c).
    """

    def __init__(self):
        self.vertices, self.edges, self.query, self.qid = [], [], None, None

    def eval(self, row):
        self.qid = row["qid"]
        if row["kind"] == "vertex":
            self.vertices.append((row["a"], row["x"], row["y"], row["words"] or []))
        elif row["kind"] == "edge":
            self.edges.append((row["a"], row["b"]))
        else:
            self.query = (row["x"], row["y"], list(row["words"] or []), row["a"], row["b"])

    def terminate(self):
        from nearcohort.kernels import local_search as L

        if self.query is None:
            return
        qx, qy, phi, rho, c = self.query
        near = sorted((round(((x - qx) ** 2 + (y - qy) ** 2) ** 0.5, 6), i, w) for i, x, y, w in self.vertices if x is not None and y is not None)
        at = {i: n for n, (_, i, _) in enumerate(near)}
        hold = [tuple(phi.index(k) for k in set(w) if k in phi) for _, _, w in near]
        pairs = [(min(at[a], at[b]), max(at[a], at[b])) for a, b in self.edges if a in at and b in at]
        p = L.Problem([i for _, i, _ in near], [d for d, _, _ in near], hold, pairs, [rho] * len(phi), c)
        ans = L.two_phase(p)
        for gid, members, _ in L.groups(p, ans):
            for m in members:
                yield self.qid, ans.d, gid, p.ids[m], p.dist[m]


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    from nearcohort.plans.runtime import ship

    ship(spark)
    spark.udf.register("jaccard_sets", jaccard_udf)
    spark.udf.register("haversine_km", haversine_udf)
    spark.udtf.register("nearest_group", F.udtf(NearestGroup, returnType=GROUP_COLUMNS))


def tagged_relation(vertices, edges, queries):
    """The one relation that ``nearest_group`` takes."""
    none = F.lit(None)
    q = queries.select("qid", F.lit("query").alias("kind"), F.col("rho").cast("long").alias("a"), F.col("c").cast("long").alias("b"),
                       F.col("qx").alias("x"), F.col("qy").alias("y"), F.col("phi").alias("words"))
    ids = F.broadcast(queries.select("qid"))
    v = vertices.crossJoin(ids).select("qid", F.lit("vertex").alias("kind"), F.col("id").alias("a"), none.cast("long").alias("b"), "x", "y",
                                       F.filter(F.array("kw"), lambda k: k.isNotNull()).alias("words"))
    e = edges.crossJoin(ids).select("qid", F.lit("edge").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"),
                                    none.cast("double").alias("x"), none.cast("double").alias("y"), none.cast("array<string>").alias("words"))
    return q.unionByName(v).unionByName(e)
