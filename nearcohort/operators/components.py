"""Connected components by alternating star contraction.

Each round is two grouped minima and two equi-joins.  Hubs are handled by the partial
aggregate and by AQE's skew join; no group is ever gathered in one task.
"""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from nearcohort.plans.runtime import Workspace, ship


def _pairs(df: DataFrame, keys: list[str], big, low) -> DataFrame:
    return df.select(*keys, big.alias("u"), low.alias("v"))


def _by_key(pairs: DataFrame, keys: list[str]) -> DataFrame:
    """Union-find of each key in one task."""
    ship(pairs.sparkSession)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        up: dict = {}

        def find(x):
            while up.setdefault(x, x) != x:
                up[x] = x = up[up[x]]
            return x

        for a, b in zip(pdf["u"].tolist(), pdf["v"].tolist(), strict=True):
            a, b = find(a), find(b)
            if a != b:
                up[max(a, b)] = min(a, b)  # roots are least members
        out = pd.DataFrame({"id": list(up), "comp": [find(x) for x in list(up)]})
        for k in keys:
            out[k] = pdf[k].iloc[0]
        return out[[*keys, "id", "comp"]]

    kinds = dict(pairs.dtypes)
    schema = ", ".join([*(f"`{k}` {kinds[k]}" for k in keys), "id long", "comp long"])
    return pairs.groupBy(*keys).applyInPandas(run, schema)


def components(edges: DataFrame, keys: Sequence[str] = (), src: str = "src", dst: str = "dst",
               work: Workspace | None = None, max_rounds: int = 100, kernel_edges: int = 0) -> DataFrame:
    """Label every vertex of ``edges`` with the least vertex it can reach, within its keys.

    Returns ``keys + (id, comp)``.  Self-loops and rows with a null end are ignored; an
    empty input gives an empty output.  Vertices without an edge do not appear.  If no key
    has more than ``kernel_edges`` edges, each key is labelled in one task instead.
    """
    keys = list(keys)
    work = work or Workspace(edges.sparkSession, "components")
    u, v = F.col(src), F.col(dst)
    stars = work.save(
        _pairs(edges.where(u != v), keys, F.greatest(u, v), F.least(u, v)).distinct(), "pairs")
    if kernel_edges and keys:
        most = stars.groupBy(*keys).count().agg(F.max("count")).first()[0] or 0
        if most <= kernel_edges:
            return _by_key(stars, keys)
    seen = None
    for _ in range(max_rounds):
        sym = stars.unionByName(_pairs(stars, keys, F.col("v"), F.col("u")))
        low = sym.groupBy(*keys, "u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
        large = (_pairs(sym.where(F.col("v") > F.col("u")).join(low, [*keys, "u"]), keys,
                        F.col("v"), F.col("m")).where("u <> v").distinct())
        low = large.groupBy(*keys, "u").agg(F.min("v").alias("m"))
        hung = large.join(low, [*keys, "u"])
        small = (_pairs(hung, keys, F.col("v"), F.col("m"))
                 .unionByName(_pairs(hung, keys, F.col("u"), F.col("m")))
                 .where("u <> v").distinct())
        noted = Observation()  # taken while the stars are written
        nxt = work.save(small.observe(noted, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")), "stars")
        mark = noted.get
        work.drop(stars)
        stars = nxt
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return (stars.select(*keys, F.col("u").alias("id"), F.col("v").alias("comp"))
            .unionByName(stars.select(*keys, F.col("v").alias("id"), F.col("v").alias("comp")))
            .distinct())
