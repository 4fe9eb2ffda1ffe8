"""Relations of the engine, their checks, and the graph object."""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass, replace
from typing import Protocol

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearcohort.plans.runtime import few_rows

VERTICES = T.StructType([T.StructField("id", T.LongType()), T.StructField("kw", T.StringType()),
                         T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())])
EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])
QUERIES = T.StructType([T.StructField("qid", T.LongType()), T.StructField("qx", T.DoubleType()),
                        T.StructField("qy", T.DoubleType()), T.StructField("phi", T.ArrayType(T.StringType())),
                        T.StructField("rho", T.IntegerType()), T.StructField("c", T.IntegerType())])
GROUPS = ("qid long, d double, group_id long, member long, kw string, dist double")
GROUP_EDGES = "qid long, group_id long, src long, dst long"
ROUNDS = ("qid long, round int, d double, edges long, potential long, peeled long, v_edges long, v_potential long, "
          "v_peeled long, found boolean")


def require(df: DataFrame, schema: T.StructType, what: str) -> DataFrame:
    """The columns of ``schema`` cast to its types (others are kept); ValueError if one is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"{what} lacks {', '.join(missing)}")
    return df.withColumns({f.name: F.col(f.name).cast(f.dataType) for f in schema})


@dataclass(frozen=True)
class Graph:
    """Vertices (id, kw, x, y, optionally attrs and influence) and canonical edges.

    ``among`` builds the edges between given vertices (id) only, for graphs whose edges are dear to find.
    """

    vertices: DataFrame
    edges: DataFrame
    name: str = "graph"
    among: Callable[[DataFrame], DataFrame] | None = None

    def __post_init__(self):
        object.__setattr__(self, "vertices", require(self.vertices, VERTICES, "vertices"))
        object.__setattr__(self, "edges", require(self.edges, EDGES, "edges").select("src", "dst"))

    def with_(self, **changes) -> Graph:
        if "edges" in changes:
            changes = {"among": None} | changes
        return replace(self, **changes)


def make_queries(spark, rows) -> DataFrame:
    """Rows (qid, qx, qy, phi, rho, c) as a relation of queries."""
    return spark.createDataFrame(list(rows), QUERIES)


def check_queries(queries: DataFrame) -> DataFrame:
    """Validated queries as a local relation (a batch is small: one row per query).

    ValueError for a bad c, rho, location or qid before any search starts.
    """
    rows = require(queries, QUERIES, "queries").select(*[f.name for f in QUERIES]).collect()
    bad = [name for name, wrong in (
        ("c", any(r["c"] is None or r["c"] < 2 for r in rows)),
        ("rho", any(r["rho"] is None or r["rho"] < 0 for r in rows)),
        ("qid or location", any(None in (r["qid"], r["qx"], r["qy"]) for r in rows)),
        ("duplicate qid", len({r["qid"] for r in rows}) < len(rows))) if wrong]
    if bad:
        raise ValueError(f"queries with a bad {', '.join(bad)}")
    return few_rows(
        queries.sparkSession, [(r["qid"], r["qx"], r["qy"], list(dict.fromkeys(k for k in r["phi"] or [] if k is not None)), r["rho"], r["c"])
         for r in rows], QUERIES)


class Rule(Protocol):
    """A constraint of the caller's own, checked inside the task of a query.

    What can be said of a vertex alone is a filter of the graph's vertices (push it down before
    ``solve``).  ``peel`` is a greatest fixpoint: it must be monotone, so that more edges never keep
    fewer.  ``accept`` judges a connected part and must stay true when the part grows.  The search
    then costs the number of tested radii times the dearer of the two checks.
    """

    def peel(self, edges: set[tuple[int, int]]) -> set[tuple[int, int]]:
        """The maximal part of the edges (pairs of vertex ids) that the rule keeps."""

    def accept(self, members: set[int]) -> bool:
        """Does a connected part with these members satisfy the rule?"""


@dataclass(frozen=True)
class Constraints:
    """The constraints of a search besides c, phi and rho of each query.

    ``social``: truss, core, nucleus (triangles in four-cliques) or nucleus-r-s with 2 <= r < s
    (r-cliques in s-cliques), at level c each, which a clique of c vertices has.  ``coverage='closed'`` admits query
    keywords only.  ``jaccard``: members need that similarity of ``attrs`` with phi, and the
    keyword minimum is then not asked for.  ``per_keyword`` overrides rho by keyword,
    ``min_size`` is a group's least size.  ``min_influence`` asks each member, ``sum_influence``
    the group.  ``rules`` are of the caller's own.  All of them are monotone in the radius.
    """

    social: str = "truss"
    coverage: str = "open"
    jaccard: float | None = None
    per_keyword: dict[str, int] | None = None
    min_size: int = 0
    min_influence: float | None = None
    sum_influence: float | None = None
    metric: str = "euclid"
    rules: tuple[Rule, ...] = ()

    def __post_init__(self):
        rs = re.fullmatch(r"nucleus-(\d)-(\d)", self.social)
        if self.social not in ("truss", "core", "nucleus") and not (rs and 2 <= int(rs[1]) < int(rs[2])):
            raise ValueError(f"unknown social constraint {self.social}")
        if self.coverage not in ("open", "closed"):
            raise ValueError(f"unknown coverage {self.coverage}")
        if self.metric not in ("euclid", "haversine"):
            raise ValueError(f"unknown metric {self.metric}")


def demands(queries: DataFrame, cons: Constraints) -> DataFrame:
    """(qid, kw, least) for every keyword that must be held at least once."""
    if cons.jaccard is not None:
        return few_rows(queries.sparkSession, [], "qid long, kw string, least int")
    own = cons.per_keyword or {}
    rows = [(r["qid"], k, own.get(k, r["rho"])) for r in queries.collect() for k in r["phi"]]
    return few_rows(queries.sparkSession, [r for r in rows if r[2] > 0], "qid long, kw string, least int")


def push_vertices(g: Graph, queries: DataFrame, cons: Constraints) -> DataFrame:
    """(qid, id, kw, x, y, held, influence): vertices that may be members for a query.

    Vertices without a location can lie in no radius and are dropped; those without a
    keyword stay as connectors.
    """
    v = g.vertices.where("x is not null and y is not null and id is not null")
    if "influence" not in v.columns:
        v = v.withColumn("influence", F.lit(0.0))
    if cons.min_influence is not None:
        v = v.where(F.col("influence") >= cons.min_influence)
    attrs = F.col("attrs") if "attrs" in v.columns else F.filter(F.array("kw"), lambda k: k.isNotNull())
    v = v.select("id", "kw", "x", "y", "influence", attrs.alias("held"))
    out = v.crossJoin(F.broadcast(queries))
    if cons.coverage == "closed":
        out = out.where(F.arrays_overlap("held", "phi"))
    if cons.jaccard is not None:
        out = out.where(F.size(F.array_intersect("held", "phi")) >= cons.jaccard * F.size(F.array_union("held", "phi")))
    return out
