"""Building blocks of the social graph."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.model import Graph


def canonical_edges(df: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Undirected edges once each: src < dst, no loops, no nulls."""
    return (df.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
            .select(F.least(a, b).cast("long").alias("src"), F.greatest(a, b).cast("long").alias("dst"))
            .dropDuplicates())


def latest_checkin(checkins: DataFrame, user: str = "user", order: Sequence[str] = ("ts", "seq")) -> DataFrame:
    """The last check-in of every user, ties by ``order``; partial aggregates, no sort."""
    rest = [c for c in checkins.columns if c != user]
    last = F.max_by(F.struct(*rest), F.struct(*order))
    return checkins.where(F.col(user).isNotNull()).groupBy(user).agg(last.alias("r")).select(user, *[f"r.{c}" for c in rest])


def assign_keywords(vertices: DataFrame, vocabulary: Sequence[str], seed: int = 0) -> DataFrame:
    """A reproducible pseudo-random keyword per vertex, the same in SQL engines."""
    words = F.array(*map(F.lit, vocabulary))
    pick = F.pmod(F.col("id") * F.lit(2654435761) + F.lit(seed), F.lit(len(vocabulary)))
    return vertices.withColumn("kw", F.element_at(words, (pick + 1).cast("int")))


def induce(edges: DataFrame, ids: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Edges with both ends in ``ids`` (keys + id)."""
    keys = list(keys)
    for end in ("src", "dst"):
        edges = edges.join(ids.select(*keys, F.col("id").alias(end)), [*keys, end], "left_semi")
    return edges


def sample_vertices(g: Graph, percent: int, seed: int = 0) -> Graph:
    """The graph induced by ``percent`` of the vertices, chosen by a hash of the id."""
    chosen = g.vertices.where(F.pmod(F.col("id") * F.lit(2654435761) + F.lit(seed), F.lit(100)) < percent)
    return g.with_(vertices=chosen, edges=induce(g.edges, chosen.select("id")), name=f"{g.name}-{percent}")


def degrees(edges: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """keys + (id, degree)."""
    return (edges.select(*keys, F.explode(F.array("src", "dst")).alias("id"))
            .groupBy(*keys, "id").agg(F.count("*").alias("degree")))


def triangles(edges: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """keys + (a, b, w), a < b < w, each triangle once.

    Every edge points from its end of lower (degree, id) to the other, which bounds the
    out-degree by sqrt(2E) and so the wedges by E*sqrt(E), whatever the hubs.
    """
    keys = list(keys)
    deg = degrees(edges, keys)
    both = (edges.select(*keys, "src", "dst")
            .join(deg.withColumnsRenamed({"id": "src", "degree": "ds"}), [*keys, "src"])
            .join(deg.withColumnsRenamed({"id": "dst", "degree": "dd"}), [*keys, "dst"]))
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    arcs = both.select(*keys, F.when(up, F.col("src")).otherwise(F.col("dst")).alias("t"),
                       F.when(up, F.col("dst")).otherwise(F.col("src")).alias("h"))
    one, two = arcs.withColumnRenamed("h", "p"), arcs.withColumnRenamed("h", "q")
    wedges = one.join(two, [*keys, "t"]).where("p < q")
    closed = wedges.join(edges.select(*keys, F.col("src").alias("p"), F.col("dst").alias("q")), [*keys, "p", "q"])
    s = F.array_sort(F.array("t", "p", "q"))
    return closed.select(*keys, s[0].alias("a"), s[1].alias("b"), s[2].alias("w"))


def cliques(edges: DataFrame, size: int, keys: Sequence[str] = ()) -> DataFrame:
    """keys + (v0, v1, …), ascending: every clique of ``size`` >= 2 vertices once.

    Triangles come from degree order; a clique grows by a vertex that is joined to all it holds.
    """
    keys = list(keys)
    own = edges.select(*keys, "src", "dst")
    if size == 2:
        return own.withColumnsRenamed({"src": "v0", "dst": "v1"})
    out = triangles(own, keys).withColumnsRenamed({"a": "v0", "b": "v1", "w": "v2"})
    for n in range(3, size):
        link = lambda i, n=n: own.withColumnsRenamed({"src": f"v{i}", "dst": f"v{n}"})
        out = out.join(link(n - 1), [*keys, f"v{n - 1}"])
        for i in range(n - 1):
            out = out.join(link(i), [*keys, f"v{i}", f"v{n}"], "left_semi")
    return out.select(*keys, *[f"v{i}" for i in range(size)])


def triangle_sides(tri: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """keys + (src, dst): the three sides of every triangle."""
    side = lambda p, q: F.struct(F.col(p).alias("src"), F.col(q).alias("dst"))
    return (tri.select(*keys, F.explode(F.array(side("a", "b"), side("a", "w"), side("b", "w"))).alias("e"))
            .select(*keys, "e.src", "e.dst"))


def support(edges: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """keys + (src, dst, sup): triangles on every edge, zero included."""
    keys = list(keys)
    n = triangle_sides(triangles(edges, keys), keys).groupBy(*keys, "src", "dst").agg(F.count("*").alias("sup"))
    return (edges.select(*keys, "src", "dst").join(n, [*keys, "src", "dst"], "left")
            .withColumn("sup", F.coalesce("sup", F.lit(0)).cast("long")))


def census(labels: DataFrame, held: DataFrame, wanted: DataFrame, keys: Sequence[str] = ("qid",)) -> DataFrame:
    """keys + (comp, kw, n): members of each component that hold a wanted keyword.

    ``labels`` is keys + (id, comp), ``held`` (qid, id, held array), ``wanted`` (qid, kw).
    """
    hold = held.select("qid", "id", F.explode("held").alias("kw")).join(F.broadcast(wanted.select("qid", "kw")), ["qid", "kw"], "left_semi")
    return labels.join(hold, ["qid", "id"]).groupBy(*keys, "comp", "kw").agg(F.count("*").alias("n"))


def merge_census(a: DataFrame, b: DataFrame, keys: Sequence[str] = ("qid",)) -> DataFrame:
    """Counts of two disjoint parts added up."""
    return a.unionByName(b).groupBy(*keys, "comp", "kw").agg(F.sum("n").alias("n"))


def meets_minimum(counts: DataFrame, wanted: DataFrame, keys: Sequence[str] = ("qid",)) -> DataFrame:
    """keys + comp of components that hold every wanted keyword often enough.

    A keyword without a census row counts as zero, so the rows are compared with the number
    of wanted keywords.  Queries that want nothing are not listed: see ``qualify``.
    """
    n = wanted.groupBy("qid").agg(F.count("*").alias("n_wanted"))
    return (counts.join(F.broadcast(wanted), ["qid", "kw"]).where("n >= least")
            .groupBy(*keys, "comp").agg(F.count("*").alias("n_met"))
            .join(F.broadcast(n), "qid").where("n_met = n_wanted").select(*keys, "comp"))


def covers(members: DataFrame, queries: DataFrame, mode: str = "open", keys: Sequence[str] = ("qid", "comp")) -> DataFrame:
    """keys + covered: do the members' keywords cover phi (``closed``: and nothing else)."""
    have = members.groupBy(*keys).agg(F.collect_set("kw").alias("have")).join(F.broadcast(queries.select("qid", "phi")), "qid")
    ok = F.size(F.array_except("phi", "have")) == 0
    if mode == "closed":
        ok = ok & (F.size(F.array_except("have", "phi")) == 0)
    return have.select(*keys, ok.alias("covered"))


def group_distance(members: DataFrame) -> DataFrame:
    """qid, group_id, d: distance of the farthest member."""
    return members.groupBy("qid", "group_id").agg(F.max("dist").alias("d"))
