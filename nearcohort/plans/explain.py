"""What a search would do, and why, before it runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.model import Constraints, Graph, check_queries
from nearcohort.operators.graph import degrees
from nearcohort.operators.truss import KERNEL_EDGES
from nearcohort.plans.runtime import Workspace
from nearcohort.plans.solve import _prepare


def explain_strategy(graph: Graph, queries: DataFrame, kernel_edges: int = KERNEL_EDGES) -> str:
    """Text with sizes, the wedge estimate and, for each query, the engine that its pruned graph leads to.

    The graph is pruned for the queries, as ``solve`` does, so nothing here is a guess but the wedges.
    """
    q = check_queries(queries)
    n, cs = q.agg(F.count("*"), F.count_distinct("c")).first()
    deg = degrees(graph.edges)
    edges = graph.edges.count()
    v, top, wedges = deg.agg(F.count("*"), F.max("degree"), F.sum(F.least(F.col("degree"), F.lit((2 * edges) ** 0.5)) ** 2) / 2).first()
    job = _prepare(graph, q, Constraints(), Workspace(graph.edges.sparkSession, "explain"), kernel_edges, True, None)
    left = {r["qid"]: r["count"] for r in job.pruned.groupBy("qid").count().collect()}
    lines = [f"graph {graph.name}: {v} vertices, {edges} edges, greatest degree {top}",
             f"queries: {n} with {cs} levels of cohesion; one peel per level, by {'one task' if edges <= kernel_edges else 'rounds'}",
             f"wedges after degree orientation: at most about {int(wedges or 0)}; edges are never broadcast"]
    for r in sorted(q.select("qid").collect()):
        k = left.get(r["qid"], 0)
        how = ("no part qualifies: no search" if not k else "one task: forest seed, anchored pool, trimming on a levelled forest" if k <= kernel_edges
               else "distributed rounds: merged forests, anchored pool, then trimming by bands or in a task")
        lines.append(f"query {r['qid']}: {k} edges after pruning; {how}")
    return "\n".join(lines)
