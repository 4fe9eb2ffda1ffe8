"""The experiment workloads: query batches, sweeps and their runs."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearcohort.model import QUERIES, Graph, make_queries
from nearcohort.operators.graph import sample_vertices
from nearcohort.plans.runtime import Workspace, ship
from nearcohort.plans.solve import SEEDS, Result, solve

#: Defaults and ranges of the parameters.
DEFAULTS = {"c": 6, "n_keywords": 3, "rho": 3}
RANGES = {"c": (3, 4, 5, 6, 7, 8), "n_keywords": (1, 3, 5, 7, 9), "rho": (1, 3, 5, 7, 9)}
SHARES = (20, 40, 60, 80, 100)
DELTAS = (1.25, 2 ** (2 / 3), 2.0, 3.0, 4.0)
#: Searches of the ablation under way at once: each is short jobs that leave most cores idle.
AT_ONCE = 8
SOLVERS = ("two_phase", "two_phase_plain", "radius_bisect", "farthest_peel", "nearest_insert")


def random_queries(spark: SparkSession, n: int, vocabulary: Sequence[str], n_keywords: int, rho: int, c: int, seed: int = 1) -> DataFrame:
    """``n`` queries at random places of [0, 100)^2 with random keywords of the vocabulary."""
    place = lambda k: F.pmod(F.xxhash64("id", F.lit(seed * 1000 + k)), F.lit(10_000)) / 100
    words = F.array(*map(F.lit, vocabulary))
    order = F.transform(words, lambda w: F.struct(F.xxhash64(F.col("id"), w, F.lit(seed)).alias("h"), w.alias("w")))
    phi = F.transform(F.slice(F.array_sort(order), 1, n_keywords), lambda s: s["w"])
    df = spark.range(n).select(F.col("id").alias("qid"), place(0).alias("qx"), place(1).alias("qy"), phi.alias("phi"),
                               F.lit(rho).alias("rho"), F.lit(c).alias("c"))
    return make_queries(spark, [tuple(r) for r in df.select(*[f.name for f in QUERIES]).collect()])


def vocabulary(graph: Graph) -> list[str]:
    """All distinct keywords of a graph, in order."""
    return sorted(r["kw"] for r in graph.vertices.where("kw is not null").select("kw").distinct().collect())


def cached(graph: Graph, work: Workspace) -> Graph:
    """The graph written once, so that timings leave its construction out."""
    return graph.with_(vertices=work.save(graph.vertices, "vertices"), edges=work.save(graph.edges, "edges"))


def sweep(graph: Graph, parameter: str, values: Iterable, methods: Sequence[str] = SOLVERS, n: int = 20, seed: int = 1,
          base: dict | None = None, **options) -> list[dict]:
    """Rows (parameter, value, method, seconds, per_query, found, tested): one parameter varies, the rest stays."""
    spark = graph.edges.sparkSession
    graph = cached(graph, Workspace(spark, "sweep"))
    words, out = vocabulary(graph), []
    for value in values:
        p = DEFAULTS | (base or {})
        g, opt = graph, dict(options)
        if parameter in p:
            p[parameter] = value
        elif parameter == "share":
            g = cached(sample_vertices(graph, value, seed), Workspace(spark, "sweep"))
        else:
            opt[parameter] = value
        q = random_queries(spark, n, words, min(p["n_keywords"], len(words)), p["rho"], p["c"], seed)
        for m in methods:
            extra = opt if m == "two_phase" else {k: v for k, v in opt.items() if k in ("engine", "constraints", "preprune")}
            work = Workspace(spark, f"sweep-{m}")
            r = solve(g, q, m, work=work, **extra)
            tested = r.rounds.agg(F.sum("edges")).first()[0]
            out.append({"graph": g.name, "parameter": parameter, "value": value, "method": m, "seconds": round(r.seconds, 3),
                        "per_query": round(r.seconds / n, 4), "found": r.groups.select("qid").distinct().count(), "tested": tested})
            work.clear()  # a workload holds the tables of one search at a time
    return out


def ablation(graph: Graph, queries: DataFrame, banded: Sequence[str] = ("kruskal",)) -> DataFrame:
    """(qid, seed, check, pool, trim, engine, d, members) of every combination of seed, check and trim:
    all agree in d and members.  Trimming by bands is a form of the distributed rounds; it is combined with the
    seeds ``banded``, all of ``SEEDS`` in the query."""
    spark = graph.edges.sparkSession
    graph = cached(graph, Workspace(spark, "ablation"))
    checks = (("full", "anchored"), ("update", "anchored"), ("lazy", "anchored"), ("incremental", "anchored"), ("incremental", "induced"))
    runs = [(seed, check, pool, trim, "kernel") for seed in SEEDS for check, pool in checks for trim in ("forest", "traverse")]
    # first, as they take longest
    runs = [(seed, check, pool, "banded", "rounds") for seed in banded for check, pool in checks] + runs
    ship(spark)  # once, before the threads

    def search(run):
        options = dict(zip(("seed", "check", "pool", "trim", "engine"), run, strict=True))
        work = Workspace(spark, "ablation-search")
        found = solve(graph, queries, "two_phase", work=work, **options).groups
        rows = [(r["qid"], *run, r["d"], r["members"]) for r in found.groupBy("qid").agg(F.max("d").alias("d"), F.count("*").alias("members")).collect()]
        work.clear()
        return rows

    with ThreadPoolExecutor(AT_ONCE) as threads:
        rows = [r for found in threads.map(search, runs) for r in found]
    return spark.createDataFrame(rows, "qid long, seed string, check string, pool string, trim string, engine string, d double, members long")


def batch(graph: Graph, n: int, rho: int, c: int, n_keywords: int = 3, seed: int = 1, **options) -> tuple[DataFrame, Result]:
    """A batch of random queries with its result."""
    q = random_queries(graph.edges.sparkSession, n, vocabulary(graph), n_keywords, rho, c, seed)
    return q, solve(graph, q, **options)
