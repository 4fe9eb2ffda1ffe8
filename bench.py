"""Headline timings: one JSON line.  BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores.

Each search is run once uncounted, so that no solver pays for starting workers, and then
``RUNS`` times; the median counts.  ``claims`` says which statements on rank and trend hold here.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from nearcohort.model import make_queries  # noqa: E402
from nearcohort.operators.truss import truss_decompose  # noqa: E402
from nearcohort.plans.metrics import pruning_ratios  # noqa: E402
from nearcohort.plans.runtime import Workspace  # noqa: E402
from nearcohort.plans.solve import solve  # noqa: E402
from nearcohort.plans.workloads import SOLVERS, cached, random_queries, vocabulary  # noqa: E402
from nearcohort.sources.graphs import load  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = 3
_SEG = ["BUILDING", "MACHINERY", "FURNITURE"]


def main() -> None:
    spark = (SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS)
             .config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
             .config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def clock(name, f, runs=1):
        if runs > 1:
            f()
        each = []
        for _ in range(runs):
            a = time.perf_counter()
            out = f()
            each.append(time.perf_counter() - a)
        took[name] = round(statistics.median(each), 3)
        return out

    work = Workspace(spark, "bench")
    buyers = clock("graph_buyers", lambda: cached(load(spark, SF_DIR, "buyers"), work))
    active = clock("graph_active", lambda: cached(load(spark, SF_DIR, "active"), work))
    index = clock("truss_index_buyers", lambda: work.save(truss_decompose(buyers.edges), "index"))
    one = lambda g, phi, rho, c, **o: solve(g, make_queries(spark, [(1, 50.0, 50.0, phi, rho, c)]), **o)
    for m in SOLVERS:
        clock(f"q7_{m}", lambda m=m: one(buyers, _SEG, 3, 4, method=m, index=index), RUNS)
    clock("q9_two_phase", lambda: one(buyers, [*_SEG, "AUTOMOBILE", "HOUSEHOLD"], 1, 4, index=index), RUNS)
    clock("q15_two_phase", lambda: one(active, ["click", "view", "purchase"], 3, 6), RUNS)
    batch = random_queries(spark, 100, vocabulary(buyers), 3, 2, 4)
    res = None
    for m in ("two_phase", "two_phase_plain", "radius_bisect"):
        got = clock(f"batch100_{m}", lambda m=m: solve(buyers, batch, m, index=index))
        res = res or got
    ratios = pruning_ratios(buyers, res).agg(*[F.round(F.avg(x), 4).alias(x) for x in ("h_g", "dh_h", "p_dh", "c_p")]).first().asDict()
    claims = {"q7: two_phase is first": took["q7_two_phase"] <= min(took[f"q7_{m}"] for m in SOLVERS),
              "batch: two_phase is first": took["batch100_two_phase"] <= min(took["batch100_two_phase_plain"], took["batch100_radius_bisect"]),
              "q7: far peel is slower than bisection": took["q7_farthest_peel"] >= took["q7_radius_bisect"]}
    print(json.dumps({"metric": "seconds of all headline queries", "value": round(sum(took.values()), 3), "unit": "sec",
                      "queries": took, "sf": SF_DIR, "ratios": ratios, "claims": claims}))


if __name__ == "__main__":
    main()
