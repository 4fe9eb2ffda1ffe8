"""Solvers, variants and comparison models on the fixture queries."""

from __future__ import annotations

from nearcohort.model import Constraints, Graph, make_queries
from nearcohort.plans import comparators
from nearcohort.plans.solve import solve
from nearcohort.queries.sqlgen import edges_sql, search_sql, vertices_sql
from nearcohort.sources.graphs import load

_SEG = ["BUILDING", "MACHINERY", "FURNITURE"]
_ALL_SEG = ["BUILDING", "MACHINERY", "FURNITURE", "AUTOMOBILE", "HOUSEHOLD"]
_ACT = ["click", "view", "purchase"]
_TYPES = ["PROMO", "LARGE", "SMALL"]


def q(phi, rho, c, qid=1, at=(50.0, 50.0)):
    return (qid, at[0], at[1], list(phi), rho, c)


Q1, Q2, Q4 = q(_SEG, 1, 4), q(_SEG, 3, 3), q(_ACT, 3, 4)
Q5, Q11 = q(_TYPES, 3, 6), q([f"Brand#{i}" for i in range(1, 10)], 3, 6)
BATCH = [q(_SEG, 1, 4, 1), q(_SEG, 2, 3, 2, (20.0, 70.0)), q(_ALL_SEG, 1, 4, 3), q(["BUILDING"], 2, 3, 4, (80.0, 10.0)), q(_SEG, 9, 5, 5)]

QUERIES, ORACLES = {}, {}


def search(name, graph, rows, band=None, method="two_phase", sql=None, oracle=True, **options):
    """Register a search with its oracle."""

    def run(spark, sf_dir):
        return solve(load(spark, sf_dir, graph), make_queries(spark, rows), method, **options).groups

    QUERIES[name] = run
    if oracle:
        ORACLES[name] = search_sql(graph, rows, band, **(sql or {}))


# solvers, each against the same statement
search("group_two_phase", "buyers", [Q1])
search("group_plain", "buyers", [Q1], method="two_phase_plain")
search("group_insert", "buyers", [Q1], method="nearest_insert")
search("group_peel_far", "buyers", [Q1], method="farthest_peel")
search("group_bisect", "buyers", [Q1], method="radius_bisect")
search("group_all_radii", "buyers", [Q1], method="all_radii")
search("group_two_phase_rounds", "buyers", [Q1], engine="rounds", seed="kruskal")
search("group_plain_rounds", "buyers", [Q1], method="two_phase_plain", engine="rounds")
search("group_bisect_rounds", "buyers", [Q1], method="radius_bisect", engine="rounds")
search("group_banded_trim", "buyers", [Q1], engine="rounds", trim="banded")
search("group_bisect_noprune", "buyers", [Q1], method="radius_bisect", preprune=False)
search("group_peel_far_noprune", "buyers", [Q1], method="farthest_peel", preprune=False)
search("group_batch", "buyers", BATCH)
search("group_batch_rounds", "buyers", BATCH, engine="rounds", seed="degree", check="lazy", delta=4.0)
search("group_seed_degree", "buyers", [Q1], seed="degree")
search("group_seed_relax", "buyers", [Q1], seed="relax_keyword")
search("group_seed_none", "buyers", [Q1], seed="none")
search("group_check_full", "buyers", [Q1], check="full")
search("group_check_update", "buyers", [Q1], check="update")
search("group_check_lazy", "buyers", [Q1], check="lazy")
search("group_pool_induced", "buyers", [Q1], pool="induced")
search("group_buyers_q2", "buyers", [Q2], (30.0, 30.6))
search("group_active_q4", "active", [Q4])
search("group_baskets_q5", "baskets", [Q5], (30.4, 30.5))
search("group_brands_q11", "baskets_brand", [Q11], (32.85, 32.92))
# the two teams of the case studies
search("group_small_team", "buyers", [q(_ALL_SEG, 1, 4)])
search("group_large_team", "baskets", [q(_TYPES, 5, 6)], (30.4, 30.5))
# variants of the constraints
search("group_min_size", "buyers", [Q1], sql={"min_size": 9}, constraints=Constraints(min_size=9))
search("group_per_keyword", "buyers", [Q1], sql={"per_keyword": {"BUILDING": 3}}, constraints=Constraints(per_keyword={"BUILDING": 3}))
search("group_core", "buyers", [q(_SEG, 1, 5)], (33.85, 33.88), sql={"social": "core"}, constraints=Constraints(social="core"))
search("group_influence", "buyers", [q(_SEG, 1, 3)], (26.9, 27.02), sql={"min_influence": 2_000_000.0}, constraints=Constraints(min_influence=2_000_000.0))
search("group_sum_influence", "buyers", [Q1], sql={"min_total": 2_000_000.0}, constraints=Constraints(sum_influence=2_000_000.0))
search("group_closed", "buyers", [q(_SEG, 1, 3)], (26.99, 27.02), sql={"coverage": "closed"}, constraints=Constraints(coverage="closed"))
search("group_jaccard", "baskets_attrs", [q(["PROMO", "LARGE", "SMALL"], 1, 6)], (30.3, 30.33), sql={"jaccard": 0.25, "attrs": True},
       constraints=Constraints(jaccard=0.25))
search("group_social_only", "buyers", [q([], 1, 4)])
search("group_nucleus", "active", [q(_ACT, 1, 4)], sql={"social": "nucleus"}, constraints=Constraints(social="nucleus"))
search("group_nucleus_plain", "active", [q(_ACT, 1, 4)], method="two_phase_plain", sql={"social": "nucleus"}, constraints=Constraints(social="nucleus-3-4"))
search("group_nucleus_23", "active", [q(_ACT, 1, 4)], method="farthest_peel", constraints=Constraints(social="nucleus-2-3"))
search("group_core_insert", "active", [q(_ACT, 1, 4)], method="nearest_insert", sql={"social": "core"}, constraints=Constraints(social="core"))
search("group_core_peel_far", "active", [q(_ACT, 1, 4)], method="farthest_peel", sql={"social": "core"}, constraints=Constraints(social="core"))


class AnyLink:
    """A rule of the caller's own that forbids nothing: the answer must be that without it."""

    def peel(self, edges):
        return edges

    def accept(self, members):
        return len(members) > 1


search("group_own_rule", "active", [q(_ACT, 1, 4)], constraints=Constraints(rules=(AnyLink(),)))
# every step distributed: no task holds a query's edges, whatever their number
_FAR = {"engine": "rounds", "kernel_edges": 0}
search("rounds_two_phase", "active", [Q4], seed="kruskal", trim="banded", **_FAR)
search("rounds_lazy", "active", [Q4], seed="none", check="lazy", trim="banded", delta=4.0, **_FAR)
search("rounds_update", "active", [Q4], seed="bisect", check="update", trim="banded", delta=4.0, **_FAR)
search("rounds_induced", "active", [Q4], seed="degree", pool="induced", trim="banded", delta=4.0, **_FAR)
search("rounds_plain", "active", [Q4], method="two_phase_plain", delta=4.0, **(_FAR | {"trim": "banded"}))
search("rounds_bisect", "active", [Q4], method="radius_bisect", **_FAR)
search("rounds_bisect_cells", "active", [Q4], method="radius_bisect", spatial="cells", **_FAR)
search("rounds_insert", "active", [Q4], method="nearest_insert", **_FAR)
search("rounds_peel_far", "active", [Q4], method="farthest_peel", **_FAR)
search("rounds_core", "active", [q(_ACT, 1, 4)], sql={"social": "core"}, seed="degree", delta=4.0, constraints=Constraints(social="core"), **_FAR)
search("rounds_nucleus", "active", [q(_ACT, 1, 4)], method="radius_bisect", sql={"social": "nucleus"}, constraints=Constraints(social="nucleus"), **_FAR)
# a batch whose larger queries go through rounds and whose smaller ones are searched in tasks
search("group_batch_split", "buyers", BATCH, kernel_edges=1000)


def nearest_by_role(spark, sf_dir):
    """The game-style team: the nearest holders of each keyword, whatever their ties."""
    return comparators.nearest_by_role(load(spark, sf_dir, "buyers"), make_queries(spark, [q(_ALL_SEG, 1, 4)]))


def fixed_size(spark, sf_dir):
    """An exact group size is not monotone: a heuristic, with a flag if the size was met."""
    return comparators.fixed_size_group(load(spark, sf_dir, "buyers"), make_queries(spark, [q([], 1, 4)]), 6)


QUERIES["team_by_role"] = nearest_by_role
QUERIES["team_aggregate"] = lambda s, d: comparators.aggregate_group(load(s, d, "buyers"), make_queries(s, [q([], 0, 2), q([], 0, 2, 2, (10.0, 90.0))]), 0.4)


def quest_graph(spark):
    """Six players of the running example: three roles twice; one player is farthest and needed."""
    five = [(i, j) for i in range(5) for j in range(i + 1, 5) if (i, j) != (0, 2)]
    edges = [*five, (1, 5), (2, 5), (3, 5), (4, 5), (5, 6), (6, 7), (5, 7)]
    roles = ["healer", "fighter", "healer", "fighter", "ranger", "ranger", "healer", "fighter"]
    rows = [(i, roles[i], float(i + 1), 0.0) for i in range(8)]
    return Graph(spark.createDataFrame(rows, "id long, kw string, x double, y double"), spark.createDataFrame(edges, "src long, dst long"), "quest")


QUERIES["quest_example"] = lambda s, d: solve(quest_graph(s), make_queries(s, [(1, 0.0, 0.0, ["healer", "fighter", "ranger"], 2, 4)])).groups
ORACLES["quest_example"] = """SELECT CAST(1 AS BIGINT) AS qid, CAST(6 AS DOUBLE) AS d, CAST(0 AS BIGINT) AS group_id, CAST(m AS BIGINT) AS member, kw, CAST(m + 1 AS DOUBLE) AS dist
FROM (VALUES (0, 'healer'), (1, 'fighter'), (2, 'healer'), (3, 'fighter'), (4, 'ranger'), (5, 'ranger')) t(m, kw)"""
ORACLES["team_by_role"] = f"""
WITH v AS ({vertices_sql('buyers')}), d AS (
  SELECT id, kw, round(sqrt(pow(x - 50, 2) + pow(y - 50, 2)), 6) AS dist FROM v WHERE kw IN ({', '.join(map(repr, _ALL_SEG))}))
SELECT CAST(1 AS BIGINT) AS qid, id AS member, kw, dist FROM d QUALIFY row_number() OVER (PARTITION BY kw ORDER BY dist, id) <= 1"""
QUERIES["team_fixed_size"] = fixed_size
