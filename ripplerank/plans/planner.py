"""Choosing walks for a memory budget, laps for walks, and a method for a batch."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT
from ..operators.graph import Graph, sample_vertices
from ..operators.walks import simulate_walks

#: Laps that suffice for a number of walks.
DEPTHS = ((0, 7), (10, 5), (100, 2), (2000, 0))


#: Walks of an online answer and the steps that they take until few are left.
ONLINE_WALKS, ONLINE_STEPS = 2000, 40
#: Fixed cost of a lap or step in rows, and the threshold under which frontier entries are dropped.
LAP_ROWS, LEAST_MASS = 5e7, 1e-4


def depth_for_walks(walks: int) -> int:
    """Laps for an index of `walks` walks: between the table's entries in proportion to the logarithm of walks, rounded up."""
    if walks >= DEPTHS[-1][0]:
        return DEPTHS[-1][1]
    (r0, t0), (r1, t1) = next((a, b) for a, b in zip(DEPTHS, DEPTHS[1:]) if a[0] <= walks < b[0])
    return math.ceil(t0 + (t1 - t0) * math.log((1 + walks) / (1 + r0)) / math.log((1 + r1) / (1 + r0)) - 1e-9)


def walks_for_budget(vertices: int, budget: int, bytes_per_entry: float = 12, overhead: float = 1.0, c: float = TELEPORT) -> int:
    """Most walks whose expected visits fit the budget: a safe number, as repeated visits share an entry."""
    return int(budget * c / (vertices * bytes_per_entry * overhead)) if vertices else 0


def pilot_walks_for_budget(g: Graph, budget: int, bytes_per_entry: float = 12, overhead: float = 1.0, c: float = TELEPORT, sample: int = 100, most: int = 4096) -> int:
    """The same from entries measured on sampled sources: walks double while their entries still fit."""
    n = g.size[0]
    sources = sample_vertices(g, sample)
    best, r = walks_for_budget(n, budget, bytes_per_entry, overhead, c), max(1, walks_for_budget(n, budget, bytes_per_entry, overhead, c))
    while r <= most:
        per = simulate_walks(g, sources, r, c).visits.groupBy("source").count().agg(F.avg("count")).first()[0] or 0
        if n * per * bytes_per_entry * overhead > budget:
            break
        best, r = r, r * 2
    return best


def budget_grid(g: Graph, budgets: list[int], c: float = TELEPORT) -> DataFrame:
    """budget, walks, laps for each budget."""
    n = g.size[0]
    rows = [(b, walks_for_budget(n, b, c=c), depth_for_walks(walks_for_budget(n, b, c=c))) for b in budgets]
    return g.spark.createDataFrame(rows, "budget long, walks long, laps int")


def plan_query(queries: int, walks: int, stored_walks: int = 0, single: int = 10, vertices: int = 0, edges: int = 0, c: float = TELEPORT) -> tuple[str, int, str]:
    """(method, laps, reason) for a batch of `queries`, given the in-memory index's walks and those of a large index on disk.

    A large stored index answers a handful of queries fastest, as cost there is linear in
    queries; a batch goes to the decomposition. Without any index the graph's size decides, if given: settling takes few
    laps, but each query reaches many vertices; walking takes many steps of bounded size a query, so that it wins for
    batches that outweigh the passes over the graph.
    """
    if stored_walks >= 2000 and queries <= single:
        return "lookup", 0, "few queries: reading stored rows costs least"
    if walks >= 2000:
        return "lookup", 0, "the index in memory is accurate by itself"
    if walks:
        return "decompose", depth_for_walks(walks), "a batch shares its passes over graph and index"
    laps = depth_for_walks(0)
    if vertices and edges:
        degree = edges / vertices
        settled = sum(min(degree ** (t + 1), edges, degree / LEAST_MASS) for t in range(laps))
        if ONLINE_STEPS * (edges + LAP_ROWS) + queries * ONLINE_WALKS / c < laps * (edges + LAP_ROWS) + queries * settled:
            return "walk", ONLINE_STEPS, "no index: walks of bounded size cost less than wide frontiers"
    return "index_free", laps, "no index: settle over more laps"


def plan_grid(batches: DataFrame, walks: list[int], stored: list[int]) -> DataFrame:
    """queries, walks, stored_walks, method, laps: the plan of every batch size (column queries) over a grid of indexes."""
    plan = F.udf(lambda q, r, t: plan_query(q, r, t)[:2], "method string, laps int")
    grid = batches.select(F.col("queries").cast("int").alias("queries"), F.explode(F.array(*map(F.lit, walks))).alias("walks")).select("*", F.explode(F.array(*map(F.lit, stored))).alias("stored_walks"))
    return grid.withColumn("plan", plan("queries", "walks", "stored_walks")).select("queries", "walks", "stored_walks", "plan.method", "plan.laps")


def plan_by_size(batches: DataFrame, sizes: DataFrame) -> DataFrame:
    """queries, vertices, edges, method: without any index, for every batch size and every graph (vertices, edges)."""
    plan = F.udf(lambda q, v, m: plan_query(q, 0, vertices=v, edges=m)[0], "string")
    grid = batches.select(F.col("queries").cast("long").alias("queries")).crossJoin(F.broadcast(sizes))  # a row a graph
    return grid.withColumn("method", plan("queries", "vertices", "edges")).select("queries", "vertices", "edges", "method")


def run_plan(g: Graph, queries: DataFrame, idx: DataFrame | None, walks: int, stored: DataFrame | None = None, stored_walks: int = 0, **how) -> DataFrame:
    """Answer a batch by the planned method."""
    from ..operators import baselines, decompose

    method, laps, _ = plan_query(queries.count(), walks, stored_walks, vertices=g.size[0], edges=g.size[1])
    if method == "walk":
        return baselines.online_walking(g, queries, ONLINE_WALKS)
    if method == "lookup":
        return baselines.precomputed_lookup(stored if stored is not None and stored_walks >= 2000 else idx, queries)
    return decompose.batch_ppr(g, idx if method == "decompose" else None, queries, laps, **how)


def calibrate_depth(g: Graph, idx: DataFrame | None, queries: DataFrame, target: float = 0.99, k: int = 200) -> int | None:
    """Laps that reach the target on this very graph, against exact vectors of sampled queries."""
    from ..operators import evaluate

    return evaluate.minimal_depth(g, idx, queries, evaluate.truth(g, queries), target, k)
