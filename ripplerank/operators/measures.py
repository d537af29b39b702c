"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT
from ..functions.lineage import cut
from .decompose import Frontier, path_rows, top_k
from .graph import Graph


def keyed(ppr: DataFrame) -> DataFrame:
    """Vectors with their key named query."""
    return ppr.withColumnRenamed("source", "query") if "source" in ppr.columns else ppr


def rag(exact: DataFrame, approx: DataFrame, ks: list[int]) -> DataFrame:
    """query, k, rag: exact mass of the approximate top k over exact mass of the exact top k.

    Both rankings are made once, up to the largest k. An approximate ranking that is shorter
    than k counts what it has.
    """
    exact, approx = keyed(exact), keyed(approx)
    most = max(ks)
    e = exact.select("query", "vertex", F.col("score").alias("p"))
    by_exact = top_k(exact, most).select("query", F.col("rank").alias("r"), F.col("score").alias("best"))
    by_approx = top_k(approx, most).select("query", "vertex", F.col("rank").alias("r")).join(e, ["query", "vertex"], "left")
    def sums(df: DataFrame, value: str, out: str) -> DataFrame:
        rows = df.withColumn("k", F.explode(F.array(*map(F.lit, ks)))).where(F.col("r") <= F.col("k"))
        return rows.groupBy("query", "k").agg(F.sum(F.coalesce(value, F.lit(0.0))).alias(out))

    got, best = sums(by_approx, "p", "got"), sums(by_exact, "best", "best")
    return best.join(got, ["query", "k"], "left").select("query", "k", (F.coalesce("got", F.lit(0.0)) / F.col("best")).alias("rag"))


def mean_rags(exact: DataFrame, approximations: list[DataFrame], ks: list[int]) -> DataFrame:
    """which, k, rag, queries: mean RAG of several approximations, `which` being the place in the list.

    The exact vectors, which may be long, are ranked once and met once with the best of all approximations.
    """
    most = max(ks)
    exact = keyed(exact)
    tops = [top_k(keyed(a), most).select(F.lit(i).alias("which"), "query", "vertex", F.col("rank").alias("r")) for i, a in enumerate(approximations)]
    by_approx = cut(reduce(DataFrame.unionByName, tops), "tops")
    met = exact.join(by_approx.select("query", "vertex").distinct(), ["query", "vertex"], "left_semi").select("query", "vertex", F.col("score").alias("p"))
    depths = F.explode(F.array(*map(F.lit, ks))).alias("k")

    def sums(df: DataFrame, keys: list[str], value: str, out: str) -> DataFrame:
        rows = df.select("*", depths).where(F.col("r") <= F.col("k"))
        return rows.groupBy(*keys, "k").agg(F.sum(F.coalesce(value, F.lit(0.0))).alias(out))

    best = sums(top_k(exact, most).select("query", F.col("rank").alias("r"), "score"), ["query"], "score", "best")
    got = sums(by_approx.join(met, ["query", "vertex"], "left"), ["which", "query"], "p", "got")
    every = best.select("*", F.explode(F.sequence(F.lit(0), F.lit(len(approximations) - 1))).alias("which"))
    rags = every.join(got, ["which", "query", "k"], "left").select("which", "k", (F.coalesce("got", F.lit(0.0)) / F.col("best")).alias("rag"))
    return rags.groupBy("which", "k").agg(F.avg("rag").alias("rag"), F.count("*").alias("queries"))


def mean_rag(rags: DataFrame, buckets: DataFrame | None = None) -> DataFrame:
    """k, rag, queries; with buckets (bucket, vertex) also per bucket, bucket null being the mean of all."""
    if buckets is None:
        return rags.groupBy("k").agg(F.avg("rag").alias("rag"), F.count("*").alias("queries"))
    placed = rags.join(buckets.select("bucket", F.col("vertex").alias("query")), "query")
    return placed.rollup("k", "bucket").agg(F.avg("rag").alias("rag"), F.count("*").alias("queries")).where("k is not null")


def precision_at_k(exact: DataFrame, approx: DataFrame, k: int) -> DataFrame:
    """query, precision: share of the exact top k that the approximate top k holds."""
    e = top_k(keyed(exact), k).select("query", "vertex")
    hit = top_k(keyed(approx), k).select("query", "vertex").join(e, ["query", "vertex"], "left_semi").groupBy("query").agg(F.count("*").alias("hit"))
    return e.groupBy("query").agg(F.count("*").alias("n")).join(hit, "query", "left").select("query", (F.coalesce("hit", F.lit(0)) / F.col("n")).alias("precision"))


def rank_agreement(exact: DataFrame, approx: DataFrame, k: int) -> DataFrame:
    """query, common, rho: vertices in the top k of both, and the correlation of their ranks there."""
    x = top_k(keyed(exact), k).select("query", "vertex", F.col("rank").alias("x"))
    y = top_k(keyed(approx), k).select("query", "vertex", F.col("rank").alias("y"))
    return x.join(y, ["query", "vertex"]).groupBy("query").agg(F.count("*").alias("common"), F.corr("x", "y").alias("rho"))


def score_error(exact: DataFrame, approx: DataFrame) -> DataFrame:
    """query, max_error, l1_error, over, under: the largest overshoot and undershoot included."""
    e, a = keyed(exact).select("query", "vertex", F.col("score").alias("p")), keyed(approx).select("query", "vertex", F.col("score").alias("x"))
    d = e.join(a, ["query", "vertex"], "full_outer").select("query", (F.coalesce("x", F.lit(0.0)) - F.coalesce("p", F.lit(0.0))).alias("d"))
    return d.groupBy("query").agg(
        F.max(F.abs("d")).alias("max_error"), F.sum(F.abs("d")).alias("l1_error"),
        F.greatest(F.max("d"), F.lit(0.0)).alias("over"), F.greatest(-F.min("d"), F.lit(0.0)).alias("under"),
    )


def walk_stats(stats: DataFrame) -> DataFrame:
    """One row: sources, walks, moves, mean_length."""
    return stats.agg(F.count("*").alias("sources"), F.sum("walks").alias("walks"), F.sum("moves").alias("moves")).withColumn("mean_length", F.col("moves") / F.col("walks"))


def index_loads(g: Graph, queries: DataFrame, laps: int, c: float = TELEPORT) -> DataFrame:
    """query, recursive, shared: stored vectors loaded by plain recursion and with merged frontiers."""
    last = path_rows(g, queries, laps, c)[-1]
    return last.groupBy("query").agg(F.count("*").alias("recursive"), F.count_distinct("vertex").alias("shared"))


def frontier_growth(g: Graph, queries: DataFrame, laps: int, c: float = TELEPORT, eps: float = 0.0) -> DataFrame:
    """lap, settled, frontier: non-zeros of both vectors over all queries, after each number of laps."""
    from .decompose import push, seeds

    f = cut(seeds(g, queries), "growth")
    out = seen = None
    for lap in range(laps + 1):
        held = f.agg(F.lit(lap).alias("lap"), F.count("*").alias("frontier"))
        reach = (f.limit(0) if seen is None else seen).select("query", "vertex").distinct().agg(F.count("*").alias("settled"))
        row = held.crossJoin(reach).select("lap", "settled", "frontier")  # one row each
        out = row if out is None else out.unionByName(row)
        seen = f if seen is None else seen.unionByName(f)
        if lap < laps:
            f = cut(push(g, f, c), "growth")
            f = f.where(F.col("mass") >= eps) if eps > 0 else f
    return out


def residual_mass(f: Frontier) -> DataFrame:
    """query, residual: mass left in the frontier."""
    return f.frontier.groupBy("query").agg(F.sum("mass").alias("residual"))


def relative_gain(before: float, after: float) -> float:
    """Share of a time that an improvement saves."""
    return 1 - after / before


def timed(run: Callable[[], DataFrame]) -> tuple[float, DataFrame]:
    """Seconds of a plan run into a sink that keeps nothing."""
    began = time.perf_counter()
    df = run()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began, df


def shuffle_bytes(spark) -> int:
    """Bytes that finished stages of this application have written to shuffles, from the status store."""
    context = spark.sparkContext
    none = context._gateway.new_array(context._jvm.double, 0)
    stages = context._jsc.sc().statusStore().stageList(None, False, False, none, context._jvm.java.util.ArrayList())
    it, total = stages.iterator(), 0
    while it.hasNext():
        total += it.next().shuffleWriteBytes()
    return int(total)


def cumulative_mass(ppr: DataFrame, key: str = "query") -> DataFrame:
    """Adds rank and the share of the vector's mass within it."""
    order = Window.partitionBy(key).orderBy(F.desc(F.round(F.col("score") + 1.7e-12, 10)), "vertex")
    part = F.sum("score").over(order.rowsBetween(Window.unboundedPreceding, 0)) / F.sum("score").over(Window.partitionBy(key))
    return ppr.withColumns({"rank": F.row_number().over(order), "mass": part})
