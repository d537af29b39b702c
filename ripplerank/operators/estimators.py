"""PPR estimates from walk counts, and checks of their theory."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT, tail_bound
from .graph import Graph
from .walks import SEED, Walks, simulate_walks


def full_path_ppr(w: Walks, normalise: str = "moves") -> DataFrame:
    """source, vertex, score from every visit: visits / moves, or c * visits / walks (`walks`: unbiased for the
    unnormalised vector, which is what the decomposition combines)."""
    if normalise == "walks":
        return w.visits.select("source", "vertex", (F.lit(w.c) * F.col("visits") / F.lit(w.walks)).alias("score"))
    if normalise != "moves":
        raise ValueError(f"unknown normalisation {normalise!r}")
    return w.visits.join(w.stats.select("source", "moves"), "source").select("source", "vertex", (F.col("visits") / F.col("moves")).alias("score"))


def end_point_ppr(w: Walks) -> DataFrame:
    """source, vertex, score from where the coin stopped walks; absorbed walks count nowhere."""
    total = w.stats.where("ends > 0").select("source", F.col("ends").alias("all"))
    return w.visits.where("ends > 0").join(total, "source").select("source", "vertex", (F.col("ends") / F.col("all")).alias("score"))


def tail_frequency(g: Graph, source: int, gamma: float, walks: int, exact: DataFrame, runs: int = 50, c: float = TELEPORT, seed: int = SEED, **how) -> DataFrame:
    """vertex, over, under, bound: how often `runs` estimates miss the exact score by gamma, beside the tail bound.

    All runs are one simulation whose walk numbers are cut into blocks.
    """
    one = g.spark.createDataFrame([(source,)], "vertex long")
    from .walks import walk_paths

    paths = walk_paths(g, one, walks * runs, c, seed, **how).withColumn("run", F.floor(F.col("walk") / walks).cast("int"))
    moves = paths.groupBy("run").agg(F.count("*").alias("moves"))
    est = paths.groupBy("run", "vertex").agg(F.count("*").alias("visits"))
    grid = exact.where(F.col("source") == source).select("vertex", F.col("score").alias("p")).crossJoin(moves)  # one vector x runs
    off = grid.join(est, ["run", "vertex"], "left").withColumn("d", F.coalesce("visits", F.lit(0)) / F.col("moves") - F.col("p"))
    share = lambda test: F.avg(test.cast("double"))
    return off.groupBy("vertex").agg(share(F.col("d") >= gamma).alias("over"), share(F.col("d") <= -gamma).alias("under"), F.lit(tail_bound(gamma, walks, c)).alias("bound"))


def estimate(g: Graph, sources: DataFrame, walks: int, estimator: str = "full_path", **how) -> DataFrame:
    """Scores of the sources straight from fresh walks, by `full_path` or `end_point`."""
    w = simulate_walks(g, sources, walks, **how)
    return full_path_ppr(w) if estimator == "full_path" else end_point_ppr(w)
