"""The methods compared with, each under its own name."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT
from . import decompose, exact, index, walks
from .estimators import end_point_ppr, full_path_ppr
from .graph import Graph


def _as_sources(queries: DataFrame) -> DataFrame:
    return queries.select(F.col("query").alias("vertex"))


def _answer(ppr: DataFrame) -> DataFrame:
    return ppr.select(F.col("source").alias("query"), "vertex", "score")


def power_iteration_online(g: Graph, queries: DataFrame, **how) -> DataFrame:
    """Power iteration at query time."""
    return _answer(exact.power_iteration(g, _as_sources(queries), **how))


def online_walking(g: Graph, queries: DataFrame, r: int = 2000, **how) -> DataFrame:
    """The full-path estimator run for the queried vertices only."""
    mode = exact.pick_mode(g, how.pop("mode", "auto"))
    if mode == "broadcast":
        return _answer(walks.walk_scores(g, _as_sources(queries), r, **how))
    return _answer(full_path_ppr(walks.simulate_walks(g, _as_sources(queries), r, mode=mode, **how)))


def online_end_points(g: Graph, queries: DataFrame, r: int = 2000, **how) -> DataFrame:
    """The end-point estimator at query time."""
    return _answer(end_point_ppr(walks.simulate_walks(g, _as_sources(queries), r, **how)))


def precomputed_lookup(idx: DataFrame, queries: DataFrame) -> DataFrame:
    """Rows of a large index as stored."""
    return index.lookup(idx, queries)


def recursive(g: Graph, idx: DataFrame, queries: DataFrame, laps: int = 2, **how) -> DataFrame:
    return decompose.recursive_decompose(g, idx, queries, laps, **how)


def index_free(g: Graph, queries: DataFrame, laps: int = 7, **how) -> DataFrame:
    """Decomposition without an index: the settled vector."""
    return decompose.batch_ppr(g, None, queries, laps, **how)


def long_walk(g: Graph, queries: DataFrame, moves: int, **how) -> DataFrame:
    return _answer(walks.long_walk(g, _as_sources(queries), moves, **how))


def walk_database(paths: DataFrame, queries: DataFrame, estimator: str = "full_path") -> DataFrame:
    """Answers from stored trajectories (source, walk, step, vertex, stop) at query time."""
    q = queries.select(F.col("query").alias("source")).distinct()
    rows = paths.join(q, "source", "left_semi")
    rows = rows if estimator == "full_path" else rows.where("stop")
    n = rows.groupBy("source").agg(F.count("*").alias("n"))
    return _answer(rows.groupBy("source", "vertex").agg(F.count("*").alias("x")).join(n, "source").select("source", "vertex", (F.col("x") / F.col("n")).alias("score")))


def stitching(g: Graph, queries: DataFrame, r: int, stock: int = 20, length: int = 3, **how) -> DataFrame:
    """Walks put together from stored segments."""
    segments = walks.stored_segments(g, stock, length)
    return _answer(full_path_ppr(walks.stitched_walk(g, _as_sources(queries), r, segments, stock, length, **how)))


def hubs(g: Graph, n: int) -> DataFrame:
    """The n vertices of largest in-degree, ties by id: column vertex."""
    into = g.edges.groupBy(F.col("dst").alias("vertex")).agg(F.count("*").alias("d"))
    return into.orderBy(F.desc("d"), "vertex").limit(n).select("vertex")


def hub_only(g: Graph, hub_index: DataFrame, queries: DataFrame, laps: int = 0, c: float = TELEPORT, **how) -> DataFrame:
    """Personalisation to indexed hubs: queries outside them are answered only if laps > 0, by pushing on to hubs."""
    if laps == 0:
        return index.lookup(hub_index, queries)
    return decompose.batch_ppr(g, hub_index, queries, laps, c, **how)
