"""Accuracy experiments: stratified queries, exact vectors, then estimates ranked against them."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT
from ..functions.lineage import cut
from . import baselines, decompose, measures, walks
from .estimators import end_point_ppr, full_path_ppr
from .graph import Graph, sample_queries
from .index import compact


def truth(g: Graph, queries: DataFrame, c: float = TELEPORT, tol: float = 1e-10) -> DataFrame:
    """Exact vectors of the sampled queries: query, vertex, score."""
    return cut(baselines.power_iteration_online(g, queries, c=c, tol=tol), "truth")


def stratified(g: Graph, per_bucket: int = 10, seed: int = 7) -> DataFrame:
    """query, bucket of vertices drawn from every out-degree bucket."""
    return sample_queries(g, per_bucket, seed).select(F.col("vertex").alias("query"), "bucket")


def rag_by_walks(g: Graph, queries: DataFrame, exact_vectors: DataFrame, rs: Iterable[int], ks: list[int], **how) -> DataFrame:
    """estimator, walks, k, rag, queries: both estimators from the same walks at growing walk counts."""
    names, found = [], []
    for r in rs:
        w = walks.simulate_walks(g, queries.select(F.col("query").alias("vertex")), r, **how)
        w = walks.Walks(cut(w.visits, "visits"), r, w.c)
        names += [("full_path", r), ("end_point", r)]
        found += [full_path_ppr(w), end_point_ppr(w)]
    return _named(measures.mean_rags(exact_vectors, found, ks), names, "estimator", "walks")


def _named(rags: DataFrame, names: list[tuple], *columns: str) -> DataFrame:
    """Rows of mean_rags with the settings of each approximation in place of its number."""
    settings = [F.element_at(F.array(*[F.lit(n[i]) for n in names]), F.col("which") + 1).alias(c) for i, c in enumerate(columns)]
    return rags.select(*settings, "k", "rag", "queries")


def rag_by_laps(g: Graph, queries: DataFrame, exact_vectors: DataFrame, rs: Iterable[int], depths: Iterable[int], ks: list[int], c: float = TELEPORT, **how) -> DataFrame:
    """walks, laps, k, rag, queries of the decomposition; walks = 0 is index-free (from one lap on)."""
    names, found = [], []
    for r in rs:
        idx = cut(compact(walks.simulate_walks(g, None, r, c, **how).visits, r), "idx") if r else None
        for t in depths:
            if r or t:
                names.append((r, t))
                found.append(decompose.batch_ppr(g, idx, queries, t, c))
    return _named(measures.mean_rags(exact_vectors, found, ks), names, "walks", "laps")


def minimal_depth(g: Graph, idx: DataFrame | None, queries: DataFrame, exact_vectors: DataFrame, target: float = 0.99, k: int = 200, most: int = 12, c: float = TELEPORT) -> int | None:
    """Least number of laps at which the mean RAG exceeds target."""
    for t in range(0 if idx is not None else 1, most + 1):
        mean = measures.mean_rag(measures.rag(exact_vectors, decompose.batch_ppr(g, idx, queries, t, c), [k])).first()
        if mean and mean.rag > target:
            return t
    return None


def rag_by_teleport(g: Graph, queries: DataFrame, cs: list[float], ks: list[int], base: float = TELEPORT) -> DataFrame:
    """c, k, rag of the exact vectors under other teleport chances, judged by those of the base chance."""
    reference = truth(g, queries, base)
    out = None
    for c in cs:
        row = measures.mean_rag(measures.rag(reference, truth(g, queries, c), ks)).select(F.lit(c).alias("c"), "k", "rag", "queries")
        out = row if out is None else out.unionByName(row)
    return out


