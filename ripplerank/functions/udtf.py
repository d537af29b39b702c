"""Table functions and a grouped measure for SQL users."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


@udtf(returnType=T.StructType([T.StructField("vertex", T.LongType()), T.StructField("score", T.DoubleType())]))
class IndexEntries:
    """Scores of one compact index row: visits over moves."""

    def eval(self, entries: list, moves: int):
        for e in entries or []:
            yield e["vertex"], e["visits"] / moves


def walker(g, seed: int = 7, rng: str = "xxhash64", c: float = 0.15):
    """A table function (source, walks) -> vertex, visits, ends over the broadcast graph, whose size is checked."""
    shared = g.shared()

    @udtf(returnType="vertex bigint, visits bigint, ends bigint")
    class Walker:
        def eval(self, source: int, walks: int):
            from ripplerank.operators.kernel import walk_counts

            local = shared.value
            at = local.find(np.array([source]))
            if at[0] >= 0:
                _, v, visits, ends = walk_counts(local, at, walks, c, seed, rng, 0, "absorb", None)
                yield from zip(local.ids[v].tolist(), visits.tolist(), ends.tolist())

    return Walker


@pandas_udf(T.DoubleType())
def rag_of(p: pd.Series, exact_rank: pd.Series, approx_rank: pd.Series, k: pd.Series) -> float:
    """RAG of one group of rows (exact score, both ranks, k): a cross-check of the windowed form."""
    n = k.iloc[0]
    best = p[exact_rank <= n].sum()
    return float(p[approx_rank <= n].sum() / best) if best else 0.0


def register(spark: SparkSession) -> None:
    """Make index_entries(entries, moves) known to SQL."""
    spark.udtf.register("index_entries", IndexEntries)


def register_views(g, idx=None, frontier=None) -> None:
    """Temporary views ppr_edges, ppr_vertices, and ppr_index and ppr_frontier if given."""
    g.edges.createOrReplaceTempView("ppr_edges")
    g.vertices.createOrReplaceTempView("ppr_vertices")
    if idx is not None:
        idx.createOrReplaceTempView("ppr_index")
    if frontier is not None:
        frontier.createOrReplaceTempView("ppr_frontier")


#: SQL templates over those views.
LAP_SQL = """
    select f.query, e.dst as vertex, sum(f.mass * (1 - :c) / v.out_deg) as mass
    from ppr_frontier f join ppr_edges e on e.src = f.vertex join ppr_vertices v on v.vertex = f.vertex
    group by f.query, e.dst"""
CLOSE_SQL = """
    select f.query, x.vertex, sum(f.mass * :c * x.visits / i.walks) as score
    from ppr_frontier f join ppr_index i on i.source = f.vertex lateral view inline(i.entries) x as vertex, visits
    group by f.query, x.vertex"""


def sql_lap(spark: SparkSession, c: float):
    return spark.sql(LAP_SQL, args={"c": c})


def sql_close(spark: SparkSession, c: float):
    return spark.sql(CLOSE_SQL, args={"c": c})


