"""Small graphs and numeric comparisons for the tests."""

import numpy as np

from ripplerank.operators.graph import build_graph
from ripplerank.sources import edges as E

SMALL = "/root/testdata/sf0.001"


def pairs(spark, *edges, **how):
    return build_graph(spark.createDataFrame(list(edges), "src long, dst long"), **how)


def named(spark, name):
    return build_graph(E.GRAPHS[name](spark, SMALL))


def queries(spark, *ids, column="query"):
    return spark.createDataFrame([(i,) for i in ids], f"{column} long")


def scores(df, key=None):
    key = key or ("query" if "query" in df.columns else "source")
    value = "mass" if "mass" in df.columns else "score"
    return {(r[key], r["vertex"]): r[value] for r in df.collect()}


def close(a, b, tol=1e-9):
    return max((abs(a.get(k, 0) - b.get(k, 0)) for k in {*a, *b}), default=0) <= tol


def dense(g, sources, c=0.15):
    """Exact vectors by a direct solve, dangling to source."""
    from ripplerank.operators.exact import dense_solve

    ids, p = dense_solve(g, c)
    at = {v: i for i, v in enumerate(ids.tolist())}
    return {(s, v): p[at[s], i] for s in sources for i, v in enumerate(ids.tolist()) if p[at[s], i] > 0}


def dominates(x, y):
    return np.mean(list(x)) > np.mean(list(y))
