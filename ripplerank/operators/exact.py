"""Exact references: power iteration for sources, for all vertices at once, and for preference mixes."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructType

from ..functions.bounds import TELEPORT
from ..functions.lineage import cut, release
from .graph import Graph, _columns

#: Vectors that the streamed form takes at most, and scores that a task writes of them.
STREAMED, ROWS = 256, 1_000_000
PPR = "source bigint, vertex bigint, score double"


def known(g: Graph, sources: DataFrame, column: str = "vertex") -> DataFrame:
    """Distinct sources that are vertices of the graph; others have no walk and no answer."""
    return sources.select(F.col(column).cast("long").alias("vertex")).distinct().join(g.vertices.select("vertex"), "vertex", "left_semi")


def pick_mode(g: Graph, mode: str, budget: int | None = None) -> str:
    """`auto` becomes `broadcast` where the graph is proven small, else `shuffle`."""
    if mode == "auto":
        return "broadcast" if g.fits(*([budget] if budget else [])) else "shuffle"
    return mode


def _streamed_block(g: Graph, picked: str, mode: str, vectors: int) -> int:
    """Vectors of a block of the streamed form, 0 where another is to be taken."""
    return g.streams(vectors) if mode == "streamed" or mode == "auto" and picked == "shuffle" else 0


def power_iteration(
    g: Graph, sources: DataFrame, c: float = TELEPORT, tol: float = 1e-10, max_iter: int = 200, dangling: str = "to_source", mode: str = "auto"
) -> DataFrame:
    """Personalised PageRank of each source (column vertex): source, vertex, score; zero scores are left out.

    dangling: `to_source` leads the mass of dangling vertices back to the source; `absorb` loses
    it (the unnormalised vector). Stops when no source's vector moves more than tol in
    total, or after max_iter laps. In shuffled mode all sources share every lap: one
    join with the edges and one sum. In `streamed` mode, which `auto` takes where the vectors fit
    and the graph does not, the executors go over their edges and the vectors come and go.
    """
    s = known(g, sources)
    picked = pick_mode(g, mode)
    if picked == "broadcast":
        from .kernel import power

        def run(local, batches):
            for batch in batches:
                for v in batch.column(0).to_numpy():
                    p = power(local, local.find(np.array([v])), np.array([1.0]), c, tol, max_iter, dangling == "to_source")
                    at = np.flatnonzero(p)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), v)), pa.array(local.ids[at]), pa.array(p[at])], ["source", "vertex", "score"])

        return g.on_lists(s, run, PPR, min(64, max(1, s.count())))
    if picked != "shuffle" or mode == "auto" and g.streams(1):
        ids = np.sort(np.array([r[0] for r in s.limit(STREAMED + 1).collect()], np.int64))
        if len(ids) <= STREAMED and (block := _streamed_block(g, picked, mode, len(ids))):
            at = np.searchsorted(g.order[0], ids)
            return _streamed(g, [(x[None], np.ones(1)) for x in at], ids.tolist(), "source bigint", block, c, tol, max_iter, dangling == "to_source")
    unit = cut(s.select(F.col("vertex").alias("source"), "vertex", F.lit(1.0).alias("score")), "unit")
    loose = g.vertices.where("out_deg = 0").select("vertex") if dangling == "to_source" else None
    return _iterated(g, unit, "source", unit.withColumn("score", F.lit(c)), loose, c, tol, max_iter).select("source", "vertex", "score")


def _streamed(g: Graph, starts: list[tuple[np.ndarray, np.ndarray]], names: list, key: str, block: int, c: float, tol: float, max_iter: int, to_source: bool) -> DataFrame:
    """Vectors by name (column `key`, with its type) from their starts (positions, weights), `block` of them a lap, in arrays of the driver."""
    ids, degree = g.order
    over, loose = 1 / np.maximum(degree, 1)[:, None], degree == 0
    parts = []
    for begin in range(0, len(starts), block):
        own = starts[begin : begin + block]
        p = np.zeros((len(ids), len(own)))
        for column, (at, weight) in enumerate(own):
            p[at, column] = weight
        for _ in range(max_iter):
            lost = (1 - c) * p[loose].sum(0) if to_source else np.zeros(len(own))
            q = g.pulled(p * over)
            q *= 1 - c
            for column, (at, weight) in enumerate(own):
                q[at, column] += (c + lost[column]) * weight
            change = max(float(np.abs(q[:, column] - p[:, column]).sum()) for column in range(len(own)))
            p = q
            if change <= tol:
                break
        parts.append(_written(g, p, names[begin : begin + block], key))
    return reduce(DataFrame.unionByName, parts)


def _written(g: Graph, p: np.ndarray, names: list, key: str) -> DataFrame:
    """Non-zero scores of a block of vectors as a table that the executors write."""
    tasks = max(1, -(-p.size // ROWS))
    sent = g.spark.sparkContext.broadcast((g.order[0], p))
    kind = to_arrow_type(StructType.fromDDL(key).fields[0].dataType)

    def run(batches):
        ids, scores = sent.value
        for batch in batches:
            for task in batch.column(0).to_pylist():
                some = slice(task * len(ids) // tasks, (task + 1) * len(ids) // tasks)
                for column, name in enumerate(names):
                    at = np.flatnonzero(scores[some, column])
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), kind), pa.array(ids[some][at]), pa.array(scores[some, column][at])], [key.split()[0], "vertex", "score"])

    out = cut(g.spark.range(0, tasks, numPartitions=tasks).mapInArrow(run, f"{key}, vertex bigint, score double"), "streamed")
    sent.destroy()
    return out


def _iterated(g: Graph, unit: DataFrame, key: str, teleport: DataFrame, loose: DataFrame | None, c: float, tol: float, max_iter: int) -> DataFrame:
    """Laps of all vectors (key, vertex, score) from `unit`, with `teleport` added in each: one join with the edges and one sum for all.

    Mass at the vertices of `loose` goes back to the vertex that the key names.
    """
    p = unit
    for _ in range(max_iter):
        pushed = g.pushed(p).select(key, F.col("dst").alias("vertex"), (F.col("score") * F.col("share") * (1 - c)).alias("score"))
        parts = pushed.unionByName(teleport)
        if loose is not None:
            parts = parts.unionByName(p.join(loose, "vertex", "left_semi").select(key, F.col(key).alias("vertex"), ((1 - c) * F.col("score")).alias("score")))
        after = cut(parts.groupBy(key, "vertex").agg(F.sum("score").alias("score")), "power")
        still = False
        if tol > 0:
            moved = after.join(p.withColumnRenamed("score", "old"), [key, "vertex"], "full_outer").groupBy(key).agg(
                F.sum(F.abs(F.coalesce("score", F.lit(0.0)) - F.coalesce("old", F.lit(0.0)))).alias("d")
            )
            still = (moved.agg(F.max("d")).first()[0] or 0.0) <= tol
        if p is not unit:
            release(p)
        p = after
        if still:
            break
    return p


def global_pagerank(g: Graph, c: float = TELEPORT, tol: float = 1e-10, max_iter: int = 200, mode: str = "auto") -> DataFrame:
    """PageRank with uniform teleport, dangling mass spread evenly: vertex, score."""
    n = g.size[0]
    if pick_mode(g, mode) == "broadcast":
        from .kernel import power

        shared = g.shared()

        def run(batches):
            local = shared.value
            for batch in batches:
                if batch.num_rows:
                    size = len(local.ids)
                    p = power(local, np.arange(size), np.full(size, 1 / max(1, size)), c, tol, max_iter, True)
                    yield pa.RecordBatch.from_arrays([pa.array(local.ids), pa.array(p)], ["vertex", "score"])

        return g.spark.range(1, numPartitions=1).mapInArrow(run, "vertex bigint, score double")
    p, last = g.vertices.select("vertex", "out_deg", F.lit(1.0 / max(1, n)).alias("score")), None
    for _ in range(max_iter):
        lost = p.where("out_deg = 0").agg(F.sum("score")).first()[0] or 0.0
        base = (c + (1 - c) * lost) / max(1, n)
        pushed = g.pushed(p).groupBy(F.col("dst").alias("vertex")).agg(F.sum(F.col("score") * F.col("share")).alias("m"))
        after = cut(
            p.join(pushed, "vertex", "left").select("vertex", "out_deg", F.col("score").alias("old"), (F.lit(base) + (1 - c) * F.coalesce("m", F.lit(0.0))).alias("score")), "pagerank",
            {"change": F.sum(F.abs(F.col("score") - F.col("old")))},
        )
        change = after.facts["change"] or 0.0
        release(last)
        last, p = after, after.drop("old")
        if change <= tol:
            break
    return p.select("vertex", "score")


def normalised(q: DataFrame, key: str = "source") -> DataFrame:
    """Scores divided by their sum per key."""
    total = q.groupBy(key).agg(F.sum("score").alias("__t"))
    return q.join(total, key).select(*[c for c in q.columns if c != "score"], (F.col("score") / F.col("__t")).alias("score"))


def preference_ppr(g: Graph, prefs: DataFrame, c: float = TELEPORT, **how) -> DataFrame:
    """PPR of weighted mixes of sources (profile, vertex, weight): profile, vertex, score.

    Each profile is one vector that starts from its weighted mix: one solve a profile where the graph is small; otherwise
    the vectors of all profiles share every lap. The mix is normalised last, which leads dangling mass back to the mix.
    """
    total = prefs.groupBy("profile").agg(F.sum("weight").alias("t"))
    w = prefs.join(total, "profile").select("profile", F.col("vertex").cast("long").alias("source"), (F.col("weight") / F.col("t")).alias("w"))
    mode = how.get("mode", "auto")
    picked = pick_mode(g, mode)
    if picked == "broadcast":
        from .kernel import power

        shared, tol, laps = g.shared(), how.get("tol", 1e-10), how.get("max_iter", 200)
        kind = prefs.schema["profile"].dataType
        starts = w.join(known(g, prefs).withColumnRenamed("vertex", "source"), "source", "left_semi").groupBy("profile", "source").agg(F.sum("w").alias("w"))
        starts = starts.groupBy("profile").agg(F.collect_list(F.struct("source", "w")).alias("mix"))

        def run(batches):
            local = shared.value
            for batch in batches:
                for profile, mix in zip(batch.column("profile"), batch.column("mix")):
                    at, weight = (mix.values.field(c).to_numpy() for c in ("source", "w"))
                    p = power(local, local.find(at), weight, c, tol, laps, False)
                    found = np.flatnonzero(p)
                    names = pa.array([profile.as_py()] * len(found), profile.type)
                    yield pa.RecordBatch.from_arrays([names, pa.array(local.ids[found]), pa.array(p[found])], ["profile", "vertex", "score"])

        return normalised(starts.repartition("profile").mapInArrow(run, f"profile {kind.simpleString()}, vertex bigint, score double"), "profile")
    mix = cut(w.join(known(g, prefs).withColumnRenamed("vertex", "source"), "source", "left_semi").groupBy("profile", F.col("source").alias("vertex")).agg(F.sum("w").alias("score")), "mix")
    if picked != "shuffle" or mode == "auto" and g.streams(1):
        names = [r[0] for r in mix.select("profile").distinct().limit(STREAMED + 1).collect()]
        if len(names) <= STREAMED and (block := _streamed_block(g, picked, mode, len(names))):
            starts = []
            for name in names:  # one after the other, so that the driver receives the mix in parts
                one = mix.where(F.col("profile").eqNullSafe(F.lit(name))).select("vertex", "score")
                vertex, weight = (np.concatenate(x) for x in zip(*_columns(one, one.count())))
                starts.append((np.searchsorted(g.order[0], vertex), weight))
            kind = f"profile {prefs.schema['profile'].dataType.simpleString()}"
            return normalised(_streamed(g, starts, names, kind, block, c, how.get("tol", 1e-10), how.get("max_iter", 200), False), "profile")
    q = _iterated(g, mix, "profile", mix.withColumn("score", F.lit(c) * F.col("score")), None, c, how.get("tol", 1e-10), how.get("max_iter", 200))
    return normalised(q, "profile")


def dense_solve(g: Graph, c: float = TELEPORT, dangling: str = "to_source", most: int = 5000):
    """All vectors of a small graph by a direct solve, for tests: (ids, matrix of rows)."""
    if g.size[0] > most:
        raise ValueError("the graph is too large for a dense solve")
    local = g._local
    n = len(local.ids)
    a = np.zeros((n, n))
    a[np.repeat(np.arange(n), local.degree), local.dst] = np.repeat(1 / np.maximum(local.degree, 1), local.degree)
    q = c * np.linalg.inv(np.eye(n) - (1 - c) * a)
    return local.ids, q / q.sum(1, keepdims=True) if dangling == "to_source" else q


def ppr_residual(g: Graph, ppr: DataFrame, c: float = TELEPORT) -> DataFrame:
    """source, residual: the largest absolute error of each vector in its defining equation (dangling to source)."""
    unit = ppr.select("source").distinct()
    loose = g.vertices.where("out_deg = 0").select("vertex")
    right = (
        g.pushed(ppr).select("source", F.col("dst").alias("vertex"), ((1 - c) * F.col("score") * F.col("share")).alias("r"))
        .unionByName(ppr.join(loose, "vertex", "left_semi").select("source", F.col("source").alias("vertex"), ((1 - c) * F.col("score")).alias("r")))
        .unionByName(unit.select("source", F.col("source").alias("vertex"), F.lit(c).alias("r")))
        .unionByName(ppr.select("source", "vertex", (-F.col("score")).alias("r")))
    )
    return right.groupBy("source", "vertex").agg(F.sum("r").alias("r")).groupBy("source").agg(F.max(F.abs("r")).alias("residual"))
