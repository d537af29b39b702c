"""Online answers: push query mass a few hops, settle part of it, close the rest with stored vectors.

All queries of a batch advance together. In shuffled mode a lap is one join with the edges
and one two-phase sum for the whole batch; where graph and index are proven to fit a
machine, each task answers its queries from broadcast arrays without any exchange.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT, laps_for_residual
from ..functions.lineage import cut, release
from .exact import known, normalised, pick_mode
from .graph import Graph

#: Bytes of index arrays that the driver and each task may hold, and of one entry in them.
INDEX_BYTES, ENTRY_BYTES = 256 << 20, 16
#: Cells of the dense answers that a task works on together.
BLOCK_CELLS = 1 << 22
#: Queries that share a frontier vertex from which on its stored vector is sent to them; as many vertices at most are (the
#: others then hold under a 200th of the frontier each).
HOT_ROWS, HOT_VERTICES = 50_000, 200
ANSWER = "query bigint, vertex bigint, score double"


@dataclass
class Frontier:
    """Settled mass, frontier mass (query, vertex, mass) and mass dropped by the threshold (query, dropped) after `laps`."""

    settled: DataFrame
    frontier: DataFrame
    dropped: DataFrame
    laps: int


def seeds(g: Graph, queries: DataFrame) -> DataFrame:
    q = known(g, queries, "query")
    return q.select(F.col("vertex").alias("query"), "vertex", F.lit(1.0).alias("mass"))


def prepare(g: Graph, mode: str = "auto") -> None:
    """Make the tables that every batch over `g` reads."""
    g.vertices
    if pick_mode(g, mode) == "broadcast":
        g.shared() if g.held else g.lists
    else:
        g.push_edges


def push(g: Graph, frontier: DataFrame, c: float = TELEPORT) -> DataFrame:
    """One lap: every vertex hands (1-c) of its mass to its out-neighbours. Dangling vertices hand on nothing.

    The frontier is moved to the edges' buckets and the sums to their pairs; the edges are not moved.
    """
    return (
        g.pushed(frontier)
        .select("query", F.col("dst").alias("vertex"), (F.col("mass") * F.col("share") * (1 - c)).alias("mass"))
        .groupBy("query", "vertex").agg(F.sum("mass").alias("mass"))
    )


def frontier_vectors(
    g: Graph, queries: DataFrame, laps: int, c: float = TELEPORT, eps: float = 0.0, residual: float | None = None
) -> Frontier:
    """Settled and frontier vectors of all queries after `laps` laps, or once every frontier holds at most `residual`.

    eps > 0 drops frontier entries below it after each lap and reports their sum per query,
    which bounds the error of the final answer. Queries that are not vertices give no rows.
    """
    if residual is not None:
        laps = max(laps, laps_for_residual(residual, c))
    f = cut(seeds(g, queries), "frontier")
    settled = dropped = None
    done = 0
    for _ in range(laps):
        if residual is not None:
            most = f.groupBy("query").agg(F.sum("mass").alias("m")).agg(F.max("m")).first()[0]
            if most is None or most <= residual:
                break
        kept = f.select("query", "vertex", (F.lit(c) * F.col("mass")).alias("mass"))
        settled = kept if settled is None else settled.unionByName(kept)
        after = cut(push(g, f, c), "frontier")
        if eps > 0:
            low = after.where(F.col("mass") < eps).select("query", "mass")
            dropped = low if dropped is None else dropped.unionByName(low)
            after = after.where(F.col("mass") >= eps)
        f = after
        done += 1
    empty = f.limit(0)
    settled = (empty if settled is None else settled).groupBy("query", "vertex").agg(F.sum("mass").alias("mass"))
    dropped = (empty.select("query", "mass") if dropped is None else dropped).groupBy("query").agg(F.sum("mass").alias("dropped"))
    return Frontier(settled, f, dropped, done)


def close(frontier: DataFrame, idx: DataFrame, c: float = TELEPORT, hot_rows: int = HOT_ROWS) -> DataFrame:
    """Frontier mass spread by the stored vectors of its vertices: each stored row is read once for the whole batch.

    An index in buckets by source is not moved; the frontier goes to its buckets. Vertices that over `hot_rows` queries share
    are left out of that join: the vectors of the hottest are sent to the frontier instead, which stays spread as it is.
    """
    stored = idx.select(F.col("source").alias("vertex"), "walks", "entries")
    spread = ["query", (F.col("mass") * c / F.col("walks")).alias("w"), F.inline("entries")]
    done = ["query", "vertex", (F.col("w") * F.col("visits")).alias("mass")]
    hot = [r[0] for r in frontier.groupBy("vertex").count().where(F.col("count") > hot_rows).orderBy(F.desc("count")).limit(HOT_VERTICES).collect()]
    if not hot:
        return frontier.join(stored, "vertex").select(*spread).select(*done)
    held = F.broadcast(stored.where(F.col("vertex").isin(hot)))
    cold = frontier.where(~F.col("vertex").isin(hot)).join(stored, "vertex").select(*spread)
    return cold.unionByName(frontier.where(F.col("vertex").isin(hot)).join(held, "vertex").select(*spread)).select(*done)


def combine(settled: DataFrame, closed: DataFrame | None, normalise: bool) -> DataFrame:
    parts = settled if closed is None else settled.unionByName(closed)
    q = parts.groupBy("query", "vertex").agg(F.sum("mass").alias("score"))
    return normalised(q, "query") if normalise else q


def batch_ppr(
    g: Graph, idx: DataFrame | None, queries: DataFrame, laps: int = 2, c: float = TELEPORT, eps: float = 0.0, k: int | None = None,
    normalise: bool = True, residual: float | None = None, mode: str = "auto",
) -> DataFrame:
    """PPR of every query (column query) by `laps` laps and the index: query, vertex, score (and rank with k).

    Without an index the settled vector is the answer. laps = 0 gives the stored vectors as
    they are. Frontier mass at vertices that a partial index lacks is left out, so normalise
    makes up for it. The answers are normalised last, which is also what makes dangling
    vertices exact. Repeated queries are answered once; unknown ones not at all. In
    broadcast mode `idx` may also be what share_index gave, which many batches then use.
    """
    if idx is None and laps < 1 and residual is None:
        raise ValueError("without an index at least one lap is needed")
    if mode == "auto" and isinstance(idx, DataFrame) and not (g.held and _index_fits(idx)):
        mode = "shuffle"
    if pick_mode(g, mode) == "broadcast":
        answer = _local_answers(g, idx, queries, laps, c, eps, k, normalise, residual)
    else:
        f = frontier_vectors(g, queries, laps, c, eps, residual)
        answer = combine(f.settled, None if idx is None else close(f.frontier, idx, c), normalise)
    return answer if k is None else top_k(answer, k)


def _index_fits(idx: DataFrame) -> bool:
    n = idx.agg(F.sum(F.size("entries"))).first()[0] or 0
    return ENTRY_BYTES * n <= INDEX_BYTES


def share_index(g: Graph, idx: DataFrame):
    """The index as broadcast arrays beside the graph's, after a check of their size: first, vertex, weight of each position.

    Rows arrive whole and one partition at a time, so the driver holds the arrays and one partition's rows.
    """
    if not _index_fits(idx):
        raise ValueError("the index exceeds the broadcast budget")
    local = g._local

    def positions(batches):
        own = shared.value
        for b in batches:
            lists = b.column("entries")
            yield pa.RecordBatch.from_arrays([
                pa.array(own.find(b.column("source").to_numpy())), pa.array(np.diff(lists.offsets.to_numpy()).astype(np.int64)), b.column("walks").cast(pa.float64()),
                pa.array([own.find(x).astype("<i4").tobytes() for x in _runs(lists, "vertex")], pa.binary()), pa.array([x.astype("<i4").tobytes() for x in _runs(lists, "visits")], pa.binary()),
            ], ["at", "n", "walks", "to", "visits"])

    shared = g.shared()
    rows = idx.select("source", "walks", "entries").mapInArrow(positions, "at bigint, n bigint, walks double, to binary, visits binary")
    size = np.zeros(len(local.ids), np.int64)
    held = cut(rows, "positions")
    for at, n in ((r["at"], r["n"]) for r in held.select("at", "n").toLocalIterator()):
        size[at] += n
    first = np.zeros(len(local.ids) + 1, np.int64)
    np.cumsum(size, out=first[1:])
    vertex, weight, next_ = np.zeros(int(first[-1]), np.intp), np.zeros(int(first[-1])), first[:-1].copy()
    for r in held.toLocalIterator():
        a = next_[r["at"]]
        vertex[a : a + r["n"]] = np.frombuffer(r["to"], "<i4")
        weight[a : a + r["n"]] = np.frombuffer(r["visits"], "<i4") / r["walks"]
        next_[r["at"]] += r["n"]
    release(held)
    return g.spark.sparkContext.broadcast((first, vertex, weight))


def _runs(lists: pa.ListArray, field: str):
    """Values of one field of each list."""
    at, values = lists.offsets.to_numpy(), lists.values.field(field).to_numpy()
    return (values[a:b] for a, b in zip(at[:-1], at[1:]))


def _local_answers(g, idx, queries, laps, c, eps, k, normalise, residual) -> DataFrame:
    stored = None if idx is None else share_index(g, idx) if isinstance(idx, DataFrame) else idx
    if residual is not None:
        laps = max(laps, laps_for_residual(residual, c))

    def run(local, batches):
        from .kernel import close_block, laps_block, rows_of

        n = len(local.ids)
        block = max(1, min(256, BLOCK_CELLS // max(1, n)))
        views = None if stored is None else (np.diff(stored.value[0]), *(rows_of(stored.value[0], x) for x in stored.value[1:]))
        for batch in batches:
            every = batch.column(0).to_numpy()
            for part in np.split(every, range(block, len(every), block)):
                settled, row, at, mass = laps_block(local, local.find(part), laps, c, eps, residual)
                if views is not None:
                    close_block(settled, row, at, mass * c, *views)
                for query, x in zip(part, settled):
                    if normalise and (total := x.sum()) > 0:
                        x /= total
                    hit = np.flatnonzero(x)
                    if k is not None and len(hit) > k:  # all that can be among the k best once rounded
                        least = -np.partition(-x[hit], k - 1)[k - 1]
                        hit = hit[x[hit] >= least - 1e-9]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hit), query)), pa.array(local.ids[hit]), pa.array(x[hit])], ["query", "vertex", "score"])

    q = known(g, queries, "query").select(F.col("vertex").alias("query"))
    n = q.count()
    return g.on_lists(q, run, ANSWER, max(1, min(n, 4 * g.spark.sparkContext.defaultParallelism, 4096)), g.held or stored is not None)


def frontier_decompose(g: Graph, idx: DataFrame | None, query: int, laps: int = 2, **how) -> DataFrame:
    """The answer for a single query."""
    return batch_ppr(g, idx, g.spark.createDataFrame([(query,)], "query long"), laps, **how)


def decompose_once(g: Graph, vectors: DataFrame, queries: DataFrame, c: float = TELEPORT) -> DataFrame:
    """Each query's vector from those (source, vertex, score) of its out-neighbours: one step of the decomposition identity."""
    s = seeds(g, queries)
    pushed = push(g, s, c).withColumnRenamed("vertex", "source")
    closed = pushed.join(vectors, "source").select("query", "vertex", (F.col("mass") * F.col("score")).alias("mass"))
    own = s.select("query", "vertex", F.lit(c).alias("mass"))
    return combine(own, closed, False)


def path_rows(g: Graph, queries: DataFrame, laps: int, c: float = TELEPORT) -> list[DataFrame]:
    """Rows (query, vertex, mass) per level of the recursion, one per path: nothing is merged."""
    levels = [cut(seeds(g, queries), "paths")]
    for _ in range(laps):
        levels.append(cut(
            g.pushed(levels[-1]).select("query", F.col("dst").alias("vertex"), (F.col("mass") * F.col("share") * (1 - c)).alias("mass")), "paths",
        ))
    return levels


def recursive_decompose(g: Graph, idx: DataFrame, queries: DataFrame, laps: int, c: float = TELEPORT, normalise: bool = True) -> DataFrame:
    """The same answer by plain recursion: every path of length `laps` loads a stored vector of its own."""
    levels = path_rows(g, queries, laps, c)
    settled = levels[0].limit(0)
    for x in levels[:-1]:
        settled = settled.unionByName(x.select("query", "vertex", (F.lit(c) * F.col("mass")).alias("mass")))
    return combine(settled, close(levels[-1], idx, c), normalise)


def per_query_loop(g: Graph, idx: DataFrame | None, queries: list[int], laps: int, **how) -> list[DataFrame]:
    """One job per query, for comparison with a shared batch; the caller bounds the list."""
    return [frontier_decompose(g, idx, q, laps, **how) for q in queries]


def top_k(ppr: DataFrame, k: int, key: str = "query") -> DataFrame:
    """The k best of each query by score rounded to ten digits, ties by vertex: adds rank."""
    order = Window.partitionBy(key).orderBy(F.desc(F.round(F.col("score") + 1.7e-12, 10)), "vertex")
    return ppr.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def pair_scores(ppr: DataFrame, pairs: DataFrame) -> DataFrame:
    """Scores of asked pairs (query, vertex), 0 where a vertex is not reached."""
    return pairs.select("query", "vertex").distinct().join(ppr.select("query", "vertex", "score"), ["query", "vertex"], "left").fillna(0.0, ["score"])


def effective_walks(f: Frontier, walks: int, c: float = TELEPORT) -> DataFrame:
    """query, walks, shrink: walks that an answer rests on, walks * (sum f)^2 / sum f^2, and the factor (1-c)^laps on their error."""
    return f.frontier.groupBy("query").agg(
        (walks * F.sum("mass") * F.sum("mass") / F.sum(F.col("mass") * F.col("mass"))).alias("walks"), F.lit((1 - c) ** f.laps).alias("shrink")
    )
