"""Short walks from many sources at once, in the form that fits the graph's size."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT
from ..functions.draws import choose, draw_arrays, draw_columns, stop_bound
from ..functions.lineage import cut, release
from .exact import known, pick_mode
from .graph import Graph, source_intervals

SEED = 7
#: Surviving walks that are sent whole to the adjacency, and so few that their vertices become literals, which skip row groups.
TAIL_ROWS, LITERAL_ROWS = 100_000, 1000
#: Steps whose walkers are kept until their visits are counted together.
KEPT_STEPS = 8
#: Draws that a task of the compressed form makes at once.
DRAWS = 1_000_000
#: Blocks in which the walks that stand at one vertex take their turns.
TURN_BLOCKS = 64
VISITS = "source bigint, vertex bigint, visits bigint, ends bigint"


@dataclass
class Walks:
    """Visit and end counts by (source, vertex), and the number of walks of every source."""

    visits: DataFrame
    walks: int
    c: float

    @property
    def stats(self) -> DataFrame:
        """source, walks, moves (all visits), ends (walks that the coin stopped)."""
        return self.visits.groupBy("source").agg(F.lit(self.walks).cast("long").alias("walks"), F.sum("visits").alias("moves"), F.sum("ends").alias("ends"))


def simulate_walks(
    g: Graph, sources: DataFrame | None, walks: int, c: float = TELEPORT, seed: int = SEED, mode: str = "auto", rng: str = "xxhash64",
    max_steps: int | None = None, first_walk: int = 0, dangling: str = "absorb", intervals: int = 8, path: str | None = None,
) -> Walks:
    """`walks` short walks from each source (column vertex; None: all vertices).

    A walk counts a visit wherever it stands, its start included, and stops there with
    chance c; otherwise it moves to a uniform out-neighbour. At a dangling vertex it is
    absorbed, or returns to its source (`to_source`). Draws depend only on (seed, source,
    walk, step): all modes give equal counts. `broadcast`: the graph fits a machine and
    a walk never leaves its task. `shuffle`: one exchange of survivors per step, to where the adjacency lies. `interval`:
    disjoint source ranges one after the other, each written below `path` and skipped when
    already there. `compress`: one row per (source, vertex) with a count, split by
    draws that also depend on the vertex (another sample of the same law). `auto`: by size.
    Unknown sources are ignored; no sources give no rows.
    """
    s = g.vertices.select("vertex") if sources is None else known(g, sources)
    if mode == "interval":
        return _by_interval(g, s, walks, c, seed, rng, max_steps, first_walk, dangling, intervals, path)
    mode = pick_mode(g, mode)
    if mode == "broadcast":
        visits = _broadcast(g, s, walks, c, seed, rng, max_steps, first_walk, dangling)
        if sources is not None and not g.held:  # lists are sent to the tasks once, however often the counts are read
            visits = cut(visits, "counts")
    elif mode == "shuffle":
        visits = _counted(_laps(g, s, walks, c, seed, rng, max_steps, first_walk, dangling))
    elif mode == "compress":
        visits = _compressed(g, s, walks, c, seed, rng, max_steps, first_walk, dangling)
    else:
        raise ValueError(f"unknown mode {mode!r}")
    return Walks(visits, walks, c)


def _tasks(s: DataFrame, walks: int) -> int:
    n = s.count()
    return max(1, min(n, -(-n * walks // 100_000), 4096), min(n, 2 * s.sparkSession.sparkContext.defaultParallelism))


def _broadcast(g, s, walks, c, seed, rng, max_steps, first_walk, dangling) -> DataFrame:
    from .kernel import chunks, walk_counts

    def run(local, batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for part in chunks(len(ids), walks):
                own = ids[part]
                s, v, visits, ends = walk_counts(local, local.find(own), walks, c, seed, rng, first_walk, dangling, max_steps)
                yield pa.RecordBatch.from_arrays([pa.array(own[s]), pa.array(local.ids[v]), pa.array(visits), pa.array(ends)], ["source", "vertex", "visits", "ends"])

    return g.on_lists(s, run, VISITS, _tasks(s, walks))


def walk_scores(g: Graph, sources: DataFrame, walks: int, c: float = TELEPORT, seed: int = SEED, rng: str = "xxhash64", first_walk: int = 0, dangling: str = "absorb", max_steps: int | None = None) -> DataFrame:
    """Full-path scores (source, vertex, score) of a graph that fits a machine: a source's walks lie in one task, which divides by their visits itself."""
    from .kernel import chunks, walk_counts

    def run(local, batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for part in chunks(len(ids), walks):
                own = ids[part]
                s, v, visits, _ = walk_counts(local, local.find(own), walks, c, seed, rng, first_walk, dangling, max_steps)
                moves = np.bincount(s, visits, len(own))
                yield pa.RecordBatch.from_arrays([pa.array(own[s]), pa.array(local.ids[v]), pa.array(visits / moves[s])], ["source", "vertex", "score"])

    s = known(g, sources)
    return g.on_lists(s, run, "source bigint, vertex bigint, score double", _tasks(s, walks))


def _counted(laps: Iterator[DataFrame]) -> DataFrame:
    """Visits and ends by (source, vertex). Every few steps are counted together, and their walkers deleted."""
    kept: list[DataFrame] = []
    counts: list[DataFrame] = []

    def total(parts: list[DataFrame], visits: Column, ends: Column) -> DataFrame:
        return reduce(DataFrame.unionByName, parts).groupBy("source", "vertex").agg(F.sum(visits).alias("visits"), F.sum(ends).alias("ends"))

    def count(done: list[DataFrame]) -> None:
        rows = [x.select("source", F.col("v").alias("vertex"), "stop") for x in done]
        counts.append(cut(total(rows, F.lit(1).cast("long"), F.col("stop").cast("long")), "counts"))
        release(*done)

    for newest in laps:
        kept.append(newest)
        if len(kept) > KEPT_STEPS:  # the newest is still to be moved on
            count(kept[:-1])
            kept = kept[-1:]
    count(kept)
    return total(counts, F.col("visits"), F.col("ends"))


def _laps(g, s, walks, c, seed, rng, max_steps, first_walk, dangling) -> Iterator[DataFrame]:
    """One table per step: source, walk, v, deg, sdeg, stop, pos of every walk alive at it."""
    def drawn(rows: DataFrame, step: int) -> DataFrame:
        h1, h2 = draw_columns(rng, seed, F.col("source"), F.col("walk"), F.lit(step))
        rows = rows.withColumn("stop", h1 < stop_bound(c)).withColumn("pos", choose(h2, F.col("deg")))
        return cut(rows, "walkers", {"alive": F.count(F.when(~F.col("stop"), 1))})

    deg = g.vertices.join(s, "vertex", "left_semi").select(F.col("vertex").alias("source"), F.col("out_deg").alias("deg"))
    numbers = F.sequence(F.lit(first_walk).cast("long"), F.lit(first_walk + walks - 1).cast("long"))
    first = deg.withColumn("walk", F.explode(numbers if walks else F.array().cast("array<bigint>"))).select("source", "walk", F.col("source").alias("v"), "deg", F.col("deg").alias("sdeg"))
    now, step = drawn(first, 0), 0
    yield now
    while (max_steps is None or step < max_steps) and (n := now.facts.get("alive")):
        alive = now.where(~F.col("stop"))
        mover = alive.where("deg > 0").select(F.col("v").alias("src"), "pos", "source", "walk", "sdeg")
        moved = _neighbours(g, mover, n).select("source", "walk", F.col("dst").alias("v"), F.col("dst_deg").alias("deg"), "sdeg")
        if dangling == "to_source":
            moved = moved.unionByName(alive.where("deg = 0").select("source", "walk", F.col("source").alias("v"), F.col("sdeg").alias("deg"), "sdeg"))
        step += 1
        now = drawn(moved, step)
        yield now


def _neighbours(g: Graph, mover: DataFrame, n: int) -> DataFrame:
    """Rows (src, pos, ...) beside the neighbour at that position: adds dst and dst_deg.

    The adjacency stays in its buckets. Many walkers are moved there; of a tail of walks, all are sent to it, and the last
    few read only the row groups that hold their vertices.
    """
    adjacency = g.adjacency
    if n <= LITERAL_ROWS:
        adjacency = adjacency.where(F.col("src").isin([r[0] for r in mover.select("src").distinct().collect()]))
    return adjacency.join(F.broadcast(mover) if n <= TAIL_ROWS else mover, ["src", "pos"])


def walk_paths(g: Graph, sources: DataFrame, walks: int, c: float = TELEPORT, seed: int = SEED, rng: str = "xxhash64", mode: str = "auto", **how) -> DataFrame:
    """Stored trajectories: source, walk, step, vertex, stop. Any number of walks is kept as rows, none is gathered."""
    s = known(g, sources)
    options = (how.get("max_steps"), how.get("first_walk", 0), how.get("dangling", "absorb"))
    if pick_mode(g, mode) == "shuffle":
        laps = enumerate(_laps(g, s, walks, c, seed, rng, *options))
        return reduce(DataFrame.unionByName, [rows.select("source", "walk", F.lit(step).alias("step"), F.col("v").alias("vertex"), "stop") for step, rows in laps])
    from .kernel import chunks, walk

    def run(local, batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for part in chunks(len(ids), walks):
                own = ids[part]
                for step, s, w, v, stop in walk(local, local.find(own), walks, c, seed, rng, options[1], options[2], options[0]):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(own[s]), pa.array(w), pa.array(np.full(len(s), step, np.int32)), pa.array(local.ids[v]), pa.array(stop)],
                        ["source", "walk", "step", "vertex", "stop"],
                    )

    return g.on_lists(s, run, "source bigint, walk bigint, step int, vertex bigint, stop boolean", _tasks(s, walks))


def _by_interval(g, s, walks, c, seed, rng, max_steps, first_walk, dangling, intervals, path) -> Walks:
    if not path:
        raise ValueError("interval mode needs a path to write to")
    dealt = source_intervals(g, intervals).join(s, "vertex", "left_semi")
    jvm = g.spark.sparkContext._jvm
    conf = g.spark.sparkContext._jsc.hadoopConfiguration()
    for i in range(intervals):
        done = jvm.org.apache.hadoop.fs.Path(f"{path}/interval={i}/_SUCCESS")
        if not done.getFileSystem(conf).exists(done):
            part = simulate_walks(g, dealt.where(F.col("interval") == i), walks, c, seed, "auto", rng, max_steps, first_walk, dangling)
            part.visits.write.mode("overwrite").parquet(f"{path}/interval={i}")
    schema = VISITS + ", interval int"
    return Walks(g.spark.read.schema(schema).option("basePath", path).parquet(f"{path}/interval=*").drop("interval"), walks, c)


def _split(seed: int, rng: str, c: float, step: int, first_walk: int):
    """Batches (source, v, deg, n) of standing walks as (source, v, pos, n, stops): n of them go on to neighbour `pos`, -1 from a dangling vertex."""
    def run(batches):
        for batch in batches:
            source, v, deg, n = (batch.column(x).to_numpy() for x in ("source", "v", "deg", "n"))
            total = np.cumsum(n)
            begin = 0
            while begin < len(n):
                # A run of rows within a bounded number of draws; a larger row is drawn in turns.
                end = max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + DRAWS, "right")))
                for first in range(0, int(n[begin]) if end == begin + 1 else 1, DRAWS):
                    size = np.array([min(DRAWS, int(n[begin]) - first)]) if end == begin + 1 else n[begin:end]
                    at = np.repeat(np.arange(begin, end), size)
                    turn = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size) + first + first_walk
                    h1, h2 = draw_arrays(rng, seed, source[at], turn, step, v[at])
                    stop = h1 < stop_bound(c)
                    pos = np.where(stop, -2, np.where(deg[at] > 0, (h2 * deg[at]) >> 32, -1))
                    order = np.lexsort((pos, at))
                    a, p = at[order], pos[order]
                    starts = np.flatnonzero(np.append(True, (np.diff(a) != 0) | (np.diff(p) != 0))) if len(a) else np.zeros(0, int)
                    count, a, p = np.diff(np.append(starts, len(order))), a[starts], p[starts]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(source[a]), pa.array(v[a]), pa.array(p), pa.array(np.where(p == -2, 0, count)), pa.array(np.where(p == -2, count, 0))], ["source", "v", "pos", "n", "stops"]
                    )
                begin = end

    return run


def _compressed(g, s, walks, c, seed, rng, max_steps, first_walk, dangling) -> DataFrame:
    deg = g.vertices.join(s, "vertex", "left_semi")
    now = cut(deg.select(F.col("vertex").alias("source"), F.col("vertex").alias("v"), F.col("out_deg").alias("deg"), F.lit(walks).cast("long").alias("n")), "groups")
    degs = g.vertices.select(F.col("vertex").alias("source"), F.col("out_deg").alias("sdeg"))
    out, step = [], 0
    while True:
        split = now.mapInArrow(_split(seed, rng, c, step, first_walk), "source bigint, v bigint, pos bigint, n bigint, stops bigint")
        parts = cut(split.groupBy("source", "v", "pos").agg(F.sum("n").alias("n"), F.sum("stops").alias("stops")), "split", {"alive": F.sum("n")})
        out.append(cut(parts.groupBy("source", F.col("v").alias("vertex")).agg(F.sum(F.col("n") + F.col("stops")).alias("visits"), F.sum("stops").alias("ends")), "counts"))
        release(now)
        if (max_steps is not None and step >= max_steps) or not parts.facts.get("alive"):
            break
        alive = parts.where("n > 0")
        moved = alive.where("pos >= 0").withColumnRenamed("v", "src").join(g.adjacency, ["src", "pos"]).select("source", F.col("dst").alias("v"), F.col("dst_deg").alias("deg"), "n")
        if dangling == "to_source":
            moved = moved.unionByName(alive.where("pos = -1").join(degs, "source").select("source", F.col("source").alias("v"), F.col("sdeg").alias("deg"), "n"))
        now = cut(moved.groupBy("source", "v", "deg").agg(F.sum("n").alias("n")), "groups")
        release(parts)
        step += 1
    return reduce(DataFrame.unionByName, out).groupBy("source", "vertex").agg(F.sum("visits").alias("visits"), F.sum("ends").alias("ends"))


def long_walk(g: Graph, sources: DataFrame, n: int, c: float = TELEPORT, seed: int = SEED, rng: str = "xxhash64", mode: str = "auto") -> DataFrame:
    """One walk of n visits per source that returns to the source with chance c after each, and from dangling vertices: source, vertex, score.

    Between two returns it is a short walk, so it is made of the short walks of its source, one after the other, until n visits
    are counted; any graph and any n will do, as stretches are walked side by side.
    """
    s = cut(known(g, sources), "sources")
    walks = int(n * c + 4 * math.sqrt(n * c) + 16)  # stretches are at most 1/c visits long in the mean
    while True:
        paths = cut(walk_paths(g, s, walks, c, seed, rng, mode), "stretches")
        before = F.sum("moves").over(Window.partitionBy("source").orderBy("walk").rowsBetween(Window.unboundedPreceding, -1))
        lengths = paths.groupBy("source", "walk").agg(F.count("*").alias("moves"))
        short = lengths.groupBy("source").agg(F.sum("moves").alias("m")).agg(F.min("m")).first()[0]
        if short is None or short >= n:
            break
        release(paths)
        walks = int(walks * max(2, 1.2 * n / short))
    starts = lengths.withColumn("before", F.coalesce(before, F.lit(0))).where(F.col("before") < n).select("source", "walk", "before")
    within = paths.join(starts, ["source", "walk"]).where(F.col("before") + F.col("step") < n)
    return within.groupBy("source", "vertex").agg((F.count("*") / F.lit(n)).alias("score"))


def stored_segments(g: Graph, stock: int, length: int, seed: int = SEED, rng: str = "xxhash64", mode: str = "auto") -> DataFrame:
    """`stock` segments of up to `length` moves per vertex, without stops: v, segment, path (vertices after the start)."""
    paths = walk_paths(g, g.vertices.select("vertex"), stock, 0.0, seed, rng, mode, max_steps=length)
    steps = F.transform(F.array_sort(F.collect_list(F.when(F.col("step") > 0, F.struct("step", "vertex")))), lambda s: s["vertex"])
    return paths.groupBy(F.col("source").alias("v"), F.col("walk").alias("segment")).agg(steps.alias("path"))


def stitched_walk(g: Graph, sources: DataFrame, walks: int, segments: DataFrame, stock: int, length: int, c: float = TELEPORT, seed: int = SEED) -> Walks:
    """Short walks put together from stored segments, each lap joined at the walks' present ends.

    The number of moves of a walk is drawn first. In a lap every unfinished walk takes the
    next unused segment of its vertex; once a vertex's stock is used up it is dealt again
    from the start. Every lap takes a move or ends a walk, so all are finished. Turns at a vertex are counted
    in blocks, so that no task sorts all walks at a hub. Many laps of random access are this method's cost.
    """
    s = known(g, sources)
    u = (F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), F.lit("moves"), "source", "walk")), 1, 12), 16, 10).cast("double") + 0.5) / F.lit(float(1 << 48))
    moves = F.floor(F.log(u) / F.log(F.lit(1 - c)))
    now = s.select(F.col("vertex").alias("source"), F.explode(F.sequence(F.lit(0), F.lit(walks - 1))).alias("walk")).select("source", "walk", F.col("source").alias("v"), moves.alias("left"))
    now = cut(now, "stitch", {"todo": F.count(F.when(F.col("left") > 0, 1))})
    used = g.spark.createDataFrame([], "v long, used long")
    visits = [now.select("source", F.col("v").alias("vertex"), (F.col("left") == 0).cast("long").alias("ends"))]
    while now.facts.get("todo"):
        todo = now.where("left > 0").withColumn("block", F.pmod(F.hash("source", "walk"), F.lit(TURN_BLOCKS)))
        dealt = todo.withColumn("r", F.row_number().over(Window.partitionBy("v", "block").orderBy("source", "walk")) - 1)
        before = Window.partitionBy("v").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
        starts = todo.groupBy("v", "block").agg(F.count("*").alias("m")).select("v", "block", F.coalesce(F.sum("m").over(before), F.lit(0)).alias("start"))
        asked = dealt.join(starts, ["v", "block"]).join(used, "v", "left").withColumn("segment", ((F.coalesce("used", F.lit(0)) + F.col("start") + F.col("r")) % stock).cast("long"))
        taken = cut(asked.join(segments, ["v", "segment"]).select("source", "walk", "v", "left", F.slice("path", F.lit(1), F.least("left", F.lit(length)).cast("int")).alias("path")), "stitch")
        whole = F.size("path") == F.least("left", F.lit(length))
        visits.append(taken.select("source", F.posexplode("path").alias("i", "vertex"), "left").select("source", "vertex", (F.col("i") + 1 == F.col("left")).cast("long").alias("ends")))
        used = cut(taken.groupBy("v").agg(F.count("*").alias("n")).join(used, "v", "full_outer").select("v", (F.coalesce("n", F.lit(0)) + F.coalesce("used", F.lit(0))).alias("used")), "stitch")
        on = taken.where(whole & (F.size("path") > 0)).select("source", "walk", F.element_at("path", -1).alias("v"), (F.col("left") - F.size("path")).alias("left"))
        now = cut(on, "stitch", {"todo": F.count(F.when(F.col("left") > 0, 1))})
    counts = reduce(DataFrame.unionByName, visits).groupBy("source", "vertex").agg(F.count("*").alias("visits"), F.sum("ends").alias("ends"))
    return Walks(counts, walks, c)
