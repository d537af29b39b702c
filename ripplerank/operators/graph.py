"""The graph as DataFrames: edges, vertices with out-degree, ranked adjacency, degree buckets."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lineage import bucket_count, bucketed, cut, release

#: Bytes of neighbour lists up to which a graph counts as fitting one machine.
LOCAL_BYTES = 320 << 20
#: Bytes of neighbour lists up to which the driver gathers and sends them; larger ones go from the executors to the tasks.
HELD_BYTES = 128 << 20
#: Bytes of the vectors that one lap over the entering edges takes, and how often a lap may go over them for more vectors.
VECTOR_BYTES, PASSES = 36 << 20, 16
#: Bytes of ids and out-degrees up to which the driver holds those of a graph whose lists it does not hold.
PLACED_BYTES = 64 << 20
#: Edges that the driver receives, and puts in order, at once when it gathers the lists.
GATHERED_EDGES = 1_000_000
#: Edges from which on the part of a graph that some sources reach is cut out of it, and vertices that such a part may have.
REACH_EDGES, REACH_VERTICES = 4_000_000, 500_000
#: Out-degree from which a vertex's edges are ranked in blocks.
HUB_DEGREE = 1_000_000
#: Edges of one vertex that a push keeps in one task; a vertex of more is dealt over several.
PUSH_EDGES = 1_000_000


@dataclass(frozen=True)
class LocalGraph:
    """Neighbour lists as arrays: ids[k] has neighbours dst[first[k]:first[k + 1]] (positions in ids, ascending, of 32 bits)."""

    ids: np.ndarray
    first: np.ndarray
    dst: np.ndarray

    @cached_property
    def degree(self) -> np.ndarray:
        return np.diff(self.first)

    def find(self, vertices: np.ndarray) -> np.ndarray:
        """Positions of vertices, -1 for strangers."""
        if not len(self.ids):
            return np.full(len(vertices), -1)
        at = np.minimum(np.searchsorted(self.ids, vertices), len(self.ids) - 1)
        return np.where(self.ids[at] == vertices, at, -1)


class Graph:
    """A directed graph. `edges` (src, dst) is a set without nulls; everything else derives from it, lazily and once."""

    def __init__(self, edges: DataFrame, push_limit: int = PUSH_EDGES):
        self.edges = edges
        self.spark = edges.sparkSession
        self.push_limit = push_limit

    @cached_property
    def vertices(self) -> DataFrame:
        """vertex, out_deg (0 for dangling): one shuffle, both ends combined before it."""
        ends = self.edges.select(F.inline(F.array(
            F.struct(F.col("src").alias("vertex"), F.lit(1).cast("long").alias("n")), F.struct(F.col("dst").alias("vertex"), F.lit(0).cast("long").alias("n"))
        )))
        return cut(ends.groupBy("vertex").agg(F.sum("n").alias("out_deg")), "vertices")

    @cached_property
    def adjacency(self) -> DataFrame:
        """src, pos, dst, dst_deg: pos is the rank of dst among src's neighbours.

        One equi-join on (src, pos) both picks a neighbour and brings its degree. The table is
        hashed once into buckets of (src, pos), so a step moves walkers only, and those that stand at
        a hub spread over its positions. Hubs are ranked within value blocks whose offsets
        are added, so that no task sorts all edges of one vertex.
        """
        ranked = adjacency_of(self)
        deg = self.vertices.select(F.col("vertex").alias("dst"), F.col("out_deg").alias("dst_deg"))
        return bucketed(ranked.join(deg, "dst").select("src", "pos", "dst", "dst_deg"), "adjacency", ["src", "pos"], self.buckets)

    @cached_property
    def buckets(self) -> int:
        return bucket_count(self.spark, self.size[1])

    @cached_property
    def hubs(self) -> DataFrame | None:
        """vertex, salts: vertices whose edges a push deals over `salts` tasks; None where there are none."""
        found = cut(self.vertices.where(F.col("out_deg") > self.push_limit).select("vertex", F.ceil(F.col("out_deg") / F.lit(self.push_limit)).cast("int").alias("salts")), "hubs")
        return None if found.isEmpty() else found

    @cached_property
    def push_edges(self) -> DataFrame:
        """src, (salt,) dst, share = 1 / out-degree of src: what a lap joins with, hashed once into buckets by src, and by salt where there are hubs."""
        deg = self.vertices.select(F.col("vertex").alias("src"), "out_deg")
        rows = self.edges.join(deg, "src")
        share = (1.0 / F.col("out_deg")).alias("share")
        if self.hubs is None:
            return bucketed(rows.select("src", "dst", share), "push", ["src"], self.buckets)
        salts = F.ceil(F.col("out_deg") / F.lit(self.push_limit)).cast("int")
        salt = F.when(F.col("out_deg") > self.push_limit, F.pmod(F.hash("dst"), salts)).otherwise(0).alias("salt")
        return bucketed(rows.select("src", salt, "dst", share), "push", ["src", "salt"], self.buckets)

    def pushed(self, at: DataFrame) -> DataFrame:
        """Rows of `at` (column vertex) beside the edges that leave there: adds dst and share.

        The edges stay where they lie: only `at` is moved, or sent whole where it is small. A hub's edges lie in several
        tasks, and its rows of `at` go to each of them.
        """
        edges = self.push_edges.withColumnRenamed("src", "vertex")
        if self.hubs is None:
            return at.join(edges, "vertex")
        salts = F.sequence(F.lit(0), F.coalesce(F.col("salts"), F.lit(1)) - 1)
        dealt = at.join(self.hubs, "vertex", "left").select(*at.columns, F.explode(salts).alias("salt"))
        return dealt.join(edges, ["vertex", "salt"]).drop("salt")

    @cached_property
    def size(self) -> tuple[int, int]:
        """Vertices and edges."""
        return self.vertices.count(), self.edges.count()

    @cached_property
    def _local(self) -> LocalGraph:
        """Filled part by part: the driver holds the arrays and one part of the edges, never all rows of the table."""
        n, m = self.size
        ids, degree = np.zeros(n, np.int64), np.zeros(n, np.int64)
        begin = 0
        for v, d in _columns(self.vertices.select("vertex", "out_deg"), n):
            ids[begin : begin + len(v)], degree[begin : begin + len(v)] = v, d
            begin += len(v)
        order = np.argsort(ids)
        ids = ids[order]
        first = np.zeros(n + 1, np.int64)
        np.cumsum(degree[order], out=first[1:])
        dst, free = np.zeros(m, np.int32), first[:-1].copy()
        for s, t in _columns(self.edges, m):
            order = np.argsort(s)
            s, t = s[order], t[order]
            starts = np.flatnonzero(np.append(True, s[1:] != s[:-1]))
            at, size = np.searchsorted(ids, s[starts]), np.diff(np.append(starts, len(s)))
            dst[np.repeat(free[at] - starts, size) + np.arange(len(s))] = np.searchsorted(ids, t)
            free[at] += size
        # Each list in ascending order, some whole lists at a time.
        for a, b in runs(first, GATHERED_EDGES):
            part = slice(first[a], first[b])
            key = np.repeat(np.arange(b - a) * n, np.diff(first[a : b + 1])) + dst[part]
            key.sort()
            dst[part] = key % n
        return LocalGraph(ids, first, dst)

    @cached_property
    def _shared(self):
        return self.spark.sparkContext.broadcast(self._local)

    @cached_property
    def held(self) -> bool:
        """Whether the driver may hold the neighbour lists."""
        return self.fits(HELD_BYTES)

    @cached_property
    def lists(self) -> DataFrame:
        """least, n, m, ids, degree, dst (of all ids, one after the other): the neighbour lists, as bytes, of ranges of ids of about GATHERED_EDGES edges each,
        put in order by a task, with the least id and the numbers of ids and edges. Where the graph is `placed`, dst are positions among all ids."""
        n, m = self.size
        known = self.spark.sparkContext.broadcast(self.order[0]) if self.placed else None
        ends = self.vertices.where("out_deg = 0").select(F.col("vertex").alias("src"), F.lit(0).cast("long").alias("dst"), F.lit(False).alias("real"))
        rows = self.edges.select("src", "dst", F.lit(True).alias("real")).unionByName(ends).repartitionByRange(max(1, -(-(n + m) // GATHERED_EDGES)), "src")
        run = lambda batches: _as_lists(batches, known and known.value)
        return cut(rows.mapInArrow(run, "least bigint, n bigint, m bigint, ids binary, degree binary, dst binary"), "lists")

    @cached_property
    def placed(self) -> bool:
        """Whether the driver may hold all ids, so that targets are looked up once and not by each task that holds the lists."""
        return 16 * self.size[0] <= PLACED_BYTES

    @cached_property
    def order(self) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the vertices in ascending order, and their out-degrees."""
        n = self.size[0]
        ids, degree = (np.concatenate(c) for c in zip(*_columns(self.vertices.select("vertex", "out_deg"), n), strict=True)) if n else (np.zeros(0, np.int64),) * 2
        at = np.argsort(ids)
        return ids[at], degree[at]

    @cached_property
    def entering(self) -> DataFrame:
        """to, first, sources: positions of vertices, where the edges that enter each begin, and the positions of their sources, as bytes.

        A row has about GATHERED_EDGES edges, in order; those of one vertex may go on in the next row.
        """
        ids = self.spark.sparkContext.broadcast(self.order[0])

        def run(batches):
            got = [b for b in batches if b.num_rows]
            if got:
                s, t = (np.searchsorted(ids.value, np.concatenate([b.column(c).to_numpy() for b in got])) for c in ("src", "dst"))
                key = t * len(ids.value) + s
                key.sort()
                t, s = np.divmod(key, len(ids.value))
                first = np.flatnonzero(np.append(True, t[1:] != t[:-1]))
                yield pa.RecordBatch.from_arrays([pa.array([x.astype("<i4").tobytes()], pa.binary()) for x in (t[first], first, s)], ["to", "first", "sources"])

        dealt = self.edges.repartitionByRange(max(1, -(-self.size[1] // GATHERED_EDGES)), "dst", "src")
        out = cut(dealt.mapInArrow(run, "to binary, first binary, sources binary"), "entering")
        ids.destroy()
        return out

    def streams(self, vectors: int) -> int:
        """How many of so many vectors a lap over the entering edges takes at once; 0 where the vertices or the passes are too many for that."""
        n = self.size[0]
        block = min(vectors, VECTOR_BYTES // (8 * max(1, n)))
        return block if block and -(-vectors // block) <= PASSES else 0

    def pulled(self, shares: np.ndarray) -> np.ndarray:
        """Sums over the edges that enter each vertex of their sources' rows of `shares` (a row a vertex, a column a vector).

        The edges stay on the executors, which read them row by row; the vectors alone come and go.
        """
        sent = self.spark.sparkContext.broadcast(shares)

        def run(batches):
            own = sent.value
            for batch in batches:
                for row in zip(*batch.columns):
                    to, first, sources = (np.frombuffer(x.as_buffer(), "<i4") for x in row)
                    taken = own.take(sources, axis=0)
                    sums = np.stack([np.add.reduceat(taken[:, c], first) for c in range(own.shape[1])], axis=1)
                    yield pa.RecordBatch.from_arrays([pa.array([to.tobytes()], pa.binary()), pa.array([sums.astype("<f8").tobytes()], pa.binary())], ["to", "sums"])

        shape = shares.shape
        del shares
        rows = self.entering.mapInArrow(run, "to binary, sums binary").collect()
        sent.destroy()
        out = np.zeros(shape)
        rows.sort(key=lambda r: np.frombuffer(r["to"], "<i4", 1)[0], reverse=True)
        while rows:
            r = rows.pop()
            to = np.frombuffer(r["to"], "<i4")
            out[to] += np.frombuffer(r["sums"], "<f8").reshape(len(to), -1)
        return out

    def on_lists(self, rows: DataFrame, run: Callable, schema: str, tasks: int, held: bool | None = None) -> DataFrame:
        """run(lists, batches) over `rows`, one column of longs dealt over `tasks` tasks, each of which holds all neighbour lists.

        Lists that the driver may hold are broadcast. Larger ones never come to it: the executors send their parts to each task, which
        puts them together. `held` decides that instead of their size.
        """
        name = rows.columns[0]
        if self.held if held is None else held:
            shared = self.shared()
            return rows.repartition(tasks, name).mapInArrow(lambda batches: run(shared.value, batches), schema)
        if not self.fits():
            raise ValueError(f"the graph exceeds {LOCAL_BYTES} bytes; use the shuffled mode")
        tasks = min(tasks, self.spark.sparkContext.defaultParallelism)
        parts = ["ids", "degree", "dst"]
        place, n, m, placed = {}, 0, 0, self.placed
        for r in sorted(self.lists.select("least", "n", "m").collect()):
            place[r["least"]] = n, m
            n, m = n + r["n"], m + r["m"]
        own = rows.select(F.pmod(F.xxhash64(name), F.lit(tasks)).cast("int").alias("task"), F.col(name).alias("row"), *[F.lit(None).cast("binary").alias(c) for c in parts])
        sent = self.lists.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"), F.lit(None).cast("long").alias("row"), *parts)

        def on(batches):
            mine, far = [], {}
            local = LocalGraph(np.zeros(n, np.int64), np.zeros(n + 1, np.int64), np.zeros(m, np.int32))
            for b in batches:
                mine.append(b.column("row").drop_null().to_numpy())
                for i in np.flatnonzero(b.column("row").is_null().to_numpy(zero_copy_only=False)).tolist():
                    _put(local, far, place, *(b.column(c)[i].as_py() for c in parts))
            asked = np.concatenate(mine) if mine else np.zeros(0, np.int64)
            b = None
            pa.default_memory_pool().release_unused()  # what the batches took
            if len(asked):
                if placed:
                    np.cumsum(local.first, out=local.first)
                else:
                    _settle(local, far)
                yield from run(local, [pa.RecordBatch.from_arrays([pa.array(asked)], [name])])

        return own.unionByName(sent).repartitionById(tasks, "task").mapInArrow(on, schema)

    def fits(self, budget: int = LOCAL_BYTES) -> bool:
        """Whether the neighbour lists stay within `budget`: 16 bytes per vertex, and 8 per edge (4 held, 4 for what a task needs beside them)."""
        n, m = self.size
        return 8 * m + 16 * n <= budget

    def shared(self, budget: int = LOCAL_BYTES):
        """Broadcast neighbour lists, after a check of their size."""
        if not self.fits(budget):
            raise ValueError(f"the graph exceeds {budget} bytes; use the shuffled mode")
        return self._shared


def _as_lists(batches: Iterator[pa.RecordBatch], known: np.ndarray | None = None) -> Iterator[pa.RecordBatch]:
    """The rows (src, dst, real) of a task, whole lists and vertices without any, as one row of bytes; targets of 32 bits where they allow it.

    With all ids `known`, targets are their positions there.
    """
    got = [b for b in batches if b.num_rows]
    if not got:
        return
    s, t, real = (np.concatenate([b.column(c).to_numpy(zero_copy_only=False) for b in got]) for c in ("src", "dst", "real"))
    order = np.lexsort((t, s))
    s, t, real = s[order], t[order], real[order]
    starts = np.flatnonzero(np.append(True, s[1:] != s[:-1]))
    degree, t = np.add.reduceat(real.astype(np.int64), starts), t[real]
    if known is not None:
        t = np.searchsorted(known, t)
    short = not len(t) or (t.min() >= -(1 << 31) and t.max() < 1 << 31)
    arrays = s[starts].astype("<i8"), degree.astype("<i8"), t.astype("<i4" if short else "<i8")
    counts = int(s[0]), len(starts), len(t)
    yield pa.RecordBatch.from_arrays([*(pa.array([x]) for x in counts), *(pa.array([x.tobytes()], pa.binary()) for x in arrays)], ["least", "n", "m", "ids", "degree", "dst"])


def _put(local: LocalGraph, far: dict[int, np.ndarray], place: dict[int, tuple[int, int]], ids: bytes, degree: bytes, dst: bytes) -> None:
    """One part where it belongs: degrees in `first` and targets as ids, those of 64 bits aside in `far`, until all parts are there."""
    own, size = np.frombuffer(ids, "<i8"), np.frombuffer(degree, "<i8")
    a, e = place[int(own[0])]
    local.ids[a : a + len(own)] = own
    local.first[a + 1 : a + 1 + len(own)] = size
    if len(dst) == 4 * size.sum():
        local.dst[e : e + len(dst) // 4] = np.frombuffer(dst, "<i4")
    else:
        far[e] = np.frombuffer(dst, "<i8")


def _settle(local: LocalGraph, far: dict[int, np.ndarray]) -> None:
    """Degrees become offsets and targets positions, in place and some at a time."""
    np.cumsum(local.first, out=local.first)
    begin = 0
    for e in [*sorted(far), len(local.dst)]:
        for a in range(begin, e, GATHERED_EDGES):
            part = slice(a, min(e, a + GATHERED_EDGES))
            local.dst[part] = np.searchsorted(local.ids, local.dst[part])
        if e in far:
            begin = e + len(far[e])
            local.dst[e:begin] = np.searchsorted(local.ids, far.pop(e))


def runs(first: np.ndarray, edges: int) -> list[tuple[int, int]]:
    """Runs of vertices (from, to) of about so many edges each at most; a vertex of more is in a run of its own or ends one."""
    cuts = np.unique(np.concatenate([[0], np.searchsorted(first, np.arange(edges, int(first[-1]), edges)), [len(first) - 1]])).tolist()
    return list(zip(cuts[:-1], cuts[1:]))


def _columns(rows: DataFrame, n: int) -> Iterator[list[np.ndarray]]:
    """Batches of a table of `n` rows of long or double columns as arrays; the driver holds one part at a time, while the next is read.

    A larger table is dealt into parts of about GATHERED_EDGES rows, whatever its files and the session's settings are.
    """

    kinds = ["<f8" if kind == "double" else "<i8" for _, kind in rows.dtypes]

    def packed(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([c.to_numpy().astype(kind).tobytes()], pa.binary()) for c, kind in zip(b.columns, kinds)], b.schema.names)

    if n > GATHERED_EDGES:
        rows = rows.repartition(-(-n // GATHERED_EDGES), *rows.columns)
    for r in rows.mapInArrow(packed, ", ".join(f"{c} binary" for c in rows.columns)).toLocalIterator(prefetchPartitions=True):
        yield [np.frombuffer(x, kind) for x, kind in zip(r, kinds)]


def adjacency_of(g: Graph, hub_degree: int = HUB_DEGREE, blocks: int = 256) -> DataFrame:
    """src, pos, dst. Edges of vertices above `hub_degree` are ranked within blocks of dst values, whose offsets are added."""
    hubs = g.vertices.where(F.col("out_deg") > hub_degree).select(F.col("vertex").alias("src"))
    if hubs.isEmpty():
        by_src = Window.partitionBy("src").orderBy("dst")
        return g.edges.select("src", (F.row_number().over(by_src) - 1).cast("long").alias("pos"), "dst")
    at = F.array(*[F.lit(i / blocks) for i in range(1, blocks)])
    bounds = g.edges.join(hubs, "src").groupBy("src").agg(F.percentile_approx("dst", at, 20 * blocks).alias("cuts"))
    dealt = g.edges.join(bounds, "src", "left").select(
        "src", "dst", F.when(F.col("cuts").isNull(), 0).otherwise(F.size(F.filter("cuts", lambda x: x <= F.col("dst")))).alias("block")
    )
    before = Window.partitionBy("src").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("src", "block").count().select("src", "block", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    within = Window.partitionBy("src", "block").orderBy("dst")
    return dealt.withColumn("r", F.row_number().over(within) - 1).join(starts, ["src", "block"]).select("src", (F.col("start") + F.col("r")).alias("pos"), "dst")


def build_graph(edges: DataFrame, symmetric: bool = False, drop_loops: bool = False, push_limit: int = PUSH_EDGES) -> Graph:
    """Edges (src, dst) as a set: nulls and repeats go, reversed edges and loops as asked. Other columns are ignored.

    A vertex of more than `push_limit` out-edges is a hub, whose edges a push deals over several tasks.
    """
    e = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null")
    if symmetric:
        e = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    if drop_loops:
        e = e.where("src <> dst")
    return Graph(cut(e.distinct(), "edges", codec="zstd"), push_limit)


def reached(g: Graph, sources: DataFrame, least: int = REACH_EDGES, most: int = REACH_VERTICES, laps: int = 12) -> Graph:
    """The part of a graph that walks from `sources` (column vertex) can come to, with all edges that leave there.

    Vectors, walks and frontiers of the sources are the same in it. The graph itself comes back where it has at most
    `least` edges, and where more than `most` or half of the vertices are reached or new ones still are after `laps`.
    """
    if g.size[1] <= least:
        return g
    limit = min(most, g.size[0] // 2)
    seen = cut(g.vertices.select("vertex").join(sources.select(F.col("vertex").cast("long").alias("vertex")).distinct(), "vertex", "left_semi"), "reached", {"n": F.count("*")})
    for _ in range(laps):
        if seen.facts["n"] > limit:
            return g
        leaving = g.edges.join(F.broadcast(seen.withColumnRenamed("vertex", "src")), "src", "left_semi")
        after = cut(leaving.select(F.col("dst").alias("vertex")).unionByName(seen).distinct(), "reached", {"n": F.count("*")})
        if after.facts["n"] == seen.facts["n"]:
            part = Graph(cut(leaving, "edges"), g.push_limit)
            part.vertices = cut(g.vertices.join(F.broadcast(after), "vertex", "left_semi"), "vertices")  # a source without any edge here stays
            return part
        release(seen)
        seen = after
    return g


def degrees(g: Graph) -> DataFrame:
    """vertex, out_deg, in_deg."""
    into = g.edges.groupBy(F.col("dst").alias("vertex")).agg(F.count("*").alias("in_deg"))
    return g.vertices.join(into, "vertex", "left").select("vertex", "out_deg", F.coalesce("in_deg", F.lit(0)).cast("long").alias("in_deg"))


def dangling(g: Graph) -> DataFrame:
    """Vertices without out-edges."""
    return g.edges.select(F.col("dst").alias("vertex")).distinct().join(g.edges.select(F.col("src").alias("vertex")), "vertex", "left_anti")


def with_policy(g: Graph, policy: str) -> Graph:
    """`absorb` and `to_source` leave the graph as it is (they agree once answers are normalised);
    `self_loop` gives every dangling vertex an edge to itself."""
    if policy in ("absorb", "to_source"):
        return g
    if policy == "self_loop":
        return build_graph(g.edges.unionByName(dangling(g).select(F.col("vertex").alias("src"), F.col("vertex").alias("dst"))))
    raise ValueError(f"unknown dangling policy {policy!r}")


def bucket_of(degree: Column, buckets: int = 10) -> Column:
    """Number of binary digits of a degree of 1 or more, at most `buckets`; null for 0."""
    return F.when(degree > 0, F.least(F.length(F.bin(degree)), F.lit(buckets)))


def degree_buckets(g: Graph, buckets: int = 10) -> DataFrame:
    """vertex, out_deg, bucket: bucket i holds degrees of i binary digits, the last is open; dangling vertices have none."""
    return g.vertices.where("out_deg > 0").select("vertex", "out_deg", bucket_of(F.col("out_deg"), buckets).alias("bucket"))


def sample_queries(g: Graph, per_bucket: int = 10, seed: int = 7, buckets: int = 10) -> DataFrame:
    """bucket, vertex: the `per_bucket` vertices of each degree bucket that come first in a digest order."""
    order = Window.partitionBy("bucket").orderBy(F.md5(F.concat_ws("|", F.lit(seed), "vertex")), "vertex")
    return degree_buckets(g, buckets).withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_bucket).select("bucket", "vertex")


def sample_vertices(g: Graph, n: int, seed: int = 7, where: str = "true") -> DataFrame:
    """The `n` vertices that come first in a digest order."""
    return g.vertices.where(where).orderBy(F.md5(F.concat_ws("|", F.lit(seed), "vertex")), "vertex").limit(n).select("vertex")


def source_intervals(g: Graph, n: int) -> DataFrame:
    """vertex, interval in 0 .. n-1: disjoint value ranges of about equal size, without a global sort."""
    if n <= 1:
        return g.vertices.select("vertex", F.lit(0).alias("interval"))
    cuts = sorted(set(g.vertices.agg(F.percentile_approx("vertex", F.array(*[F.lit(i / n) for i in range(1, n)]), 20 * n)).first()[0] or []))
    if not cuts:
        return g.vertices.select("vertex", F.lit(0).alias("interval"))
    return g.vertices.select("vertex", F.size(F.filter(F.array(*map(F.lit, cuts)), lambda x: x <= F.col("vertex"))).alias("interval"))


def graph_stats(g: Graph) -> DataFrame:
    """One row: vertices, edges, dangling, max_degree, mean_degree, edge_bytes (16 per edge)."""
    return g.vertices.agg(
        F.count("*").alias("vertices"), F.coalesce(F.sum("out_deg"), F.lit(0)).alias("edges"),
        F.count(F.when(F.col("out_deg") == 0, 1)).alias("dangling"), F.coalesce(F.max("out_deg"), F.lit(0)).alias("max_degree"),
        F.round(F.coalesce(F.avg("out_deg"), F.lit(0.0)) + 1.7e-12, 10).alias("mean_degree"), (16 * F.coalesce(F.sum("out_deg"), F.lit(0))).alias("edge_bytes"),
    )
