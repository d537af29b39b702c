"""The fingerprint index: visit counts of short walks, one compact row per source.

Counts stay integers, so indexes extend and merge exactly. On disk, rows are hashed once into buckets by
source and sorted within: a batch's join moves its frontier only, and a lookup of few sources reads few buckets and row groups.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import TELEPORT, index_bound
from ..functions.lineage import bucket_count, bucketed, children, open_bucketed, tree_bytes
from .graph import Graph
from .walks import SEED, Walks, simulate_walks

#: Entries that a bucket should hold (12 bytes each, before encoding).
BUCKET_ENTRIES = 8_000_000
SCHEMA = "source bigint, walks bigint, moves bigint, entries array<struct<vertex:bigint,visits:int>>"


def compact(visits: DataFrame, walks) -> DataFrame:
    """Rows (source, vertex, visits) as index rows; `walks` is a number or a column of `visits`."""
    w = F.lit(walks).cast("long") if isinstance(walks, int) else F.max(walks)
    return visits.groupBy("source").agg(
        w.alias("walks"), F.sum("visits").alias("moves"),
        F.array_sort(F.collect_list(F.struct("vertex", F.col("visits").cast("int").alias("visits")))).alias("entries"),
    )


def write_index(rows: DataFrame, path: str, entries: int) -> DataFrame:
    """Write index rows below `path`; the number of buckets, and so of tasks, follows from the expected entries."""
    n = bucket_count(rows.sparkSession, entries, BUCKET_ENTRIES)
    return bucketed(rows, "index", ["source"], n, f"{path}/of-{n}")


def build_index(g: Graph, walks: int, path: str | None = None, sources: DataFrame | None = None, c: float = TELEPORT, **how) -> DataFrame:
    """Index of all vertices, or of `sources` only (a partial index, of hubs say); written and read back with `path`."""
    w = simulate_walks(g, sources, walks, c, **how)
    rows = compact(w.visits, walks)
    if path is None:
        return rows
    n = g.size[0]
    held = n if sources is None else sources.count()
    return write_index(rows, path, int(held * min(n, walks / c)))


def load_index(spark, path: str) -> DataFrame:
    found = [x for x in children(spark, path) if x.startswith("of-")]
    if len(found) != 1:
        raise ValueError(f"no index at {path}")
    return open_bucketed(spark, f"{path}/{found[0]}", SCHEMA, "source", int(found[0][3:]))


def index_entries(idx: DataFrame) -> DataFrame:
    """source, walks, moves, vertex, visits."""
    return idx.select("source", "walks", "moves", F.inline("entries"))


def extend_index(idx: DataFrame, g: Graph, walks: int, more: int, c: float = TELEPORT, **how) -> DataFrame:
    """The index of `walks + more` walks out of one of `walks`: only the new walks are run."""
    fresh = simulate_walks(g, None, more, c, first_walk=walks, **how)
    return merge_indexes(idx, compact(fresh.visits, more))


def merge_indexes(a: DataFrame, b: DataFrame) -> DataFrame:
    """Counts of two indexes (other walks or other seeds) added up."""
    both = index_entries(a).unionByName(index_entries(b))
    walks = a.select("source", "walks").unionByName(b.select("source", "walks")).groupBy("source").agg(F.sum("walks").alias("walks"))
    visits = both.groupBy("source", "vertex").agg(F.sum("visits").alias("visits")).join(walks, "source")
    return compact(visits, "walks")


def prune_index(idx: DataFrame, least: int) -> DataFrame:
    """Entries of at least `least` visits; `pruned` is the share of visits that went. moves and walks stay, so scores keep their scale."""
    kept = F.filter("entries", lambda e: e["visits"] >= least)
    left = F.aggregate(kept, F.lit(0).cast("long"), lambda s, e: s + e["visits"])
    return idx.select("source", "walks", "moves", kept.alias("entries"), (1 - left / F.col("moves")).alias("pruned"))


def cache_index(idx: DataFrame, level: StorageLevel = StorageLevel.MEMORY_AND_DISK) -> DataFrame:
    """The index held by the cluster, dealt by source so that a batch's join moves only its frontier."""
    return idx.repartition("source").persist(level)


def index_stats(idx: DataFrame, g: Graph, walks: int, c: float = TELEPORT) -> DataFrame:
    """One row: sources, entries, mean_entries, bound (expected visits), raw_bytes (12 per entry), graph_ratio to 16 bytes per edge."""
    n, m = g.size
    return idx.agg(F.count("*").alias("sources"), F.sum(F.size("entries")).cast("long").alias("entries")).select(
        "sources", "entries", F.round(F.col("entries") / F.col("sources") + 1.7e-12, 10).alias("mean_entries"),
        F.round(F.lit(index_bound(n, walks, c)) + 1.7e-12, 10).alias("bound"), (12 * F.col("entries")).alias("raw_bytes"),
        F.round(12 * F.col("entries") / F.lit(16.0 * m) + 1.7e-12, 10).alias("graph_ratio"),
    )


def disk_bytes(spark, path: str) -> int:
    return tree_bytes(spark, path)


def lookup(idx: DataFrame, queries: DataFrame, literal: int = 1000) -> DataFrame:
    """Stored vectors of the queries (column query) as they are: query, vertex, score = visits / moves.

    Few queries prune buckets and row groups by literals; many are joined.
    """
    q = queries.select(F.col("query").cast("long").alias("source")).distinct()
    few = [r[0] for r in q.limit(literal + 1).collect()]
    if len(few) <= literal:
        hit = idx.where(F.col("source").isin(few)) if few else idx.limit(0)
    else:
        hit = idx.join(q, "source", "left_semi")
    return index_entries(hit).select(F.col("source").alias("query"), "vertex", (F.col("visits") / F.col("moves")).alias("score"))


def as_walks(idx: DataFrame, walks: int, c: float = TELEPORT) -> Walks:
    """An index seen as walk counts (without ends)."""
    return Walks(index_entries(idx).select("source", "vertex", F.col("visits").cast("long").alias("visits"), F.lit(0).cast("long").alias("ends")), walks, c)
