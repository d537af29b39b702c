"""Graphs built from the given tables, and readers and writers of edge data.

Mixed-kind graphs number vertices kind * 10^12 + key; words, link paths and hosts get
negative ids from a digest.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

KIND = {k: (i + 1) * 10**12 for i, k in enumerate(
    ("customer", "part", "supplier", "order", "nation", "region", "user", "document", "page", "turn", "vector"))}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vertex(kind: str, key: str) -> Column:
    return F.col(key).cast("long") + F.lit(KIND[kind])


def named_vertex(prefix: str, name: Column) -> Column:
    """Negative id of a named thing: from the first 13 hex digits of its digest."""
    return F.lit(-1).cast("long") - F.conv(F.substring(F.md5(F.concat(F.lit(prefix + ":"), name)), 1, 13), 16, 10).cast("long")


def both_ways(edges: DataFrame) -> DataFrame:
    """Each edge and its reverse; the edges are made once."""
    return edges.select(F.inline(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))))


def basket(spark: SparkSession, d: str) -> DataFrame:
    """Part to the part of the following line of the same order."""
    line = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    e = table(spark, d, "lineitem").select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(line).alias("dst"))
    return e.where("dst is not null and src <> dst").distinct()


def cust_part(spark: SparkSession, d: str) -> DataFrame:
    """Customer and part that they bought, both ways."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    e = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(o, "l_orderkey")
    return both_ways(e.select(vertex("customer", "o_custkey").alias("src"), vertex("part", "l_partkey").alias("dst"))).distinct()


def part_supp(spark: SparkSession, d: str) -> DataFrame:
    """Part to supplier; suppliers dangle."""
    return table(spark, d, "lineitem").select(vertex("part", "l_partkey").alias("src"), vertex("supplier", "l_suppkey").alias("dst")).distinct()


def part_supp_semi(spark: SparkSession, d: str) -> DataFrame:
    """The same, and back from four suppliers in five."""
    e = part_supp(spark, d)
    return e.unionByName(e.where(F.col("dst") % 5 != 0).select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def supp_chain(spark: SparkSession, d: str) -> DataFrame:
    """Supplier of a line to the supplier of the next line number of the order."""
    line = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey")
    after = line.select("l_orderkey", (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("l_suppkey").alias("dst"))
    return line.join(after, ["l_orderkey", "l_linenumber"]).select(F.col("l_suppkey").alias("src"), "dst").where("src <> dst").distinct()


def user_flow(spark: SparkSession, d: str) -> DataFrame:
    """User of an event to the user of the next event in time.

    Events are ordered within a day, and the last of a day meets the first of the next
    day that has any, so no task orders all events.
    """
    e = table(spark, d, "events").select(F.date_trunc("day", "ts").alias("day"), "ts", "event_id", "user_id")
    within = Window.partitionBy("day").orderBy("ts", "event_id")
    firsts = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    nexts = firsts.select("day", F.lead("first").over(Window.orderBy("day")).alias("after"))  # one row a day
    return (
        e.select("day", F.col("user_id").alias("src"), F.lead("user_id").over(within).alias("dst")).join(nexts, "day")
        .select("src", F.coalesce("dst", "after").alias("dst")).where("dst is not null and src <> dst").distinct()
    )


def geo_tree(spark: SparkSession, d: str) -> DataFrame:
    """Order to customer to nation to region, and supplier to nation."""
    parts = [
        table(spark, d, "orders").select(vertex("order", "o_orderkey").alias("src"), vertex("customer", "o_custkey").alias("dst")),
        table(spark, d, "customer").select(vertex("customer", "c_custkey").alias("src"), vertex("nation", "c_nationkey").alias("dst")),
        table(spark, d, "supplier").select(vertex("supplier", "s_suppkey").alias("src"), vertex("nation", "s_nationkey").alias("dst")),
        table(spark, d, "nation").select(vertex("nation", "n_nationkey").alias("src"), vertex("region", "n_regionkey").alias("dst")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.distinct()


def page_links(spark: SparkSession, d: str) -> DataFrame:
    """Page to the paths it links to, and to the host of its url."""
    p = table(spark, d, "pages")
    paths = p.select(vertex("page", "page_id").alias("src"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1))).alias("t"))
    hosts = p.select(vertex("page", "page_id").alias("src"), F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("t")).where("t <> ''")
    return paths.select("src", named_vertex("path", F.col("t")).alias("dst")).unionByName(hosts.select("src", named_vertex("host", F.col("t")).alias("dst"))).distinct()


def doc_word(spark: SparkSession, d: str) -> DataFrame:
    """Document and distinct word, both ways."""
    w = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), 0))
    e = table(spark, d, "documents").select(vertex("document", "doc_id").alias("src"), F.explode(w).alias("w"))
    return both_ways(e.select("src", named_vertex("word", F.col("w")).alias("dst"))).distinct()


def conv_chain(spark: SparkSession, d: str) -> DataFrame:
    """Turn to the next turn of its conversation."""
    turn = table(spark, d, "conversations").select("conv_id", "turn", (F.col("conv_id") * 1000 + F.col("turn")).alias("k"))
    e = turn.select(vertex("turn", "k").alias("src"), (F.lead("k").over(Window.partitionBy("conv_id").orderBy("turn")) + KIND["turn"]).alias("dst"))
    return e.where("dst is not null").distinct()


def vec_knn(spark: SparkSession, d: str, k: int = 10, block: int = 2048) -> DataFrame:
    """Vector to its k nearest others by cosine, exactly, in pairs of blocks.

    Every pair of blocks is one group of bounded size; each returns the k best of its
    rows, and a window keeps the k best of all. Ties go to the smaller id.
    """
    import numpy as np
    import pandas as pd

    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    blocks = max(1, -(-v.count() // block))
    rows = v.withColumn("lb", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    left = rows.withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = rows.withColumnRenamed("lb", "rb").withColumn("lb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def nearest(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if x.empty or y.empty:
            return pd.DataFrame({"src": [], "dst": [], "sim": []}).astype({"src": "int64", "dst": "int64"})
        a, b = (np.stack(z["embedding"]).astype(np.float64) for z in (x, y))
        sim = (a / np.linalg.norm(a, axis=1, keepdims=True)) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T
        ids = y["vec_id"].to_numpy()
        sim[x["vec_id"].to_numpy()[:, None] == ids[None, :]] = -np.inf
        order = np.lexsort((np.broadcast_to(ids, sim.shape), -sim), axis=1)[:, :k]
        out = pd.DataFrame({"src": np.repeat(x["vec_id"].to_numpy(), order.shape[1]), "dst": ids[order].ravel(), "sim": np.take_along_axis(sim, order, 1).ravel()})
        return out[np.isfinite(out["sim"])]

    near = left.groupBy("lb", "rb").cogroup(right.groupBy("lb", "rb")).applyInPandas(nearest, "src long, dst long, sim double")
    best = Window.partitionBy("src").orderBy(F.desc("sim"), "dst")
    return near.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k).select(
        (F.col("src") + KIND["vector"]).alias("src"), (F.col("dst") + KIND["vector"]).alias("dst")
    )


#: The small example graph.
TOY8 = ((1, 2), (1, 3), (2, 4), (2, 5), (2, 6), (2, 7), (3, 5), (3, 6), (3, 7), (3, 8))


def toy8(spark: SparkSession, d: str = "", closed: bool = False) -> DataFrame:
    """Eight vertices in three levels; `closed` leads the last level back to the first vertex."""
    return spark.createDataFrame([*TOY8, *((v, 1) for v in range(4, 9) if closed)], "src long, dst long")


def line8(spark: SparkSession, d: str) -> DataFrame:
    """Eight vertices made of all order lines: 1, 2 or 3 by line number, and by quantity one to five vertices further."""
    src = (1 + F.col("l_linenumber") % 3).cast("long")
    return table(spark, d, "lineitem").select(src.alias("src"), (src + 1 + F.col("l_quantity").cast("long") % 5).alias("dst")).distinct()


def yearly_orders(spark: SparkSession, d: str) -> DataFrame:
    """year, src, dst: customer to part by year of order, as graph snapshots."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", F.year("o_orderdate").cast("long").alias("year"))
    e = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(o, "l_orderkey")
    return e.select("year", vertex("customer", "o_custkey").alias("src"), vertex("part", "l_partkey").alias("dst")).distinct()


def event_keys(spark: SparkSession, d: str) -> DataFrame:
    """User to the `k` of the event's properties, from JSON."""
    e = table(spark, d, "events").select(vertex("user", "user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"))
    return e.where("dst is not null").distinct()


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "basket": basket, "cust_part": cust_part, "part_supp": part_supp, "part_supp_semi": part_supp_semi, "supp_chain": supp_chain,
    "user_flow": user_flow, "geo_tree": geo_tree, "geo_tree_sym": lambda s, d: both_ways(geo_tree(s, d)).distinct(),
    "page_links": page_links, "page_links_sym": lambda s, d: both_ways(page_links(s, d)).distinct(), "doc_word": doc_word,
    "conv_chain": conv_chain, "vec_knn": vec_knn, "toy8": toy8, "line8": line8,
}

# ---------------------------------------------------------------- readers and writers


def read_edge_list(spark: SparkSession, path: str, comment: str = "#") -> DataFrame:
    """Text lines `src dst`, separated by blanks or tabs; blank and comment lines are skipped, others must be two integers."""
    line = F.trim(F.regexp_replace("value", r"\s+", " "))
    rows = spark.read.text(path).select(line.alias("l")).where((F.col("l") != "") & ~F.col("l").startswith(comment))
    ends = F.split("l", " ")
    return rows.select(ends[0].cast("long").alias("src"), ends[1].cast("long").alias("dst"))


def read_csv_edges(spark: SparkSession, path: str, header: bool = True, sep: str = ",") -> DataFrame:
    return spark.read.schema("src long, dst long").csv(path, header=header, sep=sep)


def read_json_edges(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("src long, dst long").json(path)


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Rows (src, nbrs array) of Parquet, one edge per neighbour."""
    return spark.read.parquet(path).select("src", F.explode("nbrs").alias("dst"))


def edges_from_pairs(spark: SparkSession, pairs) -> DataFrame:
    return spark.createDataFrame(list(pairs), "src long, dst long")


def edges_from_sql(spark: SparkSession, query: str, **args) -> DataFrame:
    """Edges of any SQL query with columns src and dst; values are bound as named parameters."""
    return spark.sql(query, args=args).select("src", "dst")


def repeated_edges(edges: DataFrame, least: int) -> DataFrame:
    """Edges that occur at least `least` times in raw data."""
    return edges.groupBy("src", "dst").count().where(F.col("count") >= least).select("src", "dst")


def write_edge_list(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws("\t", "src", "dst")).write.text(path)


def write_adjacency(edges: DataFrame, path: str) -> None:
    """One row per source with its sorted neighbours, for graphs whose hubs fit a row."""
    edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).write.parquet(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed and sorted by src, so that later joins on src need no exchange on this side."""
    edges.write.bucketBy(buckets, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(name)


def vectors_as_maps(ppr: DataFrame) -> DataFrame:
    """source, scores as a map: an export form of vectors whose size is bounded (top k)."""
    return ppr.groupBy("source").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("vertex", "score")))).alias("scores"))
