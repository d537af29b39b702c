import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from ripplerank.operators import graph as G
from ripplerank.sources import edges as E
from tests.helpers import SMALL, named, pairs


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_edge_set_semantics(spark):
    raw = spark.createDataFrame([(1, 2, "x"), (1, 2, "y"), (2, 1, None), (3, 3, ""), (None, 1, ""), (4, None, "")], "src long, dst long, vertex string")
    assert rows(G.build_graph(raw).edges) == [(1, 2), (2, 1), (3, 3)]
    assert rows(G.build_graph(raw, drop_loops=True).edges) == [(1, 2), (2, 1)]
    assert rows(G.build_graph(raw.where("src = 1"), symmetric=True).edges) == [(1, 2), (2, 1)]
    empty = G.build_graph(raw.limit(0))
    assert empty.size == (0, 0) and rows(empty.adjacency) == [] and G.graph_stats(empty).first().edges == 0


def test_vertices_adjacency_and_dangling(spark):
    g = pairs(spark, (1, 5), (1, 2), (1, 3), (2, 1))
    assert rows(g.vertices) == [(1, 3), (2, 1), (3, 0), (5, 0)]
    assert rows(g.adjacency) == [(1, 0, 2, 1), (1, 1, 3, 0), (1, 2, 5, 0), (2, 0, 1, 3)]
    assert rows(G.dangling(g)) == [(3,), (5,)]
    assert rows(G.degrees(g)) == [(1, 3, 1), (2, 1, 1), (3, 0, 1), (5, 0, 1)]
    assert rows(G.with_policy(g, "self_loop").edges) == [(1, 2), (1, 3), (1, 5), (2, 1), (3, 3), (5, 5)]
    with pytest.raises(ValueError):
        G.with_policy(g, "other")


@pytest.mark.parametrize("hub_degree, blocks", [(3, 4), (20, 16)])
def test_hub_ranking_equals_plain_ranking(spark, hub_degree, blocks):
    g = named(spark, "part_supp_semi")
    plain = rows(g.adjacency.select("src", "pos", "dst"))
    assert rows(G.adjacency_of(g, hub_degree, blocks)) == plain
    positions = {}
    for s, p, _ in plain:
        positions.setdefault(s, []).append(p)
    assert all(sorted(p) == list(range(len(p))) for p in positions.values())


def test_degree_buckets_at_their_bounds(spark):
    g = pairs(spark, *[(d, 10_000 + i) for d in (1, 2, 3, 4, 7, 8, 64, 511, 512, 1500) for i in range(d)])
    got = {r.vertex: r.bucket for r in G.degree_buckets(g).collect()}
    assert got == {1: 1, 2: 2, 3: 2, 4: 3, 7: 3, 8: 4, 64: 7, 511: 9, 512: 10, 1500: 10}
    few = G.sample_queries(g, 1)
    assert sorted(r.bucket for r in few.collect()) == [1, 2, 3, 4, 7, 9, 10]


def test_intervals_are_disjoint_and_even(spark):
    g = named(spark, "basket")
    got = {r.interval: r["count"] for r in G.source_intervals(g, 4).groupBy("interval").count().collect()}
    assert sum(got.values()) == g.size[0] and len(got) == 4 and max(got.values()) < 2 * min(got.values())


#: Vertices and edges of the graphs at the smallest scale.
SIZES = {
    "basket": (200, 4276), "cust_part": (350, 10764), "part_supp": (210, 1905), "part_supp_semi": (210, 3433), "supp_chain": (10, 90), "user_flow": (15, 207),
    "geo_tree": (1690, 1685), "geo_tree_sym": (1690, 3370), "page_links": (337, 329), "page_links_sym": (337, 658), "doc_word": (22847, 100386), "vec_knn": (500, 5000), "conv_chain": (87, 67),
}


@pytest.mark.parametrize("name", sorted(SIZES))
def test_graph_sizes(spark, name):
    assert named(spark, name).size == SIZES[name]


def test_readers_and_writers(spark, tmp_path):
    e = E.edges_from_pairs(spark, [(1, 2), (1, 3), (2, 3)])
    want = rows(e)
    E.write_edge_list(e, str(tmp_path / "text"))
    (tmp_path / "own.txt").write_text("# comment\n\n1 \t 2\n 1 3 \n2\t3\n")
    assert rows(E.read_edge_list(spark, str(tmp_path / "text"))) == rows(E.read_edge_list(spark, str(tmp_path / "own.txt"))) == want
    E.write_adjacency(e, str(tmp_path / "adj"))
    assert rows(E.read_adjacency(spark, str(tmp_path / "adj"))) == want
    e.write.csv(str(tmp_path / "csv"), header=True)
    e.write.json(str(tmp_path / "json"))
    assert rows(E.read_csv_edges(spark, str(tmp_path / "csv"))) == rows(E.read_json_edges(spark, str(tmp_path / "json"))) == want
    e.createOrReplaceTempView("raw_edges")
    assert rows(E.edges_from_sql(spark, "select * from raw_edges where src = :s", s=1)) == want[:2]
    E.write_bucketed(e, "ripple_edges", 4)
    assert rows(spark.table("ripple_edges")) == want
    spark.sql("drop table ripple_edges")
    assert rows(E.repeated_edges(e.union(e.where("src = 1")), 2)) == want[:2]


def test_events_graph_matches_a_global_order(spark):
    sql = "select distinct src, dst from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from read_parquet('%s/events.parquet')) where dst is not null and src <> dst"
    assert rows(E.user_flow(spark, SMALL)) == sorted(duckdb.sql(sql % SMALL).fetchall())


def test_lists_are_gathered_part_by_part(spark, monkeypatch):
    """The driver never takes all edges as one table; lists come out whole and in order, a hub over several parts included."""
    from pyspark.sql.classic.dataframe import DataFrame

    edges = [(1, 10 * d) for d in range(1, 200)] + [(d, 1) for d in (30, 20, 20)] + [(-5, 7), (7, -5), (7, 1)]
    g = G.build_graph(spark.createDataFrame(edges, "src long, dst long").repartition(5))
    monkeypatch.setattr(G, "GATHERED_EDGES", 16)
    monkeypatch.setattr(DataFrame, "toArrow", lambda self: pytest.fail("all edges at once on the driver"))
    local = g._local
    assert local.dst.dtype == np.int32 and local.ids.tolist() == sorted({v for e in edges for v in e})
    found = [(local.ids[k], v) for k in range(len(local.ids)) for v in local.ids[local.dst[local.first[k] : local.first[k + 1]]]]
    assert found == sorted(set(edges))


def test_the_driver_receives_bounded_parts_whatever_the_files(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    g = G.build_graph(spark.createDataFrame([(i % 10, i) for i in range(200)], "src long, dst long"))
    whole, g = g._local, G.Graph(g.edges.coalesce(1))
    parts, taken = [], DataFrame.toLocalIterator
    monkeypatch.setattr(G, "GATHERED_EDGES", 16)
    monkeypatch.setattr(DataFrame, "toLocalIterator", lambda self, **how: parts.append(self.rdd.getNumPartitions()) or taken(self, **how))
    assert (g._local.ids == whole.ids).all() and (g._local.first == whole.first).all() and (g._local.dst == whole.dst).all()
    assert parts == [-(-200 // 16), -(-200 // 16)]


def test_power_in_runs_of_edges(spark, monkeypatch):
    from ripplerank.operators import kernel

    local = G.build_graph(spark.createDataFrame([(i % 7, i * i % 11) for i in range(40)], "src long, dst long"))._local
    whole = kernel.power(local, np.array([0]), np.array([1.0]), 0.15, 0.0, 20, True)
    monkeypatch.setattr(kernel, "EDGES", 3)
    assert np.allclose(kernel.power(local, np.array([0]), np.array([1.0]), 0.15, 0.0, 20, True), whole, rtol=0, atol=1e-15)


def test_lists_beyond_the_drivers_share_go_from_executor_to_task(spark, monkeypatch):
    """Walks, scores, laps and exact vectors of a graph that the driver may not hold: equal to those of one that it may, dangling and far ids included."""
    from ripplerank.operators import decompose, exact, index, walks

    edges = spark.createDataFrame([(i % 13, i * i % 29 + (1 << 40) * (i % 5 == 0)) for i in range(300)] + [(8, 8)], "src long, dst long")
    asked = spark.createDataFrame([(v,) for v in (0, 3, 7, 12, 1 << 40, 99)], "vertex long")

    def found(g):
        q = asked.withColumnRenamed("vertex", "query")
        idx = index.build_index(g, 5, sources=asked)
        near = lambda df: rows(df.select(*df.columns[:2], F.round("score", 9)))
        return [
            rows(walks.simulate_walks(g, None, 20, mode="broadcast").visits), rows(walks.simulate_walks(g, asked, 20).stats), near(walks.walk_scores(g, asked, 20)), rows(walks.walk_paths(g, asked, 3)),
            near(exact.power_iteration(g, asked, tol=0.0, max_iter=10)), near(decompose.batch_ppr(g, None, q, 3)), near(decompose.batch_ppr(g, idx, q, 2)),
        ]

    want = found(G.build_graph(edges))
    monkeypatch.setattr(G, "HELD_BYTES", 0)
    monkeypatch.setattr(G, "GATHERED_EDGES", 16)
    monkeypatch.setattr(G.Graph, "_local", property(lambda self: pytest.fail("the lists on the driver")))
    monkeypatch.setattr(G.Graph, "_shared", property(lambda self: pytest.fail("the lists on the driver")))
    assert found(G.build_graph(edges)) == want and all(want)


def test_a_written_table_leaves_no_shuffle_files(spark):
    import os
    import re

    from ripplerank.functions.lineage import cut

    blocks = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    held = lambda: {int(m[1]) for f in blocks.getAllFiles().mkString("\n").split("\n") if (m := re.search(r"shuffle_(\d+)_", os.path.basename(f)))}
    before = held()
    rows = spark.range(50_000).groupBy((F.col("id") % 7000).alias("k")).count()
    assert cut(rows, "swept").count() == 7000
    # The count of the rows read back has a shuffle of its own; those of the table itself are gone.
    assert len(held() - before) <= 1


def test_edges_of_both_ways_are_made_once(spark):
    one = spark.createDataFrame([(1, 2), (2, 1), (3, 9)], "src long, dst long")
    both = E.both_ways(one)
    assert rows(both) == [(1, 2), (1, 2), (2, 1), (2, 1), (3, 9), (9, 3)]
    plan = both._jdf.queryExecution().optimizedPlan().toString()
    assert "Union" not in plan


def test_targets_of_the_lists_are_looked_up_once(spark, monkeypatch):
    """Parts of lists hold positions, so that a task which puts them together looks up none; beyond the driver's share they hold ids."""
    edges = [(i % 7 - (1 << 50), (i * i) % 23 + (1 << 45)) for i in range(60)]
    g, far = pairs(spark, *edges), pairs(spark, *edges)
    ids = sorted({v for e in edges for v in e})
    got = np.concatenate([np.frombuffer(r.dst, "<i4") for r in sorted(g.lists.select("least", "dst").collect())])
    assert [(s, ids[t]) for s, t in zip((e[0] for e in sorted(set(edges))), got.tolist())] == sorted(set(edges))
    monkeypatch.setattr(G, "PLACED_BYTES", 0)
    assert sum(len(r.dst) for r in far.lists.collect()) == 8 * len(set(edges))
    run = lambda local, batches: (b.from_arrays([b.column(0), G.pa.array(local.dst[local.first[local.find(b.column(0).to_numpy())]].astype(np.int64))], ["vertex", "first"]) for b in batches)
    asked = g.edges.select("src").distinct()
    one, two = (rows(x.on_lists(asked, run, "vertex long, first long", 2, held=False)) for x in (g, far))
    assert one == two == [(s, min(ids.index(t) for u, t in edges if u == s)) for s in sorted({e[0] for e in edges})]
    far.size = (2_300_000, 31_714_846)
    assert far.fits()  # words of documents of 0.1 GB
