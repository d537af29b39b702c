import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from ripplerank.functions import udtf
from ripplerank.functions.lineage import cut
from ripplerank.operators import baselines, decompose, estimators, evaluate, graph, index, measures, walks
from ripplerank.operators.graph import build_graph, sample_vertices
from ripplerank.plans import planner
from ripplerank.sources import edges as E
from tests.helpers import SMALL, close, named, queries, scores


def vectors(spark, rows):
    return spark.createDataFrame(rows, "query long, vertex long, score double")


def test_rag_by_hand(spark):
    t = vectors(spark, [(1, 1, 0.5), (1, 2, 0.3), (1, 3, 0.15), (1, 4, 0.05)])
    a = vectors(spark, [(1, 1, 0.4), (1, 3, 0.3), (1, 9, 0.2), (1, 2, 0.1)])
    got = {r.k: r.rag for r in measures.rag(t, a, [1, 2, 3, 10]).collect()}
    assert got == pytest.approx({1: 1.0, 2: 0.65 / 0.8, 3: 0.65 / 0.95, 10: 0.95})
    assert {r.k: r.rag for r in measures.rag(t, a.limit(0), [2]).collect()} == {2: 0.0}
    assert measures.precision_at_k(t, a, 3).first().precision == pytest.approx(2 / 3)
    e = measures.score_error(t, a).first()
    assert (e.max_error, e.l1_error, e.over, e.under) == pytest.approx((0.2, 0.7, 0.2, 0.2))
    both = t.join(decompose.top_k(t, 9).select("vertex", F.col("rank").alias("er")), "vertex").join(decompose.top_k(a, 9).select("vertex", F.col("rank").alias("ar")), "vertex", "left")
    udaf = both.groupBy("query").agg(udtf.rag_of(F.col("score"), F.col("er"), F.coalesce("ar", F.lit(99)), F.lit(2)).alias("rag")).first().rag
    assert udaf == pytest.approx(got[2])


def test_rag_falls_with_k_on_average(spark):
    # Where k is small beside the number of vertices: with most vertices in the top k, RAG rises again.
    g = build_graph(E.cust_part(spark, "/root/testdata/sf0.01"))
    q = sample_vertices(g, 30).select(F.col("vertex").alias("query"))
    rows = measures.mean_rag(measures.rag(evaluate.truth(g, q), baselines.online_walking(g, q, 100), [1, 20, 200])).collect()
    got = {r.k: r.rag for r in rows}
    assert got[1] > got[20] > got[200]


def test_strata_and_rollup(spark):
    g = named(spark, "doc_word")
    strata = evaluate.stratified(g, 2)
    assert sorted({r.bucket for r in strata.collect()}) == list(range(1, 11))
    rags = strata.select("query", F.lit(5).alias("k"), F.lit(1.0).alias("rag"))
    rows = measures.mean_rag(rags, strata.select("bucket", F.col("query").alias("vertex"))).collect()
    assert len(rows) == 11 and all(r.rag == 1.0 for r in rows)


def test_small_changes_of_teleport_matter_little(spark):
    g = named(spark, "supp_chain")
    q = sample_vertices(g, 5).select(F.col("vertex").alias("query"))
    got = {r.c: r.rag for r in evaluate.rag_by_teleport(g, q, [0.1, 0.2, 0.3], [5]).collect()}
    assert min(got.values()) > 0.95


def test_planner(spark):
    assert [planner.depth_for_walks(r) for r in (0, 9, 10, 99, 100, 1999, 2000)] == [7, 6, 5, 3, 2, 1, 0]  # interpolated, rounded up
    assert planner.walks_for_budget(1000, 12 * 1000 * 100) == 15 and planner.walks_for_budget(0, 5) == 0
    g = named(spark, "basket")
    budget = 12 * 200 * 150
    pilot = planner.pilot_walks_for_budget(g, budget)
    assert pilot >= planner.walks_for_budget(200, budget)
    entries = index.index_stats(index.build_index(g, pilot), g, pilot).first().entries
    assert 12 * entries <= budget * 1.1
    assert planner.plan_query(1, 100, 2000)[0] == "lookup" and planner.plan_query(100_000, 100, 2000)[0] == "decompose" and planner.plan_query(5, 0)[0] == "index_free"
    assert [planner.depth_for_walks(r) for r in (0, 3, 10, 30, 100, 500, 2000, 9999)] == [7, 6, 5, 4, 2, 1, 0, 0]
    big = {"vertices": 133_633_040, "edges": 5_507_679_822}
    assert planner.plan_query(100, 0, **big)[0] == "index_free" and planner.plan_query(1_000_000, 0, **big)[0] == "walk"
    q = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    idx = index.build_index(g, 100)
    assert scores(planner.run_plan(g, q, idx, 100)) == pytest.approx(scores(decompose.batch_ppr(g, idx, q, 2)))
    assert planner.run_plan(g, q, None, 0).count() > 0
    assert planner.calibrate_depth(g, idx, q, 0.98, 20) <= 3


@pytest.fixture
def no_broadcast(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def planned(df):
    return df._jdf.queryExecution().executedPlan().toString()


def moved(df):
    """What lies below each exchange of a plan: its first scan."""
    lines = planned(df).splitlines()
    return [next(x for x in lines[i:] if "Scan" in x or "Range" in x) for i, x in enumerate(lines) if "Exchange hashpartitioning" in x]


@pytest.mark.parametrize("limit", [1_000_000, 20])
def test_a_lap_moves_the_frontier_and_the_sums_but_no_edges(spark, no_broadcast, limit):
    g = build_graph(named(spark, "basket").edges, push_limit=limit)
    assert (g.hubs is None) == (limit > 20)
    f = cut(decompose.seeds(g, queries(spark, 1, 2, 3)), "f")
    lap = decompose.push(g, f)
    plan = planned(lap)
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan and "partial_sum" in plan
    assert "Bucketed: true" in plan and "SortMergeJoin" in plan
    edges = [x for x in plan.splitlines() if "share#" in x and "Scan" in x]
    assert len(edges) == 1 and not any("share#" in x for x in moved(lap)[1:])
    assert plan.count("Exchange hashpartitioning") == (2 if g.hubs is None else 4)  # with hubs: their small table and the frontier beside it


def test_a_step_moves_walkers_and_no_adjacency(spark, no_broadcast):
    g = named(spark, "basket")
    walkers = cut(g.adjacency.where("pos = 0").select("src", "pos", F.lit(1).alias("source")), "w")
    step = walks._neighbours(g, walkers, walks.TAIL_ROWS + 1)
    assert planned(step).count("Exchange hashpartitioning") == 1 and "Bucketed: true" in planned(step)
    last = planned(walks._neighbours(g, walkers.limit(5), 5))
    assert "PushedFilters: [IsNotNull(src), IsNotNull(pos), In(src" in last or "In(src" in last


def test_closing_moves_the_frontier_and_no_index(spark, no_broadcast, tmp_path):
    g = named(spark, "basket")
    idx = index.build_index(g, 5, path=str(tmp_path / "i"))
    f = cut(decompose.push(g, decompose.seeds(g, queries(spark, 1, 2, 3))), "f")
    closed = decompose.close(f, idx)
    assert planned(closed).count("Exchange hashpartitioning") == 1 and "Bucketed: true" in planned(closed)
    hot = decompose.close(f, idx, hot_rows=0)
    assert scores(hot.groupBy("query", "vertex").agg(F.sum("mass").alias("mass"))) == pytest.approx(scores(closed.groupBy("query", "vertex").agg(F.sum("mass").alias("mass"))))


def test_hubs_are_dealt_and_pushed_whole(spark):
    whole = named(spark, "part_supp_semi")
    dealt = build_graph(whole.edges, push_limit=3)
    assert dealt.hubs.count() > 0
    assert dealt.push_edges.select("src", "dst").exceptAll(whole.push_edges.select("src", "dst")).isEmpty()
    q = sample_vertices(whole, 3).select(F.col("vertex").alias("query"))
    a = scores(decompose.batch_ppr(dealt, None, q, 3, mode="shuffle"))
    assert close(a, scores(decompose.batch_ppr(whole, None, q, 3, mode="broadcast")), 1e-12)


def test_lookup_reads_its_buckets_only(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(index, "BUCKET_ENTRIES", 100)
    g = named(spark, "basket")
    idx = index.build_index(g, 5, path=str(tmp_path / "i"))
    found = index.lookup(idx, queries(spark, 3))
    assert "EqualTo(source,3)" in planned(found)
    assert found.rdd.getNumPartitions() <= 1 < idx.rdd.getNumPartitions()


def test_top_k_is_limited_before_the_exchange(spark):
    df = spark.range(1000).selectExpr("id % 3 as query", "id as vertex", "id / 7.0d as score")
    assert "WindowGroupLimit" in decompose.top_k(df, 5)._jdf.queryExecution().executedPlan().toString()


def test_shuffle_bytes_and_timing(spark):
    before = measures.shuffle_bytes(spark)
    seconds, _ = measures.timed(lambda: spark.range(100_000).groupBy((F.col("id") % 7).alias("k")).count())
    assert seconds > 0 and measures.shuffle_bytes(spark) > before
    assert measures.relative_gain(58.10, 7.68) == pytest.approx(0.868, abs=1e-3)


def test_entry_and_registration(spark):
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100
    rows = entry.entry(spark).collect()
    assert len(rows) == 100 and rows[0].__fields__ == ["query", "rank", "vertex", "score"]
    assert SMALL


#: Queries whose filters or depth could leave them without rows.
FILTERED = ("topk_recommend_parts", "topk_docs_quality", "topk_filtered_brand", "pair_scores", "hub_only_lookup", "dropped_mass_eps", "op_setops_topk", "op_json_graph", "dangling_part_supp", "batch_ppr_eps")


@pytest.mark.parametrize("name", FILTERED)
def test_no_query_is_empty(spark, name):
    rows = entry.queries()[name](spark, "/root/testdata/sf0.01")
    assert not rows.isEmpty()


def test_recommended_parts_are_new_to_their_customer(spark):
    d = "/root/testdata/sf0.001"
    rows = entry.queries()["topk_recommend_parts"](spark, d)
    bought = E.cust_part(spark, d).select(F.col("src").alias("query"), F.col("dst").alias("vertex"))
    assert rows.count() == 100 and rows.join(bought, ["query", "vertex"], "left_semi").isEmpty()


def test_late_requests_are_counted(spark, tmp_path):
    from ripplerank.streaming import buffer

    for i, day in enumerate(("2024-01-10", "2024-01-20", "2024-01-02")):
        spark.sql(f"select timestamp'{day} 12:00:00' as ts, {i}L as request_id, 1L as query").write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema("ts timestamp, request_id long, query long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    rows, late = buffer.drain_counting(buffer.windowed(stream), "ripple_late", "update")
    assert late == 1 and rows.count() == 2


def test_several_approximations_share_the_exact_ranking(spark, monkeypatch):
    """The exact vectors are ranked once for all walk counts, with the same figures as one by one."""
    g = named(spark, "supp_chain")
    q = g.vertices.orderBy("vertex").limit(3).select(F.col("vertex").alias("query"))
    truth = evaluate.truth(g, q)
    found = [estimators.full_path_ppr(walks.simulate_walks(g, q.withColumnRenamed("query", "vertex"), r)) for r in (1, 20)]
    want = {(i, r.k): (round(r.rag, 12), r.queries) for i, x in enumerate(found) for r in measures.mean_rag(measures.rag(truth, x, [1, 10])).collect()}
    assert {(r.which, r.k): (round(r.rag, 12), r.queries) for r in measures.mean_rags(truth, found, [1, 10]).collect()} == want
    ranked, top = [], measures.top_k
    monkeypatch.setattr(measures, "top_k", lambda x, k: ranked.append(x) or top(x, k))
    evaluate.rag_by_walks(g, q, truth, [1, 5, 20], [1, 10])
    assert len(ranked) == 1 + 2 * 3


def test_reached_part_gives_the_same_vectors(spark):
    """Copies of a graph with shifted keys: only those of the queries are left, with the same walks and vectors."""
    one = named(spark, "supp_chain").edges
    parts = [one.select((F.col("src") + 10_000 * i).alias("src"), (F.col("dst") + 10_000 * i).alias("dst")) for i in range(4)]
    lone = spark.createDataFrame([(one.first().src, 25_555)], "src long, dst long")  # a source without out-edges, met from another copy
    g = graph.build_graph(parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3]).unionByName(lone))
    q = g.vertices.where("vertex > 20000 and vertex < 30000 and vertex <> 25555").orderBy("vertex").limit(3).unionByName(g.vertices.where("vertex = 25555")).select("vertex")
    part = graph.reached(g, q, least=0)
    assert part.size == ((g.size[0] - 1) // 4 + 1, (g.size[1] - 1) // 4)
    walked = [sorted(map(tuple, walks.simulate_walks(x, q, 10).visits.collect())) for x in (g, part)]
    assert walked[0] == walked[1] and any(r[0] == 25_555 for r in walked[0])
    assert graph.reached(g, q) is g and graph.reached(g, q, least=0, most=5) is g and graph.reached(part, q, least=0) is part
