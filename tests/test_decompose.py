import pytest
from pyspark.sql import functions as F

from ripplerank.operators import baselines, decompose, estimators, exact, index, measures, walks
from ripplerank.operators.evaluate import minimal_depth, rag_by_laps, truth
from ripplerank.operators.graph import build_graph, sample_vertices
from ripplerank.sources import edges as E
from tests.helpers import close, dense, named, pairs, queries, scores

#: The worked example after two laps.
SETTLED = {(1, 1): 0.15, (1, 2): 0.06375, (1, 3): 0.06375}
FRONTIER = {(1, 4): 0.0903125, (1, 5): 0.180625, (1, 6): 0.180625, (1, 7): 0.180625, (1, 8): 0.0903125}


@pytest.mark.parametrize("closed", [False, True])
def test_worked_example(spark, closed):
    g = build_graph(E.toy8(spark, closed=closed))
    f = decompose.frontier_vectors(g, queries(spark, 1), 2)
    assert close(scores(f.settled), SETTLED, 1e-15) and close(scores(f.frontier), FRONTIER, 1e-15)
    loads = measures.index_loads(g, queries(spark, 1), 2).first()
    assert (loads.recursive, loads.shared) == (8, 5)


def exact_index(spark, g):
    """Stored vectors without sampling error: scores times a large number of walks, as visits."""
    ids, q = exact.dense_solve(g, dangling="absorb")
    n = 10**9
    rows = [(int(s), n, n, [(int(v), int(round(x * n / 0.15))) for v, x in zip(ids, row) if x > 1e-12], 0) for s, row in zip(ids, q)]
    return spark.createDataFrame(rows, "source long, walks long, moves long, entries array<struct<vertex:long,visits:long>>, bucket int")


@pytest.mark.parametrize("name", ["supp_chain", "part_supp_semi"])
@pytest.mark.parametrize("mode", ["broadcast", "shuffle"])
def test_every_depth_is_exact_on_exact_vectors(spark, name, mode):
    g = named(spark, name)
    idx = exact_index(spark, g)
    some = [r[0] for r in g.vertices.orderBy(F.desc("vertex")).limit(3).collect()]
    for laps in (0, 1, 2):
        assert close(scores(decompose.batch_ppr(g, idx, queries(spark, *some), laps, mode=mode)), dense(g, some), 1e-6)


@pytest.mark.parametrize("name", ["toy8", "supp_chain", "part_supp_semi", "dangling3"])
def test_recursion_equals_laps(spark, name):
    g = pairs(spark, (1, 2), (1, 3), (2, 1)) if name == "dangling3" else named(spark, name)
    idx = index.build_index(g, 5)
    q = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    for laps in (0, 1, 2, 3 if g.size[0] < 15 else 2):
        want = scores(decompose.batch_ppr(g, idx, q, laps))
        assert close(scores(decompose.recursive_decompose(g, idx, q, laps)), want, 1e-12)
        assert close(scores(decompose.batch_ppr(g, idx, q, laps, mode="shuffle")), want, 1e-12)


def test_masses_without_dangling_vertices(spark):
    g = named(spark, "basket")
    q = sample_vertices(g, 4).select(F.col("vertex").alias("query"))
    for laps in (1, 3):
        f = decompose.frontier_vectors(g, q, laps)
        for df, want in ((f.settled, 1 - 0.85**laps), (f.frontier, 0.85**laps)):
            assert all(abs(r[1] - want) < 1e-12 for r in df.groupBy("query").sum("mass").collect())


def test_one_step_identity_on_exact_vectors(spark):
    g = named(spark, "part_supp_semi")
    q = exact.power_iteration(g, g.vertices.select("vertex"), tol=1e-13, max_iter=400, dangling="absorb")
    some = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    asked = {r[0] for r in some.collect()}
    want = {k: v for k, v in scores(q).items() if k[0] in asked}
    assert close(scores(decompose.decompose_once(g, q, some)), want, 1e-10)


def test_index_free_converges(spark):
    g = named(spark, "part_supp_semi")
    some = [r[0] for r in sample_vertices(g, 2).collect()]
    assert close(scores(decompose.batch_ppr(g, None, queries(spark, *some), 120)), dense(g, some), 1e-7)
    assert close(scores(decompose.batch_ppr(g, None, queries(spark, *some), 1, residual=1e-8)), dense(g, some), 1e-7)
    with pytest.raises(ValueError):
        decompose.batch_ppr(g, None, queries(spark, *some), 0)


def test_no_laps_is_the_stored_vector(spark):
    g = named(spark, "basket")
    idx = index.build_index(g, 10)
    q = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    assert close(scores(decompose.batch_ppr(g, idx, q, 0)), scores(baselines.precomputed_lookup(idx, q)), 1e-12)


def test_batch_equals_single_queries(spark):
    g = named(spark, "part_supp_semi")
    idx = index.build_index(g, 10)
    some = [r[0] for r in sample_vertices(g, 3).collect()]
    batch = scores(decompose.batch_ppr(g, idx, queries(spark, *some, some[0], -77), 2))
    single = {}
    for df in decompose.per_query_loop(g, idx, some, 2):
        single |= scores(df)
    assert close(batch, single, 1e-12) and {k for k, _ in batch} == set(some)
    assert decompose.batch_ppr(g, idx, queries(spark), 2).count() == 0


def test_dropped_mass_bounds_the_error(spark):
    g = named(spark, "basket")
    q = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    idx = exact_index(spark, g)
    for mode in ("broadcast", "shuffle"):
        whole = scores(decompose.batch_ppr(g, idx, q, 2, normalise=False, mode=mode))
        cut = scores(decompose.batch_ppr(g, idx, q, 2, eps=5e-3, normalise=False, mode=mode))
        dropped = {r.query: r.dropped for r in decompose.frontier_vectors(g, q, 2, eps=5e-3).dropped.collect()}
        assert dropped
        for query, lost in dropped.items():
            off = sum(abs(whole[k] - cut.get(k, 0)) for k in whole if k[0] == query)
            assert 0 < off <= lost + 1e-6


def test_top_k_ties_and_pairs(spark):
    ppr = spark.createDataFrame([(1, 5, 0.25), (1, 3, 0.25 + 1e-15), (1, 9, 0.5), (2, 1, 1.0)], "query long, vertex long, score double")
    assert sorted((r.query, r["rank"], r.vertex) for r in decompose.top_k(ppr, 2).collect()) == [(1, 1, 9), (1, 2, 3), (2, 1, 1)]
    pairs_ = spark.createDataFrame([(1, 9), (1, 1), (3, 3)], "query long, vertex long")
    assert scores(decompose.pair_scores(ppr, pairs_)) == {(1, 9): 0.5, (1, 1): 0.0, (3, 3): 0.0}
    g = named(spark, "basket")
    q = sample_vertices(g, 3).select(F.col("vertex").alias("query"))
    for mode in ("broadcast", "shuffle"):
        full = decompose.batch_ppr(g, None, q, 3, mode=mode)
        a = {(r.query, r["rank"]): r.vertex for r in decompose.top_k(full, 7).collect()}
        assert a == {(r.query, r["rank"]): r.vertex for r in decompose.batch_ppr(g, None, q, 3, k=7, mode=mode).collect()}


def test_partial_index_and_hubs(spark):
    g = named(spark, "basket")
    h = baselines.hubs(g, 60)
    idx = index.build_index(g, 200, sources=h)
    q = sample_vertices(g, 5).select(F.col("vertex").alias("query"))
    t = truth(g, q)
    pushed = baselines.hub_only(g, idx, q, laps=3)
    assert measures.mean_rag(measures.rag(t, pushed, [20])).first().rag > 0.9
    assert {r.query for r in baselines.hub_only(g, idx, q).collect()} <= {r.vertex for r in h.collect()}


@pytest.mark.parametrize("name, k, floor", [("basket", 20, 0.985), ("geo_tree_sym", 20, 0.97), ("part_supp_semi", 20, 0.985)])
def test_accuracy_gate_at_the_known_depths(spark, name, k, floor):
    g = named(spark, name)
    q = sample_vertices(g, 25).select(F.col("vertex").alias("query"))
    t = truth(g, q)
    got = {(r.walks, r.laps): r.rag for r in rag_by_laps(g, q, t, [0, 10, 100], [0, 1, 2, 5, 7], [k]).collect()}
    assert got[0, 7] > floor and got[10, 5] > floor and got[100, 2] > floor
    assert got[10, 1] > got[10, 0] and got[10, 5] > got[10, 0]  # a composed vector beats the stored one
    assert got[100, 0] > got[10, 0] and got[0, 7] > got[0, 1]
    assert got[100, 1] > got[0, 1]


def test_larger_indexes_need_fewer_laps(spark):
    g = named(spark, "basket")
    q = sample_vertices(g, 25).select(F.col("vertex").alias("query"))
    t = truth(g, q)
    depth = [minimal_depth(g, index.build_index(g, r) if r else None, q, t, 0.99, 20) for r in (0, 10, 100, 2000)]
    assert depth == sorted(depth, reverse=True) and depth[-1] == 0 and depth[0] >= 2


def test_effective_walks(spark):
    g = build_graph(E.toy8(spark, closed=True))
    r = decompose.effective_walks(decompose.frontier_vectors(g, queries(spark, 2), 1), 100).first()
    assert r.walks == pytest.approx(400) and r.shrink == pytest.approx(0.85)


def test_estimators_agree_with_decomposition_of_fresh_walks(spark):
    g = named(spark, "supp_chain")
    w = walks.simulate_walks(g, None, 20)
    idx = index.compact(w.visits, 20)
    q = sample_vertices(g, 2).select(F.col("vertex").alias("query"))
    once = decompose.decompose_once(g, estimators.full_path_ppr(w, "walks"), q)
    assert close(scores(once), scores(decompose.batch_ppr(g, idx, q, 1, normalise=False)), 1e-12)
