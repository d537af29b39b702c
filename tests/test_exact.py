import numpy as np
from pyspark.sql import functions as F
import pytest

from ripplerank.operators import exact
from tests.helpers import close, dense, named, pairs, queries, scores


@pytest.mark.parametrize("mode", ["broadcast", "shuffle"])
def test_closed_form_with_a_dangling_vertex(spark, mode):
    g = pairs(spark, (1, 2), (1, 3), (2, 1))
    p = scores(exact.power_iteration(g, queries(spark, 1, 3, 99, column="vertex"), tol=1e-7 if mode == "shuffle" else 1e-12, mode=mode, max_iter=25 if mode == "shuffle" else 200))
    want = {(1, 1): 1 / 1.85, (1, 2): 0.425 / 1.85, (1, 3): 0.425 / 1.85, (3, 3): 1.0}
    assert close(p, want, 0.02 if mode == "shuffle" else 1e-9)


@pytest.mark.parametrize("name", ["supp_chain", "part_supp_semi", "geo_tree", "conv_chain", "user_flow"])
def test_power_iteration_against_a_direct_solve(spark, name):
    g = named(spark, name)
    some = [r[0] for r in g.vertices.orderBy("vertex").limit(5).collect()]
    ppr = exact.power_iteration(g, queries(spark, *some, column="vertex"), tol=1e-13, max_iter=400)
    assert close(scores(ppr), dense(g, some))
    assert all(r.residual < 1e-9 for r in exact.ppr_residual(g, ppr).collect())
    total = ppr.groupBy("source").sum("score").collect()
    assert all(abs(r[1] - 1) < 1e-9 for r in total)


def test_shuffled_laps_equal_local_laps(spark):
    g = named(spark, "part_supp_semi")
    q = g.vertices.orderBy("vertex").limit(3)
    for policy in ("to_source", "absorb"):
        a, b = (exact.power_iteration(g, q, tol=0.0, max_iter=3, dangling=policy, mode=m) for m in ("shuffle", "broadcast"))
        assert close(scores(a), scores(b), 1e-12)


def test_loops_and_strangers(spark):
    g = pairs(spark, (1, 1))
    assert scores(exact.power_iteration(g, queries(spark, 1, 2, column="vertex"))) == {(1, 1): pytest.approx(1.0)}


def test_global_rank_sums_to_one_and_ranks_the_hub_first(spark):
    g = pairs(spark, *[(0, i) for i in range(1, 65)], *[(i, 0) for i in range(1, 65)])
    p = {r.vertex: r.score for r in exact.global_pagerank(g).collect()}
    assert abs(sum(p.values()) - 1) < 1e-9 and max(p, key=p.get) == 0
    a = exact.global_pagerank(named(spark, "part_supp"), tol=0.0, max_iter=3, mode="shuffle").collect()
    b = exact.global_pagerank(named(spark, "part_supp"), tol=0.0, max_iter=3).collect()
    assert np.allclose([r.score for r in sorted(a)], [r.score for r in sorted(b)])


def test_preferences_mix_linearly(spark):
    g = named(spark, "part_supp_semi")
    a, b = [r[0] for r in g.vertices.orderBy("vertex").limit(2).collect()]
    prefs = spark.createDataFrame([("x", a, 3.0), ("x", b, 1.0), ("only", a, 2.0)], "profile string, vertex long, weight double")
    got = {(r.profile, r.vertex): r.score for r in exact.preference_ppr(g, prefs, tol=1e-12).collect()}
    ids, q = exact.dense_solve(g, dangling="absorb")
    at = ids.tolist().index
    mix = 0.75 * q[at(a)] + 0.25 * q[at(b)]
    want = {("x", int(v)): s / mix.sum() for v, s in zip(ids, mix) if s > 0} | {("only", int(v)): s / q[at(a)].sum() for v, s in zip(ids, q[at(a)]) if s > 0}
    assert close(got, want)


def test_profiles_and_streams_take_whole_tables(spark):
    from ripplerank.plans import catalogue

    d = "/root/testdata/sf0.001"
    got = catalogue.QUERIES["ppr_preference_mix"](spark, d).collect()
    customers = spark.read.parquet(f"{d}/customer.parquet")
    orders = spark.read.parquet(f"{d}/orders.parquet").join(customers, F.col("o_custkey") == F.col("c_custkey")).collect()
    prefs = [(r.c_mktsegment, r.o_custkey + catalogue.K, 1.0) for r in orders]
    g = catalogue.graph(spark, d, "cust_part")
    want = exact.preference_ppr(g, spark.createDataFrame(prefs, "profile string, vertex long, weight double"), tol=0.0, max_iter=20, mode="shuffle").collect()
    a, b = ({(r.profile, r.vertex): r.score for r in x} for x in (got, want))
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-8 for k in a)
    asked = spark.read.parquet(f"{d}/events.parquet").select((F.col("user_id") + catalogue.K).alias("query")).distinct().join(g.vertices.withColumnRenamed("vertex", "query"), "query", "left_semi")
    assert {r.query for r in catalogue.QUERIES["stream_query_batches"](spark, d).select("query").distinct().collect()} == {r.query for r in asked.collect()}


def test_shuffled_profiles_are_not_solved_source_by_source(spark, monkeypatch):
    g = named(spark, "supp_chain")
    prefs = g.vertices.orderBy("vertex").limit(6).select((F.col("vertex") % 2).alias("profile"), "vertex", F.lit(1.0).alias("weight"))
    monkeypatch.setattr(exact, "power_iteration", lambda *a, **how: pytest.fail("one vector a source"))
    a, b = ({(r.profile, r.vertex): r.score for r in exact.preference_ppr(g, prefs, tol=0.0, max_iter=4, mode=m).collect()} for m in ("shuffle", "broadcast"))
    assert close(a, b)


def test_streamed_vectors_as_shuffled(spark, monkeypatch):
    """Where the vectors fit and the edges do not, vectors come and go and no lap joins rows; parts and blocks change nothing."""
    from ripplerank.operators import graph

    monkeypatch.setattr(graph, "GATHERED_EDGES", 97)
    g = named(spark, "part_supp_semi")
    monkeypatch.setattr(graph, "VECTOR_BYTES", 8 * g.size[0] * 2)
    sources = g.vertices.orderBy(F.desc("out_deg"), "vertex").limit(3).unionByName(g.vertices.where("out_deg = 0").orderBy("vertex").limit(2)).select("vertex")
    prefs = sources.select((F.col("vertex") % 3).cast("string").alias("profile"), "vertex", (F.col("vertex") % 5 + 1).cast("double").alias("weight"))
    want = scores(exact.power_iteration(g, sources, tol=0.0, max_iter=4, mode="shuffle"))
    absorbed = scores(exact.power_iteration(g, sources, tol=0.0, max_iter=4, mode="shuffle", dangling="absorb"))
    mixed = {(r.profile, r.vertex): r.score for r in exact.preference_ppr(g, prefs, tol=0.0, max_iter=4, mode="shuffle").collect()}
    assert g.entering.count() > 5
    monkeypatch.setattr(exact, "pick_mode", lambda g, mode, budget=None: "shuffle")  # as if the graph were large
    monkeypatch.setattr(exact, "_iterated", lambda *a, **how: pytest.fail("joined row by row"))
    assert close(scores(exact.power_iteration(g, sources, tol=0.0, max_iter=4)), want)
    assert close(scores(exact.power_iteration(g, sources, tol=0.0, max_iter=4, dangling="absorb")), absorbed)
    assert close({(r.profile, r.vertex): r.score for r in exact.preference_ppr(g, prefs, tol=0.0, max_iter=4).collect()}, mixed)
    assert g.streams(32) == 2 and g.streams(33) == 0
    few = prefs.select(F.col("profile").cast("int").alias("profile"), "vertex", "weight")
    monkeypatch.setattr(exact, "ROWS", 50)  # many tasks write, some of them nothing of a vector
    assert close({(str(r.profile), r.vertex): r.score for r in exact.preference_ppr(g, few, tol=0.0, max_iter=4).collect()}, mixed)
    none = exact.power_iteration(g, g.vertices.where("out_deg = 0").select("vertex").limit(1), tol=0.0, max_iter=1)
    assert [r.score for r in none.collect()] == [1.0]
