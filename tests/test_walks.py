import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ripplerank.functions import bounds, draws
from ripplerank.operators import baselines, estimators, index, walks
from ripplerank.operators.evaluate import truth
from ripplerank.operators.graph import sample_vertices
from ripplerank.operators.measures import mean_rag, rag, score_error
from tests.helpers import SMALL, close, dense, named, pairs, queries, scores


def counts(w):
    return sorted(tuple(r) for r in w.visits.select("source", "vertex", "visits", "ends").collect())


@pytest.mark.parametrize("rng", ["md5", "xxhash64"])
def test_columns_and_arrays_draw_alike(spark, rng):
    rows = [(s, w, st) for s in (0, 7, -5, 10**12) for w in (0, 3) for st in (0, 11)]
    df = spark.createDataFrame(rows, "s long, w long, st int")
    h1, h2 = draws.draw_columns(rng, 7, F.col("s"), F.col("w"), F.col("st"))
    for r in df.select("s", "w", "st", h1.alias("a"), h2.alias("b")).collect():
        a, b = draws.draw_arrays(rng, 7, np.array([r.s]), np.array([r.w]), r.st)
        assert (r.a, r.b) == (a[0], b[0]) and 0 <= r.a < draws.SPAN and 0 <= r.b < draws.SPAN


@pytest.mark.parametrize("dangling", ["absorb", "to_source"])
def test_all_modes_count_the_same_walks(spark, dangling, tmp_path):
    g = named(spark, "part_supp_semi")
    some = sample_vertices(g, 12)
    base = counts(walks.simulate_walks(g, some, 6, mode="broadcast", dangling=dangling, max_steps=5))
    assert base == counts(walks.simulate_walks(g, some.repartition(5), 6, mode="shuffle", dangling=dangling, max_steps=5))
    path = str(tmp_path / "intervals")
    assert base == counts(walks.simulate_walks(g, some, 6, mode="interval", intervals=3, path=path, dangling=dangling, max_steps=5))
    assert base == counts(walks.simulate_walks(g, some, 6, mode="interval", intervals=3, path=path, dangling=dangling, max_steps=5))  # resumed


def test_paths_fold_into_counts(spark):
    g = named(spark, "supp_chain")
    some = sample_vertices(g, 4)
    for mode in ("broadcast", "shuffle"):
        p = walks.walk_paths(g, some, 5, mode=mode, max_steps=4)
        folded = p.groupBy("source", "vertex").agg(F.count("*").alias("visits"), F.sum(F.col("stop").cast("long")).alias("ends"))
        assert sorted(tuple(r) for r in folded.collect()) == counts(walks.simulate_walks(g, some, 5, max_steps=4))


def test_lengths_and_ends(spark):
    g = named(spark, "basket")
    w = walks.simulate_walks(g, None, 50)
    total = w.stats.agg(F.sum("walks").alias("w"), F.sum("moves").alias("m"), F.sum("ends").alias("e")).first()
    assert total.e == total.w == 200 * 50
    sigma = math.sqrt(0.85) / 0.15 / math.sqrt(total.w)
    assert abs(total.m / total.w - 1 / 0.15) < 4 * sigma
    absorbed = walks.simulate_walks(named(spark, "part_supp"), None, 20).stats.agg(F.sum("ends"), F.sum("walks")).first()
    assert absorbed[0] < absorbed[1]


def test_compressed_walks_follow_the_same_law(spark):
    g = pairs(spark, (1, 2), (1, 3), (2, 1), (3, 1), (3, 2))
    w = walks.simulate_walks(g, queries(spark, 1, column="vertex"), 20_000, mode="compress", max_steps=20)
    got = scores(estimators.full_path_ppr(w, "walks"))
    assert close(got, dense(g, [1]), 0.05)
    assert counts(w) == counts(walks.simulate_walks(g, queries(spark, 1, column="vertex"), 20_000, mode="compress", max_steps=20))


def test_no_sources_strangers_and_no_walks(spark):
    g = named(spark, "supp_chain")
    assert counts(walks.simulate_walks(g, queries(spark, column="vertex"), 5)) == []
    assert counts(walks.simulate_walks(g, queries(spark, -1, column="vertex"), 5)) == []
    with pytest.raises(ValueError):
        walks.simulate_walks(g, None, 1, mode="other")


def test_long_and_stitched_walks_estimate_the_same_vector(spark):
    g = named(spark, "supp_chain")
    source = sample_vertices(g, 1).first()[0]
    want = dense(g, [source])
    q = queries(spark, source)
    assert close(scores(baselines.long_walk(g, q, 40_000)), want, 0.02)
    assert close(scores(baselines.stitching(g, q, 2000, stock=400, length=8)), want, 0.1)


def test_both_estimators_converge_and_full_paths_do_sooner(spark):
    g = named(spark, "basket")
    q = sample_vertices(g, 30).select(F.col("vertex").alias("query"))
    t = truth(g, q)
    got = {}
    for r in (10, 100, 1000):
        w = walks.simulate_walks(g, q.select(F.col("query").alias("vertex")), r)
        for name, ppr in (("full", estimators.full_path_ppr(w)), ("end", estimators.end_point_ppr(w))):
            got[name, r] = mean_rag(rag(t, ppr, [20])).first().rag
            assert abs(ppr.groupBy("source").sum("score").agg(F.max("sum(score)")).first()[0] - 1) < 1e-9
    for r in (10, 100, 1000):
        assert got["full", r] > got["end", r]
    assert got["full", 10] < got["full", 100] < got["full", 1000] and got["full", 1000] > 0.97
    assert got["full", 10] > 0.70 and got["full", 100] > 0.86


def test_equal_samples_give_equal_accuracy(spark):
    g = named(spark, "cust_part")
    q = sample_vertices(g, 30).select(F.col("vertex").alias("query"))
    t, v = truth(g, q), q.select(F.col("query").alias("vertex"))
    full = mean_rag(rag(t, estimators.full_path_ppr(walks.simulate_walks(g, v, 1000)), [20])).first().rag
    end = mean_rag(rag(t, estimators.end_point_ppr(walks.simulate_walks(g, v, bounds.equivalent_endpoint_walks(1000))), [20])).first().rag
    assert abs(full - end) < 0.02


def test_error_shrinks_like_the_root(spark):
    g = named(spark, "supp_chain")
    q = sample_vertices(g, 10).select(F.col("vertex").alias("query"))
    t, v = truth(g, q), q.select(F.col("query").alias("vertex"))
    small, large = (score_error(t, estimators.full_path_ppr(walks.simulate_walks(g, v, r))).agg(F.avg("l1_error")).first()[0] for r in (50, 5000))
    assert 6 < small / large < 16


def test_tail_stays_under_its_bound(spark):
    g = named(spark, "supp_chain")
    q = sample_vertices(g, 1).select(F.col("vertex").alias("query"))
    t = truth(g, q).withColumnRenamed("query", "source")
    for r in estimators.tail_frequency(g, q.first()[0], 0.1, 1000, t, runs=30).collect():
        assert r.over <= r.bound and r.under <= r.bound


def test_closed_forms():
    assert bounds.tail_bound(0.05, 1000, clip=False) == pytest.approx(2.28, abs=0.01) and bounds.tail_bound(0.05, 1000) == 1
    assert bounds.walks_for_precision(0.05, 0.01) == pytest.approx(44_400, rel=0.01)
    assert bounds.tail_bound(0.05, bounds.walks_for_precision(0.05, 0.01)) <= 0.01
    assert bounds.equivalent_endpoint_walks(1000) == 6667
    assert bounds.truncated_mass(10) == pytest.approx(0.1969, abs=1e-4)
    assert bounds.laps_for_residual(0.33) == 7 and bounds.laps_for_residual(1.0) == 0


def test_index_extends_merges_prunes_and_loads(spark, tmp_path):
    g = named(spark, "part_supp_semi")
    path = str(tmp_path / "index")
    ten = index.build_index(g, 10, path=path)
    full = sorted(tuple(r) for r in index.index_entries(index.build_index(g, 25)).collect())
    assert sorted(tuple(r) for r in index.index_entries(index.extend_index(ten, g, 10, 15)).collect()) == full
    both = index.merge_indexes(ten, index.build_index(g, 15, first_walk=10))
    assert sorted(tuple(r) for r in index.index_entries(both).collect()) == full
    assert index.disk_bytes(spark, path) > 0
    stats = index.index_stats(ten, g, 10).first()
    assert stats.sources == g.size[0] and stats.entries <= stats.bound * 1.1
    pruned = index.prune_index(ten, 2).collect()
    assert all(0 <= r.pruned < 1 and all(e.visits >= 2 for e in r.entries) for r in pruned)
    few = [r[0] for r in sample_vertices(g, 3).collect()]
    a = scores(index.lookup(ten, queries(spark, *few, -1)))
    b = scores(index.lookup(ten, queries(spark, *few, -1), literal=0))
    w = walks.simulate_walks(g, queries(spark, *few, column="vertex"), 10)
    assert a == b and close(a, scores(estimators.full_path_ppr(w)))
    assert index.lookup(ten, queries(spark)).count() == 0
    assert sorted(tuple(r) for r in index.index_entries(index.load_index(spark, path)).collect()) == sorted(tuple(r) for r in index.index_entries(ten).collect())
    cached = index.cache_index(ten)
    assert cached.count() == g.size[0]
    cached.unpersist()


def test_walk_database_answers_like_fresh_walks(spark):
    g = named(spark, "part_supp_semi")
    few = sample_vertices(g, 3)
    paths = walks.walk_paths(g, few, 40)
    q = few.select(F.col("vertex").alias("query"))
    w = walks.simulate_walks(g, few, 40)
    assert close(scores(baselines.walk_database(paths, q)), scores(estimators.full_path_ppr(w)))
    assert close(scores(baselines.walk_database(paths, q, "end_point")), scores(estimators.end_point_ppr(w)))
    assert SMALL


def test_long_walk_is_alike_in_all_modes_and_counts_its_visits(spark):
    g = named(spark, "supp_chain")
    q = sample_vertices(g, 2)
    a = scores(walks.long_walk(g, q, 300))
    b = scores(walks.long_walk(g, q, 300, mode="shuffle"))
    assert close(a, b, 1e-12)
    for source in {s for s, _ in a}:
        assert sum(v for (s, _), v in a.items() if s == source) == pytest.approx(1)


def test_stitched_walks_all_finish(spark):
    g = named(spark, "supp_chain")
    segments = walks.stored_segments(g, 10, 1)
    w = walks.stitched_walk(g, sample_vertices(g, 2), 30, segments, 10, 1)
    assert all(r.ends == 30 for r in w.stats.collect())


def test_compressed_draws_do_not_depend_on_the_batch(spark, monkeypatch):
    g = named(spark, "part_supp_semi")
    q = sample_vertices(g, 3)
    some = lambda: sorted(tuple(r) for r in walks.simulate_walks(g, q, 40, mode="compress", max_steps=5).visits.collect())
    whole = some()
    run = walks._split(7, "md5", 0.15, 0, 0)
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"source": [1, 2], "v": [1, 2], "deg": [5, 0], "n": [1000, 7]})
    a = pa.Table.from_batches(run([batch])).to_pandas().groupby(["source", "pos"])[["n", "stops"]].sum()
    monkeypatch.setattr(walks, "DRAWS", 13)
    b = pa.Table.from_batches(run([batch])).to_pandas().groupby(["source", "pos"])[["n", "stops"]].sum()
    assert a.equals(b) and a.n.sum() + a.stops.sum() == 1007 and set(a.loc[2].index) <= {-1, -2}
    assert whole == some()
