"""Headline measurements: prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS (default: all) choose data and cores. The rows follow
queries by each method, in broadcast form and with every join shuffled.
"""

from __future__ import annotations

import json
import os
import tempfile
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", str(os.cpu_count() or 8))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from ripplerank.functions.lineage import cut, shared_path
    from ripplerank.operators import baselines, decompose, evaluate, exact, index, measures, walks
    from ripplerank.operators.graph import sample_vertices
    from ripplerank.plans import catalogue

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "16g").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.maxResultSize", "2g").config("spark.checkpoint.dir", "file://" + tempfile.mkdtemp(prefix="ripplerank-bench-")).getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name: str, run):
        began = time.perf_counter()
        out = run()
        if hasattr(out, "write"):
            out.write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    def build(name: str):
        g = catalogue.graph(spark, SF_DIR, name)
        g.size, g.push_edges, g.shared()
        return g

    def moved(name: str, run):
        """Seconds, and bytes that the run writes to shuffles."""
        before = measures.shuffle_bytes(spark)
        out = timed(name, run)
        facts[f"shuffle_bytes_{name}"] = measures.shuffle_bytes(spark) - before
        return out

    basket = timed("graph_basket", lambda: build("basket"))
    cust = timed("graph_cust_part", lambda: build("cust_part"))

    # Preprocessing: time and bytes by walks.
    paths = {}
    for r in (10, 100):
        paths[r] = shared_path(spark, f"bench-{r}")
        timed(f"index_cust_part_R{r}", lambda r=r: index.build_index(cust, r, path=paths[r]).agg(F.sum(F.size("entries"))))
        facts[f"index_bytes_cust_part_R{r}"] = index.disk_bytes(spark, paths[r])
        facts[f"index_ratio_cust_part_R{r}"] = round(facts[f"index_bytes_cust_part_R{r}"] / (16 * cust.size[1]), 2)
    timed("walks_basket_100_per_vertex", lambda: walks.simulate_walks(basket, None, 100).visits)
    facts["walks_per_s"] = round(basket.size[0] * 100 / seconds["walks_basket_100_per_vertex"])
    facts["walks_per_s_per_core"] = round(facts["walks_per_s"] / int(CPUS))

    # Queries: batches of customers, ten best each.
    idx = {r: index.load_index(spark, p) for r, p in paths.items()}
    shared = {r: timed(f"share_index_R{r}", lambda r=r: decompose.share_index(cust, idx[r])) for r in idx}
    batches = {n: cut(sample_vertices(cust, n, where=catalogue.CUSTOMERS).select(F.col("vertex").alias("query")), "q") for n in (1, 100, 1000, 10_000)}
    # A large index of the queried vertices alone: rows as a full one of 2000 walks would hold them.
    stored = timed("index_cust_part_R2000_10000_sources", lambda: index.build_index(
        cust, 2000, path=shared_path(spark, "bench-2000"), sources=batches[10_000].select(F.col("query").alias("vertex"))))
    # A broadcast index answers batches like a cached one: it is checked and sent once.
    for n, q in batches.items():
        for r, t in ((0, 7), (10, 5), (100, 2)):
            timed(f"decompose_R{r}_T{t}_{n}", lambda r=r, t=t, q=q: decompose.batch_ppr(cust, shared.get(r), q, t, eps=1e-4, k=10, mode="broadcast"))
        if n != 1000:
            timed(f"online_walking_R2000_{n}", lambda q=q: baselines.online_walking(cust, q, 2000))
            timed(f"lookup_R2000_{n}", lambda q=q: baselines.precomputed_lookup(stored, q))
    few = [r[0] for r in batches[100].limit(10).collect()]

    def one_by_one():
        for answer in decompose.per_query_loop(cust, shared[100], few, 2, eps=1e-4, k=10, mode="broadcast"):
            answer.write.format("noop").mode("overwrite").save()

    timed("one_by_one_R100_T2_10", one_by_one)
    # A hundred queries one by one, from the ten measured.
    facts["shared_gain_100"] = round(measures.relative_gain(10 * seconds["one_by_one_R100_T2_10"], seconds["decompose_R100_T2_100"]), 3)
    for n in (1000, 10_000):
        facts[f"index_gain_{n}"] = round(measures.relative_gain(seconds[f"decompose_R0_T7_{n}"], seconds[f"decompose_R100_T2_{n}"]), 3)

    # The same without any broadcast of graph or index: laps and steps that move frontiers and walkers to where edges lie.
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    timed("adjacency_cust_part", lambda: cust.adjacency)
    moved("shuffled_R100_T2_100", lambda: decompose.batch_ppr(cust, idx[100], batches[100], 2, eps=1e-4, k=10, mode="shuffle"))
    for lap in (1, 2, 3):
        moved(f"shuffled_frontier_T{lap}_100", lambda lap=lap: decompose.frontier_vectors(cust, batches[100], lap, eps=1e-4).frontier)
    moved("shuffled_walks_10000x10", lambda: walks.simulate_walks(cust, batches[10_000].select(F.col("query").alias("vertex")), 10, mode="shuffle", max_steps=12).visits)
    facts["visits_per_s_shuffled"] = round(100_000 * sum(0.85**t for t in range(13)) / seconds["shuffled_walks_10000x10"])
    moved("shuffled_power_10_laps_1", lambda: exact.power_iteration(cust, batches[1].select(F.col("query").alias("vertex")), tol=0.0, max_iter=10, mode="shuffle"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    one = sample_vertices(cust, 1, where=catalogue.CUSTOMERS).select(F.col("vertex").alias("query"))
    timed("power_iteration_1", lambda: baselines.power_iteration_online(cust, one))
    facts["queries_per_s_R100"] = round(10_000 / seconds["decompose_R100_T2_10000"])

    # Accuracy at the known depths.
    q = cut(sample_vertices(basket, 20).select(F.col("vertex").alias("query")), "q")
    truth = timed("truth_basket_20", lambda: evaluate.truth(basket, q))
    for r, t in ((0, 7), (10, 5), (100, 2)):
        built = cut(index.build_index(basket, r), "i") if r else None
        ppr = decompose.batch_ppr(basket, built, q, t)
        for row in timed(f"rag_R{r}_T{t}", lambda ppr=ppr: cut(measures.mean_rag(measures.rag(truth, ppr, [20, 200])), "rag")).collect():
            facts[f"rag_R{r}_T{t}_k{row.k}"] = round(row.rag, 4)

    for name in ("edges_basket", "adjacency_basket", "frontier_vectors_T2", "topk_recommend_parts", "flagship_basket"):
        timed(name, lambda name=name: catalogue.queries()[name](spark, SF_DIR))
    total = round(sum(seconds.values()), 2)
    print(json.dumps({"metric": "total_seconds", "value": total, "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"), "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    main()
