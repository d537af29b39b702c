"""Every method, variant, baseline, measure and workload as a registered query with its SQL oracle."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bounds
from ..functions.lineage import cut, shared_path
from ..functions.udtf import IndexEntries, register_views, sql_close, sql_lap, walker
from ..operators import baselines, decompose, estimators, evaluate, exact, index, measures, walks
from ..operators.graph import Graph, adjacency_of, build_graph, dangling, degree_buckets, degrees, graph_stats, reached, sample_queries, sample_vertices, source_intervals, with_policy
from ..sources import edges as E
from ..streaming import buffer
from . import oracles as O
from . import planner

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
K = O.K


def query(name: str, sql: str | None = None):
    def add(run):
        QUERIES[name] = run
        if sql:
            ORACLES[name] = sql
        return run

    return add


def graph(spark: SparkSession, d: str, name: str) -> Graph:
    return build_graph(E.GRAPHS[name](spark, d))


def tidy(c: str | Column, name: str | None = None) -> Column:
    """Ten digits, nudged off halves, so that the order of summation does not show."""
    col = F.col(c) if isinstance(c, str) else c
    return F.round(col + 1.7e-12, 10).alias(name or c)


def asked(g: Graph, n: int = 10, where: str = "true") -> DataFrame:
    return sample_vertices(g, n, where=where).select(F.col("vertex").alias("query"))


def ids(spark: SparkSession, *queries: int) -> DataFrame:
    return spark.createDataFrame([(q,) for q in queries], "query long")


CUSTOMERS = f"vertex < {2 * K} and vertex >= {K}"
DOCUMENTS = f"vertex >= {8 * K} and vertex < {9 * K}"

# ---------------------------------------------------------------- graphs

for _name in E.GRAPHS:
    if _name not in ("toy8", "line8"):
        query(f"edges_{_name}", O.EDGES[_name])(lambda s, d, n=_name: E.GRAPHS[n](s, d).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")))

_DEG = "select vertex, out_deg, coalesce(n, 0) as in_deg from v left join (select dst, count(*) as n from e group by dst) on dst = vertex"
_STATS = f"""select count(*) as vertices, sum(out_deg)::bigint as edges, count(*) filter (where out_deg = 0) as dangling, max(out_deg) as max_degree,
    {O.rounded('avg(out_deg)')} as mean_degree, (16 * sum(out_deg))::bigint as edge_bytes from v"""
for _name in ("basket", "part_supp_semi", "doc_word"):
    query(f"degrees_{_name}", O.with_graph(_name, select=_DEG))(lambda s, d, n=_name: degrees(graph(s, d, n)))
for _name in ("basket", "cust_part", "page_links", "conv_chain"):
    query(f"graph_stats_{_name}", O.with_graph(_name, select=_STATS))(lambda s, d, n=_name: graph_stats(graph(s, d, n)))
for _name in ("part_supp", "conv_chain"):
    query(f"dangling_{_name}", O.with_graph(_name, select="select vertex from v where out_deg = 0"))(lambda s, d, n=_name: dangling(graph(s, d, n)))
for _name in ("basket", "part_supp_semi"):
    query(f"adjacency_{_name}", O.with_graph(_name, select="select * from adj"))(lambda s, d, n=_name: graph(s, d, n).adjacency)

_BUCKETS = "b as (select vertex, out_deg, least(length(bin(out_deg)), 10)::int as bucket from v where out_deg > 0)"


@query("adjacency_blockwise_supp_chain", O.with_graph("supp_chain", select="select src, pos, dst from adj"))
def _(s, d):
    """The hub-safe ranking, forced on vertices of more than 20 edges."""
    return adjacency_of(graph(s, d, "supp_chain"), hub_degree=20)


@query("degree_buckets_doc_word", O.with_graph("doc_word", _BUCKETS, select="select * from b"))
def _(s, d):
    return degree_buckets(graph(s, d, "doc_word"))


@query("bucket_sample_doc_word", O.with_graph("doc_word", _BUCKETS, select="""
    select bucket, vertex from b qualify row_number() over (partition by bucket order by md5('7|' || vertex), vertex) <= 10"""))
def _(s, d):
    return sample_queries(graph(s, d, "doc_word"))


@query("self_loop_policy_part_supp", O.with_graph("part_supp", select="select src, dst from e union select vertex, vertex from v where out_deg = 0"))
def _(s, d):
    return with_policy(graph(s, d, "part_supp"), "self_loop").edges


@query("source_intervals_basket")
def _(s, d):
    return source_intervals(graph(s, d, "basket"), 8)


# ---------------------------------------------------------------- exact references

_EXACT = f"select query as source, vertex, {O.rounded('score')} as score from p_exact"


def _exact(s, d, name, n, laps, where="true", **how):
    g = graph(s, d, name)
    q = sample_vertices(g, n, where=where)
    return exact.power_iteration(g, q, tol=0.0, max_iter=laps, **how).select("source", "vertex", tidy("score"))


query("ppr_exact_supp_chain", O.with_graph("supp_chain", O.power_ctes(150), select=_EXACT, q=O.sampled(10)))(lambda s, d: _exact(s, d, "supp_chain", 10, 150))
# Vectors after a fixed number of laps carry it in their names: up to .85^laps of the mass may still move.
query("ppr_30_laps_basket_batch", O.with_graph("basket", O.power_ctes(30), select=_EXACT, q=O.sampled(5)))(lambda s, d: _exact(s, d, "basket", 5, 30))
query("ppr_30_laps_dangling_part_supp_semi", O.with_graph("part_supp_semi", O.power_ctes(30), select=_EXACT, q=O.sampled(5)))(lambda s, d: _exact(s, d, "part_supp_semi", 5, 30))
query("ppr_12_laps_absorb_conv_chain", O.with_graph("conv_chain", O.power_ctes(12, False), select=_EXACT, q=O.sampled(20)))(lambda s, d: _exact(s, d, "conv_chain", 20, 12, dangling="absorb"))
query("ppr_4_laps_shuffled_part_supp", O.with_graph("part_supp", O.power_ctes(4), select=_EXACT, q=O.sampled(5)))(lambda s, d: _exact(s, d, "part_supp", 5, 4, mode="shuffle"))

for _name, _n, _where in (("basket", 5, "true"), ("cust_part", 3, CUSTOMERS)):
    query(f"ppr_6_laps_shuffled_{_name}", O.with_graph(_name, O.power_ctes(6), select=_EXACT, q=O.sampled(_n, where=_where)))(
        lambda s, d, g=_name, n=_n, w=_where: _exact(s, d, g, n, 6, w, mode="shuffle"))


@query("ppr_residual_supp_chain", O.with_graph("supp_chain", select=f"{O.sampled(10)}").replace("select vertex as query from v", "select vertex as source, true as solved from v"))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return exact.ppr_residual(g, cut(exact.power_iteration(g, sample_vertices(g, 10)), "p")).select("source", (F.col("residual") < 1e-9).alias("solved"))


def _global_sql(laps: int) -> str:
    out = ["n as (select count(*) as n from v)", "p0 as (select vertex, 1.0 / n as score from v, n)"]
    for i in range(laps):
        out.append(f"""l{i} as (select coalesce(sum(score), 0) as lost from p{i} join v using (vertex) where out_deg = 0),
            p{i + 1} as materialized (select v.vertex, 0.85 * coalesce(m, 0) + (0.15 + 0.85 * lost) / n as score from v left join (
                select dst, sum(score / out_deg) as m from p{i} p join e on e.src = p.vertex join v on v.vertex = p.vertex group by dst) on dst = v.vertex, n, l{i})""")
    return O.with_graph("user_flow", *out, select=f"select vertex, {O.rounded('score')} as score from p{laps}")


@query("pagerank_40_laps_user_flow", _global_sql(40))
def _(s, d):
    return exact.global_pagerank(graph(s, d, "user_flow"), tol=0.0, max_iter=40).select("vertex", tidy("score"))


@query("pagerank_4_laps_shuffled_user_flow", _global_sql(4))
def _(s, d):
    return exact.global_pagerank(graph(s, d, "user_flow"), tol=0.0, max_iter=4, mode="shuffle").select("vertex", tidy("score"))


@query("ppr_preference_mix")
def _(s, d):
    """One profile for each market segment, weighing all its customers by their orders. Too slow in SQL; a test holds it against single vectors."""
    return _segments(s, d)


def _segments(s, d):
    o = E.table(s, d, "orders").join(E.table(s, d, "customer").withColumnRenamed("c_custkey", "o_custkey"), "o_custkey")
    prefs = o.groupBy(F.col("c_mktsegment").alias("profile"), E.vertex("customer", "o_custkey").alias("vertex")).agg(F.count("*").cast("double").alias("weight"))
    return exact.preference_ppr(graph(s, d, "cust_part"), cut(prefs, "prefs"), tol=0.0, max_iter=20).select("profile", "vertex", tidy("score"))


# ---------------------------------------------------------------- walks and estimators

MD5 = {"rng": "md5"}


def _walks(s, d, name, n, r, where="true", **how):
    g = graph(s, d, name)
    return walks.simulate_walks(g, sample_vertices(g, n, where=where), r, **{**MD5, **how})


_W = O.walk_ctes
_VISITS = "select source, vertex, visits, ends from w_visits"
query("walk_visits_basket", O.with_graph("basket", _W(20), select=_VISITS, q=O.sampled(20)))(lambda s, d: _walks(s, d, "basket", 20, 20).visits)
query("walk_visits_dangling", O.with_graph("part_supp_semi", _W(20), select=_VISITS, q=O.sampled(20)))(lambda s, d: _walks(s, d, "part_supp_semi", 20, 20).visits)
query("walk_visits_shuffled_supp_chain", O.with_graph("supp_chain", _W(5, max_steps=6), select=_VISITS, q=O.sampled(20)))(
    lambda s, d: _walks(s, d, "supp_chain", 20, 5, mode="shuffle", max_steps=6).visits)
query("walk_visits_shuffled_basket", O.with_graph("basket", _W(5, max_steps=12), select=_VISITS, q=O.sampled(20)))(
    lambda s, d: _walks(s, d, "basket", 20, 5, mode="shuffle", max_steps=12).visits)
query("walk_visits_shuffled_cust_part", O.with_graph("cust_part", _W(5, max_steps=12), select=_VISITS, q=O.sampled(20, where=CUSTOMERS)))(
    lambda s, d: _walks(s, d, "cust_part", 20, 5, CUSTOMERS, mode="shuffle", max_steps=12).visits)
query("walk_ends_basket", O.with_graph("basket", _W(20), select="select source, vertex, ends from w_visits where ends > 0", q=O.sampled(20)))(
    lambda s, d: _walks(s, d, "basket", 20, 20).visits.where("ends > 0").select("source", "vertex", "ends"))
query("walk_stats_basket", O.with_graph("basket", _W(50), select="select source, walks, moves, ends from w_stats", q=O.sampled(20)))(lambda s, d: _walks(s, d, "basket", 20, 50).stats)
query("walk_totals_page_links", O.with_graph("page_links_sym", _W(20), select=f"""
    select count(*) as sources, sum(walks)::bigint as walks, sum(moves)::bigint as moves, {O.rounded('sum(moves) / sum(walks)')} as mean_length from w_stats""", q=O.sampled(50)))(
    lambda s, d: measures.walk_stats(_walks(s, d, "page_links_sym", 50, 20).stats).withColumn("mean_length", tidy("mean_length")))


@query("walk_visits_interval_supp_chain", O.with_graph("supp_chain", _W(5), select=_VISITS, q=O.sampled(20)))
def _(s, d):
    return _walks(s, d, "supp_chain", 20, 5, mode="interval", intervals=3, path=shared_path(s, "intervals")).visits


@query("walk_paths_supp_chain", O.with_graph("supp_chain", _W(5), select=f"select source, walk, step, vertex, ('0x' || substr(h, 1, 8))::bigint < {O.STOP} as stop from w", q=O.sampled(10)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return walks.walk_paths(g, sample_vertices(g, 10), 5, **MD5)


@query("walk_truncated_share", O.with_graph("supp_chain", _W(100, max_steps=10), select=f"""
    select 10 as steps, {O.rounded('count(*) filter (where step = 10) / 1000.0')} as alive, {O.rounded('pow(0.85, 10)')} as expected from w""", q=O.sampled(10)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    p = walks.walk_paths(g, sample_vertices(g, 10), 100, max_steps=10, **MD5)
    return p.agg(F.lit(10).alias("steps"), tidy(F.count(F.when(F.col("step") == 10, 1)) / 1000.0, "alive"), tidy(F.lit(bounds.truncated_mass(10)), "expected"))


_C = 4  # steps of the compressed walks


def _compressed_sql(walks: int) -> str:
    out = [f"c0 as (select query as source, query as vertex, out_deg as deg, {walks}::bigint as n from q join v on v.vertex = query)"]
    for i in range(_C + 1):
        out.append(f"""d{i} as materialized (select source, vertex, deg, md5('7|' || source || '|' || k || '|{i}|' || vertex) as h from (select *, unnest(range(n)) as k from c{i})),
            x{i} as (select source, vertex, count(*) as visits, count(*) filter (where ('0x' || substr(h, 1, 8))::bigint < {O.STOP}) as ends from d{i} group by source, vertex),
            c{i + 1} as materialized (select source, a.dst as vertex, a.dst_deg as deg, count(*) as n from d{i} d join adj a on a.src = d.vertex and a.pos = (('0x' || substr(h, 9, 8))::bigint * d.deg) >> 32
                where ('0x' || substr(h, 1, 8))::bigint >= {O.STOP} group by all)""")
    every = " union all ".join(f"select * from x{i}" for i in range(_C + 1))
    return O.with_graph("supp_chain", *out, select=f"select source, vertex, sum(visits)::bigint as visits, sum(ends)::bigint as ends from ({every}) group by source, vertex", q=O.sampled(10))


@query("walk_compressed_supp_chain", _compressed_sql(200))
def _(s, d):
    return _walks(s, d, "supp_chain", 10, 200, mode="compress", max_steps=_C).visits


_LONG = f"""select query, vertex, {O.rounded('count(*) / 2000.0::double')} as score from (
    select source as query, vertex, row_number() over (partition by source order by walk, step) as n from w) where n <= 2000 group by query, vertex"""
query("long_walk_supp_chain", O.with_graph("supp_chain", _W(600), select=_LONG, q=O.sampled(4)))(lambda s, d: _scores(baselines.long_walk(g := graph(s, d, "supp_chain"), asked(g, 4), 2000, **MD5)))
query("long_walk_shuffled_supp_chain", O.with_graph("supp_chain", _W(600), select=_LONG.replace("2000", "100"), q=O.sampled(2)))(
    lambda s, d: _scores(baselines.long_walk(g := graph(s, d, "supp_chain"), asked(g, 2), 100, mode="shuffle", **MD5)))


@query("stitched_walk_supp_chain")
def _(s, d):
    """Without SQL: which segment a walk takes depends on the turns of all walks in every lap before; tests hold it against exact vectors."""
    g = graph(s, d, "supp_chain")
    return baselines.stitching(g, asked(g, 5), 50)


def _ppr_sql(name, r, score, extra=""):
    return O.with_graph(name, _W(r), select=f"select source, vertex, {O.rounded(score)} as score from w_visits join w_stats s using (source){extra}", q=O.sampled(20))


query("full_path_ppr_basket", _ppr_sql("basket", 50, "visits / moves"))(lambda s, d: estimators.full_path_ppr(_walks(s, d, "basket", 20, 50)).select("source", "vertex", tidy("score")))
query("full_path_walk_normalised", _ppr_sql("basket", 50, "0.15 * visits / 50"))(
    lambda s, d: estimators.full_path_ppr(_walks(s, d, "basket", 20, 50), "walks").select("source", "vertex", tidy("score")))
query("end_point_ppr_basket", _ppr_sql("basket", 50, "w_visits.ends / s.ends", " where w_visits.ends > 0"))(
    lambda s, d: estimators.end_point_ppr(_walks(s, d, "basket", 20, 50)).select("source", "vertex", tidy("score")))


@query("walk_database_answers", O.with_graph("supp_chain", _W(20), select=f"select source as query, vertex, {O.rounded('visits / moves')} as score from w_visits join w_stats using (source)", q=O.sampled(10)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    paths = cut(walks.walk_paths(g, sample_vertices(g, 15), 20, **MD5), "paths")
    return baselines.walk_database(paths, asked(g)).select("query", "vertex", tidy("score"))


_TAIL = f"""select vertex, {O.rounded('avg((d >= 0.02)::int)')} as over, {O.rounded('avg((d <= -0.02)::int)')} as under, {O.rounded(str(bounds.tail_bound(0.02, 200)))} as bound from (
    select p.vertex, coalesce(visits, 0) / moves - p.score as d from p_exact p cross join (select walk // 200 as run, count(*) as moves from w group by run) m
    left join (select walk // 200 as run, vertex, count(*) as visits from w group by all) x on x.run = m.run and x.vertex = p.vertex) group by vertex"""


@query("tail_frequency_supp_chain", O.with_graph("supp_chain", O.power_ctes(150), _W(4000), select=_TAIL, q=O.sampled(1)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    source = asked(g, 1)
    exact_scores = _truth(g, source, 150).withColumnRenamed("query", "source")
    out = estimators.tail_frequency(g, source.first()[0], 0.02, 200, exact_scores, runs=20, **MD5)
    return out.select("vertex", tidy("over"), tidy("under"), tidy("bound"))


# The grids hold the discounts, taxes and quantities of all order lines.
_GRID = "from (select distinct l_discount as gamma, (1000 * l_quantity)::int as walks, l_tax + 0.1::double as c from lineitem)"


@query("tail_bound_grid", f"select gamma, walks, c, {O.rounded('least(1, (1 + gamma * c / 10) / sqrt(c) * exp(-gamma * gamma * walks / 20))')} as bound {_GRID}")
def _(s, d):
    grid = E.table(s, d, "lineitem").select(F.col("l_discount").alias("gamma"), (1000 * F.col("l_quantity")).cast("int").alias("walks"), (F.col("l_tax") + 0.1).alias("c")).distinct()
    return grid.withColumn("bound", tidy(bounds.tail_bound_column(F.col("gamma"), F.col("walks"), F.col("c")), "bound"))


@query("walks_for_precision_grid", """
    select gamma, delta, ceil(20 / (gamma * gamma) * ln((1 + gamma * 0.15 / 10) / (delta * sqrt(0.15::double))))::bigint as walks
    from (select distinct l_discount as gamma, l_tax as delta from lineitem where l_discount > 0 and l_tax > 0)""")
def _(s, d):
    grid = E.table(s, d, "lineitem").where("l_discount > 0 and l_tax > 0").select(F.col("l_discount").alias("gamma"), F.col("l_tax").alias("delta")).distinct()
    return grid.withColumn("walks", bounds.walks_for_precision_column(F.col("gamma"), F.col("delta"), F.lit(0.15)))


@query("equivalent_walks", "select walks, round(walks / 0.15::double)::bigint as end_points from (select distinct l_quantity::int as walks from lineitem)")
def _(s, d):
    walks = E.table(s, d, "lineitem").select(F.col("l_quantity").cast("int").alias("walks")).distinct()
    return walks.withColumn("end_points", bounds.equivalent_endpoint_walks_column(F.col("walks")))


# ---------------------------------------------------------------- index

_ALL = "select vertex as query from v"
_EVERYONE = f"everyone as ({_ALL})"


def _index(g: Graph, r: int, **how) -> DataFrame:
    return index.build_index(g, r, path=shared_path(g.spark, "index"), **{**MD5, **how})


_ENTRIES = "select source, walks, moves, vertex, visits from w_visits join w_stats using (source)"


def _entries(idx: DataFrame) -> DataFrame:
    return index.index_entries(idx).select("source", "walks", "moves", "vertex", F.col("visits").cast("long").alias("visits"))


query("index_build_supp_chain", O.with_graph("supp_chain", _W(10), select=_ENTRIES, q=_ALL))(
    lambda s, d: _entries(index.build_index(graph(s, d, "supp_chain"), 10, path=shared_path(s, "index"), **MD5)))


@query("index_extend_equals_rebuild", O.with_graph("supp_chain", _W(15), select=_ENTRIES, q=_ALL))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return _entries(index.extend_index(_index(g, 5), g, 5, 10, **MD5))


@query("index_merge_seeds", O.with_graph("supp_chain", _W(5), _W(5, seed=11, name="x"), select="""
    select source, 10::bigint as walks, sum(visits) over (partition by source)::bigint as moves, vertex, visits from (
        select source, vertex, sum(visits)::bigint as visits from (select * from w_visits union all select * from x_visits) group by all)""", q=_ALL))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return _entries(index.merge_indexes(_index(g, 5), _index(g, 5, seed=11)))


@query("index_prune_two_visits", O.with_graph("supp_chain", _W(10), select=f"""
    select source, count(*) filter (where visits >= 2)::int as entries, {O.rounded('1 - sum(case when visits >= 2 then visits else 0 end) / sum(visits)')} as pruned from w_visits group by source""", q=_ALL))
def _(s, d):
    return index.prune_index(_index(graph(s, d, "supp_chain"), 10), 2).select("source", F.size("entries").alias("entries"), tidy("pruned"))


@query("index_stats_supp_chain", O.with_graph("supp_chain", _W(10), select=f"""
    select count(distinct source) as sources, count(*) as entries, {O.rounded('count(*) / count(distinct source)')} as mean_entries,
        {O.rounded('(select count(*) from v) * 10 / 0.15::double')} as bound, 12 * count(*) as raw_bytes,
        {O.rounded('12 * count(*) / (16.0::double * (select count(*) from e))')} as graph_ratio from w_visits""", q=_ALL))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return index.index_stats(_index(g, 10), g, 10)


_HUBS = "select vertex as query from (select dst as vertex, count(*) as n from e group by dst) order by n desc, vertex limit 50"


@query("hub_only_lookup", O.with_graph("basket", _W(20), select=f"select source as query, vertex, {O.rounded('visits / moves')} as score from w_visits join w_stats using (source)", q=_HUBS))
def _(s, d):
    g = graph(s, d, "basket")
    h = cut(baselines.hubs(g, 50), "hubs")
    return baselines.hub_only(g, _index(g, 20, sources=h), h.select(F.col("vertex").alias("query"))).select("query", "vertex", tidy("score"))


@query("hub_only_pushed", O.with_graph("basket", f"hubs as materialized ({_HUBS})", f"q as materialized ({O.sampled(5)})", _W(20, "hubs"), O.frontier_ctes(2), O.answer_cte(2, "w_visits", 20),
                                       select=f"select query, vertex, {O.rounded('score')} as score from ans"))
def _(s, d):
    g = graph(s, d, "basket")
    return baselines.hub_only(g, _index(g, 20, sources=baselines.hubs(g, 50)), asked(g, 5), laps=2).select("query", "vertex", tidy("score"))


# ---------------------------------------------------------------- decomposition

_MASS = f"select 'settled' as part, query, vertex, {O.rounded('mass')} as mass from settled union all select 'frontier', query, vertex, {O.rounded('mass')} from f{{}}"


def _parts(f: decompose.Frontier) -> DataFrame:
    return f.settled.select(F.lit("settled").alias("part"), "query", "vertex", tidy("mass")).unionByName(f.frontier.select(F.lit("frontier").alias("part"), "query", "vertex", tidy("mass")))


for _t in (1, 2, 5):
    query(f"frontier_vectors_T{_t}", O.with_graph("basket", O.frontier_ctes(_t), select=_MASS.format(_t), q=O.sampled(5)))(
        lambda s, d, t=_t: _parts(decompose.frontier_vectors(g := graph(s, d, "basket"), asked(g, 5), t)))
# Eight vertices that all order lines make up.
query("frontier_toy8", O.with_graph("line8", O.frontier_ctes(2), select=_MASS.format(2), q="select 1::bigint as query"))(
    lambda s, d: _parts(decompose.frontier_vectors(graph(s, d, "line8"), ids(s, 1), 2)))


def _batch_sql(name, laps, r, n=5, eps=0.0, select=None, q=None, tail=()):
    ctes = ([_W(r, "everyone")] if r else []) + [O.frontier_ctes(laps, eps), O.answer_cte(laps, "w_visits" if r else None, r or 1), *tail]
    return O.with_graph(name, _EVERYONE, *ctes, q=q or O.sampled(n), select=select or f"select query, vertex, {O.rounded('score')} as score from ans")


def _batch(s, d, name, laps, r, n=5, where="true", **how):
    g = graph(s, d, name)
    return decompose.batch_ppr(g, _index(g, r) if r else None, asked(g, n, where), laps, **how)


def _scores(df: DataFrame) -> DataFrame:
    return df.select("query", "vertex", tidy("score"))


query("batch_ppr_T2_R10", _batch_sql("basket", 2, 10))(lambda s, d: _scores(_batch(s, d, "basket", 2, 10)))
query("batch_ppr_T5_R10", _batch_sql("basket", 5, 10))(lambda s, d: _scores(_batch(s, d, "basket", 5, 10)))
query("batch_ppr_index_free_T7", _batch_sql("basket", 7, 0))(lambda s, d: _scores(_batch(s, d, "basket", 7, 0)))
query("batch_ppr_T0", _batch_sql("basket", 0, 10))(lambda s, d: _scores(_batch(s, d, "basket", 0, 10)))
query("batch_ppr_eps", _batch_sql("basket", 3, 10, eps=1e-3))(lambda s, d: _scores(_batch(s, d, "basket", 3, 10, eps=1e-3)))
query("batch_ppr_dangling", _batch_sql("part_supp_semi", 2, 10))(lambda s, d: _scores(_batch(s, d, "part_supp_semi", 2, 10)))
query("batch_ppr_shuffled_T2_R5", _batch_sql("supp_chain", 2, 5, 10))(lambda s, d: _scores(_batch(s, d, "supp_chain", 2, 5, 10, mode="shuffle")))
query("batch_ppr_shuffled_basket", _batch_sql("basket", 2, 5))(lambda s, d: _scores(_batch(s, d, "basket", 2, 5, mode="shuffle")))
query("batch_ppr_shuffled_cust_part", _batch_sql("cust_part", 2, 2, q=O.sampled(5, where=CUSTOMERS)))(lambda s, d: _scores(_batch(s, d, "cust_part", 2, 2, where=CUSTOMERS, mode="shuffle")))


@query("batch_ppr_shuffled_hubs_part_supp", _batch_sql("part_supp_semi", 3, 0))
def _(s, d):
    """Every vertex of more than five edges dealt as a hub."""
    g = build_graph(E.GRAPHS["part_supp_semi"](s, d), push_limit=5)
    return _scores(decompose.batch_ppr(g, None, asked(g, 5), 3, mode="shuffle"))


query("batch_ppr_adaptive", _batch_sql("basket", 5, 0))(lambda s, d: _scores(_batch(s, d, "basket", 1, 0, residual=0.45)))


@query("recursive_T2", _batch_sql("supp_chain", 2, 5, 3))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return _scores(baselines.recursive(g, _index(g, 5), asked(g, 3), 2))


@query("decompose_once", O.with_graph("basket", _EVERYONE, _W(10, "everyone"), O.frontier_ctes(1), q=O.sampled(5), select=f"""
    select query, vertex, {O.rounded('sum(s)')} as score from (
        select query, x.vertex, mass * 0.15 * visits / 10 as s from f1 join w_visits x on x.source = f1.vertex union all select query, query, 0.15 from q) group by query, vertex"""))
def _(s, d):
    g = graph(s, d, "basket")
    vectors = estimators.full_path_ppr(walks.simulate_walks(g, None, 10, **MD5), "walks")
    return _scores(decompose.decompose_once(g, vectors, asked(g, 5)))


@query("sql_surface_lap_and_close", O.with_graph("supp_chain", _EVERYONE, _W(5, "everyone"), O.frontier_ctes(1), q=O.sampled(5), select=f"""
    select query, x.vertex, {O.rounded('sum(mass * 0.15 * visits / 5)')} as score from f1 join w_visits x on x.source = f1.vertex group by query, x.vertex"""))
def _(s, d):
    g = graph(s, d, "supp_chain")
    register_views(g, _index(g, 5), decompose.seeds(g, asked(g, 5)))
    cut(sql_lap(s, 0.15), "lap").createOrReplaceTempView("ppr_frontier")
    return sql_close(s, 0.15).select("query", "vertex", tidy("score"))


_TOP = f"select query, rank, vertex, {O.rounded('score')} as score from r where rank <= 10"


def _top(df: DataFrame) -> DataFrame:
    return df.select("query", F.col("rank").cast("long").alias("rank"), "vertex", tidy("score"))


@query("topk_recommend_parts", _batch_sql(
    "cust_part", 4, 0, q=O.sampled(10, where=CUSTOMERS), tail=(f"""fresh as (select * from ans where vertex >= {2 * K}
        and not exists (select 1 from e where e.src = ans.query and e.dst = ans.vertex))""", O.ranked("fresh", "r")), select=_TOP))
def _(s, d):
    """Parts for customers, without those that they have bought: four laps settle mass at distance three, where other customers' parts lie."""
    g = graph(s, d, "cust_part")
    ppr = decompose.batch_ppr(g, None, asked(g, 10, CUSTOMERS), 4)
    fresh = ppr.where(F.col("vertex") >= 2 * K).join(g.edges.select(F.col("src").alias("query"), F.col("dst").alias("vertex")), ["query", "vertex"], "left_anti")
    return _top(decompose.top_k(fresh, 10))


@query("topk_filtered_brand", _batch_sql(
    "basket", 2, 10, q=O.sampled(5), tail=("b as (select ans.* from ans join part on p_partkey = vertex where p_brand = (select min(p_brand) from part))", O.ranked("b", "r")), select=_TOP))
def _(s, d):
    part = E.table(s, d, "part")
    brand = part.join(F.broadcast(part.agg(F.min("p_brand").alias("p_brand"))), "p_brand").select(F.col("p_partkey").alias("vertex"))
    return _top(decompose.top_k(_batch(s, d, "basket", 2, 10).join(brand, "vertex", "left_semi"), 10))


@query("topk_docs_quality", _batch_sql(
    "doc_word", 4, 0, q=O.sampled(5, where=DOCUMENTS), tail=(f"b as (select ans.* from ans join labels on doc_id + {8 * K} = vertex where quality = 1 and vertex <> query)", O.ranked("b", "r")), select=_TOP))
def _(s, d):
    """Other documents of good quality, two words away or more."""
    good = E.table(s, d, "labels").where("quality = 1").select(E.vertex("document", "doc_id").alias("vertex"))
    others = _batch(s, d, "doc_word", 4, 0, where=DOCUMENTS).where("vertex <> query")
    return _top(decompose.top_k(others.join(good, "vertex", "left_semi"), 10))


@query("pair_scores", _batch_sql("basket", 2, 10, select=f"""
    select a.query, b.query as vertex, {O.rounded('coalesce(score, 0)')} as score from q a cross join q b left join ans on ans.query = a.query and ans.vertex = b.query"""))
def _(s, d):
    g = graph(s, d, "basket")
    q = cut(asked(g, 5), "q")
    pairs = q.crossJoin(q.select(F.col("query").alias("vertex")))  # five by five
    return _scores(decompose.pair_scores(decompose.batch_ppr(g, _index(g, 10), q, 2), pairs))


# ---------------------------------------------------------------- measures and experiments

_KS = [1, 10, 20, 100]
_DEEP = [1, 10, 100, 1000, 5000]
_MEAN = f"select k, {O.rounded('avg(rag)')} as rag, count(*) as queries from {{}} group by k"


def _eval_sql(name: str, n: int, *ctes: str, select: str, laps: int = 60, q: str | None = None) -> str:
    return O.with_graph(name, O.power_ctes(laps), *ctes, q=q or O.sampled(n), select=select)


def _truth(g: Graph, q: DataFrame, laps: int = 60) -> DataFrame:
    return cut(baselines.power_iteration_online(g, q, tol=0.0, max_iter=laps), "truth")


def _around(g: Graph, q: DataFrame) -> Graph:
    """What the queries reach of a large graph, which gives the same vectors and walks."""
    return reached(g, q.select(F.col("query").alias("vertex")))


def _by_walks_sql(name: str, rs: list[int], ks: list[int] = _KS, n: int = 8) -> str:
    ctes, rows = [], []
    for r in rs:
        w = f"w{r}"
        ctes += [O.walk_ctes(r, name=w), f"{w}_f as (select source as query, vertex, visits as score from {w}_visits)", f"{w}_y as (select source as query, vertex, ends as score from {w}_visits where ends > 0)",
                 O.rag_ctes("p_exact", f"{w}_f", ks, f"{w}_rf"), O.rag_ctes("p_exact", f"{w}_y", ks, f"{w}_ry")]
        for label, cte in (("full_path", f"{w}_rf"), ("end_point", f"{w}_ry")):
            rows.append(f"select '{label}' as estimator, {r} as walks, k, {O.rounded('avg(rag)')} as rag, count(*) as queries from {cte} group by k")
    return _eval_sql(name, n, *ctes, select=" union all ".join(rows))


def _rag_by_walks(s, d, name, rs, ks=_KS):
    g = graph(s, d, name)
    q = cut(asked(g, 8), "q")
    g = _around(g, q)
    return evaluate.rag_by_walks(g, q, _truth(g, q), rs, ks, **MD5).withColumn("rag", tidy("rag"))


query("rag_by_R_supp_chain", _by_walks_sql("supp_chain", [1, 10, 100]))(lambda s, d: _rag_by_walks(s, d, "supp_chain", [1, 10, 100]))
query("rag_by_k_user_flow", _by_walks_sql("user_flow", [100]))(lambda s, d: _rag_by_walks(s, d, "user_flow", [100]))
for _name in ("basket", "cust_part", "page_links_sym", "doc_word"):
    query(f"rag_by_R_{_name}", _by_walks_sql(_name, [1, 10, 100, 1000], [20, 200]))(lambda s, d, n=_name: _rag_by_walks(s, d, n, [1, 10, 100, 1000], [20, 200]))
    query(f"rag_by_k_{_name}", _by_walks_sql(_name, [1000, 6700], _DEEP, 4))(lambda s, d, n=_name: _rag_by_k(s, d, n))


def _rag_by_k(s, d, name):
    """Both estimators at 1000 and 6700 walks, by k: the longer end-point sample is as good as the shorter full-path one."""
    g = graph(s, d, name)
    q = cut(asked(g, 4), "q")
    g = _around(g, q)
    return evaluate.rag_by_walks(g, q, _truth(g, q), [1000, 6700], _DEEP, **MD5).withColumn("rag", tidy("rag"))


def _by_laps_sql(name, settings, ks, n=8):
    """settings: walks -> depths; walks = 0 is index-free."""
    top = max(t for ts in settings.values() for t in ts)
    ctes, rows = ["everyone as (select vertex as query from v)", O.frontier_ctes(top)], []
    parts = {t: " union all ".join(f"select query, vertex, 0.15 * mass as mass from f{i}" for i in range(t)) or "select * from f0 where false" for t in range(top + 1)}
    for r, depths in settings.items():
        if r:
            ctes.append(O.walk_ctes(r, "everyone", name=f"w{r}"))
        for t in depths:
            closed = f" union all select query, x.vertex, mass * 0.15 * visits / {r} from f{t} f join w{r}_visits x on x.source = f.vertex" if r else ""
            ctes.append(f"a{r}_{t} as materialized (select query, vertex, sum(mass) / (sum(sum(mass)) over (partition by query)) as score from ({parts[t]}{closed}) group by query, vertex)")
            ctes.append(O.rag_ctes("p_exact", f"a{r}_{t}", ks, f"r{r}_{t}"))
            rows.append(f"select {r} as walks, {t} as laps, k, {O.rounded('avg(rag)')} as rag, count(*) as queries from r{r}_{t} group by k")
    return _eval_sql(name, n, *ctes, select=" union all ".join(rows))


def _rag_by_laps(s, d, name, settings, ks, n=8):
    g = graph(s, d, name)
    q = cut(asked(g, n), "q")
    g = _around(g, q)
    exact_vectors = _truth(g, q)
    parts = [evaluate.rag_by_laps(g, q, exact_vectors, [r], ts, ks, **MD5) for r, ts in settings.items()]
    return reduce(DataFrame.unionByName, parts).withColumn("rag", tidy("rag"))


_FREE, _STORED = {0: [1, 2, 3, 5, 7]}, {10: [0, 1, 2, 5], 100: [0, 1, 2]}
query("rag_by_T_index_free", _by_laps_sql("basket", _FREE, _KS))(lambda s, d: _rag_by_laps(s, d, "basket", _FREE, _KS))
query("rag_by_T_R10_R100", _by_laps_sql("basket", _STORED, [20, 200]))(lambda s, d: _rag_by_laps(s, d, "basket", _STORED, [20, 200]))
# On the larger graphs the index of ten walks stands for both.
for _name in ("cust_part", "page_links_sym", "doc_word"):
    _both = {0: [1, 3, 5, 7], 10: [0, 1, 2, 5]}
    query(f"rag_by_T_{_name}", _by_laps_sql(_name, _both, [20, 200], 4))(lambda s, d, n=_name, b=_both: _rag_by_laps(s, d, n, b, [20, 200], 4))


_CS = (0.1, 0.2, 0.3)


@query("rag_by_teleport_supp_chain", _eval_sql(
    "supp_chain", 5, *(x for c in _CS for x in (O.power_ctes(60, c=c, name=f"c{int(10 * c)}"), O.rag_ctes("p_exact", f"c{int(10 * c)}_exact", [10, 50], f"r{int(10 * c)}"))),
    select=" union all ".join(f"select {c}::double as c, k, {O.rounded('avg(rag)')} as rag, count(*) as queries from r{int(10 * c)} group by k" for c in _CS)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    q = cut(asked(g, 5), "q")
    base = _truth(g, q)
    out = None
    for c in _CS:
        other = baselines.power_iteration_online(g, q, c=c, tol=0.0, max_iter=60)
        row = measures.mean_rag(measures.rag(base, other, [10, 50])).select(F.lit(c).alias("c"), "k", tidy("rag"), "queries")
        out = row if out is None else out.unionByName(row)
    return out


_STRATA = "strata as materialized (select vertex as query, least(length(bin(out_deg)), 10)::int as bucket from v where out_deg > 0 qualify row_number() over (partition by least(length(bin(out_deg)), 10) order by md5('7|' || vertex), vertex) <= 2)"


@query("rag_rollup_bucket", O.with_graph(
    "page_links_sym", _STRATA, "q as (select query from strata)", O.power_ctes(40), _W(50), "app as (select source as query, vertex, visits as score from w_visits)", O.rag_ctes("p_exact", "app", [5, 20]),
    select=f"select k, bucket, {O.rounded('avg(rag)')} as rag, count(*) as queries from rag join strata using (query) group by rollup (k, bucket) having k is not null"))
def _(s, d):
    g = graph(s, d, "page_links_sym")
    strata = cut(evaluate.stratified(g, 2), "strata")
    ppr = estimators.full_path_ppr(walks.simulate_walks(g, strata.select(F.col("query").alias("vertex")), 50, **MD5))
    rags = measures.rag(_truth(g, strata, 40), ppr, [5, 20])
    return measures.mean_rag(rags, strata.select("bucket", F.col("query").alias("vertex"))).select("k", "bucket", tidy("rag"), "queries")


@query("rag_strata_doc_word", O.with_graph(
    "doc_word", _STRATA.replace("<= 2)", "<= 10)"), "q as (select query from strata)", O.power_ctes(24), _W(100),
    *(x for name, value in (("whole", "visits"), ("ends", "ends")) for x in (f"{name} as (select source as query, vertex, {value} as score from w_visits where {value} > 0)", O.rag_ctes("p_exact", name, [20, 200], f"rag_{name}"))),
    select=" union all ".join(f"select '{label}' as estimator, k, bucket, {O.rounded('avg(rag)')} as rag, count(*) as queries from rag_{name} join strata using (query) group by rollup (k, bucket) having k is not null"
                              for label, name in (("full_path", "whole"), ("end_point", "ends")))))
def _(s, d):
    """Ten vertices of each of the ten degree buckets, both estimators at 100 walks, against vectors of 24 laps."""
    g = graph(s, d, "doc_word")
    strata = cut(evaluate.stratified(g), "strata")
    w = walks.simulate_walks(g, strata.select(F.col("query").alias("vertex")), 100, **MD5)
    w = walks.Walks(cut(w.visits, "visits"), 100, w.c)
    exact_vectors = _truth(g, strata, 24)
    placed = strata.select("bucket", F.col("query").alias("vertex"))
    rows = [measures.mean_rag(measures.rag(exact_vectors, x, [20, 200]), placed).select(F.lit(name).alias("estimator"), "k", "bucket", tidy("rag"), "queries")
            for name, x in (("full_path", estimators.full_path_ppr(w)), ("end_point", estimators.end_point_ppr(w)))]
    return rows[0].unionByName(rows[1])


_ERR = _eval_sql("supp_chain", 10, _W(50), f"""d as (select coalesce(x.query, y.query) as query, coalesce(y.score, 0) - coalesce(x.score, 0) as d from p_exact x full join
    (select source as query, vertex, visits / moves as score from w_visits join w_stats using (source)) y on x.query = y.query and x.vertex = y.vertex)""", select=f"""
    select query, {O.rounded('max(abs(d))')} as max_error, {O.rounded('sum(abs(d))')} as l1_error, {O.rounded('greatest(max(d), 0)')} as over, {O.rounded('greatest(-min(d), 0)')} as under from d group by query""")


@query("score_error_full_path", _ERR)
def _(s, d):
    g = graph(s, d, "supp_chain")
    q = cut(asked(g, 10), "q")
    e = measures.score_error(_truth(g, q), estimators.full_path_ppr(walks.simulate_walks(g, q.select(F.col("query").alias("vertex")), 50, **MD5)))
    return e.select("query", *[tidy(c) for c in ("max_error", "l1_error", "over", "under")])


@query("precision_at_k", _eval_sql("supp_chain", 10, O.frontier_ctes(2), O.answer_cte(2, None, 1), O.ranked("p_exact", "x"), O.ranked("ans", "y"), select=f"""
    select x.query, {O.rounded('count(y.vertex) / count(*)')} as precision from (select * from x where rank <= 20) x
    left join (select * from y where rank <= 20) y on x.query = y.query and x.vertex = y.vertex group by x.query"""))
def _(s, d):
    g = graph(s, d, "supp_chain")
    q = cut(asked(g, 10), "q")
    return measures.precision_at_k(_truth(g, q), decompose.batch_ppr(g, None, q, 2), 20).select("query", tidy("precision"))


@query("rank_agreement", _eval_sql("supp_chain", 10, O.frontier_ctes(2), O.answer_cte(2, None, 1), O.ranked("p_exact", "x"), O.ranked("ans", "y"), select=f"""
    select x.query, count(*) as common, {O.rounded('corr(x.rank, y.rank)')} as rho from x join y on x.query = y.query and x.vertex = y.vertex
    where x.rank <= 50 and y.rank <= 50 group by x.query"""))
def _(s, d):
    g = graph(s, d, "supp_chain")
    q = cut(asked(g, 10), "q")
    return measures.rank_agreement(_truth(g, q), decompose.batch_ppr(g, None, q, 2), 50).select("query", "common", tidy("rho"))


_LOADS = "paths1 as (select query, dst as vertex from q join e on src = query), paths2 as (select query, dst as vertex from paths1 join e on src = vertex)"
_LOADED = "select query, count(*) as recursive, count(distinct vertex) as shared from paths2 group by query"
query("index_loads_toy8", O.with_graph("line8", _LOADS, select=_LOADED, q="select 1::bigint as query"))(lambda s, d: measures.index_loads(graph(s, d, "line8"), ids(s, 1), 2))
query("index_loads_basket", O.with_graph("basket", _LOADS, select=_LOADED, q=O.sampled(10)))(lambda s, d: measures.index_loads(g := graph(s, d, "basket"), asked(g, 10), 2))


@query("frontier_growth_basket", O.with_graph("basket", O.frontier_ctes(3), q=O.sampled(5), select=" union all ".join(
    f"select {t} as lap, (select count(*) from (select distinct query, vertex from ({' union all '.join(f'select query, vertex from f{i}' for i in range(t)) or 'select query, vertex from f0 where false'}))) as settled, (select count(*) from f{t}) as frontier" for t in range(4))))
def _(s, d):
    g = graph(s, d, "basket")
    return measures.frontier_growth(g, asked(g, 5), 3)


@query("residual_mass_by_T", O.with_graph("part_supp_semi", O.frontier_ctes(3), q=O.sampled(10), select=f"select query, {O.rounded('sum(mass)')} as residual from f3 group by query"))
def _(s, d):
    g = graph(s, d, "part_supp_semi")
    return measures.residual_mass(decompose.frontier_vectors(g, asked(g, 10), 3)).select("query", tidy("residual"))


@query("dropped_mass_eps", O.with_graph("basket", O.frontier_ctes(3, 2e-3), q=O.sampled(5), select=f"""
    select query, {O.rounded('sum(mass)')} as dropped from (select * from g1 where mass < 2e-3 union all select * from g2 where mass < 2e-3 union all select * from g3 where mass < 2e-3) group by query"""))
def _(s, d):
    g = graph(s, d, "basket")
    return decompose.frontier_vectors(g, asked(g, 5), 3, eps=2e-3).dropped.select("query", tidy("dropped"))


@query("effective_walks_T1", O.with_graph("basket", O.frontier_ctes(1), q=O.sampled(10), select=f"""
    select query, {O.rounded('100 * sum(mass) * sum(mass) / sum(mass * mass)')} as walks, {O.rounded('0.85::double')} as shrink from f1 group by query"""))
def _(s, d):
    g = graph(s, d, "basket")
    return decompose.effective_walks(decompose.frontier_vectors(g, asked(g, 10), 1), 100).select("query", tidy("walks"), tidy("shrink"))


@query("query_scaling_rows", O.with_graph("cust_part", q=f"select vertex as query from v where {CUSTOMERS}", select="""
    select n, count(*) as reached from (values (1), (10), (100)) t(n) join (select query, row_number() over (order by md5('7|' || query), query) as r from q) on r <= n
    join e a on a.src = query join e b on b.src = a.dst group by n""").replace("count(*) as reached", "count(distinct (query, b.dst)) as reached"))
def _(s, d):
    """Frontier entries after two laps by batch size."""
    g = graph(s, d, "cust_part")
    out = None
    for n in (1, 10, 100):
        row = decompose.frontier_vectors(g, asked(g, n, CUSTOMERS), 2).frontier.agg(F.lit(n).alias("n"), F.count("*").alias("reached"))
        out = row if out is None else out.unionByName(row)
    return out


# ---------------------------------------------------------------- baselines and planner

_LOOK = f"select source as query, vertex, {O.rounded('visits / moves')} as score from w_visits join w_stats using (source)"


@query("lookup_R100", O.with_graph("supp_chain", _W(100), select=_LOOK, q=O.sampled(10)))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return _scores(baselines.precomputed_lookup(index.build_index(g, 100, path=shared_path(s, "big"), **MD5), asked(g, 10)))


@query("online_walk_R200", O.with_graph("basket", _W(200), select=_LOOK, q=O.sampled(5)))
def _(s, d):
    g = graph(s, d, "basket")
    return _scores(baselines.online_walking(g, asked(g, 5), 200, **MD5))


@query("online_end_points_R200", O.with_graph("basket", _W(200), q=O.sampled(5), select=f"select source as query, vertex, {O.rounded('w_visits.ends / s.ends')} as score from w_visits join w_stats s using (source) where w_visits.ends > 0"))
def _(s, d):
    g = graph(s, d, "basket")
    return _scores(baselines.online_end_points(g, asked(g, 5), 200, **MD5))


@query("per_query_loop", _batch_sql("supp_chain", 2, 5, 3))
def _(s, d):
    g = graph(s, d, "supp_chain")
    out = None
    for part in decompose.per_query_loop(g, _index(g, 5), [r[0] for r in asked(g, 3).collect()], 2):
        out = part if out is None else out.unionByName(part)
    return _scores(out)


@query("plan_budget_grid", O.with_graph("basket", select="""
    select budget, walks, (case when walks >= 2000 then 0 when walks >= 100 then ceil(2 - 2 * ln((1 + walks) / 101.0) / ln(2001 / 101.0) - 1e-9)
        when walks >= 10 then ceil(5 - 3 * ln((1 + walks) / 11.0) / ln(101 / 11.0) - 1e-9) else ceil(7 - 2 * ln(1 + walks) / ln(11.0) - 1e-9) end)::int as laps from (
        select budget, floor(budget * 0.15::double / ((select count(*) from v) * 12))::bigint as walks from (values (100000::bigint), (10000000), (1000000000)) t(budget))"""))
def _(s, d):
    return planner.budget_grid(graph(s, d, "basket"), [100_000, 10_000_000, 1_000_000_000])


_SIZES = "select distinct {}count(*) as queries from events group by rollup (date_trunc('day', ts), user_id)"


def _batch_sizes(s, d) -> DataFrame:
    """Batch sizes of the requests: of a user's day, of a day, of all."""
    return E.table(s, d, "events").rollup(F.date_trunc("day", "ts"), "user_id").count().select(F.col("count").alias("queries")).distinct()


@query("plan_strategy", f"""
    select queries::int as queries, walks, stored_walks, case when stored_walks >= 2000 and queries <= 10 then 'lookup' when walks >= 2000 then 'lookup' when walks > 0 then 'decompose' else 'index_free' end as method,
        case when (stored_walks >= 2000 and queries <= 10) or walks >= 2000 then 0 when walks >= 100 then 2 when walks >= 10 then 5 else 7 end as laps
    from ({_SIZES.format('')}) a, (values (0), (10), (100), (2000)) b(walks), (values (0), (2000)) c(stored_walks)""")
def _(s, d):
    return planner.plan_grid(_batch_sizes(s, d), [0, 10, 100, 2000], [0, 2000])


_SIZED = ("user_flow", "part_supp")
_SIZES_OF = " union all ".join(
    f"select (select count(*) from (select src from ({O.EDGES[x]}) union select dst from ({O.EDGES[x]}))) as vertices, (select count(*) from ({O.EDGES[x]})) as edges" for x in _SIZED)


@query("plan_strategy_by_size", f"""
    with recursive g as (select queries, vertices, edges, edges::double / vertices as d from ({_SIZES.format('100 * ')}) a, ({_SIZES_OF}) b),
    w as (select *, (select sum(least(pow(d, t + 1), edges, d / 1e-4)) from range(7) r(t)) as work from g)
    select queries, vertices, edges, case when 40 * (edges + 5e7) + queries * (2000 / 0.15) < 7 * (edges + 5e7) + queries * work then 'walk' else 'index_free' end as method from w""")
def _(s, d):
    """Without any index: walking online against settling, by graph size, for batches a hundred times the requests of the stream."""
    sizes = reduce(DataFrame.unionByName, [graph_stats(graph(s, d, x)).select("vertices", "edges") for x in _SIZED])
    return planner.plan_by_size(_batch_sizes(s, d).select((100 * F.col("queries")).alias("queries")), sizes)


# ---------------------------------------------------------------- streams and surrounding operators


@query("stream_windows", "select date_trunc('day', ts)::timestamp as start, count(*) as requests from events group by all")
def _(s, d):
    return buffer.drain(buffer.windowed(buffer.query_events(s, d), "1 day").select("start", "requests"), "ripple_windows", "complete")


@query("stream_sliding", """
    select w as start, count(*) as requests from (select unnest([date_trunc('day', ts)::timestamp - interval 1 day, date_trunc('day', ts)::timestamp]) as w from events) group by w""")
def _(s, d):
    return buffer.drain(buffer.windowed(buffer.query_events(s, d), "2 days", "1 day").select("start", "requests"), "ripple_sliding", "complete")


@query("stream_sessions", f"""
    with e as (select user_id + {K} as query, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end as fresh from events),
    n as (select *, sum(fresh) over (partition by query order by ts rows unbounded preceding) as run from e)
    select query, min(ts)::timestamp as start, count(*) as requests from n group by query, run""")
def _(s, d):
    return buffer.drain(buffer.sessions(buffer.query_events(s, d)), "ripple_sessions", "complete")


@query("stream_per_query_state", f"select user_id + {K} as query, count(*) as requests, max(ts)::timestamp as last from events group by user_id")
def _(s, d):
    return buffer.drain(buffer.per_query_state(buffer.query_events(s, d)), "ripple_state", "update").groupBy("query").agg(F.max("requests").alias("requests"), F.max("last").alias("last"))


@query("stream_query_batches", _batch_sql(
    "cust_part", 1, 0, q=f"select distinct user_id + {K} as query from events", tail=(O.ranked("ans", "r"),), select=_TOP))
def _(s, d):
    """Answers to every request of the stream."""
    return _answered(s, d)


def _answered(s, d):
    g = graph(s, d, "cust_part")
    path = shared_path(s, "answers")
    buffer.answer_batches(g, None, buffer.query_events(s, d), path, laps=1).awaitTermination()
    return _top(s.read.parquet(f"{path}/batch=*"))


@query("op_range_join_bucket", O.with_graph("doc_word", select="""
    select lo, hi, count(*) as vertices from (select (1 << (i - 1))::bigint as lo, (case when i = 10 then 1 << 40 else 1 << i end)::bigint as hi from range(1, 11) t(i))
    join v on out_deg >= lo and out_deg < hi group by lo, hi""").replace("1 << 40", "1099511627776").replace("(1 << (i - 1))", "pow(2, i - 1)").replace("1 << i", "pow(2, i)"))
def _(s, d):
    """Degree intervals by a range join with a ten-row table."""
    b = s.createDataFrame([(1 << (i - 1), 1 << 40 if i == 10 else 1 << i) for i in range(1, 11)], "lo long, hi long")
    v = graph(s, d, "doc_word").vertices
    return v.join(F.broadcast(b), (v.out_deg >= b.lo) & (v.out_deg < b.hi)).groupBy("lo", "hi").agg(F.count("*").alias("vertices"))


@query("op_asof_snapshot", f"""
    with snaps as (select distinct date_trunc('month', o_orderdate)::timestamp as built from orders),
    r as (select event_id, ts from events)
    select event_id, (select max(built) from snaps where built <= ts) as built from r""")
def _(s, d):
    """Each request with the newest snapshot built before it: a union, ordered once, carrying the last snapshot on.

    Snapshots are few, so requests are dealt by month and the last snapshot before each month is attached to it.
    """
    snaps = E.table(s, d, "orders").select(F.date_trunc("month", "o_orderdate").alias("built")).distinct()
    ev = E.table(s, d, "events").select("event_id", "ts", F.date_trunc("month", "ts").alias("month"))
    months = ev.select("month").distinct()
    timeline = snaps.select(F.col("built").alias("at"), "built").unionByName(months.select(F.col("month").alias("at"), F.lit(None).cast("timestamp").alias("built")))
    merged = timeline.groupBy("at").agg(F.max("built").alias("built"))
    carried = merged.withColumn("built", F.last("built", True).over(Window.orderBy("at").rowsBetween(Window.unboundedPreceding, 0)))  # one row a month
    return ev.join(carried.withColumnRenamed("at", "month"), "month", "left").select("event_id", "built")


@query("op_cube_degrees", O.with_graph("part_supp_semi", select=f"""
    select kind, bucket, count(*) as vertices, {O.rounded('avg(out_deg)')} as mean_degree from (
        select case when vertex >= {3 * K} then 'supplier' else 'part' end as kind, least(length(bin(out_deg)), 10)::int as bucket, out_deg from v where out_deg > 0) group by cube (kind, bucket)"""))
def _(s, d):
    b = degree_buckets(graph(s, d, "part_supp_semi")).withColumn("kind", F.when(F.col("vertex") >= 3 * K, "supplier").otherwise("part"))
    return b.cube("kind", "bucket").agg(F.count("*").alias("vertices"), tidy(F.avg("out_deg"), "mean_degree"))


@query("op_setops_topk", _eval_sql("supp_chain", 5, O.frontier_ctes(2), O.answer_cte(2, None, 1), O.ranked("p_exact", "x"), O.ranked("ans", "y"), select="""
    select 'both' as side, * from (select query, vertex from x where rank <= 10 intersect select query, vertex from y where rank <= 10)
    union all select 'missed', * from (select query, vertex from x where rank <= 10 except select query, vertex from y where rank <= 10)"""))
def _(s, d):
    g = graph(s, d, "supp_chain")
    q = cut(asked(g, 5), "q")
    x = decompose.top_k(_truth(g, q), 10).select("query", "vertex")
    y = decompose.top_k(decompose.batch_ppr(g, None, q, 2), 10).select("query", "vertex")
    return x.intersect(y).select(F.lit("both").alias("side"), "query", "vertex").unionByName(x.subtract(y).select(F.lit("missed").alias("side"), "query", "vertex"))


@query("op_cumulative_mass", _batch_sql("supp_chain", 2, 0, tail=(O.ranked("ans", "r"),), select=f"""
    select query, vertex, rank, {O.rounded('sum(score) over (partition by query order by rank) / sum(score) over (partition by query)')} as mass from r"""))
def _(s, d):
    g = graph(s, d, "supp_chain")
    return measures.cumulative_mass(decompose.batch_ppr(g, None, asked(g, 5), 2)).select("query", "vertex", F.col("rank").cast("long").alias("rank"), tidy("mass"))


@query("op_udtf_entries", O.with_graph("supp_chain", _W(10), select=f"select source, vertex, {O.rounded('visits / moves')} as score from w_visits join w_stats using (source)", q=_ALL))
def _(s, d):
    idx = _index(graph(s, d, "supp_chain"), 10)
    return idx.lateralJoin(IndexEntries(F.col("entries").outer(), F.col("moves").outer())).select("source", "vertex", tidy("score"))


@query("op_udtf_walks", O.with_graph("basket", _W(20), select="select source, vertex, visits, ends from w_visits", q=O.sampled(5)))
def _(s, d):
    g = graph(s, d, "basket")
    sources = sample_vertices(g, 5).withColumnRenamed("vertex", "source")
    return sources.lateralJoin(walker(g, rng="md5")(F.col("source").outer(), F.lit(20))).select("source", "vertex", "visits", "ends")


@query("op_json_graph", f"select distinct user_id + {7 * K} as src, json_extract(props, '$.k')::bigint as dst from events where json_extract(props, '$.k') is not null")
def _(s, d):
    return E.event_keys(s, d)


@query("op_snapshot_edges", f"""
    with y as (select distinct year(o_orderdate)::bigint as year, o_custkey + {K} as src, l_partkey + {2 * K} as dst from orders join lineitem on o_orderkey = l_orderkey)
    select year, count(*) as edges, count(*) filter (where not exists (select 1 from y b where b.src = y.src and b.dst = y.dst and b.year = y.year - 1)) as added from y group by year""")
def _(s, d):
    """Edges of each year's snapshot, and those that the year before lacks."""
    y = cut(E.yearly_orders(s, d), "years")
    fresh = y.join(y.withColumn("year", F.col("year") + 1), ["year", "src", "dst"], "left_anti").groupBy("year").agg(F.count("*").alias("added"))
    return y.groupBy("year").agg(F.count("*").alias("edges")).join(fresh, "year", "left").select("year", "edges", F.coalesce("added", F.lit(0)).alias("added"))


# ---------------------------------------------------------------- the driver's view


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Batched decomposition for ten sampled parts, ten walks per vertex, two laps, the ten best of each."""
    g = graph(spark, sf_dir, "basket")
    return _top(decompose.batch_ppr(g, _index(g, 10), asked(g, 10), 2, k=10))


query("flagship_basket", _batch_sql("basket", 2, 10, 10, tail=(O.ranked("ans", "r"),), select=_TOP))(flagship)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
