"""DuckDB SQL that recomputes the registered queries from the given tables."""

from __future__ import annotations

K = 10**12
#: Keeps values that end on a 5 from flipping with the order of summation.
NUDGE = "1.7e-12"


def rounded(x: str) -> str:
    return f"round({x} + {NUDGE}, 10)"


def _named(prefix: str, x: str) -> str:
    return f"(-1 - ('0x' || substr(md5('{prefix}:' || {x}), 1, 13))::bigint)"


def _both(sql: str) -> str:
    return f"with e0 as ({sql}) select src, dst from e0 union select dst, src from e0"


_GEO = f"""
    select o_orderkey + {4 * K} as src, o_custkey + {K} as dst from orders
    union select c_custkey + {K}, c_nationkey + {5 * K} from customer
    union select s_suppkey + {3 * K}, s_nationkey + {5 * K} from supplier
    union select n_nationkey + {5 * K}, n_regionkey + {6 * K} from nation"""
_PAGES = f"""
    with p as (select page_id + {9 * K} as src, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) as t from pages),
    h as (select page_id + {9 * K} as src, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as t from pages)
    select distinct src, {_named('path', 't')} as dst from p union select src, {_named('host', 't')} from h where t <> ''"""

#: src, dst of every graph.
EDGES = {
    "basket": """
        select distinct src, dst from (
            select l_partkey as src, lead(l_partkey) over (
                partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) as dst from lineitem)
        where dst is not null and src <> dst""",
    "cust_part": _both(f"select distinct o_custkey + {K} as src, l_partkey + {2 * K} as dst from orders join lineitem on o_orderkey = l_orderkey"),
    "part_supp": f"select distinct l_partkey + {2 * K} as src, l_suppkey + {3 * K} as dst from lineitem",
    "part_supp_semi": f"""
        with e0 as (select distinct l_partkey + {2 * K} as src, l_suppkey + {3 * K} as dst from lineitem)
        select src, dst from e0 union select dst, src from e0 where dst % 5 <> 0""",
    "supp_chain": """
        select distinct a.l_suppkey as src, b.l_suppkey as dst from lineitem a
        join lineitem b on a.l_orderkey = b.l_orderkey and b.l_linenumber = a.l_linenumber + 1 where a.l_suppkey <> b.l_suppkey""",
    "user_flow": """
        select distinct src, dst from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from events)
        where dst is not null and src <> dst""",
    "geo_tree": _GEO,
    "geo_tree_sym": _both(_GEO),
    "page_links": _PAGES,
    "page_links_sym": _both(f"select * from ({_PAGES})"),
    "doc_word": _both(f"""
        select distinct src, {_named('word', 'w')} as dst
        from (select doc_id + {8 * K} as src, unnest(regexp_extract_all(lower(text), '\\p{{L}}+')) as w from documents)"""),
    "conv_chain": f"""
        select distinct src, dst from (select conv_id * 1000 + turn + {10 * K} as src,
            lead(conv_id * 1000 + turn) over (partition by conv_id order by turn) + {10 * K} as dst from conversations) where dst is not null""",
    "vec_knn": f"""
        select a.vec_id + {11 * K} as src, b.vec_id + {11 * K} as dst from embeddings a join embeddings b on a.vec_id <> b.vec_id
        qualify row_number() over (partition by a.vec_id
            order by list_cosine_similarity(a.embedding::double[], b.embedding::double[]) desc, b.vec_id) <= 10""",
    "line8": """
        select distinct 1 + (l_linenumber % 3)::bigint as src, 2 + (l_linenumber % 3)::bigint + l_quantity::bigint % 5 as dst from lineitem""",
}


def graph_ctes(graph: str) -> str:
    """e (src, dst), v (vertex, out_deg) and adj (src, pos, dst, dst_deg) of a graph, to follow `with`."""
    return f"""
        e as materialized ({EDGES[graph]}),
        v as materialized (select vertex, sum(n)::bigint as out_deg from (select src as vertex, 1 as n from e union all select dst, 0 from e) group by vertex),
        adj as materialized (select src, (row_number() over (partition by src order by dst) - 1)::bigint as pos, dst, v.out_deg as dst_deg
                             from e join v on v.vertex = e.dst)"""


def sampled(n: int, seed: int = 7, where: str = "true") -> str:
    """The query vertices that come first in a digest order."""
    return f"select vertex as query from v where {where} order by md5('{seed}|' || vertex), vertex limit {n}"


# ---------------------------------------------------------------- building blocks

STOP = int(0.15 * 2**32)


def walk_ctes(walks: int, sources: str = "q", seed: int = 7, first: int = 0, name: str = "w", max_steps: int | None = None) -> str:
    """Replays the digest draws: w (source, walk, step, vertex, deg, h) and from it visits and stats, for sources q (query)."""
    h = lambda step: f"md5('{seed}|' || source || '|' || walk || '|' || {step})"
    more = "" if max_steps is None else f" and step < {max_steps}"
    return f"""
        {name} as (
            select *, {h('0')} as h from (
                select s.query as source, k.walk::bigint as walk, 0 as step, s.query as vertex, v.out_deg as deg
                from {sources} s join v on v.vertex = s.query, range({first}, {first + walks}) k(walk))
            union all
            select *, {h('step')} from (
                select w.source, w.walk, w.step + 1 as step, a.dst as vertex, a.dst_deg as deg
                from {name} w join adj a on a.src = w.vertex and a.pos = (('0x' || substr(w.h, 9, 8))::bigint * w.deg) >> 32
                where ('0x' || substr(w.h, 1, 8))::bigint >= {STOP}{more})),
        {name}_visits as materialized (
            select source, vertex, count(*) as visits,
                   count(*) filter (where ('0x' || substr(h, 1, 8))::bigint < {STOP}) as ends from {name} group by source, vertex),
        {name}_stats as materialized (
            select source, {walks}::bigint as walks, sum(visits)::bigint as moves, sum(ends)::bigint as ends from {name}_visits group by source)"""


def frontier_ctes(laps: int, eps: float = 0.0, c: float = 0.15) -> str:
    """f0 .. f<laps> (query, vertex, mass), unpruned g<i>, and settled (query, vertex, mass), for queries q."""
    out = ["f0 as (select query, query as vertex, 1.0::double as mass from q where query in (select vertex from v))"]
    for i in range(laps):
        out.append(f"g{i + 1} as materialized (select query, dst as vertex, sum(mass * (1.0 / out_deg) * {1 - c}) as mass from f{i} "
                   f"join e on e.src = f{i}.vertex join v on v.vertex = f{i}.vertex group by query, dst)")
        out.append(f"f{i + 1} as (select * from g{i + 1} where mass >= {eps})")
    parts = " union all ".join(f"select query, vertex, {c} * mass as mass from f{i}" for i in range(laps)) or "select * from f0 where false"
    out.append(f"settled as materialized (select query, vertex, sum(mass) as mass from ({parts}) group by query, vertex)")
    return ",\n".join(out)


def answer_cte(laps: int, index: str | None, walks: int, c: float = 0.15, name: str = "ans") -> str:
    """Normalised answers (query, vertex, score) from settled and f<laps> closed by visit counts `index` (source, vertex, visits)."""
    closed = f" union all select query, x.vertex, mass * {c} * visits / {walks} from f{laps} f join {index} x on x.source = f.vertex" if index else ""
    return f"""
        {name}_raw as materialized (select query, vertex, sum(mass) as score from (select * from settled{closed}) group by query, vertex),
        {name} as materialized (select query, vertex, score / sum(score) over (partition by query) as score from {name}_raw)"""


def power_ctes(laps: int, to_source: bool = True, c: float = 0.15, name: str = "p") -> str:
    """<name>0 .. and exact (query, vertex, score) after `laps` iterations, for queries q."""
    out = [f"{name}0 as (select query, query as vertex, 1.0::double as score from q where query in (select vertex from v))"]
    for i in range(laps):
        back = f" union all select query, query, {1 - c} * score from {name}{i} p join v using (vertex) where out_deg = 0" if to_source else ""
        out.append(
            f"{name}{i + 1} as materialized (select query, vertex, sum(s) as score from ("
            f"select query, dst as vertex, score * (1.0 / out_deg) * {1 - c} as s from {name}{i} p join e on e.src = p.vertex join v on v.vertex = p.vertex"
            f"{back} union all select query, query, {c} from {name}0) group by query, vertex)")
    out.append(f"{name}_exact as (select * from {name}{laps})")
    return ",\n".join(out)


def ranked(cte: str, out: str) -> str:
    return f"{out} as materialized (select *, row_number() over (partition by query order by {rounded('score')} desc, vertex) as rank from {cte})"


def rag_ctes(exact: str, approx: str, ks: list[int], name: str = "rag") -> str:
    """<name> (query, k, rag)."""
    values = ", ".join(f"({k})" for k in ks)
    return f"""
        {ranked(exact, name + '_e')}, {ranked(approx, name + '_a')}, {name}_k as (select * from (values {values}) t(k)),
        {name} as materialized (
            select query, k, coalesce(got, 0) / best as rag
            from (select query, k, sum(score) as best from {name}_e join {name}_k on rank <= k group by query, k)
            left join (select a.query, k, sum(coalesce(x.score, 0)) as got from {name}_a a join {name}_k on a.rank <= k
                       left join {exact} x on x.query = a.query and x.vertex = a.vertex group by a.query, k) using (query, k))"""


def with_graph(graph: str, *ctes: str, select: str, q: str | None = None) -> str:
    parts = [graph_ctes(graph)] + ([f"q as materialized ({q})"] if q else []) + list(ctes)
    return "with recursive " + ",\n".join(parts) + "\n" + select
