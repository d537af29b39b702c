"""DuckDB SQL for the corpus queries that SQL can express over whole tables."""

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

SQL = {
    "op2_exact_dedup": f"""
        with d as (select doc_id, {_LOWER} as norm from documents),
        g as (select norm, max(doc_id) as keep_id, count(*) as group_size from d group by norm)
        select doc_id, keep_id, group_size, doc_id = keep_id as kept, sha256(norm) as text_sha256
        from d join g using (norm)
    """,
    "op4_source_mix": r"""
        with recursive d as (
            select doc_id, source,
                   len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> ''))::bigint as size,
                   ('0x' || substr(md5(doc_id::varchar), 1, 2))::int as bucket
            from documents),
        s as (select source, sum(size)::bigint as source_size,
                     row_number() over (order by source nulls last) - 1 as i from d group by source),
        w as (select *, list_extract([3.0::double, 1.0::double, 2.0::double], (i % 3 + 1)::int) as weight,
                     sum(source_size) over () as total from s),
        fill as (
            select 0 as lap, source, source_size, weight, total, false as capped,
                   1.5 * total * weight / sum(weight) over () as target from w
            union all
            select lap + 1, source, source_size, weight, total, now_capped,
                   case when now_capped then 2.0 * source_size
                        else (1.5 * total - sum(case when now_capped then 2.0 * source_size else 0 end) over ())
                             / sum(case when now_capped then 0 else weight end) over () * weight end
            from (select *, target >= 2.0 * source_size as now_capped from fill) where lap < 40),
        t as (select source, source_size, target,
                     case when source_size > 0 then target / source_size else 0 end as rate,
                     ('0x' || substr(md5('20177|' || coalesce('0' || source, '1')), 1, 5))::int / 1048576.0::double as shift
              from fill where lap = 40),
        r as (select d.doc_id, d.size, t.source_size, t.target, t.rate, t.shift,
                     row_number() over (partition by d.source order by d.size, d.bucket, d.doc_id) as k
              from d join t on d.source is not distinct from t.source)
        select doc_id, size, source_size, round(target, 6) as target,
               (least(floor(shift + rate * k) - floor(shift + rate * (k - 1)), ceil(rate)) * size)::bigint as taken
        from r
    """,
    # The given pages state no canonical link or refresh, so the method's own verdict is `allow` throughout.
    "op7_redirect_blocklist": r"""
        with p as (select page_id,
                translate(regexp_extract(coalesce(url, ''), '^(?s:.*?)://([^/?#]*)([^?#]*)', 1),
                          'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
                regexp_extract(coalesce(url, ''), '^(?s:.*?)://([^/?#]*)([^?#]*)', 2) as path from pages),
        r as (select * from (values ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('allow', 'net', '/de/'),
                                    ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')) t(verdict, h, q)),
        m as (select page_id, h || q as rule, verdict,
                     row_number() over (partition by page_id order by length(h || q) desc) as k
              from p join r on (host = h or ends_with(host, '.' || h)) and starts_with(path, q))
        select p.page_id, host, path, rule, coalesce(verdict, 'allow') as verdict
        from p left join m on m.page_id = p.page_id and k = 1
    """,
}
