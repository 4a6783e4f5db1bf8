"""DuckDB statements for the queries that SQL can express."""

from __future__ import annotations

from roundmm.llm.licences import COVER, PHRASES, SENTENCES, SLACK
from roundmm.llm.urls import WEIGHTS

#: unsigned CRC-32 of column ``text`` as UTF-8, byte by byte over a table built from the polynomial
CRC_TABLE = "crc_table as (select list(c order by i) as t from (select i, list_reduce(list_prepend(i, range(8)), lambda c, k: case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end) as c from range(256) r(i)))"
CRC = "xor(list_reduce(list_prepend(4294967295::bigint, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda h: ('0x' || h)::bigint)), lambda a, b: xor(a >> 8, crc_table.t[(xor(a, b) & 255) + 1])), 4294967295)"

OP2 = f"""
with {CRC_TABLE},
d as (select doc_id, source, (octet_length(encode(coalesce(text, ''))) + 16)::bigint as size, {CRC}::bigint as text_crc32,
             row_number() over (partition by doc_id, source, octet_length(encode(coalesce(text, ''))), {CRC}) - 1 as copy from documents, crc_table),
h as (select *, md5('11:' || coalesce(doc_id::varchar, '') || ':' || text_crc32 || ':' || size || ':' || copy) as k from d),
r as (select *, (row_number() over (partition by source order by k, doc_id, text_crc32, size, copy) - 0.5::double) / count(*) over (partition by source) as part from h),
a as (select *, row_number() over (order by part, k, doc_id, text_crc32, size, copy) - 1 as pos, count(*) over () as n from r),
s as (select *, (pos * 40 // n)::int as shard from a)
select doc_id, size, text_crc32, 'rows' as law, shard, row_number() over (partition by shard order by pos)::bigint - 1 as slot, null::int as grown_shard, source from s
"""

OP6 = """
with n as (select source, count(*) as n_rows from documents group by source),
r as (select source, n_rows, sum(n_rows) over () * pow(n_rows, 0.7) / sum(pow(n_rows, 0.7)) over () / n_rows as rate from n),
k as (select source, rate, unnest(range((ceil(rate + 9 * sqrt(rate) + 25) + 1)::bigint)) as k from r),
l as (select *, sum(case when k > 0 then ln(k) else 0 end) over (partition by source order by k) as lf from k),
f as (select source, rate, k, sum(exp(k * ln(rate) - rate - lf)) over (partition by source order by k) as f from l),
u as (select doc_id, source, md5(coalesce(text, '')) as t,
             ('0x' || substr(md5('23:' || coalesce(doc_id::varchar, '') || ':' || md5(coalesce(text, ''))), 1, 12))::bigint / 281474976710656.0::double as u from documents),
c as (select u.doc_id, u.source, any_value(u.t) as t, any_value(f.rate) as rate, count(*) filter (where f.f <= u.u) as n_copies
      from u join f on u.source is not distinct from f.source group by u.doc_id, u.source, u.t)
select doc_id, source, copy::int as copy, n_copies::int as n_copies, round(rate, 9) as rate,
       md5('24:' || coalesce(doc_id::varchar, '') || ':' || t || ':' || copy) as shuffle_key
from (select *, unnest(range(n_copies)) as copy from c)
"""



def _templates() -> str:
    rows = [
        f"({i}, '{t.label}', {str(t.exact).lower()}, {len(t.words) - 1}, {p}, '{t.words[p]}', '{t.words[p + 1]}')"
        for i, t in enumerate(PHRASES + SENTENCES)
        for p in range(len(t.words) - 1)
    ]
    return "(values " + ", ".join(rows) + ") g(template, label, exact, n_grams, t_pos, w0, w1)"


def _template_words() -> str:
    return "(values " + ", ".join(f"({i}, {list(t.words)}, {t.budget})" for i, t in enumerate(PHRASES + SENTENCES)) + ") tw(template, t_words, budget)"


OP4 = f"""
with w as (select doc_id, row_number() over () as rid,
                  regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as ws from documents),
p as (select rid, ws, unnest(range(len(ws) - 1)) as pos from w where len(ws) > 1),
h as (select rid, template, label, exact, n_grams, pos - t_pos as diag, t_pos from p join {_templates()} on ws[pos + 1] = w0 and ws[pos + 2] = w1),
o as (select distinct rid, template, diag from h),
n as (select *, coalesce((diag - lag(diag) over (partition by rid, template order by diag) > {SLACK})::int, 1) as fresh from o),
r as (select *, sum(fresh) over (partition by rid, template order by diag) as run from n),
m as (select h.rid, h.template, label, exact, n_grams, case when exact then h.diag else run end as run, min(h.diag) as start, count(distinct t_pos) / n_grams::double as cover
      from h join r on h.rid = r.rid and h.template = r.template and h.diag = r.diag group by 1, 2, 3, 4, 5, 6),
x as (select r.rid, r.template, r.run, t_words, budget, list_slice(ws, greatest(r.diag, 0) + 1, e.diag + len(t_words)) as span
      from r join m on r.rid = m.rid and r.template = m.template and r.run = m.run and not m.exact and m.cover >= {COVER} join w on r.rid = w.rid
      join {_template_words()} on r.template = tw.template join o e on e.rid = r.rid and e.template = r.template and e.diag between r.diag - budget and r.diag + budget),
y as (select rid, template, run from x group by rid, template, run, budget
      having min(levenshtein(list_aggregate(list_transform(span, lambda v: chr((coalesce(list_position(t_words, v), 0) + 32)::int)), 'string_agg', ''),
                             list_aggregate(list_transform(t_words, lambda v: chr((list_position(t_words, v) + 32)::int)), 'string_agg', ''))) <= budget),
s as (select * from m where exact and cover = 1 union all select m.* from m join y on m.rid = y.rid and m.template = y.template and m.run = y.run and not m.exact),
e as (select rid, count(*) filter (where exact) as n_base, min(start) filter (where exact) as first_word, max(start) filter (where exact) as last_word,
             string_agg(distinct label, ',' order by label) filter (where exact) as base_labels, string_agg(distinct label, ',' order by label) as labels, max(cover) as score
      from s group by rid)
select doc_id, len(ws)::bigint as n_words, coalesce(n_base, 0)::bigint as n_base, first_word::bigint as first_word, last_word::bigint as last_word,
       coalesce(base_labels, '') as base_labels, coalesce(labels, '') as labels, coalesce(score, 0)::double as score
from w left join e on w.rid = e.rid
"""

LOWER_URL = "translate(coalesce(url, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _terms(strict: bool | None) -> str:
    """Distinct strict or soft terms of a url, or (None) their weights, added."""
    hit = lambda t: f"regexp_matches(u, '(^|[^\\pL\\pN]){t}($|[^\\pL\\pN])')::int"
    return " + ".join(hit(t) if strict is not None else f"{w}::double * {hit(t)}" for t, w in WEIGHTS.items() if strict is None or (w >= 1) == strict)


OP9 = f"""
with p as (select page_id, {LOWER_URL} as u, regexp_extract({LOWER_URL}, '://([^/?#]*)', 1) as host, regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) as path from pages),
t as (select *, ({_terms(True)})::int as strict_terms, ({_terms(False)})::int as soft_terms, {_terms(None)} as weight from p),
r as (select *, case when (host = 'example.net' or host like '%.example.net') and path like '/en/%' then 'example.net/en/'
                     when (host = 'example.com' or host like '%.example.com') and path like '/de/%' then 'example.com/de/'
                     when (host = 'org' or host like '%.org') and path like '/fr/%' then 'org/fr/'
                     when (host = 'net' or host like '%.net') and path like '/%' then 'net/' end as rule from t)
select page_id, host, path, rule, case when rule in ('net/', 'example.com/de/') then 'block' when rule is not null then 'allow'
       when weight >= 1 then 'block' else 'allow' end as verdict, strict_terms, soft_terms, weight from r
"""

ORACLES: dict[str, str] = {"op2_stratified_shards": OP2, "op4_licence_votes": OP4, "op6_poisson_mix": OP6, "op9_url_terms": OP9}
