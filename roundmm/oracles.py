"""DuckDB statements for the queries: plain joins and aggregates on coordinates, which know nothing of rounds or blocks.

Cost statements list ``range()`` products and filter by the congruence, so they don't repeat a closed form.
"""

from __future__ import annotations

N = 64


def fold(first: str, second: str, n: int, agg: str = "sum") -> str:
    return f"select {first} % {n} as r, {second} % {n} as c, {agg}(l_quantity)::double as v from lineitem group by 1, 2"


def fold_a(n: int = N, agg: str = "sum") -> str:
    return fold("l_orderkey", "l_partkey", n, agg)


def fold_b(n: int = N, agg: str = "sum") -> str:
    return fold("l_partkey", "l_suppkey", n, agg)


def scatter(n: int) -> str:
    return f"select distinct (7 * l_orderkey + 131 * l_linenumber) % {n} as r, (31 * l_partkey + 17 * l_orderkey + 7 * l_suppkey) % {n} as c, 1.0::double as v from lineitem"


def product(a: str, b: str, plus: str = "sum", times: str = "a.v * b.v") -> str:
    return f"with a as ({a}), b as ({b}) select a.r::bigint as \"row\", b.c::bigint as col, {plus}({times})::double as val from a join b on a.c = b.r group by 1, 2"


def dense(n: int = N, zero: str = "0", **options: str) -> str:
    """Every cell of an n x n product; cells without products are zeros of the semiring."""
    p = product(fold_a(n, options.get("plus", "sum")), fold_b(n, options.get("plus", "sum")), **options)
    return f'select i.i as "row", j.j as col, coalesce(p.val, {zero})::double as val from range({n}) i(i) cross join range({n}) j(j) left join ({p}) p on p."row" = i.i and p.col = j.j'


def cells(sql: str) -> str:
    return f'select r::bigint as "row", c::bigint as col, v::double as val from ({sql})'


HOUR = "(datediff('day', date '2024-01-01', ts::date) * 24 + extract(hour from ts))::bigint"
USER_HOUR = f"select user_id as r, {HOUR} as c, sum(round(value * 100))::double as v from events group by 1, 2"
SUPP_PART = "select distinct l_suppkey as r, l_partkey as c, 1.0::double as v from lineitem"
ORDER_PART = "select distinct l_orderkey as r, l_partkey as c, 1.0::double as v from lineitem"
CUST_ORDER = "select distinct o_custkey as r, o_orderkey as c, 1.0::double as v from orders"
GRAM = "select vec_id as r, generate_subscripts(embedding, 1) - 1 as c, floor(unnest(embedding)::double * 1024)::double as v from embeddings"


def flip(sql: str) -> str:
    return f"select c as r, r as c, v from ({sql})"


ORACLES: dict[str, str] = {}

for _key in ("dense_rho1", "dense_rho2", "dense_rho3", "dense_rho4", "dense_monolithic", "dense_block4", "dense_block8", "append", "stationary", "hash_partitioner", "elided_fold", "store_checkpoint", "store_persist", "store_none", "resume"):
    ORACLES[f"mm3d_{_key}"] = dense()
ORACLES["mm3d_dense_ragged"] = dense(60)
for _block, _rho in ((4, 32), (8, 16), (8, 4), (16, 1), (16, 2), (16, 4), (16, 8)):
    ORACLES[f"mm3d_n128_block{_block}_rho{_rho}"] = dense(128)
for _key in ("dense_rho1", "dense_rho2", "rho3", "dense_rho4", "dense_rho8", "dense_rho16", "naive_schedule"):
    ORACLES[f"mm2d_{_key}"] = dense()
for _key in ("er_rho1", "er_rho2", "er_rho4", "q16", "packed", "er_sized", "append", "packed_append", "q8_rho8", "q16_rho8", "q16_rho16"):
    ORACLES[f"mm3d_sparse_{_key}"] = product(scatter(8192), scatter(8192))
for _side, _grids in ((1024, ("q4_rho1", "q8_rho4", "q16_rho16")), (65536, ("q4_rho2", "q8_rho8", "q16_rho4"))):
    for _grid in _grids:
        ORACLES[f"mm3d_sparse_n{_side}_{_grid}"] = product(scatter(_side), scatter(_side))
ORACLES["mm_sparse_join"] = product(scatter(8192), scatter(8192))
ORACLES["mm3d_sparse_general"] = ORACLES["mm3d_sparse_permuted"] = product(USER_HOUR, flip(USER_HOUR))
ORACLES["mm3d_sparse_dense_out"] = product(SUPP_PART, flip(SUPP_PART))
ORACLES["mm3d_sparse_unknown"] = product(CUST_ORDER, ORDER_PART)
for _key in ("join", "broadcast", "mllib"):
    ORACLES[f"mm_{_key}"] = product(fold_a(), fold_b())
for _key in ("outer", "local", "count", "cogroup"):
    ORACLES[f"mm_{_key}"] = dense()
ORACLES["mm_rect_gram"] = product(GRAM, flip(GRAM))
ORACLES["mm_gram_cols"] = product(flip(GRAM), GRAM)
ORACLES["mm_minplus"] = dense(zero="'inf'::double", plus="min", times="a.v + b.v")
ORACLES["mm_maxplus"] = dense(zero="'-inf'::double", plus="max", times="a.v + b.v")
ORACLES["mm_maxmin"] = dense(zero="'-inf'::double", plus="max", times="least(a.v, b.v)")
ORACLES["mm_maxtimes"] = dense(plus="max", times="a.v * b.v")
ORACLES["mm_orand"] = product(scatter(8192), scatter(8192), "max", "least(a.v, b.v)")

ORACLES["mm_chain_trade"] = """
select c_nationkey::bigint as "row", s_nationkey::bigint as col, count(*)::double as val
from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2
"""
ORACLES["mm_region_brand"] = """
with b as (select p_brand, row_number() over (order by p_brand) - 1 as idx from (select distinct p_brand from part))
select n_regionkey::bigint as "row", idx::bigint as col, count(*)::double as val
from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey
join part on l_partkey = p_partkey join b using (p_brand) group by 1, 2
"""
AXIS = "x as (select event_type, row_number() over (order by event_type) - 1 as idx from (select distinct event_type from events))"
TRANSITIONS = f"""{AXIS},
l as (select event_type as a, lead(event_type) over (partition by user_id order by ts, event_id) as b from events),
t as (select p.idx as r, q.idx as c, count(*)::double as v from l join x p on p.event_type = l.a join x q on q.event_type = l.b group by 1, 2)"""
ORACLES["op_transitions"] = f'with {TRANSITIONS} select r::bigint as "row", c::bigint as col, v as val from t'
ORACLES["mm_power_transition"] = f'with {TRANSITIONS} select a.r::bigint as "row", d.c::bigint as col, sum(a.v * b.v * d.v)::double as val from t a join t b on a.c = b.r join t d on b.c = d.r group by 1, 2'
ORACLES["mm_copurchase"] = product(flip(ORDER_PART), ORDER_PART)
ORACLES["mm_triangles"] = f"""
with x as ({ORDER_PART}), e as (select distinct a.c as u, b.c as w from x a join x b on a.r = b.r where a.c < b.c)
select p.u::bigint as "row", count(*)::bigint as triangles from e p join e q on p.w = q.u join e s on s.u = p.u and s.w = q.w group by 1
"""
ORACLES["mm_links2"] = """
with l as (select distinct regexp_extract(url, '://([^/?#]+)', 1) as host, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) as target from pages),
h as (select host, row_number() over (order by host) - 1 as idx from (select distinct host from l)),
k as (select l.target, h.idx from l join h using (host))
select distinct a.idx::bigint as "row", b.idx::bigint as col, 1.0::double as val from k a join k b using (target)
"""
TOKENS = "unnest(regexp_extract_all(lower(text), '[a-z]+'))"


def _overlap(first: str, row: str, second: str, col: str) -> str:
    return f"""
with s as (select {row} as r, {TOKENS} as token from {first}), t as (select {col} as c, {TOKENS} as token from {second}),
a as (select r, token, count(*)::double as x from s group by 1, 2), b as (select c, token, count(*)::double as y from t group by 1, 2)
select r as "row", c as col, sum(x * y)::double as val from a join b using (token) group by 1, 2
"""


ORACLES["mm_sources"] = _overlap("documents", "source", "documents", "source")
ORACLES["mm_roles"] = _overlap("conversations", "role", "benchmark", "item_id")
ORACLES["mm_items_documents"] = _overlap("benchmark", "item_id", "documents", "doc_id")
ORACLES["mm_quality_tokens"] = f"""
with t as (select doc_id, {TOKENS} as token from documents)
select quality::bigint as "row", token as col, count(*)::double as val from t join labels using (doc_id) group by 1, 2
"""
ORACLES["mm_price_hops"] = """
with p as (select c_nationkey as r, s_nationkey as c, min(round(l_extendedprice * 100)) as v
from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2)
select a.r::bigint as "row", b.c::bigint as col, min(a.v + b.v)::double as val from p a join p b on a.c = b.r group by 1, 2
"""
ORACLES["mm_masked"] = f'with m as ({scatter(8192)}), p as ({product(scatter(8192), scatter(8192))}) select p."row", p.col, p.val from p join m on m.r = p."row" and m.c = p.col'
ORACLES["mm_topk"] = f'select "row", col, val, rank from (select *, row_number() over (partition by "row" order by val desc, col) as rank from ({product(fold_a(), fold_b())})) where rank <= 3'
ORACLES["mm_topk_lateral"] = f'select "row", col, val from ({ORACLES["mm_topk"]})'
ORACLES["mm_sliced_chain"] = f'select "row", col, 2 * val as val from ({product(fold_a(), fold_b())}) where "row" < 10 and col >= 3 and col < 5'

_grids = "(values " + ", ".join(f"({q}, {rho})" for q in (1, 2, 3, 4, 6, 8) for rho in range(1, q + 1)) + ") g(q, rho)"
ORACLES["schedule3d_cover"] = f"""
with p as (select q, rho, i.x as i, h.x as h, j.x as j, (((h.x - i.x - j.x) % q + q) % q) // rho as r
           from {_grids}, range(8) i(x), range(8) h(x), range(8) j(x) where i.x < q and h.x < q and j.x < q),
c as (select q, rho, max(n) as copies from (select q, rho, r, i, h, count(*) as n from p group by all) group by 1, 2)
select q, rho, count(*)::bigint as products, count(distinct (i, h, j))::bigint as distinct_products, (max(r) + 1)::bigint as product_rounds, any_value(copies)::bigint as copies
from p join c using (q, rho) group by 1, 2
"""
_rects = "(values (2, 3, 5, 2), (5, 2, 3, 1), (4, 1, 4, 1), (1, 8, 1, 3), (3, 4, 2, 4)) g(qi, qh, qj, rho)"
ORACLES["schedule3d_rect_cover"] = f"""
with p as (select qi, qh, qj, rho, i.x as i, h.x as h, j.x as j, (((h.x - i.x - j.x) % qh + qh) % qh) // rho as r
           from {_rects}, range(8) i(x), range(8) h(x), range(8) j(x) where i.x < qi and h.x < qh and j.x < qj)
select qi, qh, qj, rho, r::int as round, count(*)::bigint as products, count(distinct (i, h, j))::bigint as distinct_products from p group by 1, 2, 3, 4, 5
"""
_squares = "(values " + ", ".join(f"({s}, {rho}, {n})" for s in (1, 2, 4, 7, 16) for rho in sorted({1, 2, 3, 4, s} & set(range(1, s + 1))) for n in ("false", "true")) + ") g(s, rho, naive)"
ORACLES["schedule2d_cover"] = f"""
with p as (select s, rho, naive, i.x as i, j.x as j, case when naive then (i.x * s + j.x) // (rho * s) else ((j.x - i.x) % s + s) % s // rho end as r from {_squares}, range(16) i(x), range(16) j(x) where i.x < s and j.x < s)
select s, rho, naive, count(*)::bigint as products, count(distinct (i, j))::bigint as distinct_products, (max(r) + 1)::bigint as rounds from p group by 1, 2, 3
"""

def table_ledger(rhos: str, n: int = N, side: int = 16) -> str:
    """Blocks and entries by round and side of the product of the folds of line items: every product has its group, every cell the first round that its slot reaches it."""
    q = -(-n // side)
    group = f"((h - i - j) % {q} + {q}) % {q}"
    return f"""with m as ({fold_a(n)}), m2 as ({fold_b(n)}), a as (select r // {side} as i, c // {side} as h, count(*) as n from m group by 1, 2), b as (select r // {side} as h, c // {side} as j, count(*) as n from m2 group by 1, 2),
v as (select * from (values {rhos}) v(rho)),
t as (select x.r as "row", y.c as col, x.r // {side} as i, x.c // {side} as h, y.c // {side} as j from m x join m2 y on x.c = y.r),
c as (select rho, i, j, ({group}) % rho as slot, "row", col, min(({group}) // rho) as since from t, v group by all),
n as (select rho, i, j, slot, since, count(*) as n from c group by all),
ja as (select rho, g // rho as r, i, h, n, j.x as j from a, v, range({q}) u(g), range({q}) j(x) where ((h - i - j.x) % {q} + {q}) % {q} = g),
jb as (select rho, g // rho as r, i.x as i, h, n, j from b, v, range({q}) u(g), range({q}) i(x) where ((h - i.x - j) % {q} + {q}) % {q} = g),
held as (select rho, x as r, least(rho, {q} - x * rho) as slots from v, range(1, {q}) t(x) where x * rho < {q} union all select rho, ({q} + rho - 1) // rho, rho from v),
l as (select rho, r, 'A' as side, count(*) as pairs, sum(n) as words from ja group by 1, 2 union all select rho, r, 'B', count(*), sum(n) from jb group by 1, 2
      union all select held.rho, held.r, 'C', count(distinct (i, j, slot)), sum(n) from held join n on n.rho = held.rho and n.since < held.r and n.slot < held.slots group by 1, 2)"""


#: product rounds of the square 3D schedule, q = 4, blocks of 256 words
_P = "p as (select rho, i.x as i, h.x as h, j.x as j, ((h.x - i.x - j.x) % 4 + 4) % 4 as g from (values (1), (2), (3), (4)) r(rho), range(4) i(x), range(4) h(x), range(4) j(x))"
LEDGER = f"""with {_P},
o as (select rho, g // rho as r, i, h, j, g % rho as slot from p),
l as (select rho, r, 'A' as side, count(*) as pairs from o group by 1, 2 union all select rho, r, 'B', count(*) from o group by 1, 2
      union all select rho, r, 'C', count(*) from o where r > 0 group by 1, 2
      union all select rho, max(r) + 1, 'C', 16 * least(rho, 4) from o group by rho)"""
ORACLES["cost3d_rounds"] = table_ledger("(1), (2), (3), (4)") + " select '3d' as method, rho, r::int as round, side, pairs::bigint as pairs, words::bigint as words from l"
ORACLES["mm3d_observed_words"] = LEDGER + " select r::int as round, side, pairs::bigint as pairs, (pairs * 256)::bigint as words from l where rho = 2 and r < 2"
ORACLES["cost3d_total"] = table_ledger("(1), (2), (3), (4)") + " select rho, sum(pairs)::bigint as pairs, sum(words)::bigint as words from l group by rho"
#: strips of four rows or columns of the folds of line items
_STRIPS = f"a as (select r // 4 as i, count(*) as n from ({fold_a()}) group by 1), b as (select c // 4 as j, count(*) as n from ({fold_b()}) group by 1)"
_STRIP_WORDS = """ select '2d' as method, rho, r::int as round, 'A' as side, count(*)::bigint as pairs, sum(n)::bigint as words from p join a using (i) group by 2, 3
union all select '2d', rho, r::int, 'B', count(*)::bigint, sum(n)::bigint from p join b using (j) group by 2, 3"""
ORACLES["cost2d_rounds"] = f"with p as (select rho, i.x as i, j.x as j, ((j.x - i.x) % 16 + 16) % 16 // rho as r from (values (1), (2), (4), (8), (16)) g(rho), range(16) i(x), range(16) j(x)), {_STRIPS}" + _STRIP_WORDS
ORACLES["cost2d_naive_rounds"] = f"with p as (select 4 as rho, x // 16 as i, x % 16 as j, x // 64 as r from range(256) t(x)), {_STRIPS}" + _STRIP_WORDS
def sparse_ledger(rhos: str) -> str:
    """Entries by round and side of the sparse product, q = 4: every product has its group, every cell the first round that its slot reaches it."""
    return f"""with m as ({scatter(8192)}), a as (select r // 2048 as i, c // 2048 as h, count(*) as n from m group by 1, 2), b as (select r // 2048 as h, c // 2048 as j, count(*) as n from m group by 1, 2),
v as (select * from (values {rhos}) v(rho)),
t as (select x.r as "row", y.c as col, x.r // 2048 as i, x.c // 2048 as h, y.c // 2048 as j from m x join m y on x.c = y.r),
c as (select rho, i, j, (((h - i - j) % 4 + 4) % 4) % rho as slot, "row", col, min((((h - i - j) % 4 + 4) % 4) // rho) as since from t, v group by all),
n as (select rho, i, j, slot, since, count(*) as n from c group by all),
k as (select rho, x as o, g, g // rho as r from v, range(4) t(x), range(4) u(g)),
w as (select rho, x as r, least(rho, 4 - x * rho) as slots from v, range(1, 4) t(x) where x * rho < 4 union all select rho, (4 + rho - 1) // rho, rho from v),
l as (select rho, r, 'A' as side, count(*) // 4 as pairs, sum(n) // 4 as words from a, k group by 1, 2 union all select rho, r, 'B', count(*) // 4, sum(n) // 4 from b, k group by 1, 2
      union all select w.rho, w.r, 'C', count(distinct (i, j, slot)), sum(n) from w join n on n.rho = w.rho and n.since < w.r and n.slot < w.slots group by 1, 2)"""


ORACLES["cost_sparse_rounds"] = sparse_ledger("(1), (2), (4)") + " select 'sparse' as method, rho, r::int as round, side, pairs::bigint as pairs, words::bigint as words from l"
ORACLES["mm3d_sparse_observed_words"] = sparse_ledger("(2)") + " select r::int as round, side, words::bigint as words from l where r < 2"
ORACLES["cost_sparse_bound"] = sparse_ledger("(1), (2), (4)") + f""", s as (select rho, r, sum(words) as w from l group by 1, 2)
select rho, max(w)::bigint as greatest, round(3 * rho * pow((select count(*) from ({scatter(8192)})) / 67108864.0::double, 2) * pow(8192.0::double, 3), 6) as bound from s group by rho"""
ORACLES["rounds_sparse_formula"] = """
select side::int as side, m::int as m, rho::int as rho, (ceil(sqrt(1 / 1024.0::double) * side / (rho * sqrt(m))) + 1)::int as rounds from (values (1024), (8192), (65536)) s(side), (values (64), (256), (1024)) t(m), (values (1), (2), (4)) r(rho)
"""
ORACLES["accuracy_real_values"] = "select count(*)::bigint as cells, true as exact from (select i.i, j.j from range(64) i(i) cross join range(64) j(j))"
ORACLES["rounds_formula"] = """
select '3d' as method, side::int as side, b::int as size, rho::int as rho, (ceil(ceil(side / b::double) / rho) + 1)::int as rounds from (values (64), (60), (128)) s(side), (values (4), (8), (16)) t(b), (values (1), (2), (3), (4)) r(rho)
union all select '2d', 64, m::int, rho::int, ceil((64 * 64 // m) / rho::double)::int from (values (64), (256), (1024)) t(m), (values (1), (2), (3), (4)) r(rho)
"""
ORACLES["reducer_words"] = f"with {_P} select (g // 2)::int as round, count(*)::bigint as reducers, min(case when g < 2 then 512 else 768 end)::bigint as least, max(case when g < 2 then 512 else 768 end)::bigint as greatest from p where rho = 2 group by 1"
ORACLES["reducer_words_sparse"] = sparse_ledger("(2)") + """, p as (select a.i, a.h, b.j, a.n as x, b.n as y, ((a.h - a.i - b.j) % 4 + 4) % 4 as g from a join b using (h)),
z as (select p.i, p.h, p.j, g // 2 as r, any_value(x + y) as xy, coalesce(sum(n.n), 0) as c from p left join n on n.i = p.i and n.j = p.j and n.slot = g % 2 and n.since < g // 2 group by 1, 2, 3, 4)
select r::bigint as round, count(*)::bigint as reducers, avg(xy + c)::double as mean, max(xy + c)::bigint as greatest from z group by 1
"""
_STRIP_COPIES = """, o as (select r, 'A' as side, i as k, count(*) as n from p join a using (i) group by all union all select r, 'B', j, count(*) from p join b using (j) group by all)
select r::int as round, side, min(n)::bigint as least, max(n)::bigint as greatest from o group by 1, 2"""
ORACLES["mapper_replicas_balanced"] = f"with p as (select i.x as i, j.x as j, ((j.x - i.x) % 16 + 16) % 16 // 4 as r from range(16) i(x), range(16) j(x)), {_STRIPS}" + _STRIP_COPIES
ORACLES["mapper_replicas_naive"] = f"with p as (select x // 16 as i, x % 16 as j, x // 64 as r from range(256) t(x)), {_STRIPS}" + _STRIP_COPIES
_KEYS = "k as (select i.x as i, j.x as j, l.x as slot, (i.x + j.x + l.x) % 8 as h from range(8) i(x), range(8) j(x), range(8) l(x))"
_TASKS = "(values (16), (32), (64)) t(tasks)"
ORACLES["partition_even_hist"] = f"with {_KEYS} select ((i * 8 + j) * 8 + slot) // (512 // tasks)::int as task, count(*)::bigint as keys, tasks from k, {_TASKS} group by 1, 3"
ORACLES["partition_even_hist"] = f"select task::int as task, keys, tasks from ({ORACLES['partition_even_hist']})"
ORACLES["partition_hash_hist"] = f"""
with {_KEYS}, n as (select tasks, (961 * i + 31 * h + j) % tasks as task, count(*) as n from k, {_TASKS} group by 1, 2)
select x::int as task, coalesce(n, 0)::bigint as keys, t.tasks from {_TASKS} cross join range(64) r(x) left join n on n.tasks = t.tasks and n.task = x where x < t.tasks
"""
ORACLES["partition2d_hist"] = "with k as (select i.x as i, j.x as j, ((j.x - i.x) % 16 + 16) % 16 as g from range(16) i(x), range(16) j(x)) select ((i * 4 + g) // 4)::int as task, count(*)::bigint as keys from k where g < 4 group by 1"
ORACLES["op_balance_stats"] = f"""
with a as (select distinct r // 8 as i, c // 8 as h from ({fold_a()})), b as (select distinct r // 8 as h, c // 8 as j from ({fold_b()})),
n as (select (961 * i + 31 * h + j) % 32 as task, count(*) as n from a join b using (h) group by 1), e as (select coalesce(n, 0) as keys from range(32) r(x) left join n on task = x)
select max(keys)::bigint as greatest, avg(keys)::double as mean, median(keys)::double as median, count(*) filter (where keys = 0)::bigint as idle from e
"""

_heaviest = lambda n, b: f"select {n}::int as side, {b}::int as block, max(w)::bigint as words, max(w) / ({n} * {n} * {-(-n // b)})::double as ratio from ({table_ledger(f'({-(-n // b)})', n, b)} select r, sum(words) as w from l group by 1)"
ORACLES["lower_bound_ratio"] = " union all ".join(_heaviest(n, b) for n in (60, 64, 128) for b in (8, 16))
ORACLES["density_flops"] = f"""
with m as ({scatter(8192)}), c as (select c as k, count(*) as x from m group by 1), r as (select r as k, count(*) as y from m group by 1),
s as ({SUPP_PART}), t as (select c as k, count(*) as x from s group by 1)
select 'scatter' as input, sum(x * y)::bigint as products from c join r using (k) union all select 'supp_part', sum(x * x)::bigint from t
"""
ORACLES["density_er"] = f"with m as ({scatter(8192)}) select count(*)::bigint as nnz, round(count(*) / 67108864.0::double, 12) as delta, round(pow(count(*) / 67108864.0::double, 2) * 8192, 9) as delta_out from m"
ORACLES["density_er_exact"] = f"with m as ({scatter(8192)}) select count(*)::bigint as nnz, round(count(*) / 67108864.0::double, 12) as delta, round(1 - pow(1 - pow(count(*) / 67108864.0::double, 2), 8192), 9) as delta_out from m"
ORACLES["density_exact"] = f"select count(*)::bigint as cells from ({product(scatter(8192), scatter(8192))})"
for _side in (1024, 65536):
    ORACLES[f"density_exact_{_side}"] = f"select count(*)::bigint as cells from ({product(scatter(_side), scatter(_side))})"
    ORACLES[f"density_flops_{_side}"] = f"with m as ({scatter(_side)}), c as (select c as k, count(*) as x from m group by 1), r as (select r as k, count(*) as y from m group by 1) select sum(x * y)::bigint as products from c join r using (k)"
ORACLES["density_row_sample"] = f"""
with p as ({product(scatter(8192), scatter(8192))}), n as (select count(*) as rows from range(8192) t(x) where (x * 48271 + 11) % 100 < 10)
select round(count(*) * 8192.0::double / any_value(n.rows), 3) as cells from p, n where ("row" * 48271 + 11) % 100 < 10
"""
ORACLES["work_products"] = f"with m as ({USER_HOUR}) select sum(n * n)::bigint as products from (select c, count(*) as n from m group by 1)"

_BOTH = f"with a as ({fold_a()}), b as ({fold_b()})"
ORACLES["mat_add"] = f'{_BOTH} select coalesce(a.r, b.r)::bigint as "row", coalesce(a.c, b.c)::bigint as col, coalesce(a.v, 0) + coalesce(b.v, 0) as val from a full join b on a.r = b.r and a.c = b.c'
ORACLES["mat_sub"] = f'{_BOTH} select coalesce(a.r, b.r)::bigint as "row", coalesce(a.c, b.c)::bigint as col, coalesce(a.v, 0) - coalesce(b.v, 0) as val from a full join b on a.r = b.r and a.c = b.c'
ORACLES["mat_transpose"] = cells(flip(scatter(8192)))
ORACLES["mat_scale"] = f'select r::bigint as "row", c::bigint as col, 3 * v as val from ({fold_a()})'
ORACLES["mat_identity"] = cells(fold_a())
ORACLES["mat_trace_norms"] = f"select sum(case when r = c then v else 0 end) as trace, sum(v * v) as frobenius2, sum(v) as total, max(v) as greatest, count(*)::bigint as cells from ({fold_a()})"
ORACLES["mat_slice"] = cells(fold_a()) + " where r >= 10 and r < 20 and c < 8"
ORACLES["mat_clip_prune"] = f'select r::bigint as "row", c::bigint as col, least(greatest(v - 300, 0), 100)::double as val from ({fold_a()}) where v > 300'
ORACLES["axis_index_events"] = f"with {AXIS} select event_type, idx::bigint as idx from x"

ORACLES["op_block_roundtrip"] = f'select i.x as "row", j.x as col, coalesce(v, 0)::double as val from range(60) i(x) cross join range(60) j(x) left join ({fold_a(60)}) on r = i.x and c = j.x'
ORACLES["op_asof_value"] = f"""
with e as (select user_id, {HOUR} + 1 as mark, ts, event_id, value from events), m as (select distinct user_id, unnest(range(6, 721, 6)) as mark from e)
select m.user_id as "row", m.mark::bigint as col, arg_max(e.value, (e.ts, e.event_id)) as val from m join e on e.user_id = m.user_id and e.mark <= m.mark group by 1, 2
"""
ORACLES["op_interval_pairs"] = ORACLES["stream_close_pairs"] = """
select a.user_id, a.event_id as e1, b.event_id as e2 from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour and a.event_id <> b.event_id
"""
ORACLES["op_missing_cells"] = f"""
with x as ({ORDER_PART}), t as (select c from x group by c order by count(*) desc, c limit 1)
select distinct x.r::bigint as "row", t.c::bigint as col from x, t where x.r not in (select r from x, t where x.c = t.c)
"""
ORACLES["op_band_join"] = f'{_BOTH} select a.r::bigint as "row", b.c::bigint as col, sum(a.v * b.v)::double as val from a join b on abs(a.c - b.r) <= 1 group by 1, 2'
ORACLES["op_pattern"] = f'select "row", col from ({product(scatter(8192), scatter(8192))})'
ORACLES["op_words_by_side"] = LEDGER + " select rho, sum(case when side = 'A' then pairs * 256 else 0 end)::bigint as words_a, sum(case when side = 'B' then pairs * 256 else 0 end)::bigint as words_b, sum(case when side = 'C' then pairs * 256 else 0 end)::bigint as words_c, count(*) filter (where side = 'C')::bigint as c_rows from l group by rho"
ORACLES["op_ledger_rollup"] = table_ledger("(1), (2), (3), (4)") + " select rho, r::int as round, sum(words)::bigint as words from l group by rollup (rho, r::int)"
ORACLES["op_ledger_cube"] = table_ledger("(1), (2), (3), (4)") + " select rho, side, sum(words)::bigint as words from l group by cube (rho, side)"
ORACLES["op_ledger_gsets"] = table_ledger("(1), (2), (3), (4)") + " select rho, side, sum(words)::bigint as words from l group by grouping sets ((rho), (side), ())"
ORACLES["op_cum_shuffle"] = table_ledger("(1), (2), (3), (4)") + """, w as (select rho, r::int as round, sum(words)::bigint as words from l group by 1, 2)
select *, sum(words) over (partition by rho order by round)::bigint as so_far, words - lag(words) over (partition by rho order by round) as more from w"""
ORACLES["op_pivot_wide"] = f'with {TRANSITIONS} select r::bigint as "row", ' + ", ".join(f"sum(v) filter (where c = {k}) as c{k}" for k in range(5)) + " from t group by 1"
ORACLES["op_unpivot"] = ORACLES["op_transitions"]
ORACLES["op_range_frame"] = "with e as (select user_id, event_id, floor(epoch(ts))::bigint as t from events) select user_id, event_id, count(*) over (partition by user_id order by t range between 86400 preceding and current row)::bigint as n from e"
ORACLES["op_ntile_split"] = f"""
with w as (select r::bigint as "row", sum(v) as weight from ({fold_a()}) group by 1)
select "row", weight, ntile(8) over o as run, rank() over o as rank, round(percent_rank() over o, 9) as share, round(cume_dist() over o, 9) as upto from w window o as (order by weight desc, "row")
"""
ORACLES["op_sorted"] = cells(fold_a())
ORACLES["op_top_cells"] = cells(fold_a()) + ' order by val desc, "row", col limit 20 offset 5'
ORACLES["op_pattern_intersect"] = f'with m as ({scatter(1024)}) select r::bigint as "row", c::bigint as col from m intersect select c, r from m'
ORACLES["op_pattern_except"] = f'with m as ({scatter(1024)}) select r::bigint as "row", c::bigint as col from m except select c, r from m'
ORACLES["op_json_axis"] = "select user_id as \"row\", (props ->> '$.k')::bigint as col, count(*)::bigint as val from events where (props ->> '$.k') is not null group by 1, 2"
ORACLES["op_array_dot"] = f"""
with g as ({GRAM}), f as (select c, v as w from g where r = 0)
select r::bigint as vec_id, sum(v * v)::bigint as norm2, sum(v * w)::bigint as with_first from g join f using (c) group by 1
"""
ORACLES["op_map_rows"] = f'select r::bigint as "row", count(*)::bigint as n, count(*) filter (where v > 300)::bigint as n_big, coalesce(sum(v) filter (where v > 300), 0)::double as sum_big, max(c)::bigint as last_col from ({fold_a()}) group by 1'
ORACLES["stream_user_type"] = "select user_id, event_type, count(*)::bigint as n from events group by 1, 2"
ORACLES["stream_incremental_product"] = f"""
with {TRANSITIONS} select e.user_id as "row", t.c::bigint as col, sum(t.v)::double as val from events e join x on x.event_type = e.event_type join t on t.r = x.idx group by 1, 2
"""
ORACLES["stream_batch_rounds"] = ORACLES["stream_incremental_product"]
ORACLES["stream_deduplicated"] = "select event_id, user_id from events"
ORACLES["stream_daily_windows"] = """
with d as (select date_trunc('day', ts) as start, user_id, event_type, count(*)::bigint as n from events group by 1, 2, 3)
select start::timestamp as start, user_id, event_type, n from d where start + interval 1 day <= (select max(ts) - interval 2 days from events)
"""
ORACLES["plan_choice"] = """
with g as (select side, mem, groups, floor(sqrt(mem / 3))::bigint as most from (values (16000), (32000), (3540000)) s(side), (values (12000000), (48000000)) m(mem), (values (1), (2), (4)) b(groups)),
c as (select *, most // (2 ** k)::bigint as block, k from g, range(12) t(k)),
o as (select *, ceil(side / block::double)::bigint as q from c where block >= 1),
f as (select side, mem, groups, arg_min(block, k) as block, arg_min(q, k) as q from o where least(groups, q) * q * q >= 32 group by 1, 2, 3)
select side::int as side, mem::bigint as mem, groups::int as budget_groups, block::int as block, q::int as q, least(groups, q)::int as rho, (ceil(q / least(groups, q)::double) + 1)::int as rounds, (3 * q * side::double * side)::double as total_words from f
"""
