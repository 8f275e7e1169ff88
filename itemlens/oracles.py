"""The queries that SQL can express, in DuckDB's SQL over the same tables."""

from __future__ import annotations

GEO = "lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey"
PART = "lineitem join part on l_partkey = p_partkey"
#: Sources as distinct rows (tid, item).
LONG = {
    "order_geo": f"select distinct l_orderkey as tid, unnest([concat('n', s_nationkey), concat('r', n_regionkey)]) as item from {GEO}",
    "order_regions": f"select distinct l_orderkey as tid, concat('r', n_regionkey) as item from {GEO}",
    "order_brands": f"select distinct l_orderkey as tid, p_brand as item from {PART}",
    "order_tokens": f"select distinct l_orderkey as tid, unnest(string_split(p_name, ' ')) as item from {PART}",
    "order_parts": "select distinct l_orderkey as tid, cast(l_partkey as varchar) as item from lineitem",
    "part_suppnations": f"select distinct l_partkey as tid, concat('n', s_nationkey) as item from {GEO}",
    "part_custnations": "select distinct l_partkey as tid, concat('n', c_nationkey) as item from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey",
    "cust_brands": f"select distinct o_custkey as tid, p_brand as item from {PART} join orders on l_orderkey = o_orderkey",
    "part_attrs": "select distinct p_partkey as tid, unnest(list_concat(string_split(p_name, ' '), [p_brand, p_type])) as item from part",
    "line_attrs": "select row_number() over () as tid, unnest([concat('l_returnflag=', l_returnflag), concat('l_linestatus=', l_linestatus), concat('l_discount=', l_discount), concat('l_tax=', l_tax), concat('l_linenumber=', l_linenumber)]) as item from lineitem",
    "doc_words_en": r"select distinct doc_id as tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) as item from documents where lang = 'en'",
    "doc_stems_en": r"""select distinct tid, case when length(w) >= 5 and length(c) >= 3 then c else w end as item from (select tid, w, regexp_replace(w, '(ingly|edly|ations|ation|ings|ing|ies|ied|ness|ments|ment|ers|er|ed|ly|es|s)$', '') as c
from (select distinct doc_id as tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) as w from documents where lang = 'en')
where w not in (select unnest(string_split('a an and are as at be but by for from has have he her his i if in into is it its not of on or our she so such that the their then there these they this to was we were which will with you your', ' '))))""",
    "doc_words": r"select distinct doc_id as tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) as item from documents",
    "conv_words": r"select distinct concat(conv_id, '/', turn) as tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) as item from conversations",
    "doc_lines": "select * from (select distinct doc_id as tid, unnest(string_split(text, chr(10))) as item from documents) where trim(item) <> ''",
    "page_words": r"select distinct page_id as tid, unnest(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '\p{L}+')) as item from pages",
    "page_tags": "select distinct page_id as tid, unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) as item from pages",
    "bench_words": r"select distinct item_id as tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) as item from benchmark",
    "userday_events": "select distinct concat(user_id, '@', strftime(ts, '%Y-%m-%d')) as tid, event_type as item from events",
    "user_props": "select distinct user_id as tid, concat('k=', json_extract_string(props, '$.k')) as item from events where json_extract_string(props, '$.k') is not null",
    "vec_dims": "select tid, concat('d', i - 1) as item from (select vec_id as tid, unnest(embedding) as v, generate_subscripts(embedding, 1) as i from embeddings) where v > cast(0.15 as double)",
}
SEVERAL = "(values ('n15|r0', ['n15', 'r0']), ('n21|r1', ['n21', 'r1']), ('n12|r2', ['n12', 'r2'])) as k(key, items)"


def base(name: str) -> str:
    """b (tid, items), c (items, mult), m, s (item, n), p (a, b, n) of a source."""
    return based(LONG[name])


def based(long: str) -> str:
    return f"""
l as materialized ({long}),
b as materialized (select tid, list_sort(list(item)) as items from l group by tid),
c as materialized (select items, count(*) as mult from b group by items),
m as materialized (select count(*)::double as m from b),
s as materialized (select item, count(*) as n from l group by item),
p as materialized (select x.item as a, y.item as b, count(*) as n from l x join l y on x.tid = y.tid and x.item < y.item group by all)"""


def catalog(kind: str) -> str:
    """k0 (key, items, n, pi): items and pairs."""
    pairs = "select concat(a, '|', b), [a, b], p.n, p.n / m from p, m" if kind == "all" else "select concat(a, '|', b), [a, b], p.n, p.n / m from p join s on s.item = p.a and s.n = p.n, m"
    return f"k0 as materialized (select item as key, [item] as items, n, n / m as pi from s, m union all {pairs})"


def greedy(i: int) -> str:
    """g{i}: the covers of c with k{i}; u{i}: usages; k{i+1}: the catalog with re-estimated probabilities."""
    return f"""
g{i} as (
  select items, mult, items as rest, []::varchar[] as cover, 0::double as cost from c
  union all
  select g.items, g.mult, list_filter(g.rest, lambda x: not list_contains(best.items, x)), list_append(g.cover, best.key), g.cost + best.w
  from g{i} g, lateral (
    select k.key, k.items, -ln(k.pi) as w from k{i} k where list_has_all(g.items, k.items) and list_has_any(k.items, g.rest)
    order by round(-ln(k.pi) / len(list_intersect(k.items, g.rest)), 9), len(list_intersect(k.items, g.rest)) desc, k.n desc, k.key limit 1) best
  where len(g.rest) > 0
),
d{i} as materialized (select items, mult, cover, cost from g{i} where len(rest) = 0),
u{i} as materialized (select key, sum(mult)::bigint as usage from (select unnest(cover) as key, mult from d{i}) group by key),
k{i + 1} as materialized (select k.key, k.items, k.n, u.usage / m as pi from k{i} k join u{i} u on u.key = k.key, m)"""


H = "(case when ({0}) <= 0 or ({0}) >= 1 then 0 else -({0}) * ln({0}) - (1 - ({0})) * ln(1 - ({0})) end)"
PLANTED = "(values (['a','b'], 0.3), (['c','d','e'], 0.2), (['f','g'], 0.25), (['p'], 0.1), (['q'], 0.2), (['r'], 0.05), (['s'], 0.15)) as t(items, pi)"
SUBSETS = """
i as (select list(item order by item) as items, count(*) as n from s),
q as (select list_filter(items, lambda x, j: (mask >> (j - 1)::int) % 2 = 1) as items from i, range(1, 32) as r(mask)),
f as materialized (select array_to_string(q.items, '|') as key, q.items, len(q.items)::int as size, sum(mult)::bigint as support
  from q join c on list_has_all(c.items, q.items) group by all having sum(mult) >= 0.0575 * (select m from m))"""
DAILY = f"""
o as materialized (select b.tid, b.items, o_orderdate as ts from b join orders on b.tid = o_orderkey),
days as (select unnest(generate_series(min(ts)::date, max(ts)::date, interval 1 day))::date as day from o),
n as (select ts::date as day, k.key as itemset, count(*) as n from o join {SEVERAL} on list_has_all(o.items, k.items) group by all),
daily as materialized (select day, k.key as itemset, coalesce(n.n, 0) as n from days cross join {SEVERAL} left join n on n.day = days.day and n.itemset = k.key)"""
DAILY = DAILY.replace("select day, k.key as itemset, coalesce", "select days.day, k.key as itemset, coalesce")


def mined(long: str) -> str:
    """Two iterations of the miner with one round of EM each: the accepted set and the profit after each."""
    h = [H.format(x) for x in ("x.n / m", "y.n / m", "p.n / m", "(x.n - p.n) / m", "(y.n - p.n) / m")]
    usage = H.format("usage / m")
    return f"""with recursive {based(long)},
first as materialized (select concat(a, '|', b) as key, [a, b] as items, p.n as n, {h[0]} + {h[1]} - {h[2]} - {h[3]} - {h[4]} as gain from p join s x on x.item = a join s y on y.item = b, m),
one as materialized (select * from first where gain > 1e-12 order by n desc, key limit 1),
refused as materialized (select f.key from first f left join one on true where one.key is null or f.n > one.n or (f.n = one.n and f.key < one.key)),
k1 as materialized (select item as key, [item] as items, s.n as n, (s.n - case when list_contains(one.items, item) then one.n else 0 end) / m as pi from s cross join one, m where s.n > one.n or not list_contains(one.items, item)
  union all select key, items, n, n / m from one, m),
{greedy(1)},
{greedy(2)},
q as materialized (select key, items, n from (select array_to_string(items, '|') as key, items, (select sum(mult) from c where list_has_all(c.items, u.items)) as n
  from (select distinct list_sort(list_distinct(list_concat(x.items, y.items))) as items from k2 x join k2 y on x.key < y.key) u)
  where n > 0 and key not in (select key from k2) and key not in (select key from refused)),
w as (
  select q.key as cand, c.items, c.mult, list_filter(c.items, lambda x: not list_contains(q.items, x)) as rest, [q.key] as cover from q join c on list_has_all(c.items, q.items)
  union all
  select w.cand, w.items, w.mult, list_filter(w.rest, lambda x: not list_contains(best.items, x)), list_append(w.cover, best.key)
  from w, lateral (
    select k.key, k.items from k2 k where list_has_all(w.items, k.items) and list_has_any(k.items, w.rest)
    order by round(-ln(k.pi) / len(list_intersect(k.items, w.rest)), 9), len(list_intersect(k.items, w.rest)) desc, k.n desc, k.key limit 1) best
  where len(w.rest) > 0
),
moved as materialized (select cand, key, sum(n)::bigint as d from (
  select cand, unnest(cover) as key, mult as n from w where len(rest) = 0
  union all select q.key, unnest(d2.cover), -mult from q join d2 on list_has_all(d2.items, q.items)) group by cand, key having sum(n) <> 0),
gains as materialized (select cand, sum({H.format('coalesce(u.usage, 0) / m')} - {H.format('(coalesce(u.usage, 0) + d) / m')}) as gain from moved left join u1 u on u.key = moved.key, m group by cand),
two as materialized (select q.* from q join gains on cand = q.key where gain > 1e-12 order by n desc, q.key limit 1),
k5 as materialized (select key, items, n, pi from (select k.key, k.items, k.n, (u.usage + coalesce(v.d, 0)) / m as pi from k2 k join u1 u on u.key = k.key left join (select moved.* from moved join two on cand = two.key) v on v.key = k.key, m
  union all select two.key, two.items, two.n, v.d / m from two join moved v on v.cand = two.key and v.key = two.key, m) where pi > 0),
{greedy(5)},
start as (select -sum({H.format('n / m')}) as profit from s, m),
end1 as (select -sum({usage}) as profit from u1, m),
end2 as (select -sum({usage}) as profit from u5, m)
select 0::int as iter, (select key from one) as accepted, round(case when exists (from one) then (select profit from end1) else (select profit from start) end, 6) as profit
union all select 1::int, (select key from two), round(case when exists (from two) then (select profit from end2) else (select profit from end1) end, 6) where exists (from one)"""


def _ranked(order: str, singles: bool) -> str:
    where = "" if singles else "where len(items) > 1"
    return f"""
, z as (select k.key, k.items, coalesce(u.usage, 0) as usage, k.n as support, coalesce(u.usage, 0) / k.n as interest, coalesce(u.usage, 0) / m as pi from k0 k left join u0 u on u.key = k.key, m)
select (row_number() over (order by {order}))::int as rank, key as itemset, usage, support, round(interest, 6) as interestingness, round(pi, 6) as pi from z {where} order by {order} limit 20"""


def oracle_sql() -> dict[str, str]:
    out = {f"item_support_{n}": f"select item, count(*) as support from ({sql}) group by item" for n, sql in LONG.items()}
    for n in ("order_geo", "order_regions", "cust_brands", "part_attrs", "bench_words"):
        out[f"pair_support_{n}"] = f"with {base(n)} select concat(a, '|', b) as itemset, n as support from p"
    for n in ("order_geo", "order_regions", "order_brands", "order_tokens", "cust_brands", "userday_events", "part_attrs", "doc_lines"):
        h = [H.format(x) for x in ("x.n / m", "y.n / m", "p.n / m", "(x.n - p.n) / m", "(y.n - p.n) / m")]
        out[f"first_step_{n}"] = f"""with {base(n)}, g as (select concat(a, '|', b) as itemset, p.n as support, {h[0]} + {h[1]} - {h[2]} - {h[3]} - {h[4]} as gain
from p join s x on x.item = a join s y on y.item = b, m) select itemset, support, round(gain, 6) as gain from g where gain > 1e-9"""
    kinds = {"order_geo": "implied", "order_regions": "all", "userday_events": "all"}
    start = {n: f"with recursive {base(n)}, {catalog(k)}, {greedy(0)}" for n, k in kinds.items()}
    cover = "select array_to_string(items, '|') as basket, mult, array_to_string(cover, '+') as cover, round(cost, 6) as cost from d0"
    for n in kinds:
        out[f"greedy_cover_{n}"] = f"{start[n]} {cover}"
    out["greedy_cover_arrow_order_geo"] = out["greedy_cover_lazy_order_geo"] = out["greedy_cover_order_geo"]
    full = """, unused as (select -sum(case when pi < 1 then ln(1 - pi) else 0 end) as c from k0),
w as (select array_to_string(d.items, '|') as basket, sum(-ln(k.pi) + case when k.pi < 1 then ln(1 - k.pi) else 0 end) as g
      from (select items, unnest(cover) as key from d0) d join k0 k on k.key = d.key group by all)"""
    out["cover_cost"] = f"{start['order_regions']} {full} select basket, round(g + c, 6) as full_cost from w, unused"
    out["log_joint"] = f"{start['userday_events']} {full} select basket, round(-(g + c), 6) as logp from w, unused"
    out["description_length"] = f"{start['order_regions']} {full} select basket, round((g + c) / ln(2), 6) as bits, round(-(g + c), 6) as logp from w, unused"
    usage = H.format("usage / m")
    out["profit_closed_form"] = f"{start['order_geo']} select round(-sum({usage}), 6) as profit, count(*) as used_sets from u0, m"
    out["interestingness_order_geo"] = f"""{start['order_geo']} select k.key, coalesce(u.usage, 0) as usage, k.n as support, round(coalesce(u.usage, 0) / k.n, 6) as interestingness,
round(coalesce(u.usage, 0) / m, 6) as pi from k0 k left join u0 u on u.key = k.key, m"""
    out["rank_pi"] = start["order_geo"] + _ranked("pi desc, interest desc, key", True)
    out["top_k"] = start["order_geo"] + _ranked("interest desc, pi desc, key", False)
    for n in ("order_regions", "userday_events"):
        rounds = " union all ".join(f"select {i} as i, key, usage from u{i}" for i in range(3))
        out[f"hard_em_{n}"] = f"""{start[n]}, {greedy(1)}, {greedy(2)}, r as materialized ({rounds}), f as (select i, -sum({H.format('usage / m')}) as profit from r, m group by i),
best as (select i from f where profit >= (select max(profit) from f) - 1e-13 order by i desc limit 1)
select key, usage, round(usage / m, 6) as pi from r join best on best.i = r.i, m"""
    out["structural_step_order_geo"] = f"""with g as ({out['first_step_order_geo']}), {base('order_geo')},
best as (select itemset, support, gain from g order by support desc, itemset limit 1)
select best.itemset as accepted, round(best.gain - (select sum({H.format('n / m')}) from s, m), 6) as profit from best"""
    # The gain is not rounded before it is added.
    out["structural_step_order_geo"] = out["structural_step_order_geo"].replace("round(gain, 6) as gain from g where", "gain from g where")
    queue = "select (row_number() over (order by n desc, concat(a, '|', b)))::int as rank, concat(a, '|', b) as itemset, n as support from p"
    out["candidate_queue_order_geo"] = f"with {base('order_geo')} {queue}"
    out["apriori_queue_order_geo"] = f"""with {base('order_geo')}, least as (select floor(m / 10) as t from m),
t as (select x.item as a, y.item as b, z.item as c, count(*) as n from l x join l y on x.tid = y.tid and x.item < y.item join l z on y.tid = z.tid and y.item < z.item group by all),
a as (select concat(a, '|', b) as itemset, n from p, least where n >= t union all select concat(a, '|', b, '|', c), n from t, least where n >= least.t)
select (row_number() over (order by n desc, itemset))::int as rank, itemset, n as support from a"""
    out["prefix_tree_order_regions"] = f"""with {base('order_regions')}, t as (select unnest(list_transform(range(1, len(items) + 1), lambda j: items[1:j])) as path, mult from c)
select array_to_string(path, '|') as path, path[-1] as last, len(path)::int as depth, sum(mult)::bigint as cnt from t group by all"""
    tree = f"with {base('order_geo')} select k.key, sum(mult)::bigint as support from c join {SEVERAL} on list_has_all(c.items, k.items) group by k.key"
    out |= dict.fromkeys(("tree_support_order_geo", "tree_support_ranked_order_geo", "tree_support_compressed_order_geo", "batch_support_order_geo"), tree)
    out["encoded_round_trip"] = f"with {base('order_geo')} select tid, array_to_string(items, '|') as basket from b"
    out["compressed_baskets"] = f"with {base('userday_events')} select array_to_string(items, '|') as basket, mult from c"
    table = f"""with recursive {base('order_geo')}, {catalog('implied')},
t as materialized (select items, key, row_number() over (order by n desc, key) as r from k0 where len(items) = 2),
g as (select items, mult, items as rest, []::varchar[] as cover, 0 as r from c
  union all select g.items, g.mult, case when list_has_all(g.rest, t.items) then list_filter(g.rest, lambda x: not list_contains(t.items, x)) else g.rest end,
  case when list_has_all(g.rest, t.items) then list_append(g.cover, t.key) else g.cover end, t.r::int from g join t on t.r = g.r + 1),
d as materialized (select items, mult, list_concat(cover, list_sort(rest)) as cover from g where r = (select max(r) from t))"""
    out["code_cover_order_geo"] = out["code_cover_arrow_order_geo"] = f"{table} select array_to_string(items, '|') as basket, mult, array_to_string(cover, '+') as cover from d"
    out["codetable_bits"] = f"""{table}, u as (select key, sum(mult)::bigint as usage from (select unnest(cover) as key, mult from d) group by key)
select key, usage, round(-log2(usage / (select sum(usage) from u)), 6) as bits from u"""
    for n in ("order_regions", "userday_events"):
        out[f"frequent_{n}"] = f"with {base(n)}, {SUBSETS} select key, size, support from f"
        out[f"closed_itemsets_{n}"] = f"with {base(n)}, {SUBSETS} select key, size, support from f where not exists (select 1 from f g where g.support = f.support and g.size > f.size and list_has_all(g.items, f.items))"
    out["chi2_rank_order_regions"] = f"""with {base('order_regions')}, {SUBSETS},
x as (select key, support, (select m from m) * product(s.n / (select m from m)) as e from (select key, support, unnest(items) as item from f where size > 1
  and not exists (select 1 from f g where g.support = f.support and g.size > f.size and list_has_all(g.items, f.items))) y join s on s.item = y.item group by all),
v as (select key, support, (support - e) ** 2 / e + (support - e) ** 2 / (m - e) as chi2 from x, m)
select (row_number() over (order by round(chi2, 6) desc, key))::int as rank, key as itemset, support, round(chi2, 4) as chi2 from v order by round(chi2, 6) desc, key limit 10"""
    patterns = [("p.n / m", ""), ("(x.n - p.n) / m", ""), ("(y.n - p.n) / m", ""), ("(m - x.n - y.n + p.n) / m", "")]
    xlogx = " + ".join(f"(case when ({q}) <= 0 then 0 else ({q}) * ln({q}) end)" for q, _ in patterns)
    out["maxent_pair_logp"] = f"""with {base('order_geo')},
one as (select -sum({H.format('n / m')}) as h from s, m where item not in ('n15', 'r1', 'n21', 'r2', 'n12', 'r3')),
two as (select sum({xlogx}) as h from p join s x on x.item = a join s y on y.item = b, m where concat(a, '|', b) in ('n15|r1', 'n21|r2', 'n12|r3'))
select round(one.h + two.h, 4) as mean_logp from one, two"""
    out["generate_md5"] = f"""with {base('order_regions')}, {catalog('all')},
d as (select b.tid, k0.items, k0.pi, ('0x' || substr(md5(concat_ws('|', '7', b.tid, k0.key)), 1, 8))::bigint / 4294967296.0 as u from b, k0)
select tid, array_to_string(list_sort(list_distinct(flatten(list(case when u < pi then items else [] end)))), '|') as basket from d group by tid"""
    curve = f"""with {base('order_geo')}, t as (select concat('n', n_nationkey, '|r', n_regionkey) as itemset from nation),
k as (select itemset, row_number() over (order by n desc, itemset) as rank from (select concat(a, '|', b) as itemset, n from p) order by n desc, itemset limit 50),
r as (select rank::int as k, sum((itemset in (select itemset from t))::int) over (order by rank) as hits, (select count(*) from t) as known from k)"""
    out["precision_recall"] = f"{curve} select k, round(hits / k, 6) as precision, round(hits / known, 6) as recall from r"
    out["eleven_point"] = f"{curve} select round(l / 10, 6) as recall, round(coalesce(max(hits / k), 0), 6) as precision from range(11) as x(l) left join r on hits / known >= l / 10 - 1e-12 group by l"
    out["iid_order_geo"] = f"""with {base('order_geo')}, t as (select concat(a, '|', b) as itemset, [a, b] as items from p order by n desc, itemset limit 50),
d as (select x.itemset, min(len(x.items) + len(y.items) - 2 * len(list_intersect(x.items, y.items))) as distance from t x join t y on x.itemset <> y.itemset group by x.itemset)
select round(avg(distance), 6) as iid, count(*) as n from d"""
    geo = f"with {base('order_geo')}, {DAILY}"
    out["mentions_per_day"] = f"{geo} select day, itemset, n from daily"
    out["spikes"] = f"""{geo}, z as (select day, itemset, n, avg(n) over (partition by itemset) as mu, stddev_pop(n) over (partition by itemset) as sd from daily)
select day, itemset, n, round((n - mu) / sd, 6) as z from z where sd > 0 and n > mu + 3 * sd"""
    out["series_corr"] = f"{geo} select x.itemset as a, y.itemset as b, round(corr(x.n, y.n), 6) as corr from daily x join daily y on x.day = y.day and x.itemset < y.itemset group by all"
    out["moving_mentions"] = f"{geo} select day, itemset, round(avg(n) over (partition by itemset order by day rows between 6 preceding and current row), 6) as moving from daily"
    out["rules_order_geo"] = f"""with {base('order_geo')}, r as (select a as x, b as y, n from p union all select b, a, n from p)
select x as antecedent, y as consequent, r.n as support, round(r.n / sx.n, 6) as confidence, round(r.n / sx.n * m / sy.n, 6) as lift
from r join s sx on sx.item = x join s sy on sy.item = y, m where r.n / sx.n >= 0.3"""
    out["tiles_order_regions"] = f"{start['order_regions']} select key, usage as rows from u0"
    out["events_windows"] = "select user_id, date_trunc('day', ts) as start, array_to_string(list_sort(list(distinct event_type)), '|') as basket from events group by all"
    out["events_sessions"] = """with e as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 2 hour then 0 else 1 end as fresh from events),
g as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as session from e)
select user_id, min(ts) as start, array_to_string(list_sort(list(distinct event_type)), '|') as basket from g group by user_id, session"""
    out["stream_mentions"] = "select date_trunc('day', ts) as start, event_type as itemset, count(*) as n from events where event_type in ('click', 'purchase', 'view') group by all"
    out["usage_rollup"] = f"with {base('order_geo')}, {DAILY} select year(ts)::int as year, month(ts)::int as month, count(*) as n from o where list_has_all(items, ['n15', 'r0']) group by rollup (year(ts)::int, month(ts)::int)"
    out["sql_functions"] = f"""with {base('order_geo')} select concat(a, '|', b) as itemset, (2 + 2 - 2 * len(list_intersect([a, b], ['n1', 'r1'])))::int as distance, b = 'r1' or a = 'r1' as has_r1,
round({H.format('0.25::double')}, 6) as h, round((n - 100.0::double) ** 2 / 100 + (n - 100.0::double) ** 2 / 99900, 6) as chi2 from p"""
    out["stemmed_words_en"] = f"select item, count(*) as support from ({LONG['doc_stems_en']}) group by item"
    out["table_function_subsets"] = f"""with {base('order_regions')}, i as (select list(item order by item) as items from s),
r as (select unnest(range(1, (2 ** len(items))::bigint - 1)) as mask, items from i)
select array_to_string(list_filter(items, lambda x, j: (mask >> (j - 1)::int) % 2 = 1), '|') as subset from r"""
    out["arrow_function_jaccard"] = f"with {base('order_geo')} select concat(a, '|', b) as itemset, round(len(list_intersect([a, b], ['n1', 'r1'])) / (4 - len(list_intersect([a, b], ['n1', 'r1']))), 6) as jaccard from p"
    out["aggregate_mean_distance"] = f"select iid from ({out['iid_order_geo']})"
    out["shared_spikes"] = f"""{geo}, z as (select day, itemset, n, avg(n) over (partition by itemset) as mu, stddev_pop(n) over (partition by itemset) as sd from daily),
y as (select day, itemset from z where sd > 0 and n > mu + 2 * sd)
select day, count(*) as sets, array_to_string(list(itemset order by itemset), '+') as itemsets from y group by day having count(*) > 1"""
    out["rank_of_sets"] = f"""with {base('order_geo')}, t as (select concat(a, '|', b) as itemset, (row_number() over (order by n desc, concat(a, '|', b)))::int as rank from p),
v as (select unnest(['n15|r0', 'n21|r1', 'n12|r2', 'a|b']) as itemset) select v.itemset, t.rank from v left join t on t.itemset = v.itemset and t.rank <= 20"""
    out["shortfall_order_geo"] = f"with {base('order_geo')}, t as (select * from p where n > 1 limit 50) select count(*) as n_listed, count(*) < 50 as short from t"
    out["log_odds_weights"] = f"with {base('order_geo')}, {catalog('implied')} select key, round(-ln(pi) + ln(1 - pi), 6) as weight from k0 where pi > 0 and pi < 1"
    out["events_cube"] = "select event_type, day, count(*) as n from (select event_type, ts::date as day from events) group by cube (event_type, day)"
    # A set is accepted where, and only where, some pair gains in the first step.
    each = []
    for n in ("order_regions", "order_brands", "part_suppnations", "userday_events"):
        h = [H.format(x) for x in ("x.n / m", "y.n / m", "p.n / m", "(x.n - p.n) / m", "(y.n - p.n) / m")]
        each.append(f"(with {base(n)} select '{n}' as source, count(*) filter (where {h[0]} + {h[1]} - {h[2]} - {h[3]} - {h[4]} > 1e-12) as accepted from p join s x on x.item = a join s y on y.item = b, m)")
    out["null_accepts"] = "select * from (" + " union all ".join(each) + ")"
    drawn = f"select r.tid, t.items, t.pi, ('0x' || substr(md5(concat_ws('|', '7', r.tid, array_to_string(t.items, '|'))), 1, 8))::bigint / 4294967296.0 as u from range(400) as r(tid), {PLANTED}"
    out["mine_small_planted"] = mined(f"select distinct tid, unnest(items) as item from ({drawn}) where u < pi")
    out["mine_small_userday_events"] = mined(LONG["userday_events"])
    out["mine_small_order_geo"] = mined(LONG["order_geo"])
    return out
