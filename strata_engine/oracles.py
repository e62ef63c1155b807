"""DuckDB SQL of the catalog's queries, written from the definitions."""

from __future__ import annotations

SQL: dict[str, str] = {}


def u(purpose: str, *ids: str, seed: str = "42") -> str:
    return f"(concat('0x', substr(md5(concat_ws('|', '{seed}', '{purpose}', {', '.join(ids)})), 1, 13))::bigint / 4503599627370496.0)"


def r(x: str) -> str:
    return f"(round({x}, 6) + 0.0)"


EMB = f"""base as materialized (select vec_id as id, list_transform(embedding, lambda x: x::double) as z, label::int as y from embeddings),
emb as materialized (select id, z, y, case when {u('soft', 'id')} < (case when z[1] >= 0 then 0.8 else 0.2 end) then 's' else 't' end as domain from base)"""
SEEDS = EMB + ", seeds as materialized (select (row_number() over (order by id) - 1)::int as j, z as c from (select id, z from emb order by id limit 8))"
DIST = SEEDS + """, dist as materialized (select e.id, e.domain, list(round(list_distance(e.z, s.c), 9) order by s.j) as d from emb e, seeds s group by e.id, e.domain),
ordered as materialized (select row_number() over (order by id) as r, id, d from dist)"""


def greedy(score: str, name: str = "g", source: str = "ordered", by: str = "") -> str:
    """Rows in order, sizes and residents' sums carried as lists."""
    key = f"{by}, " if by else ""
    start = f"select distinct {by}, 0::bigint, null::bigint, -1, [0,0,0,0,0,0,0,0]::int[], [0,0,0,0,0,0,0,0]::double[] from {source}" if by else "select 0::bigint, null::bigint, -1, [0,0,0,0,0,0,0,0]::int[], [0,0,0,0,0,0,0,0]::double[]"
    on = f" and o.{by} = g.{by}" if by else ""
    pick = f"(list_position(list_transform(range(1, 9), lambda i: {score}), list_min(list_transform(range(1, 9), lambda i: {score}))) - 1)"
    return f"""{name}({key}r, id, stratum, sizes, sums) as ({start}
union all select {('o.' + by + ', ') if by else ''}r, id, p::int, list_transform(range(1, 9), lambda i: sizes[i] + (i = p + 1)::int), list_transform(range(1, 9), lambda i: sums[i] + case when i = p + 1 then d[i] else 0 end)
from (select {('o.' + by + ', ') if by else ''}o.r, o.id, o.d, g.sizes, g.sums, {pick} as p from {name} g join {source} o on o.r = g.r + 1{on}) o)"""


G8 = "with recursive " + DIST + ", " + greedy("o.d[i] * (g.sizes[i] + 1)") + ", strata as materialized (select id, stratum from g where id is not null)"
SIZES = ", sizes as materialized (select stratum, count(*) as n_h, sum(count(*)) over () as n from strata group by stratum), places as (select stratum, id, row_number() over (partition by stratum order by id) - 1 as pos from strata)"

for _n, _k in {"kernel_linear": "list_inner_product(e.z, s.c)", "kernel_rbf": "exp(-0.5 * list_distance(e.z, s.c) ** 2)", "kernel_rbf_mix": "list_sum(list_transform([0.001, 0.01, 0.1, 1.0, 10.0], lambda g: exp(-g * list_distance(e.z, s.c) ** 2)))"}.items():
    SQL[_n] = f"with {SEEDS} select e.id as a, s.j as b, {r(_k)} as k from emb e, seeds s"
SQL["kernel_quad"] = f"with {SEEDS}, comp as (select i, avg(z[i]) as m from emb, range(1, 65) t(i) group by i), mu as (select list(m order by i) as m from comp) select e.id as a, s.j as b, {r('list_sum(list_transform(range(1, 65), lambda i: (e.z[i] - mu.m[i]) * (s.c[i] - mu.m[i]))) ** 2')} as k from emb e, seeds s, mu"
SQL["assign_greedy"] = G8 + " select id as vec_id, stratum from strata"
SQL["assign_marginal"] = "with recursive " + DIST + ", " + greedy("o.d[i] * (g.sizes[i] + 1) + g.sums[i]") + " select id as vec_id, stratum from g where id is not null"
SQL["assign_bucketed"] = "with recursive " + DIST + ", dealt as materialized (select b, id, d, row_number() over (partition by b order by id) as r from (select id, d, (concat('0x', substr(md5(concat_ws('|', '0', 'bucket', id)), 1, 13))::bigint % 4)::int as b from dist)), " + greedy("o.d[i] * (g.sizes[i] + 1)", source="dealt", by="b") + " select id as vec_id, stratum from g where id is not null"
SQL["assign_nearest"] = f"with {DIST} select id as vec_id, (list_position(d, list_min(d)) - 1)::int as stratum from dist"
SQL["assign_parallel"] = "with recursive " + DIST + """, blk as materialized (select ((r - 1) // 10)::bigint as b, list(id order by r) as ids, list(d order by r) as ds from ordered group by 1),
p(b, ids, picks, sizes) as (select -1::bigint, []::bigint[], []::bigint[], [0,0,0,0,0,0,0,0]::bigint[]
union all select b, ids, picks, list_transform(range(1, 9), lambda i: sizes[i] + len(list_filter(picks, lambda x: x = i))) from (
select k.b, k.ids, p.sizes, list_transform(k.ds, lambda dd: list_position(list_transform(range(1, 9), lambda i: dd[i] * (p.sizes[i] + 1)), list_min(list_transform(range(1, 9), lambda i: dd[i] * (p.sizes[i] + 1))))) as picks from p join blk k on k.b = p.b + 1))
select unnest(ids) as vec_id, (unnest(picks) - 1)::int as stratum from p where b >= 0"""
TRIALS = "with recursive " + DIST + f", dealt as materialized (select t, id, d, row_number() over (partition by t order by {u('perm', 't', 'id')}, id) as r from dist, range(0, 4) x(t)), " + greedy("o.d[i] * (g.sizes[i] + 1)", source="dealt", by="t") + ", last as (select t, sizes, sums from g qualify row_number() over (partition by t order by r desc) = 1), costs as (select t::int as trial, list_sum(list_transform(range(1, 9), lambda i: sizes[i] * sums[i])) as c from last)"
SQL["assign_trials"] = TRIALS + f" select trial, {r('c')} as cost, c = min(c) over () as is_best from costs"
SQL["topk_trials"] = TRIALS + f" select trial, {r('c')} as cost from costs order by 2, 1 limit 2"
_cost = lambda name, src: f"select '{name}' as method, {r('sum(n * s)')} as loss from (select stratum, count(*) as n, sum(d[stratum + 1]) as s from {src} join dist using (id) group by stratum)"
SQL["assign_loss_methods"] = (
    "with recursive " + DIST + ", " + greedy("o.d[i] * (g.sizes[i] + 1)") + ", " + greedy("o.d[i] * (g.sizes[i] + 1) + g.sums[i]", "g2") + SQL["assign_parallel"].split("ordered as materialized (select row_number() over (order by id) as r, id, d from dist)")[1].rsplit("\nselect", 1)[0]
    + ", par as (select unnest(ids) as id, (unnest(picks) - 1)::int as stratum from p where b >= 0), near as (select id, (list_position(d, list_min(d)) - 1)::int as stratum from dist) "
    + " union all ".join([_cost("greedy", "(select id, stratum from g where id is not null)"), _cost("marginal", "(select id, stratum from g2 where id is not null)"), _cost("parallel10", "par"), _cost("nearest", "near")])
)
SQL["kernel_distances"] = f"""with {EMB}, k as materialized (select a.id, b.id % 8 as j, sum(exp(-0.5 * list_distance(a.z, b.z) ** 2)) as s, count(*) as n from emb a, emb b group by 1, 2),
w as (select j, sum(s) / max(n) ** 2 as inner_mean from k where id % 8 = j group by j)
select id as vec_id, k.j::int as stratum, {r('greatest(1 - 2 * s / n + inner_mean, 0)')} as dist from k join w using (j)"""
SQL["kernel_kmeans"] = f"""with {EMB}, k as materialized (select a.id, b.id % 8 as j, sum(exp(-0.5 * list_distance(a.z, b.z) ** 2)) as s, count(*) as n from emb a, emb b group by 1, 2),
w as (select j, sum(s) / max(n) ** 2 as inner_mean from k where id % 8 = j group by j)
select id as vec_id, (arg_min(k.j, (round(greatest(1 - 2 * s / n + inner_mean, 0), 9), k.j)))::int as stratum from k join w using (j) group by id"""
SQL["seed_kpp"] = f"""with recursive {EMB}, s(r, id, near) as (select 0, (select id from emb order by {u('seed', "'0'", 'id')}, id limit 1), (select map(list(id order by id), list(1e308::double order by id)) from emb)
union all select r + 1, pick, near2 from (select s.r, n.near2, (select arg_min(e.id, (-ln(1 - {u('seed', 's.r + 1', 'e.id')}) / n.near2[e.id], e.id)) from emb e where n.near2[e.id] > 1e-12) as pick
from s, lateral (select map(list(e.id order by e.id), list(least(s.near[e.id], 2 - 2 * exp(-0.5 * list_distance(e.z, c.z) ** 2)) order by e.id)) as near2 from emb e, (select z from emb where id = s.id) c) n) where r < 7)
select r::int as r, id as vec_id from s"""


def seeding(key: str, seed: str, members: str, on: str) -> str:
    """Seeds by races on squared image distances from ``gram``, for every ``key`` at once."""
    race = u("seed", "s.r + 1", "e.id", seed="@").replace("'@'", seed)
    first = u("seed", "'0'", "id", seed="@").replace("'@'", seed.replace("s.", ""))
    return f"""sk({key}, r, id, near) as (select {key}, 0, arg_min(id, ({first}, id)), map(list(id order by id), list(1e308::double order by id)) from {members} group by {key}
union all select {key}, r + 1, pick, near2 from (select s.{key}, s.r, n.near2, (select arg_min(e.id, (-ln(1 - {race}) / n.near2[e.id], e.id)) from {members} e where e.{key} = s.{key} and n.near2[e.id] > 1e-12) as pick
from sk s, lateral (select map(list(g.i order by g.i), list(least(s.near[g.i], greatest(g.ki + g.kj - 2 * g.k, 0)) order by g.i)) as near2 from gram g where g.j = s.id{on}) n) where r < 7)"""


def alternation(rounds: int = 5, trials: int = 100) -> str:
    """Strata of every domain by rounds of image distances and the cheapest of shuffled passes, ten rows at a time; the best round."""
    cost = "dd[i] * (p.sizes[i] + 1)"
    out = [seeding("domain", "42", "emb", ""), "d0 as materialized (select g.domain, g.i as id, list(greatest(g.ki + g.kj - 2 * g.k, 0) order by s.r) as d from gram g join sk s on s.domain = g.domain and s.id = g.j group by 1, 2)"]
    for x in range(rounds):
        n = x + 1
        out += [
            f"blk{n} as materialized (select domain, t, (r - 1) // 10 as b, list(id order by r) as ids, list(d order by r) as ds from (select domain, t, id, d, row_number() over (partition by domain, t order by {u('perm', f'{chr(39)}{x}{chr(39)}', 't', 'id')}, id) as r from d{x}, range(0, {trials}) y(t)) group by 1, 2, 3)",
            f"""p{n}(domain, t, b, ids, picks, sizes) as (select distinct domain, t, -1::bigint, []::bigint[], []::bigint[], [0,0,0,0,0,0,0,0]::bigint[] from blk{n}
union all select domain, t, b, ids, picks, list_transform(range(1, 9), lambda i: sizes[i] + len(list_filter(picks, lambda x: x = i))) from (
select k.domain, k.t, k.b, k.ids, p.sizes, list_transform(k.ds, lambda dd: list_position(list_transform(range(1, 9), lambda i: {cost}), list_min(list_transform(range(1, 9), lambda i: {cost})))) as picks from p{n} p join blk{n} k on k.domain = p.domain and k.t = p.t and k.b = p.b + 1))""",
            f"flat{n} as materialized (select domain, t, unnest(ids) as id, unnest(picks) as h from p{n} where b >= 0)",
            f"best{n} as materialized (select domain, arg_min(t, (c, t)) as t from (select domain, t, sum(n * s) as c from (select f.domain, f.t, f.h, count(*) as n, sum(d[f.h]) as s from flat{n} f join d{x} on d{x}.domain = f.domain and d{x}.id = f.id group by 1, 2, 3) group by 1, 2) group by 1)",
            f"a{n} as materialized (select f.domain, f.id, f.h from flat{n} f join best{n} b on b.domain = f.domain and b.t = f.t)",
            f"s{n} as materialized (select g.domain, g.i, max(g.ki) as ki, a.h, sum(g.k) as s, count(*) as n from gram g join a{n} a on a.domain = g.domain and a.id = g.j group by g.domain, g.i, a.h)",
            f"w{n} as materialized (select s.domain, s.h, sum(s.s) as inner_sum, sum(s.ki) as diag, max(s.n) as n from s{n} s join a{n} a on a.domain = s.domain and a.id = s.i and a.h = s.h group by 1, 2)",
            f"d{n} as materialized (select s.domain, s.i as id, list(greatest(s.ki - 2 * s.s / s.n + w.inner_sum / (w.n * w.n), 0) order by s.h) as d from s{n} s join w{n} w on w.domain = s.domain and w.h = s.h group by 1, 2)",
            f"v{n} as materialized (select domain, {n} as it, sum(n * (diag - inner_sum / n)) / sum(n) ** 2 as v from w{n} group by 1)",
        ]
    every = " union all ".join(f"select * from v{n}" for n in range(1, rounds + 1))
    same = " union all ".join(f"select x.domain, {n} as it, bool_and(x.h = y.h) as same from a{n} x join a{n - 1} y on x.domain = y.domain and x.id = y.id group by 1" for n in range(2, rounds + 1))
    out += [f"alike as ({same})", f"vs as (select v.* from ({every}) v where not exists (select 1 from alike where alike.domain = v.domain and alike.same and alike.it < v.it))", "won as materialized (select domain, arg_min(it, (round(v, 14), it)) as it from vs group by 1)"]
    out.append("found as materialized (select a.domain, a.id, (a.h - 1)::int as stratum from (" + " union all ".join(f"select {n} as it, * from a{n}" for n in range(1, rounds + 1)) + ") a join won on won.domain = a.domain and won.it = a.it)")
    return ", ".join(out)


GRAM_MIX = "gram as materialized (select a.domain, a.id as i, b.id as j, list_sum(list_transform([0.001, 0.01, 0.1, 1.0, 10.0], lambda g: exp(-g * list_distance(a.z, b.z) ** 2))) as k, 5.0 as ki, 5.0 as kj from emb a join emb b on a.domain = b.domain)"
GRAM_QUAD = """mu as materialized (select domain, list(m order by i) as m from (select domain, i, avg(z[i]) as m from emb, range(1, 65) t(i) group by 1, 2) group by 1),
cen as materialized (select e.id, e.domain, list_transform(range(1, 65), lambda i: e.z[i] - mu.m[i]) as c from emb e join mu on mu.domain = e.domain),
gram as materialized (select a.domain, a.id as i, b.id as j, list_inner_product(a.c, b.c) ** 2 as k, list_inner_product(a.c, a.c) ** 2 as ki, list_inner_product(b.c, b.c) ** 2 as kj from cen a join cen b on a.domain = b.domain)"""
SQL["stratify_med"] = f"with recursive {EMB}, {GRAM_MIX}, {alternation()} select domain, id as vec_id, stratum from found"
SQL["stratify_cad_exact"] = f"with recursive {EMB}, {GRAM_QUAD}, {alternation()} select domain, id as vec_id, stratum from found"
SQL["draw_swks"] = f"with recursive {EMB}, {GRAM_MIX}, {alternation()}, strata as (select id, stratum from found where domain = 's'){{SIZES}} select i::int as iter, stratum, id as vec_id, {r('n_h / n')} as weight from range(0, 20) x(i), sizes join places using (stratum) where pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39))} * n_h)".replace("{SIZES}", SIZES)
SQL["draw_seeding"] = f"with recursive {EMB}, {GRAM_MIX.replace(' from emb a join emb b on a.domain = b.domain', ' from emb a, emb b')}, many as materialized (select it, id from emb, range(0, 20) x(it)), " + seeding("it", "concat('42:', s.it)", "many", "") + " select it as iter, id as vec_id, 0.125::double as weight from sk"
SQL["draw_distinct"] = f"""with recursive {EMB}, n as (select count(*) as n from emb), f(i, c, s) as (select i, 0, []::bigint[] from range(0, 20) x(i)
union all select i, c + 1, list_append(s, case when list_contains(s, p) then l else p end) from (select f.i, f.c, f.s, n.n - 8 + f.c as l, floor({u('distinct', 'f.i', 'f.c')} * (n.n - 8 + f.c + 1))::bigint as p from f, n) where c < 8)
select f.i::int as iter, e.id as vec_id, 0.125::double as weight from (select i, unnest(s) as pos from f where c = 8) f join (select id, row_number() over (order by id) - 1 as pos from emb) e using (pos)"""
ALL_PAIRS = "pairs as materialized (select a.domain as da, b.domain as db, avg(list_sum(list_transform([0.001, 0.01, 0.1, 1.0, 10.0], lambda g: exp(-g * list_distance(a.z, b.z) ** 2)))) as m from emb a, emb b group by 1, 2)"
SQL["med_exact"] = f"with {EMB}, {ALL_PAIRS} select (select count(*) from emb where domain = 's') as n_s, (select count(*) from emb where domain = 't') as n_t, {r('sum(case when da = db then m else -m end)')} as med from pairs"
DOM = EMB + ", strata as (select id, domain, (id % 8)::int as stratum, row_number() over (partition by domain, id % 8 order by id) - 1 as pos, count(*) over (partition by domain, id % 8) as n_h, count(*) over (partition by domain) as n from emb)"


def dom_draws(uniform: bool = False) -> str:
    if uniform:
        one = lambda seed, dom: f"select i::int as iter, '{dom}' as domain, id, 0.125 as w from range(0, 20) x(i), range(0, 8) y(c), (select id, row_number() over (order by id) - 1 as pos, count(*) over () as n from emb where domain = '{dom}') s where pos = floor({u('draw', 'i', chr(39) + '0' + chr(39), 'c', seed=seed)} * n)"
    else:
        one = lambda seed, dom: f"select i::int as iter, domain, id, n_h / n as w from range(0, 20) x(i), strata s where domain = '{dom}' and pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39), seed=seed)} * n_h)"
    return f"draws as materialized ({one('42', 's')} union all {one('43', 't')})"


MIX = "list_sum(list_transform([0.001, 0.01, 0.1, 1.0, 10.0], lambda g: exp(-g * list_distance(a.z, b.z) ** 2)))"
_hat = f"q as materialized (select iter, z, case when d.domain = 's' then w else -w end as q from draws d join emb using (id)), vals as (select a.iter, sum(a.q * b.q * {MIX}) as v from q a join q b on a.iter = b.iter group by 1)"
SQL["med_hat"] = f"with {DOM}, {dom_draws()}, {_hat} select iter, {r('v')} as value from vals"
SQL["med_hat_uniform"] = f"with {DOM}, {dom_draws(True)}, {_hat} select iter, {r('v')} as value from vals"
SQL["loss_variance_mc"] = f"with {DOM}, {dom_draws()}, {_hat} select count(*) as iters, {r('avg(v)')} as mean_value, {r('var_samp(v) * 1000')} as variance_e3 from vals"
SQL["med_plugin_bias"] = f"with {DOM}, h as (select a.domain, a.stratum, max(a.n_h) as n_h, max(a.n) as n, sum({MIX}) as k from (select s.*, z from strata s join emb using (id)) a join (select s.*, z from strata s join emb using (id)) b on a.domain = b.domain and a.stratum = b.stratum group by 1, 2) select {r('sum(n_h * (5 * n_h - k / n_h) / (n * n))')} as bias from h"
LINE = f"""raw as materialized (select concat('0x', substr(md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y-%m-%d'))), 1, 15))::bigint as id, l_returnflag || l_linestatus as env,
(l_quantity - avg(l_quantity) over ()) / stddev_pop(l_quantity) over () as a, (l_extendedprice - avg(l_extendedprice) over ()) / stddev_pop(l_extendedprice) over () as b,
(l_discount - avg(l_discount) over ()) / stddev_pop(l_discount) over () as c, (l_tax - avg(l_tax) over ()) / stddev_pop(l_tax) over () as e from lineitem),
li as materialized (select id, env, case when t then 't' else 's' end as domain, case when t then a * 1.5 + 0.25 else a end as z0, case when t then b * 1.5 + 0.25 else b end as z1, case when t then c * 1.5 + 0.25 else c end as z2, case when t then e * 1.5 + 0.25 else e end as z3 from (select *, {u('affine', 'id')} >= 0.5 as t from raw))"""
PAIRS = [(i, j) for i in range(4) for j in range(i, 4)]
SQL["med_mapped"] = f"with {LINE}, m as (select domain, " + ", ".join(f"avg(z{i} * z{j}) as m{i}{j}" for i, j in PAIRS) + " from li group by domain) select " + r(" + ".join(f"{1 if i == j else 2} * (s.m{i}{j} - t.m{i}{j}) ** 2" for i, j in PAIRS)) + " as med from m s, m t where s.domain = 's' and t.domain = 't'"
SQL["cad_exact"] = f"with {LINE}, c as (select domain, count(*) as n, " + ", ".join(f"covar_samp(z{i}, z{j}) as c{i}{j}" for i, j in PAIRS) + " from li group by domain) select s.n as n_s, t.n as n_t, " + r(" + ".join(f"{1 if i == j else 2} * (s.c{i}{j} - t.c{i}{j}) ** 2" for i, j in PAIRS)) + " as cad from c s, c t where s.domain = 's' and t.domain = 't'"
LDRAWS = LINE + ", strata as materialized (select *, (id % 8)::int as stratum, row_number() over (partition by domain, id % 8 order by id) - 1 as pos, count(*) over (partition by domain, id % 8) as n_h, count(*) over (partition by domain) as n from li), draws as materialized (" + " union all ".join(f"select i::int as iter, s.*, n_h / n as w from range(0, 20) x(i), strata s where domain = '{dom}' and pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39), seed=seed)} * n_h)" for seed, dom in (("42", "s"), ("43", "t"))) + "), mb as (select domain, iter, " + ", ".join(f"sum(w * z{i}) as m{i}" for i in range(4)) + " from draws group by all)"
LCOV = LDRAWS + ", cov as materialized (select d.domain, d.iter, " + ", ".join(f"max(n) / (max(n) - 1.0) * sum(w * (z{i} - m{i}) * (z{j} - m{j})) as c_{i}_{j}" for i, j in PAIRS) + " from draws d join mb using (domain, iter) group by all)"
SQL["cov_hat"] = f"with {LCOV} select domain, iter, " + ", ".join(f"{r(f'c_{i}_{j}')} as c_{i}_{j}" for i, j in PAIRS) + " from cov"
SQL["cad_hat"] = f"with {LCOV} select s.iter, " + r(" + ".join(f"{1 if i == j else 2} * (s.c_{i}_{j} - t.c_{i}_{j}) ** 2" for i, j in PAIRS)) + " as value from cov s join cov t on s.iter = t.iter and s.domain = 's' and t.domain = 't'"
SQL["cov_known_mean"] = f"with {LDRAWS}, mu as (select domain, " + ", ".join(f"avg(z{i}) as m{i}" for i in range(4)) + " from li group by domain) select d.domain, d.iter, " + ", ".join(f"{r(f'sum(w * (z{i} - m{i}) * (z{j} - m{j}))')} as c_{i}_{j}" for i, j in PAIRS) + " from draws d join mu using (domain) group by d.domain, d.iter"
SQL["gchi2_variance"] = f"with {LINE}, h as (select domain, id % 8 as h, count(*) as n_h, " + ", ".join(f"covar_pop(z{i}, z{j}) as c{i}{j}" for i, j in PAIRS) + " from li group by all), tot as (select domain, count(*) as n, " + ", ".join(f"avg(z{i}) as m{i}" for i in range(4)) + " from li group by domain), s as (select " + ", ".join(f"sum((n_h / n) ** 2 * c{i}{j}) as s{i}{j}" for i, j in PAIRS) + " from h join tot using (domain)), m as (select " + ", ".join(f"max(case when domain = 's' then m{i} end) - max(case when domain = 't' then m{i} end) as d{i}" for i in range(4)) + " from tot) select " + r("1e3 * (2 * (" + " + ".join(f"{1 if i == j else 2} * s{i}{j} ** 2" for i, j in PAIRS) + ") + 4 * (" + " + ".join(f"{1 if i == j else 2} * s{i}{j} * d{i} * d{j}" for i, j in PAIRS) + "))") + " as variance from s, m"
NULL_LINE = LINE.split(",\nli as")[0]
SQL["vector_standardise"] = f"with {NULL_LINE} select id, {r('a')} as z0, {r('b')} as z1, {r('c')} as z2, {r('e')} as z3 from raw"
SQL["strata_join"] = f"with {NULL_LINE} select (id % 32)::int as stratum, count(*) as n, {r('avg(a)')} as mean0 from raw group by 1"
SQL["mean_variance_mc"] = f"with {NULL_LINE}, s as (select *, (id % 8)::int as stratum, row_number() over (partition by id % 8 order by id) - 1 as pos, count(*) over (partition by id % 8) as n_h, count(*) over () as n from raw), mu as (select avg(a) as ma, avg(b) as mb, avg(c) as mc, avg(e) as me from raw), g as (select i, sum(n_h / n * a) as xa, sum(n_h / n * b) as xb, sum(n_h / n * c) as xc, sum(n_h / n * e) as xe from range(0, 50) x(i), s where pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39))} * n_h) group by i) select count(*) as iters, {r('avg((xa - ma) ** 2 + (xb - mb) ** 2 + (xc - mc) ** 2 + (xe - me) ** 2)')} as variance from g, mu"


def _kmeans(source: str, cols: tuple[str, ...], name: str = "km") -> str:
    d2 = lambda c: "round(" + " + ".join(f"(p.{x} - {c}.{x}) ** 2" for x in cols) + ", 9)"
    return f"""c0 as materialized (select (row_number() over (order by id) - 1)::int as j, {', '.join(f'round({x}, 9) as {x}' for x in cols)} from (select * from {source} order by id limit 8)),
n0 as (select p.id, arg_min(c0.j, ({d2('c0')}, c0.j)) as j, {', '.join(f'any_value(p.{x}) as {x}' for x in cols)} from {source} p, c0 group by p.id, p.rowkey),
c1 as materialized (select c0.j, {', '.join(f'coalesce(max(m.{x}), max(c0.{x})) as {x}' for x in cols)} from c0 left join (select j, {', '.join(f'round(avg({x}), 9) as {x}' for x in cols)} from n0 group by j) m using (j) group by c0.j),
{name} as materialized (select p.id, arg_min(c1.j, ({d2('c1')}, c1.j))::int as stratum from {source} p, c1 group by p.id, p.rowkey)"""


KF = f"{NULL_LINE}, pts as (select *, row_number() over () as rowkey from raw), " + _kmeans("pts", ("a", "b", "c", "e"))
KI = "pts as materialized (select o_orderkey as id, o_orderkey as rowkey, (o_totalprice - avg(o_totalprice) over ()) / stddev_pop(o_totalprice) over () as a, (c_acctbal - avg(c_acctbal) over ()) / stddev_pop(c_acctbal) over () as b from orders join customer on o_custkey = c_custkey), " + _kmeans("pts", ("a", "b"))
SQL["kmeans_features"], SQL["kmeans_inputs"] = f"with {KF} select id, stratum from km", f"with {KI} select id, stratum from km"
_kd = f"select i::int as iter, stratum, id, {r('n_h / n')} as weight from range(0, 20) x(i), (select *, row_number() over (partition by stratum order by id) - 1 as pos, count(*) over (partition by stratum) as n_h, count(*) over () as n from km) s where pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39))} * n_h)"
SQL["draw_kmeans_features"], SQL["draw_kmeans_inputs"] = f"with {KF} {_kd}", f"with {KI} {_kd}"
SQL["strata_by_label"] = f"with {EMB} select id as vec_id, y as stratum, ntile(8) over (order by id)::int as equal_count from emb"
SQL["strata_sizes"] = G8 + SIZES + f", q as (select n_h, row_number() over (order by n_h, stratum) as r from sizes) select count(*) as k, min(n_h) as smallest, max(n_h) as largest, {r('sum((2 * r - 9) * n_h) / (8 * sum(n_h))')} as gini from q"
DU = f"select i::int as iter, id as vec_id, 0.125::double as weight from range(0, 20) x(i), range(0, 8) y(c), (select id, row_number() over (order by id) - 1 as pos, count(*) over () as n from emb) s where pos = floor({u('draw', 'i', chr(39) + '0' + chr(39), 'c')} * n)"
DS = f"select i::int as iter, stratum, id as vec_id, {r('n_h / n')} as weight from range(0, 20) x(i), sizes join places using (stratum) where pos = floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39))} * n_h)"
SQL["draw_uniform"] = f"with {EMB} {DU}"
SQL["draw_strata"] = f"{G8}{SIZES} {DS}"
SQL["draw_overlap"] = f"{G8}{SIZES} select vec_id from ({DU}) intersect select vec_id from ({DS})"
SQL["draw_except"] = f"{G8}{SIZES} select vec_id from ({DU}) except all select vec_id from ({DS})"
SQL["draw_alloc"] = f"{G8}{SIZES}, a as (select *, greatest(1, floor(32 * n_h / n))::int as q from sizes) select i::int as iter, stratum, id as vec_id, {r('n_h / n / q')} as weight from range(0, 10) x(i), range(0, 32) y(c), a join places using (stratum) where c < q and pos = floor({u('alloc', 'i', 'stratum', 'c')} * n_h)"
SQL["draw_alloc_deviation"] = f"{G8}{SIZES}, sd as (select stratum, round(stddev_pop(z[1]), 9) as sd from strata join emb using (id) group by 1), a as (select s.*, greatest(1, floor(32 * n_h * sd / sum(n_h * sd) over ()))::int as q from sizes s join sd using (stratum)) select i::int as iter, stratum, id as vec_id, {r('n_h / n / q')} as weight from range(0, 10) x(i), range(0, 32) y(c), a join places using (stratum) where c < q and pos = floor({u('alloc', 'i', 'stratum', 'c')} * n_h)"
SQL["draw_weighted"] = f"with w as (select c_custkey as id, greatest(c_acctbal, 0) as w from customer), t as (select sum(w) as s, count(*) as n from w), run as (select id, w, sum(w) over (order by id) as hi from w where w > 0), st as (select *, coalesce(lag(hi) over (order by id), 0) as lo from run), slot as (select i, c, {u('weighted', 'i', 'c')} * s as x, s, n from range(0, 5) a(i), range(0, 4) b(c), t) select i::int as iter, c::int as c, id as c_custkey, {r('s / (4 * n * w)')} as weight from slot join st on lo <= x and x < hi"
_sc = ", prs as (select a.stratum, sum(exp(-0.5 * list_distance(a.z, b.z) ** 2)) as k from (select * from strata join emb using (id)) a join (select * from strata join emb using (id)) b using (stratum) group by 1), sc as (select stratum, n_h, n, greatest(n_h - k / n_h, 0) as scatter from prs join sizes using (stratum))"
SQL["strata_objective"] = f"{G8}{SIZES}{_sc} select stratum, n_h, {r('scatter')} as scatter, {r('n_h * scatter')} as weighted from sc"
SQL["mean_variance"] = f"{G8}{SIZES}{_sc} select 'swks_greedy' as method, {r('1000 * sum(n_h * scatter) / max(n) ** 2')} as variance from sc"
_uni = "uni as (select (1 - avg(exp(-0.5 * list_distance(a.z, b.z) ** 2))) / 8 as v from emb a, emb b), num as (select count(*) as n from emb)"
SQL["mean_variance_uniform"] = f"with {EMB}, {_uni} select 'replace' as method, {r('1000 * v')} as variance from uni union all select 'no_replace', {r('1000 * v * (n - 8) / (n - 1)')} from uni, num"
SQL["variance_gain"] = f"{G8}{SIZES}{_sc}, {_uni} select {r('any_value(v) / (sum(n_h * scatter) / max(sc.n) ** 2)')} as gain from sc, uni"
SQL["mean_variance_enum"] = f"with n as (select n_regionkey as h, n_nationkey::double as x, count(*) over (partition by n_regionkey) / (select count(*) from nation) as w from nation), e as (select a.x * a.w + b.x * b.w + c.x * c.w + d.x * d.w + f.x * f.w as m from n a, n b, n c, n d, n f where a.h = 0 and b.h = 1 and c.h = 2 and d.h = 3 and f.h = 4) select (select count(*) from e) as tuples, (select {r('var_pop(m)')} from e) as enumerated, (select {r('sum(v)')} from (select max(w) ** 2 * var_pop(x) as v from n group by h)) as analytic"
SC = "h as (select p_size % 8 as h, count(*) as n_h, avg(p_retailprice / 1000) as mu, var_pop(p_retailprice / 1000) as v from part where p_retailprice is not null group by 1), w as (select *, n_h / sum(n_h) over () as a, sum(n_h) over () as n from h), b as (select *, mu - sum(a * mu) over () as dev from w), m as (select max(n) as n, sum((a * v) ** 2) as t1, sum(a ** 2 * v) as t2, sum(a ** 3 * v ** 2) as t3, sum(a ** 2 * v * dev ** 2) as sh from b)"
_g = "(n / (n - 1.0)) ** 2"
_target = f"{_g} * (2 * (t1 - 2 * t3 + t2 ** 2) + 4 * sh)"
SQL["cov_variance_scalar"] = f"with {SC} select {r(f'1e3 * {_target}')} as target, {r('1e3 * (2 * t1 + 4 * sh)')} as surrogate from m"
SQL["cov_variance_link"] = f"with {SC} select {r(f'1e3 * {_g} * (2 * t1 + 4 * sh + 2 * t2 ** 2 - 4 * t3)')} as link, {r(f'abs({_g} * (2 * t1 + 4 * sh + 2 * t2 ** 2 - 4 * t3) - {_target})')} as gap from m"
ENUM = """pts as (select row_number() over (order by n_regionkey) as i, round(avg(c_acctbal) / 1000, 6) as a, round(avg(o_totalprice) / 100000, 6) as b from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by n_regionkey),
parts(len, s, top) as (select 1, [0], 1 union all select len + 1, list_append(s, v::int), greatest(top, v::int + 1) from parts, range(0, 3) x(v) where len < 5 and v <= top),
p as (select row_number() over (order by s) as pid, s from parts where len = 5 and top = 3),
blocks as (select pid, s[i] as blk, count(*) / 5.0 as w, covar_pop(a, a) as aa, covar_pop(a, b) as ab, covar_pop(b, b) as bb from p, pts group by 1, 2),
sig as (select pid, sum(w ** 2 * aa) as aa, sum(w ** 2 * ab) as ab, sum(w ** 2 * bb) as bb from blocks group by 1),
fg as (select pid, round(2 * (aa ** 2 + 2 * ab ** 2 + bb ** 2) + 4 * (aa + 2 * ab + bb), 12) as f, round(aa + bb, 12) as g from sig),
rk as (select f, g, rank() over (order by f) + (count(*) over (partition by f) - 1) / 2.0 as rf, rank() over (order by g) + (count(*) over (partition by g) - 1) / 2.0 as rg from fg)"""
SQL["surrogate_spearman"] = f"with recursive {ENUM} select count(*) as p, {r('corr(rf, rg)')} as rho from rk"
SQL["rank_displacement"] = f"with recursive {ENUM} select count(*) as p, sum((rf - rg) ** 2) as sum_sq, arg_min(rf, g) as rank_of_best from rk"
_s8 = "sum(case when i % 2 = 0 then 1 else -1 end * factorial(8) / (factorial(i::int) * factorial((8 - i)::int)) * (i / 8) ** n)"
SQL["error_bounds"] = f"""with c as (select n, count(*) as users from (select user_id, count(*) as n from events group by 1) group by 1),
q as (select n, users, case when n > 8 then n * ln(8) + ln({_s8}) - ln(factorial(8)::double) when n = 8 then 0.0 end as lp from c, range(0, 9) t(i) group by n, users)
select n, users, {r('lp')} as log_p, case when lp > 0 then {r('(2 * lp + ln(1 - exp(-2 * lp)) + ln(0.01 / 6) + lp) / 2')} end as log_worst, case when lp > 0 then {r('(2 * lp + ln(1 - exp(-2 * lp)) + ln(0.01 / 6)) / 2')} end as log_expected from q"""
TXT = """t as (select *, coalesce(text, '') as x from documents), f as (select *, list_filter(string_split_regex(x, '[ \\n\\t]+'), lambda w: w <> '') as w, list_filter(string_split(x, chr(10)), lambda w: w <> '') as l, greatest(length(x), 1)::double as n from t),
g as (select *, ln(length(x) + 1) as ln_chars, ln(len(w) + 1) as ln_words, case when len(w) > 0 then list_sum(list_transform(w, lambda y: length(y))) / len(w) else 0 end as mean_word, len(regexp_extract_all(x, '[0-9]')) / n as digit_ratio, len(regexp_extract_all(x, '[!-/:-@]')) / n as punct_ratio, len(regexp_extract_all(x, '[A-Z]')) / n as upper_ratio,
case when len(w) > 0 then len(list_distinct(w)) / len(w) else 0 end as distinct_ratio, case when len(l) > 0 then 1 - len(list_distinct(l)) / len(l) else 0 end as repeat_ratio from f)"""
SQL["doc_features"] = f"with {TXT} select doc_id, " + ", ".join(f"{r(c)} as {c}" for c in ("ln_chars", "ln_words", "mean_word", "digit_ratio", "punct_ratio", "upper_ratio", "distinct_ratio", "repeat_ratio")) + " from g"
TEXTS = "(select 'documents' as env, text from documents union all select 'benchmark', text from benchmark union all select 'conversations', text from conversations union all select 'pages', html from pages)"
SQL["x17_environment_distance"] = f"""with {TXT.replace("from documents", "from " + TEXTS)}, v as (select env, [ln_chars, ln_words, mean_word, digit_ratio, punct_ratio, upper_ratio, distinct_ratio, repeat_ratio]::double[] as z from g),
m as (select env, i, j, avg(z[i] * z[j]) as m from v, range(1, 9) a(i), range(1, 9) b(j) group by env, i, j)
select p.env as a, q.env as b, {r('sum((p.m - q.m) ** 2)')} as med from m p join m q on p.i = q.i and p.j = q.j and p.env < q.env group by p.env, q.env"""
SQL["accuracy_summary"] = f"with {TXT}, lb as (select doc_id, max(quality) as y from labels group by 1), h as (select lang, avg(case when (case when punct_ratio < 0.05 then 1 else 0 end) = y then 1.0 else 0.0 end) as acc from g join lb using (doc_id) where y is not null group by lang) select count(*) as splits, {r('avg(acc)')} as mean_acc, {r('stddev_samp(acc) / sqrt(count(*))')} as std_err from h"
SQL["accuracy_pivot"] = "with lb as (select doc_id, max(quality) as y from labels group by 1) select lang as env, count(*) filter (where y = 0) as low, count(*) filter (where y = 1) as high from documents join lb using (doc_id) where y is not null group by lang"
SQL["strata_agreement"] = f"{G8}, near as (select id, (list_position(d, list_min(d)) - 1)::int as s2 from dist), t as (select stratum as x, s2 as y, count(*) as n from strata join near using (id) group by all), c as (select sum(n * (n - 1) / 2.0) as cells, sum(n) as n from t), a as (select sum(q * (q - 1) / 2.0) as xs from (select sum(n) as q from t group by x)), b as (select sum(q * (q - 1) / 2.0) as ys from (select sum(n) as q from t group by y)) select {r('(cells - xs * ys / (n * (n - 1) / 2.0)) / ((xs + ys) / 2 - xs * ys / (n * (n - 1) / 2.0))')} as ari, n::bigint as n from c, a, b"
SQL["scan_counts"] = " union all ".join(f"select '{t}' as name, count(*) as n from {t}" for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())
SQL["vector_norms"] = f"with {EMB}, n as (select id, z, sqrt(list_inner_product(z, z)) as m from emb) select id as vec_id, {r('m')} as norm, {r('list_sum(list_transform(z, lambda x: least(greatest(case when m > 0 then x / m else x end, -0.1), 0.1)))')} as clipped_sum from n"
SQL["portable_uniform"] = f"select vec_id, {u('u', 'vec_id')} as u from embeddings"
SQL["domain_split"] = f"with {EMB}, m as (select how, z[1] as z0, case how when 'hard' then z[1] >= 0 when 'soft' then domain = 's' else u < 0.5 end as s from (select *, concat('0x', substr(md5(concat_ws('|', '42', how, id)), 1, 13))::bigint / 4503599627370496.0 as u from emb, (values ('null'), ('soft'), ('hard'), ('affine')) h(how))) select case when s then 's' else 't' end as domain, count(*) as n, {r('''avg(case when how = 'affine' and not s then z0 * 1.5 + 0.25 else z0 end)''')} as mean0, how from m group by how, s"
STAR = "star as (select o_orderkey as id, r_name as env, o_totalprice / 1e4 as a, c_acctbal / 5e3 as b, sin(month(o_orderdate) * (pi() / 6)) as c, cos(month(o_orderdate) * (pi() / 6)) as e from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"
SQL["star_features"] = f"with {STAR} select id, env, {r('a')} as z0, {r('b')} as z1, {r('c')} as z2, {r('e')} as z3 from star"
SQL["split_counts"] = f"with {STAR} select env, case when {u('split', 'id')} < 0.8 then 'fit' else 'held' end as part, count(*) as n from star group by 1, 2"
SQL["page_features"] = f"select page_id, len(regexp_extract_all(html, '<[a-zA-Z]'))::bigint as tags, {r('''length(regexp_replace(html, '<[^>]*>', '', 'g')) / greatest(length(html), 1)''')} as text_ratio from pages"
SQL["conv_features"] = f"select conv_id, count(*) as turns, count(*) filter (where role = 'user') as user_turns, {r('avg(length(text))')} as mean_chars from conversations group by conv_id"
SQL["event_props"] = "select event_type, count(*) as n, sum((props->>'$.k')::bigint)::bigint as sum_k, count(distinct (props->>'$.k')::bigint) as distinct_k from events group by event_type"
SQL["event_time_features"] = f"select hour(ts)::int as hour, (dayofweek(ts) + 1)::int as dow, strftime(date_trunc('week', ts), '%Y-%m-%d') as week, count(*) as n, {r('avg(ln(1 + value))')} as mean_log from events group by 1, 2, 3"
SQL["quantile_bins"] = "with e as (select quantile_cont(o_totalprice, 0.25) as a, quantile_cont(o_totalprice, 0.5) as b, quantile_cont(o_totalprice, 0.75) as c from orders) select o_orderkey, ((o_totalprice >= a)::int + (o_totalprice >= b)::int + (o_totalprice >= c)::int)::int as bin from orders, e"
SQL["price_quartiles"] = "select p_brand, " + ", ".join(f"{r(f'quantile_cont(p_retailprice, {q})')} as q{int(q * 100)}" for q in (0.25, 0.5, 0.75)) + " from part group by p_brand"
SQL["asof_strata"] = f"with b as (select user_id, ts as bt, max(value) as v from events where event_type = 'purchase' group by all) select event_id, {r('v')} as last_buy from events e asof left join b on e.user_id = b.user_id and e.ts >= b.bt"
SQL["interval_pairs"] = "select a.user_id, a.event_id as a_id, b.event_id as b_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'purchase' and b.event_type <> 'purchase'"
SQL["labelled_docs"] = "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by lang"
SQL["unlabelled_docs"] = "select lang, count(*) as n from documents where doc_id not in (select doc_id from labels) group by lang"
SQL["weighted_moments"] = f"with m as (select *, sum(l_quantity * l_discount) over (partition by l_returnflag) / sum(l_quantity) over (partition by l_returnflag) as mu from lineitem) select l_returnflag, count(*) as n, {r('any_value(mu)')} as w_mean, {r('sum(l_quantity * (l_discount - mu) ** 2) / sum(l_quantity)')} as w_var, {r('covar_samp(l_quantity, l_extendedprice) / 1000')} as cov from m group by l_returnflag"
SQL["distinct_rows"] = "select lang, count(*) as n, count(distinct text) as distinct_n from documents group by lang"
SQL["strata_cube"] = f"{G8} select domain, stratum, count(*) as n from strata join emb using (id) group by cube (domain, stratum)"
SQL["strata_rollup"] = f"{G8} select domain, stratum, y, count(*) as n from strata join emb using (id) group by rollup (domain, stratum, y)"
SQL["stratum_positions"] = f"{G8} select id as vec_id, stratum, (row_number() over w - 1)::int as pos, ntile(4) over w::int as quarter, {r('percent_rank() over w')} as share from strata window w as (partition by stratum order by id)"
SQL["trajectory_rolling"] = f"with d as (select strftime(ts, '%Y-%m-%d') as day, avg(value) as v from events group by 1) select day, {r('v')} as v, {r('v - lag(v) over (order by day)')} as change, {r('avg(v) over (order by day rows between 1 preceding and 1 following)')} as rolling from d"
SQL["stratum_prototypes"] = f"{G8} select stratum, arg_min(id, (d[stratum + 1], id)) as vec_id, {r('min(d[stratum + 1])')} as dist from strata join dist using (id) group by stratum"
SQL["env_union"] = f"select 'customer' as env, count(*) as n, {r('avg(c_acctbal)')} as mean_v from customer union all select 'supplier', count(*), {r('avg(s_acctbal)')} from supplier"
SQL["size_map"] = f"{G8}{SIZES} select stratum, n_h from sizes"
SQL["env_pairs"] = "with n as (select lang, count(*) as n from documents group by lang) select a.lang as src, a.n as n_s, b.lang as tgt, b.n as n_t from n a join n b on a.lang <> b.lang"
SQL["sql_surface"] = f"with {EMB}, c as (select z as c from emb order by id limit 1) select id as vec_id, round(exp(-0.5 * list_distance(z, c) ** 2), 6) as k1, round(list_sum(list_transform([0.001, 0.01, 0.1, 1.0, 10.0], lambda g: exp(-g * list_distance(z, c) ** 2))), 6) as k2, {u('u', 'id')} as u from emb, c"
SQL["udtf_draws"] = f"{G8}{SIZES} select i::int as iter, stratum, floor({u('draw', 'i', 'stratum', chr(39) + '0' + chr(39))} * n_h)::int as pos, round(n_h / n, 6) as weight from range(0, 20) x(i), sizes"
SQL["udtf_partitions"] = """with recursive kinds as (select l_returnflag || l_linestatus as kind, count(*) as c, row_number() over (order by l_returnflag || l_linestatus) as i from lineitem group by 1), m as (select count(*) as m from kinds),
p(len, s, top) as (select 1, [0], 1 union all select len + 1, list_append(s, v::int), greatest(top, v::int + 1) from p, m, range(0, 3) x(v) where len < m and v <= top),
q as (select s, kind, c, s[i] as block from p, m, kinds where len = m and top = 3), w as (select s, block, sum(c) as c from q group by 1, 2)
select kind, q.block, count(*) as n, round(avg(w.c), 6) + 0.0 as mean_lines from q join w on w.s = q.s and w.block = q.block group by 1, 2"""
_w = "strftime({}, '%Y-%m-%d %H:%M:%S') as window_start"
SQL["stream_tumbling"] = f"select {_w.format('''date_trunc('day', ts)''')}, event_type, count(*) as n, {r('avg(value)')} as mean_value from events group by 1, 2"
SQL["stream_sliding"] = f"with e as (select value, unnest([date_trunc('day', ts), date_trunc('day', ts) - interval 1 day]) as w from events) select {_w.format('w')}, count(*) as n, {r('avg(value)')} as mean_value from e group by w"
SQL["stream_session"] = f"with a as (select *, case when ts <= lag(ts) over w + interval 30 minute then 0 else 1 end as new from events window w as (partition by user_id order by ts)), s as (select *, sum(new) over (partition by user_id order by ts, event_id) as k from a) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') as session_start, count(*) as n, {r('sum(value)')} as total from s group by user_id, k"
SQL["stream_reservoir"] = f"select {_w.format('''date_trunc('day', ts)''')}, event_type, arg_min(event_id, ({u('reservoir', 'event_id')}, event_id)) as event_id, count(*) as n from events group by 1, 2"
_f = ["ln(1 + value)", "sin(hour(ts) * (pi() / 12))", "cos(hour(ts) * (pi() / 12))"]
_mom = ", ".join([*(f"avg(f{i}) as m{i}" for i in range(3)), *(f"avg(f{i} * f{j}) as q{i}{j}" for i in range(3) for j in range(i, 3)), *(f"covar_samp(f{i}, f{j}) as c{i}{j}" for i in range(3) for j in range(i, 3))])
_sum = lambda c: r(" + ".join(f"{1 if i == j else 2} * (g.{c}{i}{j} - ref.{c}{i}{j}) ** 2" for i in range(3) for j in range(i, 3)))
_drift = lambda start: f"with f as (select ts, {', '.join(f'{x} as f{i}' for i, x in enumerate(_f))} from events), ref as (select {_mom} from f where ts < timestamp '2024-01-08'), g as (select {start} as w, count(*) as n, {_mom} from f group by 1) select {_w.format('g.w')}, g.n, {_sum('c')} as cad, {r(' + '.join(f'(g.m{i} - ref.m{i}) ** 2' for i in range(3)))} as mean_shift, {_sum('q')} as med from g, ref"
SQL["x16_drift"], SQL["x16_drift_weekly"] = _drift("date_trunc('day', ts)"), _drift("time_bucket(interval 7 days, ts, timestamp '1970-01-01')")
SQL["stream_dedup"] = "select event_type, count(*) as n, sum(event_id)::bigint as ids from events group by 1"
SQL["account_unpivot"] = "select p_partkey, 'size' as measure, p_size::double as value from part union all select p_partkey, 'price', p_retailprice from part"
SQL["approximate_measures"] = "select count(*) as n, true as q25, true as q50, true as q75, true as distinct_parts from lineitem"
SQL["grouped_vectors"] = f"with {NULL_LINE} select env, " + ", ".join(f"{r(f'avg({x})')} as m{i}" for i, x in enumerate("abce")) + ", " + ", ".join(f"{r('covar_samp(' + 'abce'[i] + ', ' + 'abce'[j] + ')')} as c{k}" for k, (i, j) in enumerate(PAIRS)) + " from raw group by env"
SQL["cad_wide"] = f"with {EMB}, c as materialized (select domain, i, j, count(*) as n, covar_samp(z[i], z[j]) as c from emb, range(1, 65) a(i), range(1, 65) b(j) group by all) select max(s.n) as n_s, max(t.n) as n_t, {r('1000 * sum((s.c - t.c) ** 2)')} as cad from c s join c t using (i, j) where s.domain = 's' and t.domain = 't'"
SQL["combined_objective"] = f"with {DOM}, {dom_draws()}, {_hat}, task as (select iter, sum(w * (z[1] - z[2]) ** 2) as t from draws d join emb using (id) where d.domain = 's' group by 1) select iter, {r('t')} as task, {r('v')} as value, {r('t + 2 * v')} as objective from task join vals using (iter)"
SQL["assign_by_domain"] = "with recursive " + DIST + ", dealt as materialized (select domain, id, d, row_number() over (partition by domain order by id) as r from dist), " + greedy("o.d[i] * (g.sizes[i] + 1)", source="dealt", by="domain") + " select domain, id as vec_id, stratum from g where id is not null"
SQL["splits"] = f"with {STAR} select 'star_regions' as dataset, env as target, count(*) as n from star group by env union all select 'document_languages', lang, count(*) from documents group by lang union all select 'line_flags', l_returnflag || l_linestatus, count(*) from lineitem group by 2 union all select 'language_pairs', a.lang || '>' || b.lang, (a.n + b.n)::bigint from (select lang, count(*) as n from documents group by 1) a join (select lang, count(*) as n from documents group by 1) b on a.lang <> b.lang"
SQL["x18_account_covariance"] = f"with a as (select c_nationkey as nation, var_samp(x) as xx, covar_samp(x, y) as xy, var_samp(y) as yy from (select *, c_acctbal / 1000 as x, c_custkey / (select count(*) from customer)::double as y from customer) group by 1), b as (select s_nationkey as nation, var_samp(x) as xx, covar_samp(x, y) as xy, var_samp(y) as yy from (select *, s_acctbal / 1000 as x, s_suppkey / (select count(*) from supplier)::double as y from supplier) group by 1) select nation, {r('(a.xx - b.xx) ** 2 + 2 * (a.xy - b.xy) ** 2 + (a.yy - b.yy) ** 2')} as cad from a join b using (nation) where a.xx is not null and b.xx is not null"
