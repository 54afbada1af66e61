"""DuckDB SQL with the rows of the queries, built from shared tables."""

from __future__ import annotations

import re

PI2 = "6.283185307179586"


def u(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 8))::bigint / 4294967296.0)"


def dist(a: str = "a_", b: str = "b_") -> str:
    x, y = f"radians({a}lat)", f"radians({b}lat)"
    return (
        f"(2 * 6371008.8 * asin(least(1.0, sqrt(pow(sin(({y} - {x}) / 2), 2) + cos({x}) * cos({y}) * "
        f"pow(sin((radians({b}lon) - radians({a}lon)) / 2), 2)))))"
    )


def placed(salt: str, base_lat: str, base_lon: str, box: str) -> str:
    gy, gx = (f"'{salt}y:'", f"'{salt}x:'") if salt else ("'gy:'", "'gx:'")
    away, turn = f"(-ln(1 - {u(f"'{salt}r:' || k")}) * 25)", f"({PI2} * {u(f"'{salt}a:' || k")})"
    return (
        f"{base_lat} + (({u(f'{gy} || g')} - 0.5) * {box} + {away} * sin({turn})) / 111194.93 as lat, "
        f"{base_lon} + (({u(f'{gx} || g')} - 0.5) * {box} + {away} * cos({turn})) / (111194.93 * cos(radians({base_lat}))) as lon"
    )


NODES = f"""
n0 as (select p.p_partkey as k, p.p_partkey // 4 as g, p.p_partkey % 4 as j, (p.p_partkey // 4) // 20 as town, a.p_name as m, a.p_brand as b
       from part p join part a on a.p_partkey = (p.p_partkey // 4) * 4),
n1 as (select n0.*, n_name as t, 47.0::double + 0.2::double * (town % 40) as lat0, 6.0::double + 0.25::double * ((town // 40) % 40) as lon0 from n0 join nation on n_nationkey = town % 25),
st_nodes as (select k as node_id, g, j, town, t as nation, t, m, b, case when g % 4 != 3 then g end as area_id, case when g % 10 in (1, 2) then g // 10 end as group_id,
       {placed('', 'lat0', 'lon0', '4200')} from n1)"""

IDENTS = f"""{NODES},
st_labels as (
  select *, 'generic' as kind, case when g % 5 != 0 or j = 3 then t || ' ' || m when j = 0 then t || ', ' || m when j = 1 then m
            when g % 7 = 0 then upper(m || ' (' || b || ')') else m || ' (' || b || ')' end as label from st_nodes
  union all select *, 'reference', t || ' ' || b || ' ' || m from st_nodes where (g % 5 = 0 and j in (0, 2)) or (g % 5 = 2 and j = 0)
  union all select *, 'short', substr(m, 1, 2) || '. ' || split_part(m, ' ', 2) from st_nodes where g % 5 = 0 and j = 1
  union all select *, 'local', m || ', ' || b from st_nodes where g % 5 = 0 and j = 3
  union all select *, 'area', t || ' ' || m from st_nodes where g % 2 = 0 and area_id is not null and j < 2),
st_idents as (select *, row_number() over (order by node_id, label) as ident_id from (select distinct node_id, area_id, group_id, town, nation, lat, lon, label from st_labels))"""


def pairs_of(name: str, idents: str) -> str:
    names = "ident_id node_id area_id group_id town nation lat lon label".split()
    return f"""
{name}_c as (select {', '.join(f'{s}.{c} as {s}_{c}' for s in 'ab' for c in names)} from {idents} a join {idents} b on a.town = b.town and a.ident_id < b.ident_id),
{name}_d as (select *, {dist()} as dist_m from {name}_c),
{name} as (select *, a_ident_id || ':' || b_ident_id as pair_id,
   case when a_node_id = b_node_id or a_area_id = b_area_id then 1 when a_area_id is null or b_area_id is null then null
        when a_label = b_label and dist_m < 250 then null when a_group_id = b_group_id then null else 0 end as truth, 'mapped' as origin
 from {name}_d where dist_m <= 1000)"""


PAIRS = IDENTS + "," + pairs_of("st_pairs", "st_idents")

_KEY_A, _KEY_P = "a_ident_id || ':' || i", "a_ident_id || ':' || b_ident_id"
FOREIGN = f"""
fo_n as (select max(ident_id) as n from st_idents),
fo_c as (select a.*, i, 1 + floor({u("'sw:' || a.ident_id || ':' || i")} * n)::bigint as wanted from st_idents a, fo_n, (select unnest(range(16)) as i) where {u("'sp:' || a.ident_id")} < 0.5),
fo_p as (select {', '.join(f'{s}.{c} as {s}_{c}' for s in 'ab' for c in 'ident_id node_id area_id group_id town nation lat lon label'.split())}, i
  from fo_c a join st_idents b on b.ident_id = wanted),
fo_d as (select *, row_number() over (partition by a_ident_id, b_ident_id order by i) as again from fo_p where {dist()} > 1000),
fo_k as (select * exclude (again), row_number() over (partition by a_ident_id order by i) as r from fo_d where again = 1),
fo_m as (select * replace (
   a_lat + (100 * sqrt({u(f"'sd:' || {_KEY_A}")}) * cos({PI2} * {u(f"'sb:' || {_KEY_A}")})) / 111194.93 as b_lat,
   a_lon + (100 * sqrt({u(f"'sd:' || {_KEY_A}")}) * sin({PI2} * {u(f"'sb:' || {_KEY_A}")})) / (111194.93 * cos(radians(a_lat))) as b_lon) from fo_k where r <= 5),
st_foreign as (select * exclude (i, r), {dist()} as dist_m, 'A:' || a_ident_id || ':' || i as pair_id, 0 as truth, 'spiced_label' as origin from fo_m)"""

_SIZE = f"100 * sqrt(-2 * ln(1 - {u(f"'n1:' || {_KEY_P}")}))"
_TURN = f"({PI2} * {u(f"'n2:' || {_KEY_P}")})"
SHAKEN = f"""
sh_h as (select *, coalesce(truth = 1 and {u(f"'ns:' || {_KEY_P}")} < 0.5, false) as hit from st_pairs),
sh_m as (select * replace (
   case when hit then b_lat + {_SIZE} * sin({_TURN}) / 111194.93 else b_lat end as b_lat,
   case when hit then b_lon + {_SIZE} * cos({_TURN}) / (111194.93 * cos(radians(b_lat))) else b_lon end as b_lon) from sh_h),
st_shaken as (select * exclude (hit) replace (case when hit then {dist()} else dist_m end as dist_m, case when hit then 'spiced_position' else origin end as origin) from sh_m)"""

SPICED = PAIRS + "," + FOREIGN + "," + SHAKEN + """,
spiced as (select * from st_shaken union all by name select * from st_foreign)"""



def spiced_by(p: float) -> str:
    """The pairs ``spiced`` with probability p in place of a half."""
    return PAIRS + "," + (FOREIGN + "," + SHAKEN).replace("< 0.5", f"< {p}") + SPICED.split(SHAKEN)[1]


PAGES = f"""
p0 as (select page_id as k, cast(regexp_extract(url, '/[a-z][a-z]/([0-9]+)', 1) as bigint) as g, substr(replace(regexp_extract(html, '<title>([^<]*)</title>', 1), '&amp;', '&'), 1, 80) as title from pages),
p1 as (select p0.*, count(*) over (partition by g) as pages, g // 40 as town, 52.0::double + 0.2::double * ((g // 40) % 40) as lat0, -8.0::double + 0.25::double * (((g // 40) // 40) % 40) as lon0 from p0),
pg_nodes as (select k as node_id, town, title, case when g % 2 = 0 and pages = 1 then null else g end as area_id, cast(null as bigint) as group_id, '' as nation,
   {placed('p', 'lat0', 'lon0', '3000')} from p1),
pg_labels as (select *, title as label from pg_nodes
  union all select *, array_to_string(list_slice(list_filter(regexp_split_to_array(lower(title), '[^\\p{{L}}\\p{{N}}_]+'), lambda x: x != ''), 1, 4), ' ') from pg_nodes where node_id % 2 = 1),
pg_idents as (select *, row_number() over (order by node_id, label) as ident_id from (select distinct node_id, area_id, group_id, town, nation, lat, lon, label from pg_labels))"""

PG_PAIRS = PAGES + "," + pairs_of("pg_pairs", "pg_idents")

PG_SPICED = PG_PAIRS + "," + re.sub(r"\bst_", "pg_", SPICED.split(PAIRS + ",")[1])
#: Labels with every character beyond ASCII as a tilde: DuckDB measures bytes.
PG_FOLDED = PG_SPICED + """,
folded as (select * replace (regexp_replace(a_label, '[^\\x00-\\x7F]', '~', 'g') as a_label, regexp_replace(b_label, '[^\\x00-\\x7F]', '~', 'g') as b_label) from spiced)"""


def toks(x: str) -> str:
    return f"list_distinct(list_filter(regexp_split_to_array({x}, '[^\\p{{L}}\\p{{N}}_]+'), lambda t: t != ''))"


ED = "((greatest(length({a}), length({b})) - levenshtein({a}, {b}))::double / greatest(length({a}), length({b})))"
JAC = "(len(list_intersect({x}, {y}))::double / nullif(len(list_distinct(list_concat({x}, {y}))), 0))"


def ed(a: str, b: str) -> str:
    return ED.format(a=a, b=b)


def ped(a: str, b: str) -> str:
    one = lambda x, y: f"((length({x}) - list_min(list_transform(range(length({y}) + 1), lambda i: levenshtein({x}, substr({y}, 1, i)))))::double / length({x}))"
    return f"greatest({one(a, b)}, {one(b, a)})"


#: Scores of each distinct pair of labels in a table ``src`` (a_label, b_label): lp(a, b, x, y, ed, jac, bts).
def label_pairs(src: str) -> str:
    orders = lambda x: f"case when len({x}) = 2 then list_concat({x}, [{x}[1] || ' ' || {x}[2], {x}[2] || ' ' || {x}[1]]) else {x} end"
    return f"""
lp0 as (select distinct a_label as a, b_label as b from {src}),
lp1 as (select *, list_filter(regexp_split_to_array(a, '[^\\p{{L}}\\p{{N}}_]+'), lambda t: t != '') as xs, list_filter(regexp_split_to_array(b, '[^\\p{{L}}\\p{{N}}_]+'), lambda t: t != '') as ys from lp0),
lp2 as (select a, b, list_distinct(xs) as x, list_distinct(ys) as y from lp1),
lp3 as (select *, {orders('x')} as ox, {orders('y')} as oy from lp2),
lp as (select a, b, x, y, {ed('a', 'b')} as ed, {JAC.format(x='x', y='y')} as jac,
   case when a = b then 1.0 when len(x) between 1 and 2 and len(y) between 1 and 2 then
     greatest(list_max(list_transform(ox, lambda s: {ed('s', 'b')})), list_max(list_transform(oy, lambda s: {ed('s', 'a')})))
     else {JAC.format(x='x', y='y')} end as bts from lp3)"""


COUNTS = """tp, fp, fn, tn, round(tp / nullif(tp + fp, 0)::double, 6) as prec, round(tp / nullif(tp + fn, 0)::double, 6) as rec,
 round(coalesce(2.0 * tp / nullif(2 * tp + fp + fn, 0), 0), 6) as f1"""


def confusion(src: str, predicted: str, by: str = "") -> str:
    keys = f"{by}, " if by else ""
    return f"""select {keys}{COUNTS} from (select {keys}
 coalesce(sum((truth = 1 and ({predicted}))::int), 0)::bigint as tp, coalesce(sum((truth = 0 and ({predicted}))::int), 0)::bigint as fp,
 coalesce(sum((truth = 1 and not ({predicted}))::int), 0)::bigint as fn, coalesce(sum((truth = 0 and not ({predicted}))::int), 0)::bigint as tn
 from {src} where truth is not null {'group by ' + by if by else ''})"""


STRING_GRID = "[" + ", ".join(f"{k}::double / 20" for k in range(1, 20)) + ", 0.99::double]"
DISTANCE_GRID = "[" + ", ".join(f"{d}::double" for d in (5, 10, 20, 25, 30, 40, 50, 60, 70, 75, 80, 90, 100, 125, 150, 175, 200, 225, 250)) + "]"


def sweep(src: str, score: str, grid: str, below: bool = False) -> str:
    """tp, fp, fn, tn, prec, rec, f1 by threshold t over ``src`` with ``score`` and truth."""
    return f"(select t, * exclude (t) from ({confusion(f'(select *, {score} as s from {src}), (select unnest({grid}) as t)', f's {"<" if below else ">"} t', 't')}))"


RESCALED = "(case when {s} <= t then case when t > 0 then {s} / (2 * t) else 0 end else 0.5 + ({s} - t) / (2 * (1 - t)) end)"


def best(curve: str, keys: str = "t") -> str:
    return f"(select * from {curve} order by f1 desc, {keys} limit 1)"


def tfidf(src: str, fit: str) -> str:
    """tf(a, b, sim) for distinct label pairs of ``src``, fitted on the labels of ``fit`` (label)."""
    return f"""
tf_n as (select count(*) as n from {fit}),
tf_df as (select token, count(*) as df from (select unnest({toks('label')}) as token from {fit}) group by 1),
tf_pairs as (select distinct a_label as a, b_label as b from {src}),
tf_l as (select a as label from tf_pairs union select b from tf_pairs),
tf_t as (select label, token, count(*) as c from (select label, unnest(list_filter(regexp_split_to_array(label, '[^\\p{{L}}\\p{{N}}_]+'), lambda t: t != '')) as token from tf_l) group by 1, 2),
tf_w as (select label, token, c * ln(n::double / coalesce(df, 1)) as w from tf_t left join tf_df using (token), tf_n),
tf_norm as (select label, sqrt(sum(w * w)) as norm from tf_w group by 1),
tf_dot as (select p.a, p.b, sum(x.w * y.w) as dot from tf_pairs p join tf_w x on x.label = p.a join tf_w y on y.label = p.b and y.token = x.token group by 1, 2),
tf as (select p.a, p.b, case when p.a = p.b then 1.0 when na.norm * nb.norm > 0 then least(1.0, coalesce(dot, 0) / (na.norm * nb.norm)) else 0.0 end as sim
  from tf_pairs p left join tf_dot using (a, b) left join tf_norm na on na.label = p.a left join tf_norm nb on nb.label = p.b)"""


def scored_parts(src: str) -> str:
    """sc(repeat, truth, dist_m, pair_id, ed, ped, j, jw, jac, bts, bts6, tfidf): pairs of ``src`` in the test part of each repeat."""
    return f"""
rp as materialized (select *, {u("'split:' || repeat || ':' || pair_id")} < 0.2 as train from {src}, (select unnest(range(5))::int as repeat) where truth is not null),
{label_pairs(src)},
sides as (select a, b, x as own, b as whole from lp where a != b union all select a, b, y, a from lp where a != b),
grown as (
  select a, b, own, whole, own[i] as s, [i] as used from sides, (select unnest(range(1, 7)) as i) where i <= len(own) and len(own) <= 6
  union all select a, b, own, whole, s || ' ' || own[i], list_append(used, i) from grown, (select unnest(range(1, 7)) as i) where i <= len(own) and not list_contains(used, i)),
grown_best as (select a, b, max({ed('s', 'whole')}) as sim from grown group by 1, 2),
lq as materialized (select lp.a, lp.b, ed, {ped('lp.a', 'lp.b')} as ped, jaro_similarity(lp.a, lp.b) as j, jaro_winkler_similarity(lp.a, lp.b) as jw, jac, bts,
   case when lp.a = lp.b then 1.0 when len(x) = 0 or len(y) = 0 or greatest(len(x), len(y)) > 6 then jac else sim end as bts6
   from lp left join grown_best g on g.a = lp.a and g.b = lp.b),
fit_r as (select distinct repeat, label from (select repeat, a_label as label from rp where train union all select repeat, b_label from rp where train)),
fit_n as (select repeat, count(*) as n from fit_r group by 1),
fit_df as (select repeat, token, count(*) as df from (select repeat, unnest({toks('label')}) as token from fit_r) group by 1, 2),
tr_l as (select a as label from lp union select b from lp),
tr_t as (select label, token, count(*) as c from (select label, unnest(list_filter(regexp_split_to_array(label, '[^\\p{{L}}\\p{{N}}_]+'), lambda t: t != '')) as token from tr_l) group by 1, 2),
tr_w as materialized (select n.repeat, label, t.token, c * ln(n::double / coalesce(df, 1)) as w from tr_t t cross join fit_n n left join fit_df d on d.repeat = n.repeat and d.token = t.token),
tr_norm as (select repeat, label, sqrt(sum(w * w)) as norm from tr_w group by 1, 2),
tr_dot as (select x.repeat, p.a, p.b, sum(x.w * y.w) as dot from lp p join tr_w x on x.label = p.a join tr_w y on y.label = p.b and y.token = x.token and y.repeat = x.repeat group by 1, 2, 3),
sc as materialized (
  select rp.repeat, rp.truth, rp.dist_m, rp.pair_id, lq.* exclude (a, b),
    case when lq.a = lq.b then 1.0 when na.norm * nb.norm > 0 then least(1.0, coalesce(dot, 0) / (na.norm * nb.norm)) else 0.0 end as tfidf
  from rp join lq on lq.a = a_label and lq.b = b_label
  left join tr_norm na on na.repeat = rp.repeat and na.label = lq.a left join tr_norm nb on nb.repeat = rp.repeat and nb.label = lq.b
  left join tr_dot d on d.repeat = rp.repeat and d.a = lq.a and d.b = lq.b where not train)"""


def mean_best(curves: str, keys: str) -> str:
    """Best row of each method by mean F1 over repeats of curves (method, repeat, keys, prec, rec, f1)."""
    mean = f"select method, {keys}, round(avg(prec), 6) as prec, round(avg(rec), 6) as rec, round(avg(f1), 6) as f1, min(f1) as f1_min, max(f1) as f1_max from {curves} group by method, {keys}"
    return f"(select * exclude (best) from (select *, row_number() over (partition by method order by f1 desc, {keys}) as best from ({mean})) where best = 1)"


def single_curves(columns: dict[str, str]) -> str:
    """(method, repeat, t, tp, ..., f1) of P and string scores over sc."""

    def one(m: str, c: str, grid: str, sign: str) -> str:
        return f"select '{m}' as method, * from ({confusion(f'(select repeat, truth, {c} as s, t from sc, (select unnest({grid}) as t))', f's {sign} t', 'repeat, t')})"

    return "(" + " union all ".join([one("P", "dist_m", DISTANCE_GRID, "<"), *[one(m, c, STRING_GRID, ">") for m, c in columns.items()]]) + ")"


def double_curves(columns: dict[str, str]) -> str:
    """(method, repeat, d_hat, t, tp, ..., f1) of P with string scores over sc."""

    def one(m: str, c: str) -> str:
        rows = f"(select repeat, truth, dist_m, {c} as s, d_hat, t from sc, (select unnest({DISTANCE_GRID}) as d_hat), (select unnest({STRING_GRID}) as t))"
        yes = f"(exp(dist_m * (-0.6931471805599453 / d_hat)) + {RESCALED.format(s='s')}) / 2 > 0.5"
        return f"select 'P+{m}' as method, * from ({confusion(rows, yes, 'repeat, d_hat, t')})"

    return "(" + " union all ".join(one(m, c) for m, c in columns.items()) + ")"


def tagged(sql: str, tag: str) -> str:
    """``scored_parts`` with other names, for two of them in one statement."""
    return re.sub(r"\b(rp|lp[0-3]?|sides|grown|grown_best|lq|fit_r|fit_n|fit_df|tr_l|tr_t|tr_w|tr_norm|tr_dot|sc)\b", rf"\1{tag}", sql)
