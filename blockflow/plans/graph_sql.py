"""DuckDB text of the graph methods: carriers, flow vectors, propagation, sample and function clusters. Used by oracles only."""

from __future__ import annotations

import re

from blockflow.functions.taxonomy import class_sql

WS = [f"w{k}" for k in range(1, 10)]
NUM = ["x", "y", *WS]
CLASSES = [f"c{k}" for k in range(1, 10)]

LINES = """ls as (select doc_id as sample_id, source as grp, list_filter(list_transform(string_split(text, chr(10)), lambda x: trim(x)), lambda x: x <> '') as l from documents where text is not null),
    lines as (select sample_id, grp, cast(i - 1 as int) as func_id, l[i] as line from (select *, unnest(range(1, len(l) + 1)) as i from ls))"""
#: Blocks of (sample_id, grp, func_id, line).
LINE_BLOCKS = f"""ps as (select sample_id, func_id, grp, list_filter(list_transform(string_split_regex(line, '[.!?,;]+'), lambda x: trim(x)), lambda x: x <> '') as p from lines),
    bs as (select sample_id, func_id, grp, cast(i - 1 as int) as id, p[i] as t from (select *, unnest(range(1, len(p) + 1)) as i from ps)),
    toks as (select sample_id, func_id, id, {class_sql('tok', duck=True)} as c from (select sample_id, func_id, id, unnest(list_filter(string_split_regex(t, '\\s+'), lambda x: x <> '')) as tok from bs)),
    tc as (select sample_id, func_id, id, count(*) as n, {', '.join(f'count(*) filter (where c = {k}) as c{k}' for k in range(1, 10))} from toks group by 1, 2, 3),
    blocks as (select b.sample_id, b.func_id, b.grp, b.id, lower(substr(t, 1, 1)) as a, lower(right(t, 1)) as b, coalesce(n, 0) as n, {', '.join(f'coalesce(c{k}, 0) as c{k}' for k in range(1, 10))} from bs b left join tc using (sample_id, func_id, id))"""
DOC_BLOCKS = f"{LINES}, {LINE_BLOCKS}"
TURN_BLOCKS = f"lines as (select conv_id as sample_id, role as grp, cast(turn as int) as func_id, text as line from conversations where text is not null), {LINE_BLOCKS}"
PASSAGE_BLOCKS = DOC_BLOCKS.replace("doc_id as sample_id, source as grp", "item_id as sample_id, 'benchmark' as grp").replace("from documents", "from benchmark")
ORDER_BLOCKS = f"""ty as (select p_type, row_number() over (order by p_type) as k from (select distinct p_type from part)),
    blocks as (select o_custkey as sample_id, l_orderkey as func_id, n_name as grp, cast(row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate) - 1 as int) as id, l_returnflag as a, l_linestatus as b, cast(l_quantity as bigint) as n,
    {', '.join(f'case when k = {k} then cast(l_quantity as bigint) else 0 end as c{k}' for k in range(1, 7))}, {', '.join(f"case when l_returnflag = '{f}' then 1 else 0 end as c{k}" for k, f in ((7, 'A'), (8, 'N'), (9, 'R')))}
    from lineitem join part on l_partkey = p_partkey join ty using (p_type) join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey)"""
_KIND = "case when {n} in ('p','article','h1') then 1 when {n} in ('ul','li') then 2 when {n} in ('nav','footer') then 3 when {n} in ('b','i','em','strong') then 4 when {n} = 'a' then 5 when {n} in ('div','span') then 6 when {n} in ('table','tr','td','th') then 7 when {n} in ('meta','link','script','style','head') then 8 else 9 end"
PAGE_BLOCKS = f"""cut as (select page_id as sample_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as grp, string_split(regexp_replace(html, '(<(?:nav|article|p|ul|table|h1)[ >])', chr(1) || '\\1', 'g'), chr(1)) as s from pages where html is not null),
    tg as (select sample_id, grp, cast(i - 1 as int) as func_id, regexp_extract_all(s[i], '<([a-z][a-z0-9]*)([^>]*)>([^<]*)') as t from (select *, unnest(range(2, len(s) + 1)) as i from cut)),
    one as (select sample_id, grp, func_id, cast(j - 1 as int) as id, t[j] as x, regexp_extract(t[j], '^<([a-z0-9]+)', 1) as nm from (select *, unnest(range(1, len(t) + 1)) as j from tg)),
    blocks as (select sample_id, grp, func_id, id, nm as a, nm as b, cast(len(regexp_extract_all(x, '[a-z-]+=')) + 1 + len(list_filter(string_split_regex(regexp_replace(x, '^<[^>]*>', ''), '\\s+'), lambda w: w <> '')) as bigint) as n,
    {', '.join(f"cast(case when {_KIND.format(n='nm')} = {k} then 1 else 0 end as bigint) as c{k}" for k in range(1, 10))} from one)"""
SESSION_BLOCKS = f"""ty as (select event_type, row_number() over (order by event_type) as k from (select distinct event_type from events)),
    es as (select user_id, event_id, ts, event_type, props, cast(sum(nw) over (partition by user_id order by ts, event_id) as int) as func_id from (select *, case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 12 hour then 1 else 0 end as nw from events where user_id is not null)),
    md as (select user_id, func_id, event_type as grp, row_number() over (partition by user_id, func_id order by count(*) desc, event_type) as r from es group by 1, 2, 3),
    eb as (select es.*, md.grp, ty.k, 1 + cast(json_extract_string(props, '$.k') as bigint) % 8 as q from es join ty using (event_type) join md on md.user_id = es.user_id and md.func_id = es.func_id and r = 1),
    blocks as (select user_id as sample_id, func_id, grp, cast(row_number() over (partition by user_id, func_id order by ts, event_id) - 1 as int) as id, event_type as a, cast(hour(ts) % 2 as varchar) as b, coalesce(q, 1) as n,
    {', '.join(f'case when k = {k} then q else 0 end as c{k}' for k in range(1, 10))} from eb)"""
FLOW = f"""nx as (select *, count(*) over (partition by sample_id, func_id) as nb, lead(id) over (partition by sample_id, func_id, a order by id) as na, lag(id) over (partition by sample_id, func_id, b order by id) as pb from blocks),
    edges as (select distinct sample_id, func_id, src, dst from (select sample_id, func_id, id as src, id + 1 as dst from nx where id + 1 < nb union all select sample_id, func_id, id, na from nx where na is not null union all select sample_id, func_id, id, pb from nx where pb is not null)),
    ends as (select sample_id, func_id, id, sum(o) as o, sum(e) as e from (select sample_id, func_id, src as id, 1 as o, 1 as e from edges union all select sample_id, func_id, dst, 0, 1 from edges) group by 1, 2, 3),
    deep as (select n.sample_id, n.func_id, n.id, count(k.id) as depth from nx n left join nx k on n.sample_id = k.sample_id and n.func_id = k.func_id and k.pb is not null and k.pb <= n.id and n.id <= k.id group by 1, 2, 3),
    ec as (select sample_id, func_id, count(*) as n_edges from edges group by 1, 2),
    v as (select sample_id, func_id, grp, count(*) as n_blocks, coalesce(max(n_edges), 0) as n_edges, cast(sum(coalesce(e, 0) * n) as bigint) as omega, cast(sum(coalesce(e, 0) * n * id) as bigint) as xn, cast(sum(coalesce(e, 0) * n * coalesce(o, 0)) as bigint) as yn, cast(sum(coalesce(e, 0) * n * depth) as bigint) as zn,
    {', '.join(f'cast(sum(coalesce(e, 0) * c{k}) as bigint) as w{k}' for k in range(1, 10))} from blocks left join ends using (sample_id, func_id, id) left join deep using (sample_id, func_id, id) left join ec using (sample_id, func_id) group by 1, 2, 3)"""
FLOW_SELECT = f"select sample_id, func_id, grp, cast(n_blocks as int) as n_blocks, cast(n_edges as int) as n_edges, omega, xn, yn, zn, {', '.join(WS)} from v"

def renamed(ctes: str, tag: str) -> str:
    """The same relations over those whose names end in a tag."""
    names = {x for x in re.findall(r"(?:^|, |\n\s*)([a-z_]+) as \(select", ctes)} | {"blocks", "v"}
    for x in names:
        ctes = re.sub(rf"\b(from|join) {x}\b", rf"\1 {x}{tag}", ctes)
        ctes = re.sub(rf"\b{x} as \(select", f"{x}{tag} as (select", ctes)
    return ctes


HOP0 = "h0 as (select sample_id, func_id, round(case when omega > 0 then xn / omega * n_blocks else 0 end, 9) as x, round(case when omega > 0 then yn / omega * n_blocks else 0 end, 9) as y, " + ", ".join(f"cast({w} as double) as {w}" for w in WS) + " from v)"


def hop(k: int) -> str:
    sums = ", ".join(f"coalesce(cast(sum(cast(g.{c} as decimal(28, 9))) as double), 0) as {c}" for c in NUM)
    return f"h{k} as (select h.sample_id, h.func_id, {sums} from h0 h left join calls c on c.sample_id = h.sample_id and c.caller = h.func_id left join h{k - 1} g on g.sample_id = c.sample_id and g.func_id = c.callee group by 1, 2)"


DOC_CALLS = "lk as (select sample_id, func_id, lower(substr(line, 1, 1)) as k, count(*) over (partition by sample_id) as nf from lines), calls as (select distinct sample_id, caller, callee from (select sample_id, func_id as caller, func_id + 1 as callee from lk where func_id + 1 < nf union all select sample_id, func_id, lead(func_id) over (partition by sample_id, k order by func_id) from lk) where callee is not null)"
ORDER_CALLS = "calls as (select distinct sample_id, caller, callee from (select o_custkey as sample_id, o_orderkey as caller, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as callee from orders union all select o_custkey, o_orderkey, lead(o_orderkey) over (partition by o_custkey, o_orderpriority order by o_orderdate, o_orderkey) from orders) where callee is not null)"


def reach(pairs: str, tag: str = "") -> str:
    """roots{tag} (node, root) of the links (a, b) of a relation."""
    return f"""e{tag} as (select a, b from {pairs} union select b, a from {pairs}), reach{tag}(node, root) as (select a, a from e{tag} union select e.b, r.root from reach{tag} r join e{tag} e on e.a = r.node),
    roots{tag} as (select node, min(root) as root from reach{tag} group by 1)"""


def function_pairs(least: int = 3, unique_ids: bool = False, tag: str = "", tau: float = 0.999) -> str:
    """hd{tag}: functions with their head; pp{tag}: pairs (a, b, s) of heads from tau on."""
    i = "cast(func_id as bigint)" if unique_ids else "sample_id * 10000000 + func_id"
    gap = 0.0142 if tau >= 0.999 else 0.15
    return f"""f{tag} as (select {i} as id, sample_id, func_id, grp, n_blocks, round(case when omega > 0 then xn / omega * n_blocks else 0 end, 9) as x, round(case when omega > 0 then yn / omega * n_blocks else 0 end, 9) as y, {', '.join(WS)}, sqrt({' + '.join(f'{w} * {w}' for w in WS)}) as nrm from v where n_blocks >= {least}),
    un{tag} as (select id, sample_id, func_id, grp, x, y, {', '.join(f'round(coalesce({w} / nullif(nrm, 0), 0), 10) as {w}' for w in WS)} from f{tag}),
    hd{tag} as (select id, sample_id, func_id, grp, min(id) over (partition by x, y, {', '.join(WS)}) as head from un{tag}),
    u{tag} as (select min(id) as id, x, y, {', '.join(WS)} from un{tag} group by all),
    p{tag} as (select a.id as id_a, b.id as id_b, {' + '.join(f'a.{w} * b.{w}' for w in WS)} as c, exp(-5 * ((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))) as g from u{tag} a join u{tag} b on a.id < b.id and b.x between a.x - {gap} and a.x + {gap} and b.y between a.y - {gap} and a.y + {gap}),
    pp{tag} as (select id_a as a, id_b as b, least(1, c) * g as s from p{tag} where round(round(least(1, c), 10) * round(g, 10), 10) >= {tau})"""


def members(least: int = 3, unique_ids: bool = False, tag: str = "") -> str:
    """members{tag}: id, sample_id, func_id, grp, root."""
    return f"{function_pairs(least, unique_ids, tag)}, {reach(f'pp{tag}', tag)}, members{tag} as (select id, sample_id, func_id, grp, coalesce(root, head) as root from hd{tag} left join roots{tag} on head = node)"


def sample_pairs(calls: str, gap: float = 0.0045, tau: float = 0.9999) -> str:
    """sv: samples with their head; sp: pairs (a, b, s_cls, s_shape, s) of heads from tau on; by vectors of two hops in function order."""
    hops = " union all ".join(f"select sample_id, func_id, {k} as hop, {', '.join(NUM)} from h{k}" for k in range(2))
    return f"""{calls}, {HOP0}, {hop(1)}, nd as ({hops}),
    raw as (select sample_id as id, flatten(list([x, y] order by func_id, hop)) as sh, flatten(list([{', '.join(WS)}] order by func_id, hop)) as cl from nd group by 1),
    nm as (select id, sh, cl, sqrt(list_sum(list_transform(sh, lambda q: q * q))) as ns, sqrt(list_sum(list_transform(cl, lambda q: q * q))) as nc from raw),
    uv as (select id, list_transform(sh, lambda q: coalesce(q / nullif(ns, 0), 0)) as sh, cl, nc from nm),
    sv as (select *, min(id) over (partition by list_transform(sh, lambda q: round(q, 10)), list_transform(cl, lambda q: round(q, 6))) as head from uv),
    wd as (select max(len(sh)) as ms, max(len(cl)) as mc from sv),
    hv as (select id, coalesce(sh[1], 0) as s1, coalesce(sh[2], 0) as s2, list_resize(sh, ms, 0.0) as sh, list_resize(cl, mc, 0.0) as cl, nc from sv, wd where id = head),
    sq as (select a.id as a, b.id as b, round(case when a.nc = 0 and b.nc = 0 then 1.0 when a.nc * b.nc = 0 then 0.0 else least(1.0, list_dot_product(a.cl, b.cl) / (a.nc * b.nc)) end, 10) as s_cls, round(exp(-5 * power(list_distance(a.sh, b.sh), 2)), 10) as s_shape
        from hv a join hv b on a.id < b.id and b.s1 between a.s1 - {gap} and a.s1 + {gap} and b.s2 between a.s2 - {gap} and a.s2 + {gap}),
    sp as (select *, round(s_cls * s_shape, 10) as s from sq where round(s_cls * s_shape, 10) >= {tau})"""


def sample_roots(calls: str) -> str:
    """rt: (id, root) of the samples."""
    return f"{sample_pairs(calls)}, {reach('sp')}, rt as (select id, coalesce(root, head) as root from sv left join roots on head = node)"


def scoped_roots(calls: str, groups: str) -> str:
    """rg: (id, root) inside groups only; groups is a select of id and grp."""
    return f"""{sample_pairs(calls)}, gm as (select sv.id, sv.head, g.grp from sv join ({groups}) g on g.id = sv.id), rep as (select grp, head, min(id) as rep from gm group by 1, 2),
    gl as (select x.rep as a, y.rep as b from sp join rep x on x.head = sp.a join rep y on y.head = sp.b and y.grp = x.grp), {reach('gl')},
    rg as (select gm.id, coalesce(root, rep) as root from gm join rep using (grp, head) left join roots on rep = node)"""


KEPT = """od as (select rt.id, rt.root, row_number() over (partition by root order by doc_id, md5(text), doc_id) = 1 as kept from rt join documents on doc_id = rt.id)"""
