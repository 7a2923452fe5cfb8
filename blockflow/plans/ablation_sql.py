"""DuckDB text of the truth set and of the seventeen configurations. Used by oracles only."""

from __future__ import annotations

from blockflow.config import FeatureConfig
from blockflow.operators import evaluate as E
from blockflow.plans import graph_sql as G

_HEX = " + ".join(f"(instr('0123456789abcdef', substr(md5(concat(c.sample_id, ':', c.copy)), {k}, 1)) - 1) * {16 ** (6 - k)}" for k in range(1, 7))
_CS = ", ".join(G.CLASSES)


def truth(order: str = "md5") -> str:
    """blocks, calls and tr (id, grp) of the truth set in its published design."""
    by = {"md5": "md5(cast(sample_id as varchar))", "size": "n_func desc, md5(cast(sample_id as varchar))"}[order]
    return f"""{G.DOC_BLOCKS.replace('blocks as (', 'blocks0 as (')},
    fn as (select sample_id, func_id, row_number() over (partition by sample_id order by func_id) - 1 as place, count(*) over (partition by sample_id) as n_func, max(func_id) over (partition by sample_id) as top_func, line from lines),
    nb as (select sample_id, func_id, count(*) as nb from blocks0 group by 1, 2),
    st as (select sample_id, count(*) as n_func, count(*) filter (where nb >= 3) as big, string_agg(concat(lpad(cast(func_id as varchar), 9, '0'), ':', md5(line)), '|' order by func_id) as body from fn left join nb using (sample_id, func_id) group by 1),
    bases as (select min(sample_id) as sample_id, max(n_func) as n_func from st where big >= 3 group by body),
    tops as (select sample_id, row_number() over (order by {by}) as rank from bases qualify rank <= {E.ISOLATED + E.GROUPS}),
    cp as (select sample_id, rank, unnest(range(0, ({E.copy_counts()})[rank])) as copy from tops),
    hn as (select a.rank, b.sample_id, a.sample_id as donor from tops a join tops b on b.rank = {E.ISOLATED} + a.rank where a.rank <= {E.HARD}),
    df as (select donor, min(func_id) as func_id from hn join nb on nb.sample_id = donor where nb >= 3 group by 1),
    mk as (select c.sample_id * 100 + c.copy as sid, c.rank, c.sample_id, c.copy, case when c.copy = 0 then -1 else c.copy % 5 end as op, fn.func_id, fn.place, fn.n_func, fn.place = ({_HEX}) % fn.n_func as hit from cp c join fn on fn.sample_id = c.sample_id),
    blocks as (select sid as sample_id, mk.func_id, cast(rank as varchar) as grp, case when hit and op = 2 and nb.nb >= 3 and id < 2 then 1 - id else id end as id, a, b, n + (case when hit and op = 1 and id = 0 then 1 else 0 end) as n, {', '.join(G.CLASSES[:8])}, c9 + (case when hit and op = 1 and id = 0 then 1 else 0 end) as c9
        from mk join blocks0 b0 on b0.sample_id = mk.sample_id and b0.func_id = mk.func_id join nb on nb.sample_id = mk.sample_id and nb.func_id = mk.func_id
        union all select sid, func_id + 1, cast(rank as varchar), k, ['h', 'i'][k + 1], ['x', 'y'][k + 1], 1, 1, 0, 0, 0, 0, 0, 0, 0, 0 from mk, (select unnest([0, 1]) as k) where op = 4 and place = n_func - 1
        union all select hn.sample_id * 100 + 99, b0.func_id, cast(hn.rank as varchar), id, a, b, n, {_CS} from hn join blocks0 b0 on b0.sample_id = hn.sample_id
        union all select hn.sample_id * 100 + 99, top_func + 1, cast(hn.rank as varchar), id, a, b, n, {_CS} from hn join df on df.donor = hn.donor join blocks0 b0 on b0.sample_id = hn.donor and b0.func_id = df.func_id join (select distinct sample_id, top_func from fn) t on t.sample_id = hn.sample_id),
    fs as (select sid as sample_id, func_id from mk union all select sid, func_id + 1 from mk where op = 4 and place = n_func - 1 union all select hn.sample_id * 100 + 99, func_id from hn join fn on fn.sample_id = hn.sample_id union all select hn.sample_id * 100 + 99, max(top_func) + 1 from hn join fn on fn.sample_id = hn.sample_id group by 1),
    calls as (select * from (select sample_id, func_id as caller, lead(func_id) over (partition by sample_id order by func_id) as callee from fs) where callee is not null),
    tr as (select distinct sample_id as id, grp from blocks)"""


def _vectors(cfg: FeatureConfig, tag: str) -> str:
    """vh{tag}: heads with shape and class lists, and hd{tag}: (id, head)."""
    size = "* n_blocks" if cfg.size_weight else ""
    shape = {"xy": ["x", "y"], "xyz": ["x", "y", "z"], "centroid": ["x", "y", "z", "w"]}[cfg.shape]
    ws = G.WS if cfg.semantic else []
    part = lambda c, n: f"round(case when omega > 0 then {n} / omega else 0 end {size}, 9) as {c}"
    first = [part(c, n) for c, n in (("x", "xn"), ("y", "yn"), ("z", "zn")) if c in shape] + (["round(cast(omega as double), 9) as w"] if "w" in shape else []) + [f"cast({w} as double) as {w}" for w in ws]
    names = [*shape, *ws]
    sums = ", ".join(f"coalesce(cast(sum(cast(g.{c} as decimal(28, 9))) as double), 0) as {c}" for c in names)
    out = f"""k0{tag} as (select sample_id, func_id, {', '.join(first)} from v),
    k1{tag} as (select h.sample_id, h.func_id, {sums} from k0{tag} h left join calls c on c.sample_id = h.sample_id and c.caller = h.func_id left join k0{tag} g on g.sample_id = c.sample_id and g.func_id = c.callee group by 1, 2),
    nd{tag} as (select *, 0 as hop from k0{tag} union all select *, 1 from k1{tag}), """
    if cfg.representation == "string":
        tokens = [("s", n, c) for n, c in enumerate(shape)] + [("c", n, c) for n, c in enumerate(ws)]
        value = lambda c: f"cast(cast(floor({c} * 10000 + 0.5) as bigint) as varchar)"
        code = lambda t: " + ".join(f"(instr('0123456789abcdef', substr({t}, {k}, 1)) - 1) * {16 ** (8 - k)}" for k in range(1, 9))
        out += f"""tk{tag} as (select sample_id, unnest([{', '.join(f"md5(concat('{t}:', hop, ':{n}:', {value(c)}))" for t, n, c in tokens)}]) as t from nd{tag}),
        bc{tag} as (select sample_id as id, ({code('t')}) % 1024 as b, count(*) as n from tk{tag} group by 1, 2),
        bm{tag} as (select id, map_from_entries(list((b, n))) as m from bc{tag} group by 1),
        rw{tag} as (select id, cast([] as double[]) as sh, list_transform(range(0, 1024), lambda k: cast(coalesce(m[k], 0) as double)) as cl from bm{tag}), """
    else:
        cl = f"flatten(list([{', '.join(ws)}] order by func_id, hop))" if ws else "cast([] as double[])"
        out += f"rw{tag} as (select sample_id as id, flatten(list([{', '.join(shape)}] order by func_id, hop)) as sh, {cl} as cl from nd{tag} group by 1), "
    unit = "list_transform(sh, lambda q: coalesce(q / nullif(ns, 0), 0))" if cfg.metric == "hybrid" else "sh"
    return out + f"""nm{tag} as (select id, sh, cl, sqrt(coalesce(list_sum(list_transform(sh, lambda q: q * q)), 0)) as ns, sqrt(coalesce(list_sum(list_transform(cl, lambda q: q * q)), 0)) as nc from rw{tag}),
    uv{tag} as (select id, {unit} as sh, cl, ns, nc from nm{tag}),
    hd{tag} as (select *, min(id) over (partition by list_transform(sh, lambda q: round(q, 10)), list_transform(cl, lambda q: round(q, 6))) as head from uv{tag}),
    wd{tag} as (select max(len(sh)) as ms, max(len(cl)) as mc from hd{tag}),
    vh{tag} as (select id, list_resize(sh, ms, 0.0) as sh, list_resize(cl, mc, 0.0) as cl, ns, nc from hd{tag}, wd{tag} where id = head)"""


def scored(cfg: FeatureConfig, tag: str = "", least: float = 0.9) -> str:
    """sc{tag}: (id_a, id_b, s) of all pairs of the truth set from the least score on."""
    dot = lambda c: f"coalesce(case when len(a.{c}) > 0 then list_dot_product(a.{c}, b.{c}) end, 0)"
    if cfg.metric == "hybrid":
        score = f"round(round(case when a.nc = 0 and b.nc = 0 then 1.0 when a.nc * b.nc = 0 then 0.0 else least(1.0, {dot('cl')} / (a.nc * b.nc)) end, 10) * round(exp(-5 * power(list_distance(a.sh, b.sh), 2)), 10), 10)"
    else:
        n = lambda x: f"sqrt({x}.ns * {x}.ns + {x}.nc * {x}.nc)"
        score = f"round(case when {n('a')} = 0 and {n('b')} = 0 then 1.0 when {n('a')} * {n('b')} = 0 then 0.0 else least(1.0, ({dot('sh')} + {dot('cl')}) / ({n('a')} * {n('b')})) end, 10)"
    return f"""{_vectors(cfg, tag)}, sq{tag} as (select a.id as a, b.id as b, {score} as s from vh{tag} a join vh{tag} b on a.id < b.id),
    sh{tag} as (select a, b, s from sq{tag} where s >= {least} union all select id, id, 1.0 from vh{tag}),
    sc{tag} as (select least(x.id, y.id) as id_a, greatest(x.id, y.id) as id_b, s from sh{tag} join hd{tag} x on x.head = a join hd{tag} y on y.head = b where a < b or x.id < y.id)"""


def swept(scores: str, truth_: str, taus: list[float]) -> str:
    """A select of tau, tp, fp, fn, tn, precision, recall, f1."""
    return f"""(select tau, tp, fp, fn, cast(n * (n - 1) // 2 - tp - fp - fn as bigint) as tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(p, 0), 6) as recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) as f1
    from (select tau, tp, fp, cast(p - tp as bigint) as fn, p, n from (select tau, count(*) filter (where s >= tau and same) as tp, count(*) filter (where s >= tau and not same) as fp from (select unnest([{', '.join(f'cast({t!r} as double)' for t in taus)}]) as tau) left join
        (select s, x.grp = y.grp as same from {scores} join {truth_} x on x.id = id_a join {truth_} y on y.id = id_b) on true group by 1),
        (select count(*) as n from {truth_}), (select coalesce(sum(k * (k - 1) // 2), 0) as p from (select count(*) as k from {truth_} group by grp))))"""


def one(name: str, order: str = "md5") -> str:
    return f"with {truth(order)}, {G.FLOW}, {scored(E.CONFIGS[name])} select '{name}' as config, * from {swept('sc', 'tr', E.TAUS)}"


def table(names: list[str]) -> str:
    """sweeps: config, tau, ... of several configurations."""
    parts = ", ".join(scored(E.CONFIGS[n], f"_{n.lower()}") for n in names)
    rows = " union all ".join(f"select '{n}' as config, * from {swept(f'sc_{n.lower()}', 'tr', E.TAUS)}" for n in names)
    return f"with {truth()}, {G.FLOW}, {parts}, sweeps as ({rows}), best as (select config, r.tau, r.precision, r.recall, r.f1 from (select config, arg_max({{'tau': tau, 'precision': precision, 'recall': recall, 'f1': f1}}, (coalesce(f1, -1), tau)) as r from sweeps group by 1))"
