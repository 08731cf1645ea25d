"""SQL of the registered queries, composed from common parts; it shares no code with the engine."""

from __future__ import annotations

#: Common parts by name: (names of the parts needed, body).
PARTS: dict[str, tuple[tuple[str, ...], str]] = {
    "rows_": ((), "select l_orderkey, l_linenumber, l_suppkey, l_partkey, o_custkey, o_orderpriority, o_orderdate, c_nationkey, c_mktsegment, s_nationkey, (c_nationkey % 5 = s_nationkey % 5 or (l_orderkey * 7 + l_linenumber) % 20 = 0) as planted from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey"),
    "f_trade": (("rows_",), "select c_nationkey::int as src, s_nationkey::int as dst, count(*)::bigint as w from rows_ group by 1, 2"),
    "f_planted": (("rows_",), "select c_nationkey::int as src, s_nationkey::int as dst, count(*)::bigint as w from rows_ where planted group by 1, 2"),
    "f_local": (("f_trade",), "select * from f_trade where abs(src % 5 - dst % 5) + abs(src // 5 - dst // 5) <= 2"),
    "f_tract": (("rows_",), "select ((c_nationkey // 5) * 25 + c_nationkey % 5 * 5 + o_custkey % 5)::int as src, ((s_nationkey // 5) * 25 + s_nationkey % 5 * 5 + l_suppkey % 5)::int as dst, count(*)::bigint as w from rows_ where planted group by 1, 2"),
    "pairs_": ((), "select user_id, floor(epoch(ts))::bigint - 1704067200 as t0, lead(floor(epoch(ts))::bigint - 1704067200) over (partition by user_id order by ts, event_id) as nxt from events"),
    "f_clock": (("pairs_",), "select (t0 // 21600)::int as src, (nxt // 21600)::int as dst, count(*)::bigint as w from pairs_ where nxt - t0 <= 172800 group by 1, 2"),
    "f_clockgrid": (("pairs_",), "select (t0 // 3600)::int as src, (nxt // 3600)::int as dst, count(*)::bigint as w from pairs_ where nxt - t0 <= 86400 group by 1, 2"),
    "f_basket": ((), "select ((regexp_extract(a.p_brand, '(\\d+)', 1)::int - 1) * 50 + a.p_size - 1)::int as src, ((regexp_extract(b.p_brand, '(\\d+)', 1)::int - 1) * 50 + b.p_size - 1)::int as dst, count(*)::bigint as w from (select l_partkey, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey) as nxt from lineitem) l join part a on l.l_partkey = a.p_partkey join part b on l.nxt = b.p_partkey group by 1, 2"),
    "f_ship": ((), "select floor(date_diff('day', date '1995-01-01', o_orderdate::date) / 7.0)::int as src, floor(date_diff('day', date '1995-01-01', l_shipdate::date) / 7.0)::int as dst, count(*)::bigint as w from lineitem join orders on l_orderkey = o_orderkey group by 1, 2"),
    "f_turns": ((), "select case role when 'system' then 0 when 'user' then 1 else 2 end::int as src, case nxt when 'system' then 0 when 'user' then 1 else 2 end::int as dst, count(*)::bigint as w from (select role, lead(role) over (partition by conv_id order by turn) as nxt from conversations) t where nxt is not null group by 1, 2"),
    "f_docs": ((), "select cell as src, nxt as dst, count(*)::bigint as w from (select cell, lead(cell) over (partition by h order by doc_id) as nxt from (select doc_id, (case lang when 'de' then 0 when 'en' then 1 when 'es' then 2 else 3 end * 20 + regexp_extract(source, '(\\d+)', 1)::int)::int as cell, md5(lower(trim(text))) as h from documents where text is not null) d) e where nxt is not null group by 1, 2"),
    "u_nation": ((), "select i::int as unit_id, (i % 5)::double as x, (i // 5)::double as y, (i % 5)::int as parent_id, 0 as grand_id, (1 + i % 3)::double as area from range(25) t(i)"),
    "u_tract": ((), "select i::int as unit_id, (i % 25)::double as x, (i // 25)::double as y, ((i // 25) * 5 + i % 25 // 5)::int as parent_id, (i % 25 // 5)::int as grand_id, (1 + i % 3)::double as area from range(125) t(i)"),
    "u_clock": ((), "select i::int as unit_id, i::double as x, 0.0::double as y, (i // 4)::int as parent_id, (i // 28)::int as grand_id, (1 + i % 3)::double as area from range(120) t(i)"),
    "u_clockgrid": ((), "select i::int as unit_id, (i % 24)::double as x, (i // 24)::double as y, (i // 24)::int as parent_id, (i // 24 // 7)::int as grand_id, (1 + i % 3)::double as area from range(720) t(i)"),
} | {
    f"a_{k}": ((f"u_{k}",), f"select p.unit_id as a, q.unit_id as b from u_{k} p join u_{k} q on (q.x = p.x + 1 and q.y = p.y) or (q.x = p.x and q.y = p.y + 1)")
    for k in ("nation", "tract", "clock", "clockgrid")
} | {
    # units that rows of a given table fall into, and their borders
    f"s_{k}": ((f"u_{k}",), f"select * from u_{k} where unit_id in ({cells})")
    for k, cells in (
        ("nation", "select c_nationkey from customer where c_custkey in (select o_custkey from orders) union select s_nationkey from supplier"),
        ("tract", "select (c_nationkey // 5) * 25 + c_nationkey % 5 * 5 + c_custkey % 5 from customer where c_custkey in (select o_custkey from orders) union select (s_nationkey // 5) * 25 + s_nationkey % 5 * 5 + s_suppkey % 5 from supplier"),
        ("clockgrid", "select (floor(epoch(ts))::bigint - 1704067200) // 3600 from events"),
    )
} | {
    f"b_{k}": ((f"s_{k}",), f"select p.unit_id as a, q.unit_id as b from s_{k} p join s_{k} q on (q.x = p.x + 1 and q.y = p.y) or (q.x = p.x and q.y = p.y + 1)")
    for k in ("nation", "tract", "clockgrid")
}


def compose(needs: tuple[str, ...], body: str, more: str = "", recursive: bool = False) -> str:
    """``with`` all parts needed, in order of need, then ``more`` (further parts), then the body."""
    done: list[str] = []

    def add(name: str) -> None:
        for n in PARTS[name][0]:
            add(n)
        if name not in done:
            done.append(name)

    for name in needs:
        add(name)
    parts = [f"{n} as ({PARTS[n][1]})" for n in done] + ([more] if more else [])
    head = f"with {'recursive ' if recursive else ''}" + ",\n".join(parts) if parts else ""
    return f"{head}\n{body}"


def lf(n: str) -> str:
    return f"(lgamma(({n})::double + 1) / ln(2))"


def lchoose(n: str, k: str) -> str:
    return f"(case when ({k}) = 0 or ({k}) = ({n}) then 0.0 else {lf(n)} - {lf(k)} - {lf(f'({n}) - ({k})')} end)"


def lmulti(n: str, k: str) -> str:
    return f"(case when ({k}) = 0 then 0.0 else {lchoose(f'({n}) + ({k}) - 1', k)} end)"


def lcomp(w: str, e: str) -> str:
    return f"(case when ({e}) = 0 then 0.0 else {lchoose(f'({w}) - 1', f'({e}) - 1')} end)"


def cost(nn: str, e: str, w: str, rep: str) -> str:
    return lmulti(nn, w) if rep == "mg" else f"({lchoose(nn, e)} + {lcomp(w, e)})"


def matrix(b: str, e: str, w: str, rep: str) -> str:
    square = f"({b})::double * ({b})"
    return lmulti(square, w) if rep == "mg" else f"({lmulti(square, e)} + {lmulti(square, w)})"


def length(flow: str, part: str, rep: str, n: str = "") -> str:
    """Parts g_, c_, t_: one row (n, b, e, w, partition_bits, matrix_bits, placement_bits, weight_bits, dl) of the partition table ``part``."""
    place = lmulti("nn", "w") if rep == "mg" else lchoose("nn", "e")
    weight = "0.0" if rep == "mg" else lcomp("w", "e")
    return f"""g_ as (select label, count(*)::bigint as n from {part} group by label),
c_ as (select p.label as r, q.label as s, count(*)::bigint as e, sum(f.w)::bigint as w, any_value(gp.n)::double * any_value(gq.n) as nn from {flow} f join {part} p on f.src = p.unit_id join {part} q on f.dst = q.unit_id join g_ gp on gp.label = p.label join g_ gq on gq.label = q.label group by 1, 2),
h_ as (select sum(n)::bigint as n, count(*)::bigint as b, sum({lf('n')}) as inside from g_),
k_ as (select sum(e)::bigint as e, sum(w)::bigint as w, sum({place}) as placement_bits, sum({weight}) as weight_bits from c_),
t_ as (select n, b, e, w, {lchoose('n - 1', 'b - 1')} + {lf('n')} - inside as partition_bits, {matrix('b', 'e', 'w', rep)} as matrix_bits, placement_bits, weight_bits from h_ cross join k_),
d_ as (select *, partition_bits + matrix_bits + placement_bits + weight_bits as dl from t_)"""


def greedy(flow: str, adj: str, n: int, rep: str, last: int = 1, nets: str = "select 0 as net", place=None, const=None, group=None, ends: str = "") -> str:
    """Recursive part ga(net, step, b, l, dl): at each step every touching pair is merged on trial and its whole length computed from nothing.

    flow: (net, src, dst, w) with ends 0..n-1, adj: (a, b); ends at ``last`` groups. place(nn, e, w), const(b, e, w) and
    group(n, out, into, own) give other objectives than the block model's; ends: e or w where group needs strengths.
    """
    place = place or (lambda nn, e, w: cost(nn, e, w, rep))
    const = const or (lambda b, e, w: f"({lchoose(f'{n} - 1', f'{b} - 1')} + {lf(str(n))} + {matrix(b, e, w, rep)})")
    group = group or (lambda n, out, into, own: f"(-{lf(n)})")
    first = f"select net, 0 as step, {n} as b, list_transform(range({n}), lambda x: x::int) as l from ({nets}) z"
    total = f"(select net, count(*)::bigint as e, sum(w)::bigint as w from {flow} group by net)"
    tried = "select g.net, g.step, g.b, least(g.l[a.a + 1], g.l[a.b + 1]) as r, greatest(g.l[a.a + 1], g.l[a.b + 1]) as s, any_value(g.l) as l from ga g join " + adj + f" a on g.l[a.a + 1] <> g.l[a.b + 1] where g.b > {last} group by 1, 2, 3, 4, 5"
    new = f"select net, step, b - 1 as b, r, s, list_transform(l, lambda x: case when x = s then r else x end) as l from ({tried}) y"
    size = "select net, step, r, s, x as g, count(*)::bigint as n from (select net, step, r, s, unnest(l) as x from new_) v group by 1, 2, 3, 4, 5"
    cell = f"select c.net, c.step, c.r, c.s, c.l[f.src + 1] as p, c.l[f.dst + 1] as q, count(*)::bigint as e, sum(f.w)::bigint as w from new_ c join {flow} f on f.net = c.net group by 1, 2, 3, 4, 5, 6"
    if ends:
        side = lambda table, keys, c, more: f"(select {keys}, {c} as g, sum({ends}) as x{more} from {table} group by {keys}, {c})"
        own = f", sum(case when p = q then {ends} else 0 end) as own"
        strong = lambda sizes, table, keys: f"{sizes} z left join {side(table, keys, 'p', own)} o using ({keys}, g) left join {side(table, keys, 'q', '')} i using ({keys}, g)"
        term = group("z.n", "coalesce(o.x, 0)", "coalesce(i.x, 0)", "coalesce(o.own, 0)")
    else:
        strong, term = (lambda sizes, table, keys: f"{sizes} z"), group("z.n", "0", "0", "0")
    inside = f"select net, step, r, s, sum({term}) as inside from {strong('size_', 'cell_', 'net, step, r, s')} group by net, step, r, s"
    bits = f"select k.net, k.step, k.r, k.s, sum({place('a.n::double * b.n', 'k.e', 'k.w')}) as bits from cell_ k join size_ a on a.net = k.net and a.step = k.step and a.r = k.r and a.s = k.s and a.g = k.p join size_ b on b.net = k.net and b.step = k.step and b.r = k.r and b.s = k.s and b.g = k.q group by 1, 2, 3, 4"
    dl = f"{const('c.b', 't.e', 't.w')} + i.inside + h.bits"
    step = f"""with new_ as ({new}), size_ as ({size}), cell_ as ({cell}), in_ as ({inside}), bits_ as ({bits}),
    all_ as (select c.net, c.step, c.b, c.r, c.s, c.l, {dl} as dl from new_ c join in_ i on i.net = c.net and i.step = c.step and i.r = c.r and i.s = c.s join bits_ h on h.net = c.net and h.step = c.step and h.r = c.r and h.s = c.s join {total} t on t.net = c.net)
    select net, step + 1 as step, b, arg_min(l, (round(dl, 8), r, s)) as l from all_ group by net, step, b"""
    # the length of each visited partition, again from nothing
    seen = f"""ga as ({first} union all select * from ({step}) w),
gu as (select net, step, b, unnest(l) as g, unnest(range({n})) as u from ga),
gs as (select net, step, g, count(*)::bigint as n, min(u)::int as low from gu group by 1, 2, 3),
gc as (select ga.net, ga.step, ga.l[f.src + 1] as p, ga.l[f.dst + 1] as q, count(*)::bigint as e, sum(f.w)::bigint as w from ga join {flow} f on f.net = ga.net group by 1, 2, 3, 4),
gi as (select net, step, count(*)::bigint as b, sum({term}) as inside from {strong('gs', 'gc', 'net, step')} group by net, step),
gb as (select k.net, k.step, sum(k.e)::bigint as e, sum(k.w)::bigint as w, sum({place('x.n::double * y.n', 'k.e', 'k.w')}) as bits from gc k join gs x on x.net = k.net and x.step = k.step and x.g = k.p join gs y on y.net = k.net and y.step = k.step and y.g = k.q group by 1, 2),
gd as (select i.net, i.step, i.b, {const('i.b', 'k.e', 'k.w')} + i.inside + k.bits as dl from gi i join gb k on k.net = i.net and k.step = i.step)"""
    return seen


def exhausted(flow: str, n: int) -> str:
    """Parts of all labellings of n units 0..n-1 with labels 0..B-1, each group in use, over ``flow`` (src, dst, w): v_ (id, l, b), m_ (id, r, s, e, w), z_ (id, g, n, o, i, ow, iw)."""
    choose = " cross join ".join(f"range({n}) t{k}(x{k})" for k in range(n))
    return f"""v_ as (select row_number() over (order by l) as id, l, len(list_distinct(l)) as b from (select [{', '.join(f'x{k}' for k in range(n))}] as l from {choose}) q where list_max(l) + 1 = len(list_distinct(l))),
m_ as (select id, l[src + 1] as r, l[dst + 1] as s, count(*)::bigint as e, sum(w)::bigint as w from v_ cross join {flow} group by 1, 2, 3),
y_ as (select id, g, count(*)::bigint as n from (select id, unnest(l) as g from v_) q group by 1, 2),
z_ as (select y.id, y.g, y.n, coalesce(o.e, 0) as oe, coalesce(o.w, 0) as ow, coalesce(i.e, 0) as ie, coalesce(i.w, 0) as iw from y_ y left join (select id, r as g, sum(e)::bigint as e, sum(w)::bigint as w from m_ group by 1, 2) o using (id, g) left join (select id, s as g, sum(e)::bigint as e, sum(w)::bigint as w from m_ group by 1, 2) i using (id, g))"""


def best_model(flow: str, n: int, rep: str, dc: bool, ranked: bool, nested: bool) -> str:
    """The least length of any labelling of ``flow`` under one variant, by trying all of them (and, nested, all hierarchies): one row (b, dl) as parts e_..."""
    k = "w" if rep == "mg" else "e"
    group = f"-{lf('n')}" + (f" + {lf(f'o{k}')} + {lf(f'i{k}')} + {lmulti('n', f'o{k}')} + {lmulti('n', f'i{k}')}" if dc else "")
    place = lmulti("x.n * y.n", "m.w") if rep == "mg" else lchoose("x.n * y.n", "m.e")
    place = f"-{lf('m.' + k)}" if dc else place
    weight = "0.0" if rep == "mg" else lcomp("m.w", "m.e")
    fixed = "0.0"
    if dc:
        each = f"select sum({lf('k')}) from (select {{}}, sum({'w' if rep == 'mg' else '1'})::bigint as k from {flow} group by 1) q"
        fixed = f"(select coalesce(sum({lf('w')}), 0) from {flow}) * {1 if rep == 'mg' else 0} - ({each.format('src')}) - ({each.format('dst')})"
    spread = lambda x: f"({lmulti('3', f'{x}u + {x}d + {x}f')} + case when b > 1 then {lmulti('b * (b - 1) // 2', f'{x}u')} + {lmulti('b * (b - 1) // 2', f'{x}d')} else 0 end + {lmulti('b', f'{x}f')})"
    both = lambda f: f("w") if rep == "mg" else f"({f('e')} + {f('w')})"
    ways = ", ".join(f"sum(case when r {op} s then {x} else 0 end)::bigint as {x}{c}" for x in "ew" for c, op in (("u", "<"), ("d", ">"), ("f", "=")))
    flat = both(spread) if ranked else both(lambda x: lmulti("b * b", f"{x}u + {x}d + {x}f"))
    parts = f"""{exhausted(flow, n)},
p_ as (select id, {lchoose(f'{n} - 1', 'any_value(b) - 1')} + {lf(str(n))} + sum({group}) as bits from z_ join v_ using (id) group by id),
q_ as (select m.id, sum({place} + {weight}) as bits from m_ m join z_ x on x.id = m.id and x.g = m.r join z_ y on y.id = m.id and y.g = m.s group by m.id),
w_ as (select id, {ways} from m_ group by id),
f_ as (select v.id, v.l, v.b, p.bits + q.bits + {fixed} as below, {flat} as top from v_ v join p_ p using (id) join q_ q using (id) join w_ using (id))"""
    if not nested:
        return parts + ",\nbest_ as (select arg_min(b, (round(below + top, 8), b)) as b, min(below + top) as dl from f_)"
    # one level above: the groups of v are nodes, v2 puts them together; what is above v2 is again the best for its matrix
    level = both(lambda x: lmulti("c1.n * c2.n", f"k.{x}"))
    return parts + f""",
a_ as (select distinct f.id, f.b, g.id as up, g.b as b2 from f_ f join f_ g on g.b < f.b and g.b > 1 and len(list_distinct(list_transform(range(1, {n + 1}), lambda i: [f.l[i], g.l[i]]))) = f.b),
nodes_ as (select a.id, a.up, g, count(distinct h)::bigint as n from (select a.id, a.up, unnest(g.l) as g, unnest(f.l) as h from a_ a join f_ f on f.id = a.id join f_ g on g.id = a.up) a group by 1, 2, 3),
step_ as (select a.id, a.up, {lchoose('any_value(a.b) - 1', 'any_value(a.b2) - 1')} + {lf('any_value(a.b)')} - any_value(i.inside) + sum({level}) as bits from a_ a join (select id, up, sum({lf('n')}) as inside from nodes_ group by 1, 2) i on i.id = a.id and i.up = a.up join m_ k on k.id = a.up join nodes_ c1 on c1.id = a.id and c1.up = a.up and c1.g = k.r join nodes_ c2 on c2.id = a.id and c2.up = a.up and c2.g = k.s group by 1, 2),
h_ as (select id, id as at, below as bits from f_ union all select h.id, t.up, h.bits + t.bits from h_ h join step_ t on t.id = h.at),
best_ as (select arg_min(f.b, (round(h.bits + g.top, 8), f.b)) as b, min(h.bits + g.top) as dl from h_ h join f_ f on f.id = h.id join f_ g on g.id = h.at)"""
