"""The registered queries of the regionalization engine and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from flowregions import oracle as O  # noqa: N812
from flowregions.operators import adjacency as adj
from flowregions.operators import baselines, components, contiguity, dl, network, nulls, scores, similarity
from flowregions.plans import greedy, kernel
from flowregions.plans.checkpoints import cut
from flowregions.registry import ORACLES, QUERIES, register, rounded  # noqa: F401
from flowregions.sources import tables
from flowregions.sources import units as U
from flowregions.sources import workloads as W

# ---------------------------------------------------------------- flows and borders

for _name, _part in (("trade", "f_trade"), ("planted", "f_planted"), ("local", "f_local"), ("tracts", "f_tract"), ("clock", "f_clock"), ("clock_grid", "f_clockgrid"), ("basket", "f_basket"), ("ship", "f_ship"), ("turns", "f_turns"), ("docs", "f_docs")):
    register(f"flows_{_name}", lambda s, d, f=W.WORKLOADS[_name]: f(s, d).select("src", "dst", "w"), O.compose((_part,), f"select src, dst, w from {_part}"))

UNITS = {"nation": U.nations, "tract": U.tracts, "clock": U.clock, "clockgrid": U.clock_grid}
FLOWS = {"nation": W.planted, "tract": W.tracts, "clock": W.clock, "clockgrid": W.clock_grid}
NAMES = {"nation": "planted", "tract": "tract", "clock": "clock", "clockgrid": "clockgrid"}
SQL_FLOWS = {"nation": "f_planted", "tract": "f_tract", "clock": "f_clock", "clockgrid": "f_clockgrid"}


def _net(s: SparkSession, d: str, kind: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    units = UNITS[kind](s, NAMES[kind])
    return FLOWS[kind](s, d), units, adj.from_cells(units)


CELLS = {"nation": W.nation_homes, "tract": W.tract_homes, "clockgrid": W.hours}


def _held(s: SparkSession, d: str, kind: str) -> DataFrame:
    """The units where customers with orders and suppliers live, or in which there are events."""
    return U.held(UNITS[kind](s), CELLS[kind](s, d))


for _kind in ("nation", "tract", "clockgrid"):
    register(f"adj_{_kind}", lambda s, d, k=_kind: adj.from_cells(_held(s, d, k)).select("a", "b", "shared_len"), O.compose((f"b_{_kind}",), f"select a, b, 1.0::double as shared_len from b_{_kind}"))
register("adj_segments", lambda s, d: adj.from_segments(adj.cell_segments(_held(s, d, "tract"))).select("a", "b", "shared_len"), O.compose(("b_tract",), "select a, b, 1.0::double as shared_len from b_tract"))
register("adj_problems", lambda s, d: adj.check(adj.from_cells(U.tracts(s)).unionByName(s.createDataFrame([("tract", 5, 3, 1.0), ("tract", 1, 999, 1.0)], tables.ADJACENCY)), _held(s, d, "tract")).select("a", "b", "problem"), O.compose(("a_tract", "s_tract"), "select 5 as a, 3 as b, 'not a < b' as problem union all select a, b, 'unknown ' || e from (select a, b from a_tract union all select 5, 3 union all select 1, 999) z cross join (values ('a'), ('b')) t(e) where case e when 'a' then a else b end not in (select unit_id from s_tract)"))
register("adj_vectors", lambda s, d: adj.from_knn(adj.knn(tables.read(s, d, "embeddings"), 8)).agg(F.count("*").alias("borders"), F.count_distinct("a").alias("ends")), """
with v as (select vec_id, embedding::double[] as e from embeddings), n as (select vec_id, list_transform(e, lambda x: x / sqrt(list_sum(list_transform(e, lambda y: y * y)))) as e from v),
r as (select p.vec_id as src, q.vec_id as dst, row_number() over (partition by p.vec_id order by round(list_inner_product(p.e, q.e), 9) desc, q.vec_id) as k from n p join n q on p.vec_id <> q.vec_id),
g as (select distinct least(src, dst) as a, greatest(src, dst) as b from r where k <= 8)
select count(*)::bigint as borders, count(distinct a)::bigint as ends from g""")
register("coarsen_flows", lambda s, d: network.coarsen(W.tracts(s, d), U.tracts(s)).select("src", "dst", "w"), O.compose(("f_planted",), "select src, dst, w from f_planted"))
register("coarsen_adj", lambda s, d: adj.coarsen(adj.from_cells(_held(s, d, "tract")), _held(s, d, "tract")).select("a", "b", "shared_len"), O.compose(("b_tract", "s_tract"), "select least(p.parent_id, q.parent_id)::int as a, greatest(p.parent_id, q.parent_id)::int as b, count(*)::double as shared_len from b_tract t join s_tract p on p.unit_id = t.a join s_tract q on q.unit_id = t.b where p.parent_id <> q.parent_id group by 1, 2"))
register("distance_share", lambda s, d: network.distance_share(W.trade(s, d), U.nations(s, "trade")).select("kept_w", "all_w", "share"), O.compose(("f_trade",), "select sum(case when sqrt((src % 5 - dst % 5) * (src % 5 - dst % 5) + (src // 5 - dst // 5) * (src // 5 - dst // 5)) * 80 <= 160 then w else 0 end)::bigint as kept_w, sum(w)::bigint as all_w, round(sum(case when sqrt((src % 5 - dst % 5) * (src % 5 - dst % 5) + (src // 5 - dst // 5) * (src // 5 - dst // 5)) * 80 <= 160 then w else 0 end)::double / sum(w), 6) as share from f_trade"))
register("filter_distance", lambda s, d: network.filter_distance(W.trade(s, d), U.nations(s, "trade")).select("src", "dst", "w"), O.compose(("f_trade",), "select * from f_trade where sqrt((src % 5 - dst % 5) * (src % 5 - dst % 5) + (src // 5 - dst // 5) * (src // 5 - dst // 5)) * 80 <= 160"))
register("drop_self_loops", lambda s, d: W.trade(s, d).filter("src != dst").select("src", "dst", "w"), O.compose(("f_trade",), "select * from f_trade where src <> dst"))
register("degrees", lambda s, d: network.degrees(W.planted(s, d)).drop("network_id"), O.compose(("f_planted",), "select coalesce(o.u, i.u) as unit_id, coalesce(k_out, 0)::bigint as k_out, coalesce(k_in, 0)::bigint as k_in, coalesce(s_out, 0)::bigint as s_out, coalesce(s_in, 0)::bigint as s_in from (select src as u, count(*) as k_out, sum(w) as s_out from f_planted group by 1) o full join (select dst as u, count(*) as k_in, sum(w) as s_in from f_planted group by 1) i on o.u = i.u"))
register("totals_w", lambda s, d: network.totals(W.planted(s, d), U.nations(s, "planted"), "w").select("n", "e", "w"), O.compose(("f_planted",), "select 25::bigint as n, count(*)::bigint as e, sum(w)::bigint as w from f_planted"))
register("totals_mg", lambda s, d: network.totals(W.planted(s, d), U.nations(s, "planted"), "mg").select("n", "e", "w"), O.compose(("f_planted",), "select 25::bigint as n, sum(w)::bigint as e, sum(w)::bigint as w from f_planted"))
register("multi_edges", lambda s, d: network.explode_multiedges(W.turns(s, d)).groupBy("src", "dst").agg(F.count("*").alias("edges")), O.compose(("f_turns",), "select src, dst, w as edges from f_turns"))
register("induce_region", lambda s, d: network.induce(W.tracts(s, d), U.tracts(s), "grand_id = 2").select("src", "dst", "w"), O.compose(("f_tract",), "select * from f_tract where src % 25 // 5 = 2 and dst % 25 // 5 = 2"))
register("map_endpoints", lambda s, d: network.build_flows(network.map_endpoints(W.trade_rows(s, d).select(F.format_string("N%02d", "c_nationkey").alias("o"), F.format_string("N%02d", "s_nationkey").alias("t")), U.nations(s, "trade").withColumn("code", F.format_string("N%02d", "unit_id")), "o", "t")).select("src", "dst", "w"), O.compose(("f_trade",), "select * from f_trade"))
register("by_period", lambda s, d: network.by_period(tables.read(s, d, "orders"), "o_orderdate").groupBy("period").agg(F.count("*").alias("n")), "select floor((year(o_orderdate) - 1995) / 5.0)::int as period, count(*)::bigint as n from orders group by 1")

# ---------------------------------------------------------------- lengths


def _admin(kind: str, level: str, model: str = "admin") -> Callable:
    return lambda s: baselines.admin(UNITS[kind](s, NAMES[kind]), level, model)


ADMIN_SQL = "part_ as (select unit_id, min(unit_id) over (partition by {level}) as label from {units})"
COLUMNS = "n, b, e, w, round(partition_bits, 4) as partition_bits, round(matrix_bits, 4) as matrix_bits, round(placement_bits, 4) as placement_bits, round(weight_bits, 4) as weight_bits, round(dl, 4) as dl"


def _length(kind: str, part: Callable, rep: str) -> Callable:
    return lambda s, d: rounded(dl.total(FLOWS[kind](s, d), part(s), rep).drop("network_id", "model", "rep"))


for _rep in ("mg", "w"):
    for _kind, _level, _name in (("nation", "parent_id", "region"), ("tract", "parent_id", "tract_nation"), ("tract", "grand_id", "tract_region"), ("clock", "parent_id", "clock_day")):
        register(f"dl_{_rep}_{_name}", _length(_kind, _admin(_kind, _level), _rep), O.compose((SQL_FLOWS[_kind], f"u_{_kind}"), f"select {COLUMNS} from d_", ADMIN_SQL.format(level=_level, units=f"u_{_kind}") + ",\n" + O.length(SQL_FLOWS[_kind], "part_", _rep)))
    register(f"dl_{_rep}_single", _length("nation", lambda s: baselines.single(U.nations(s, "planted")), _rep), O.compose(("f_planted", "u_nation"), f"select {COLUMNS} from d_", "part_ as (select unit_id, 0 as label from u_nation),\n" + O.length("f_planted", "part_", _rep)))
    register(f"dl_{_rep}_singletons", _length("nation", lambda s: baselines.singletons(U.nations(s, "planted")), _rep), O.compose(("f_planted", "u_nation"), f"select {COLUMNS} from d_", "part_ as (select unit_id, unit_id as label from u_nation),\n" + O.length("f_planted", "part_", _rep)))

_REGION = "part_ as (select unit_id, parent_id as label from u_nation),\n"


def _dc_sql(rep: str) -> str:
    one = "w" if rep == "mg" else "1"
    more = _REGION + O.length("f_planted", "part_", rep) + f""",
o_ as (select f.*, p.label as r, q.label as s, ({one})::bigint as k from f_planted f join part_ p on p.unit_id = f.src join part_ q on q.unit_id = f.dst),
x_ as (select label, sum(k)::bigint as k, sum({O.lf('k')}) as own from (select r as label, src, sum(k)::bigint as k from o_ group by 1, 2) z group by label),
y_ as (select label, sum(k)::bigint as k, sum({O.lf('k')}) as own from (select s as label, dst, sum(k)::bigint as k from o_ group by 1, 2) z group by label),
m_ as (select (select sum({O.lf('k')}) from o_) + (select sum({O.lf('x_.k')} + {O.lmulti('g_.n', 'x_.k')} - own) from x_ join g_ on g_.label = x_.label) + (select sum({O.lf('y_.k')} + {O.lmulti('g_.n', 'y_.k')} - own) from y_ join g_ on g_.label = y_.label) - (select sum({O.lf('w' if rep == 'mg' else 'e')}) from c_) as place)"""
    return O.compose(("f_planted", "u_nation"), "select b, round(partition_bits + matrix_bits + weight_bits + place, 4) as dl from d_ cross join m_", more)


def _ranked_sql(rep: str) -> str:
    def spread(x: str) -> str:
        half = "b * (b - 1) / 2.0"
        return f"({O.lmulti('3', f'{x}u + {x}d + {x}f')} + {O.lmulti(half, f'{x}u')} + {O.lmulti(half, f'{x}d')} + {O.lmulti('b', f'{x}f')})"

    more = _REGION + O.length("f_planted", "part_", rep) + ",\nz_ as (select " + ", ".join(f"sum(case when r {op} s then {x} else 0 end)::bigint as {x}{k}" for x in "ew" for k, op in (("u", "<"), ("d", ">"), ("f", "="))) + " from c_)"
    cost = spread("w") if rep == "mg" else f"{spread('e')} + {spread('w')}"
    return O.compose(("f_planted", "u_nation"), f"select b, round(partition_bits + placement_bits + weight_bits + {cost}, 4) as dl from d_ cross join z_", more)


for _rep in ("mg", "w"):
    register(f"dl_dc_{_rep}_region", lambda s, d, r=_rep: rounded(dl.total(W.planted(s, d), _admin("nation", "parent_id")(s), r, degree_corrected=True).select("b", "dl")), _dc_sql(_rep))
    register(f"dl_ranked_{_rep}_region", lambda s, d, r=_rep: rounded(dl.total(W.planted(s, d), _admin("nation", "parent_id")(s), r, ranked=True).select("b", "dl")), _ranked_sql(_rep))


def _given_hierarchy(s: SparkSession) -> DataFrame:
    """Tracts in nations, nations in regions, regions in one."""
    t = U.tracts(s)
    level = lambda k, node, label: t.select("network_id", F.lit("given").alias("model"), F.lit(k).alias("level"), F.col(node).alias("node"), (F.col(label) if isinstance(label, str) else label).cast("int").alias("label")).distinct()
    return level(0, "unit_id", "parent_id").unionByName(level(1, "parent_id", "grand_id")).unionByName(level(2, "grand_id", F.lit(0)))


def _nested_sql(rep: str) -> str:
    cell = (lambda t: f"sum({O.lmulti('nn', 'w')})") if rep == "mg" else (lambda t: f"sum({O.lmulti('nn', 'e')} + {O.lmulti('nn', 'w')})")
    more = "part_ as (select unit_id, parent_id as label from u_tract),\n" + O.length("f_tract", "part_", rep) + f""",
up_ as (select distinct parent_id, grand_id from u_tract),
two_ as (select p.grand_id as r, q.grand_id as s, sum(e)::bigint as e, sum(w)::bigint as w, 25.0 as nn from c_ join up_ p on p.parent_id = c_.r join up_ q on q.parent_id = c_.s group by 1, 2),
one_ as (select sum(e)::bigint as e, sum(w)::bigint as w, 25.0 as nn from two_),
part2_ as (select {O.lchoose('24', '4')} + {O.lf('25')} - 5 * {O.lf('5')} as bits)"""
    return O.compose(("f_tract", "u_tract"), f"select round(partition_bits + placement_bits + weight_bits + bits + (select {cell('two_')} from two_) + (select {cell('one_')} from one_), 4) as dl from d_ cross join part2_", more)


for _rep in ("mg", "w"):
    register(f"dl_nested_{_rep}_given", lambda s, d, r=_rep: rounded(dl.nested_total(W.tracts(s, d), _given_hierarchy(s), r).select("dl")), _nested_sql(_rep))


def _variant_sql(rep: str, dc: bool, ranked: bool) -> str:
    """The given hierarchy under the nested variants: degree-corrected placement, and the last matrix along the order of the regions."""
    k = "w" if rep == "mg" else "e"
    cell = f"sum({O.lmulti('nn', 'w')})" if rep == "mg" else f"sum({O.lmulti('nn', 'e')} + {O.lmulti('nn', 'w')})"
    half = "10.0"
    spread = lambda x: f"({O.lmulti('3', f'{x}u + {x}d + {x}f')} + {O.lmulti(half, f'{x}u')} + {O.lmulti(half, f'{x}d')} + {O.lmulti('5', f'{x}f')})"
    sums = ", ".join(f"sum(case when r {op} s then {x} else 0 end)::bigint as {x}{c}" for x in "ew" for c, op in (("u", "<"), ("d", ">"), ("f", "=")))
    last = f"(select {spread('w') if rep == 'mg' else spread('e') + ' + ' + spread('w')} from ways_)" if ranked else f"(select {cell} from one_)"
    one = "w" if rep == "mg" else "1"
    place = f"""((select sum({O.lf('k')}) from o_) + (select sum({O.lf('x_.k')} + {O.lmulti('g_.n', 'x_.k')} - own) from x_ join g_ on g_.label = x_.label) + (select sum({O.lf('y_.k')} + {O.lmulti('g_.n', 'y_.k')} - own) from y_ join g_ on g_.label = y_.label) - (select sum({O.lf(k)}) from c_))""" if dc else "placement_bits"
    more = "part_ as (select unit_id, parent_id as label from u_tract),\n" + O.length("f_tract", "part_", rep) + f""",
up_ as (select distinct parent_id, grand_id from u_tract),
two_ as (select p.grand_id as r, q.grand_id as s, sum(e)::bigint as e, sum(w)::bigint as w, 25.0 as nn from c_ join up_ p on p.parent_id = c_.r join up_ q on q.parent_id = c_.s group by 1, 2),
one_ as (select sum(e)::bigint as e, sum(w)::bigint as w, 25.0 as nn from two_), ways_ as (select {sums} from two_),
o_ as (select f.*, p.label as r, q.label as s, ({one})::bigint as k from f_tract f join part_ p on p.unit_id = f.src join part_ q on q.unit_id = f.dst),
x_ as (select label, sum(k)::bigint as k, sum({O.lf('k')}) as own from (select r as label, src, sum(k)::bigint as k from o_ group by 1, 2) z group by label),
y_ as (select label, sum(k)::bigint as k, sum({O.lf('k')}) as own from (select s as label, dst, sum(k)::bigint as k from o_ group by 1, 2) z group by label)"""
    return O.compose(("f_tract", "u_tract"), f"select round(partition_bits + {place} + weight_bits + {O.lchoose('24', '4')} + {O.lf('25')} - 5 * {O.lf('5')} + (select {cell} from two_) + {last}, 4) as dl from d_", more)


for _rep in ("mg", "w"):
    for _dcs, _ranks, _vname in ((True, False, "ndc"), (False, True, "rn"), (True, True, "rndc")):
        register(f"dl_{_vname}_{_rep}_given", lambda s, d, r=_rep, x=_dcs, y=_ranks: rounded(dl.nested_total(W.tracts(s, d), _given_hierarchy(s), r, x, y).select("dl")), _variant_sql(_rep, _dcs, _ranks))
    _both = _dc_sql(_rep).replace("select b, round(partition_bits + matrix_bits + weight_bits + place, 4) as dl from d_ cross join m_", "")
    _way = _ranked_sql(_rep)
    _z = _way[_way.index(",\nz_ as") : _way.rindex("\nselect b,")]
    _cost = _way[_way.rindex("weight_bits + ") + len("weight_bits + ") : _way.rindex(", 4) as dl")]
    register(f"dl_rdc_{_rep}_region", lambda s, d, r=_rep: rounded(dl.total(W.planted(s, d), _admin("nation", "parent_id")(s), r, degree_corrected=True, ranked=True).select("b", "dl")), _both.rstrip() + _z + f"\nselect b, round(partition_bits + weight_bits + place + {_cost}, 4) as dl from d_ cross join m_ cross join z_")
register("null_bits", lambda s, d: rounded(nulls.null_scores(W.planted(s, d), U.nations(s, "planted")).select("n", "w", "dl_null")), O.compose(("f_planted",), f"select 25::bigint as n, sum(w)::bigint as w, round({O.lmulti('625', 'sum(w)')}, 4) as dl_null from f_planted"))
register("eta_admin", lambda s, d: rounded(scores.compression_ratio(dl.total(W.planted(s, d), _admin("nation", "parent_id")(s), "w"), nulls.null_scores(W.planted(s, d), U.nations(s, "planted"))).select("b", "eta"), 6), O.compose(("f_planted", "u_nation"), f"select b, round(dl / {O.lmulti('625', 'w')}, 6) as eta from d_", _REGION + O.length("f_planted", "part_", "w")))


def _odds(s: SparkSession, d: str) -> DataFrame:
    flows, units = W.planted(s, d), U.nations(s, "planted")
    both = dl.total(flows, baselines.admin(units).unionByName(baselines.single(units)), "w")
    return rounded(dl.log2_odds(both, "admin", "single").select("log2_odds"))


register("log2_odds", _odds, O.compose(("f_planted", "u_nation"), f"select round(({O.lf('25')} - {O.lf('25')} + {O.matrix('1', 'e', 'w', 'w')} + {O.cost('625', 'e', 'w', 'w')}) - dl, 4) as log2_odds from d_", _REGION + O.length("f_planted", "part_", "w")))
register("modularity_region", lambda s, d: rounded(dl.modularity(W.planted(s, d), _admin("nation", "parent_id")(s)).select("modularity"), 6), O.compose(("f_planted", "u_nation"), "select round(sum(own / a - o * i / (a * a)), 6) as modularity from (select label, sum(case when r = label then w else 0 end)::double as o, sum(case when s = label then w else 0 end)::double as i, sum(case when r = label and s = label then w else 0 end)::double as own, (select sum(w) from c_)::double as a from c_ cross join g_ group by label) z", _REGION + O.length("f_planted", "part_", "w")))
register("blocks_region", lambda s, d: dl.blocks(W.planted(s, d), _admin("nation", "parent_id")(s)).drop("network_id", "model"), O.compose(("f_planted", "u_nation"), "select r, s, e, w, 5::bigint as n_r, 5::bigint as n_s from c_", _REGION + O.length("f_planted", "part_", "w")))


def _gain_sql(kind: str, label: str, rep: str) -> str:
    """Every candidate's gain from whole lengths: after, minus before, both without the terms of the groups' number."""
    flow, units, border = SQL_FLOWS[kind], f"u_{kind}", f"a_{kind}"
    more = f"""part_ as (select unit_id, {label} as label from {units}),
cand_ as (select distinct least(p.label, q.label)::int as r, greatest(p.label, q.label)::int as s from {border} b join part_ p on p.unit_id = b.a join part_ q on q.unit_id = b.b where p.label <> q.label),
all_ as (select c.r, c.s, v.v, u.unit_id, case when v.v = 1 and u.label = c.s then c.r else u.label end as label from cand_ c cross join (select unnest([0, 1]) as v) v cross join part_ u),
size_ as (select r, s, v, label, count(*)::bigint as n from all_ group by 1, 2, 3, 4),
cell_ as (select p.r, p.s, p.v, p.label as i, q.label as j, count(*)::bigint as e, sum(f.w)::bigint as w from {flow} f join all_ p on p.unit_id = f.src join all_ q on q.unit_id = f.dst and q.r = p.r and q.s = p.s and q.v = p.v group by 1, 2, 3, 4, 5),
bits_ as (select k.r, k.s, k.v, sum({O.cost('a.n::double * b.n', 'k.e', 'k.w', rep)}) as bits from cell_ k join size_ a on a.r = k.r and a.s = k.s and a.v = k.v and a.label = k.i join size_ b on b.r = k.r and b.s = k.s and b.v = k.v and b.label = k.j group by 1, 2, 3),
own_ as (select r, s, v, -sum({O.lf('n')}) as own from size_ group by 1, 2, 3)"""
    return O.compose((flow, units, border), "select r, s, round(sum(case when v = 1 then bits + own else -bits - own end), 4) as delta from bits_ join own_ using (r, s, v) group by r, s", more)


for _rep in ("mg", "w"):
    register(f"merge_gain_first_{_rep}", lambda s, d, r=_rep: rounded(dl.merge_gains(W.planted(s, d), baselines.singletons(U.nations(s, "planted")), adj.from_cells(U.nations(s, "planted")), r).select("r", "s", "delta")), _gain_sql("nation", "unit_id", _rep))
    register(f"merge_gain_tract_{_rep}", lambda s, d, r=_rep: rounded(dl.merge_gains(W.tracts(s, d), _admin("tract", "parent_id")(s), adj.from_cells(U.tracts(s)), r).select("r", "s", "delta")), _gain_sql("tract", "min(unit_id) over (partition by parent_id)", _rep))

# ---------------------------------------------------------------- the greedy method


def _greedy(kind: str, rep: str, stop: str = "full", b: int | None = None, objective: str = "bm") -> Callable:
    def make(s: SparkSession, d: str) -> DataFrame:
        flows, units, borders = _net(s, d, kind)
        path = cut(greedy.run(flows, units, borders, rep, objective, stop, b))
        part = greedy.cut_path(path, units, "ga", b)
        chosen = greedy.best_step(path) if b is None else path.filter(F.col("b") == b)
        return rounded(part.join(chosen.select("network_id", "b", "dl"), "network_id").select("unit_id", "label", "b", "dl"))

    return make


def _greedy_sql(flow: str, border: str, n: int, rep: str, body: str, last: int = 1, nets: str = "select 0 as net", more: str = "", needs: tuple[str, ...] = ()) -> str:
    parts = (more + ",\n" if more else "") + f"fl_ as (select 0 as net, src, dst, w from {flow}),\n" * (not more) + O.greedy("fl_", border, n, rep, last, nets)
    return O.compose(needs or (flow, border), body, parts, recursive=True)


_BEST = "select u.u::int as unit_id, g.low as label, d.b::int as b, round(d.dl, 4) as dl from (select net, arg_min(step, (round(dl, 8), b)) as step from gd group by net) m join gd d on d.net = m.net and d.step = m.step join gu u on u.net = m.net and u.step = m.step join gs g on g.net = u.net and g.step = u.step and g.g = u.g"
for _rep in ("w", "mg"):
    register(f"ga_nation_{_rep}", _greedy("nation", _rep), _greedy_sql("f_planted", "a_nation", 25, _rep, _BEST))
    register(f"ga_trajectory_{_rep}", lambda s, d, r=_rep: rounded(greedy.run(*_net(s, d, "nation"), r).select("step", "b", "dl")), _greedy_sql("f_planted", "a_nation", 25, _rep, "select step::int as step, b::int as b, round(dl, 4) as dl from gd"))
register("ga_fixed_b", _greedy("nation", "w", "fixed_b", 8), _greedy_sql("f_planted", "a_nation", 25, "w", "select u.u::int as unit_id, g.low as label, d.b::int as b, round(d.dl, 4) as dl from gd d join gu u on u.net = d.net and u.step = d.step join gs g on g.net = u.net and g.step = u.step and g.g = u.g where d.b = 8", last=8))
register("ga_first_increase", lambda s, d: rounded(greedy.run(W.trade(s, d).withColumn("network_id", F.lit("trade")), U.nations(s, "trade"), adj.from_cells(U.nations(s, "trade")), "mg", stop="first_increase").agg(F.min("b").alias("b"), F.min_by("dl", "b").alias("dl"))), _greedy_sql("f_trade", "a_nation", 25, "mg", "select min(b)::int as b, round(arg_min(dl, b), 4) as dl from gd where step <= coalesce((select min(d.step) - 1 from gd d join gd p on p.step = d.step - 1 where d.dl >= p.dl), 999)"))
register("ga_local_w", lambda s, d: rounded(greedy.best_step(greedy.run(W.local(s, d), U.nations(s, "local"), adj.from_cells(U.nations(s, "local")), "w")).select("b", "dl")), _greedy_sql("f_local", "a_nation", 25, "w", "select arg_min(b, (round(dl, 8), b))::int as b, round(min(dl), 4) as dl from gd"))
register("ga_state_tracts_w", lambda s, d: rounded(_state_best(s, d)), _greedy_sql("f_tract", "a_nation", 25, "w", "select 'state' || net as network_id, arg_min(b, (round(dl, 8), b))::int as b, round(min(dl), 4) as dl from gd group by net", nets="select unnest(range(5)) as net", more="fl_ as (select src % 25 // 5 as net, (src // 25) * 5 + src % 5 as src, (dst // 25) * 5 + dst % 5 as dst, w from f_tract where src % 25 // 5 = dst % 25 // 5)"))


def _state_best(s: SparkSession, d: str) -> DataFrame:
    from flowregions.experiments import states

    return greedy.best_step(greedy.run(*states(s, d), "w")).select("network_id", "b", "dl")


for _kind, _rep in (("tract", "w"), ("tract", "mg"), ("clock", "w"), ("clock", "mg")):
    register(f"ga_{_kind}_{_rep}", _greedy(_kind, _rep), _greedy_sql(SQL_FLOWS[_kind], f"a_{_kind}", 125 if _kind == "tract" else 120, _rep, _BEST))
register("ga_clockgrid_w", _greedy("clockgrid", "w"))
for _rep in ("mg", "w"):
    _k = "w" if _rep == "mg" else "e"
    _dc = O.greedy("fl_", "a_nation", 25, _rep, place=lambda nn, e, w, k=_k, r=_rep: f"(-{O.lf(w if k == 'w' else e)}" + ("" if r == "mg" else f" + {O.lcomp(w, e)}") + ")", group=lambda n, o, i, own: f"(-{O.lf(n)} + {O.lf(o)} + {O.lf(i)} + {O.lmulti(n, o)} + {O.lmulti(n, i)})", ends=_k)  # noqa: ARG005
    _one = "sum(w)::bigint" if _rep == "mg" else "count(*)::bigint"
    _same = ("(select sum(" + O.lf("w") + ") from fl_)" if _rep == "mg" else "0.0") + "".join(f" - (select sum({O.lf('k')}) from (select {_one} as k from fl_ group by {c}) z)" for c in ("src", "dst"))
    register(f"ga_dc_{_rep}", _greedy("nation", _rep, objective="bm_dc"), O.compose(("f_planted", "a_nation"), _BEST.replace("round(d.dl, 4)", f"round(d.dl + {_same}, 4)"), "fl_ as (select 0 as net, src, dst, w from f_planted),\n" + _dc, recursive=True))
_W = "(select sum(w)::double from fl_)"
register("ga_modularity", _greedy("nation", "w", objective="modularity"), O.compose(("f_planted", "a_nation"), _BEST, "fl_ as (select 0 as net, src, dst, w from f_planted),\n" + O.greedy("fl_", "a_nation", 25, "w", place=lambda nn, e, w: "0.0", const=lambda b, e, w: "0.0", group=lambda n, o, i, own: f"(-({own} / {_W} - ({o}) * (({i}) / {_W}) / {_W}))", ends="w"), recursive=True))  # noqa: ARG005
_POISSON = O.greedy("fl_", "a_nation", 25, "w", place=lambda nn, e, w: f"(-({w}) * log2(({w}) / ({nn})))", const=lambda b, e, w: f"(({b}) * ({b}) * 0.5 * log2({w}))", group=lambda n, o, i, own: "0.0")  # noqa: ARG005
register("ga_user_objective", _greedy("nation", "w", objective=lambda net: kernel.poisson_objective()), O.compose(("f_planted", "a_nation"), _BEST, "fl_ as (select 0 as net, src, dst, w from f_planted),\n" + _POISSON, recursive=True))  # noqa: ARG005
register("ga_objective_modularity", _greedy("nation", "w", objective=lambda net: kernel.modularity_objective(float(net.w.sum()))), ORACLES["ga_modularity"])


def _poisson(n: Column, b: Column, e: Column, w: Column) -> Column:  # noqa: ARG001
    return b * b * 0.5 * F.log2(w)


register("objective_region", lambda s, d: rounded(dl.objective_total(W.planted(s, d), _admin("nation", "parent_id")(s), _poisson, pair=lambda nn, e, w: -w * F.log2(w / nn)).select("b", "total")), O.compose(("f_planted", "u_nation"), "select b, round(b * b * 0.5 * log2(w) + (select sum(-w * log2(w / nn)) from c_), 4) as total from d_", _REGION + O.length("f_planted", "part_", "w")))  # noqa: ARG005
register("objective_modularity", lambda s, d: rounded(dl.objective_total(W.planted(s, d), _admin("nation", "parent_id")(s), lambda n, b, e, w: F.lit(0.0), group=lambda n, o, i, own, w: -(own / w - o * (i / w) / w)).select("b", (-F.col("total")).alias("modularity")), 6), ORACLES["modularity_region"].replace("select round(", "select 5::bigint as b, round(", 1))  # noqa: ARG005
register("ga_map_equation", _greedy("nation", "w", objective="map_equation"))
register("ga_basket", lambda s, d: rounded(greedy.best_step(greedy.run(W.basket(s, d), U.brand_sizes(s), adj.from_cells(U.brand_sizes(s)), "w")).select("b", "dl")))
_ROLES = "select i as a, i + 1 as b from range(2) t(i)"
register("ga_frames", lambda s, d: rounded(greedy.run_frames(W.turns(s, d), U.roles(s), adj.from_cells(U.roles(s)), "w").select("step", "b", "dl")), O.compose(("f_turns",), "select step::int as step, b::int as b, round(dl, 4) as dl from gd", f"rol_ as ({_ROLES}),\nfl_ as (select 0 as net, src, dst, w from f_turns),\n" + O.greedy("fl_", "rol_", 3, "w"), recursive=True))


def _rounds(s: SparkSession, d: str) -> DataFrame:
    """The turns of conversations merged in rounds by joins: a round is dozens of small jobs, so the network is the smallest one. Two merges at most, so four rounds are enough."""
    return rounded(greedy.run_rounds(W.turns(s, d), U.roles(s), adj.from_cells(U.roles(s)), "w", most_rounds=4)[1].select("round", "b", "dl"))


register("ga_rounds", _rounds)
register("ga_no_borders", lambda s, d: rounded(greedy.best_step(greedy.run(W.planted(s, d), U.nations(s, "planted"), adj.from_pairs(W.planted(s, d).select("network_id", F.col("src").alias("a"), F.col("dst").alias("b"))), "w")).select("b", "dl")), _greedy_sql("f_planted", "any_", 25, "w", "select arg_min(b, (round(dl, 8), b))::int as b, round(min(dl), 4) as dl from gd", more="any_ as (select distinct least(src, dst) as a, greatest(src, dst) as b from f_planted where src <> dst),\nfl_ as (select 0 as net, src, dst, w from f_planted)", needs=("f_planted",)))

# ---------------------------------------------------------------- contiguity and similarity

RULES = {"parity": "(x + y) % 2", "rows": "y", "mixed": "(x * 7 + y * 3) % 4 >= 2"}
RULE_SQL = {"parity": "((x + y) % 2)::int", "rows": "y::int", "mixed": "((x * 7 + y * 3) % 4 >= 2)::int"}


def _rule(s: SparkSession, kind: str, rule: str, model: str = "rule") -> DataFrame:
    return baselines.by_rule(UNITS[kind](s, NAMES[kind]), RULES[rule], model)


def _rule_part(kind: str, rule: str, name: str = "part_") -> str:
    return f"{name} as (select unit_id, min(unit_id) over (partition by {RULE_SQL[rule]}) as label from u_{kind})"


def _reach(kind: str, rule: str) -> str:
    return _rule_part(kind, rule) + f""",
edge_ as (select b.a, b.b from a_{kind} b join part_ p on p.unit_id = b.a join part_ q on q.unit_id = b.b where p.label = q.label union all select b.b, b.a from a_{kind} b join part_ p on p.unit_id = b.a join part_ q on q.unit_id = b.b where p.label = q.label),
reach_ as (select unit_id as u, unit_id as v from part_ union select r.u, e.b from reach_ r join edge_ e on e.a = r.v),
comp_ as (select u as unit_id, min(v)::int as comp from reach_ group by u),
size_ as (select p.label, c.comp, count(*)::bigint as n_rc from part_ p join comp_ c on c.unit_id = p.unit_id group by 1, 2),
eff_ as (select label, sum(n_rc)::bigint as n, count(*)::bigint as c, exp(ln(sum(n_rc)) - sum(n_rc * ln(n_rc)) / sum(n_rc)) as c_eff from size_ group by label)"""


for _kind, _rule_name in (("nation", "parity"), ("tract", "mixed"), ("tract", "rows")):
    _key = f"{_kind}_{_rule_name}"
    register(f"components_{_key}", lambda s, d, k=_kind, r=_rule_name: components.sizes(components.within(_rule(s, k, r), adj.from_cells(UNITS[k](s, NAMES[k])))).select("label", "comp", "n_rc"), O.compose((f"u_{_kind}", f"a_{_kind}"), "select label, comp, n_rc from size_", _reach(_kind, _rule_name), recursive=True))
    register(f"eff_components_{_key}", lambda s, d, k=_kind, r=_rule_name: rounded(contiguity.effective_components(components.sizes(components.within(_rule(s, k, r), adj.from_cells(UNITS[k](s, NAMES[k]))))).select("label", "n", "c", "c_eff"), 6), O.compose((f"u_{_kind}", f"a_{_kind}"), "select label, n, c, round(c_eff, 6) as c_eff from eff_", _reach(_kind, _rule_name), recursive=True))
    register(f"cvm_{_key}", lambda s, d, k=_kind, r=_rule_name: rounded(contiguity.measures(_rule(s, k, r), adj.from_cells(UNITS[k](s, NAMES[k]))).drop("network_id", "model"), 6), O.compose((f"u_{_kind}", f"a_{_kind}"), "select sum(n)::bigint as n, count(*)::bigint as b, sum(case when c > 1 then 1 else 0 end)::bigint as broken, round(avg(c), 6) as mean_components, round(sum(n)::double / sum(c), 6) as mean_component_size, round(avg(n::double / c), 6) as mean_group_component_size, round(avg(c_eff) - 1, 6) as cvm, round(sum(case when c > 1 then 1 else 0 end)::double / count(*), 6) as broken_fraction from eff_", _reach(_kind, _rule_name), recursive=True))
register("split_components", lambda s, d: rounded(dl.total(W.tracts(s, d), cut(baselines.split_components(_rule(s, "tract", "mixed"), adj.from_cells(U.tracts(s)))), "w").select("b", "dl")), O.compose(("f_tract", "u_tract", "a_tract"), "select b, round(dl, 4) as dl from d_", _reach("tract", "mixed").replace("part_", "broken_") + ",\npart_ as (select unit_id, comp as label from comp_),\n" + O.length("f_tract", "part_", "w").replace("g_ as", "g_ as"), recursive=True))

_TWO = "p_ as (select unit_id, min(unit_id) over (partition by grand_id) as label from u_tract), q_ as (select unit_id, min(unit_id) over (partition by ((x * 7 + y * 3) % 4 >= 2)::int) as label from u_tract)"
_INFO = _TWO + ",\nn_ as (select p.label as r, q.label as s, sum({weight})::double as n from p_ p join q_ q on q.unit_id = p.unit_id join u_tract u on u.unit_id = p.unit_id group by 1, 2),\na_ as (select r, sum(n) as m from n_ group by r), b_ as (select s, sum(n) as m from n_ group by s), all_ as (select sum(n) as t from n_),\ni_ as (select -(select sum(m / t * log2(m / t)) from a_ cross join all_) as hp, -(select sum(m / t * log2(m / t)) from b_ cross join all_) as hq, -(select sum(n / t * log2(n / t)) from n_ cross join all_) as h)"


def _pair(s: SparkSession) -> tuple[DataFrame, DataFrame]:
    return baselines.admin(U.tracts(s, "tract"), "grand_id", "region"), _rule(s, "tract", "mixed")


def _held_pair(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """The same partitions of the tracts where customers with orders and suppliers live."""
    units = _held(s, d, "tract")
    return baselines.admin(units, "grand_id", "region"), baselines.by_rule(units, RULES["mixed"], "rule")


def _trivial(s: SparkSession, d: str) -> DataFrame:
    units = _held(s, d, "nation")
    one = baselines.single(units)
    return similarity.ami(one, one).unionByName(similarity.ami(one, baselines.admin(units))).select("q_model", "ami")


register("contingency", lambda s, d: similarity.contingency(*_pair(s)).select("r", "s", "n"), O.compose(("u_tract",), "select r, s, n::bigint as n from n_", _INFO.format(weight="1")))
register("nmi", lambda s, d: rounded(similarity.nmi(*_pair(s)).select("nmi"), 6), O.compose(("u_tract",), "select round(2 * (hp + hq - h) / (hp + hq), 6) as nmi from i_", _INFO.format(weight="1")))
register("snmi", lambda s, d: rounded(similarity.spatial_nmi(*_pair(s), U.tracts(s)).select("snmi"), 6), O.compose(("u_tract",), "select round(2 * (hp + hq - h) / (hp + hq), 6) as snmi from i_", _INFO.format(weight="u.area")))
_EMI = ",\nx_ as (select a.m as a, b.m as b, t, unnest(range(greatest(1, (a.m + b.m - t)::bigint), least(a.m, b.m)::bigint + 1)) as k from a_ a cross join b_ b cross join all_),\ne_ as (select sum(k / t * log2(t * k / (a * b)) * exp(ln(2) * (" + f"{O.lchoose('b', 'k')} + {O.lchoose('t - b', 'a - k')} - {O.lchoose('t', 'a')}" + "))) as emi from x_)"
for _norm, _top in (("mean", "(hp + hq) / 2"), ("max", "greatest(hp, hq)")):
    register(f"ami_{_norm}", lambda s, d, k=_norm: rounded(similarity.ami(*_held_pair(s, d), normaliser=k).select("ami"), 6), O.compose(("s_tract",), f"select round((hp + hq - h - emi) / ({_top} - emi), 6) as ami from i_ cross join e_", _INFO.format(weight="1").replace("u_tract", "s_tract") + _EMI))
register("ami_trivial", _trivial, O.compose(("s_nation",), "select 'single' as q_model, 1.0::double as ami from s_nation having count(*) > 0 union all select 'admin', case when count(distinct parent_id) > 1 then 0.0 else 1.0 end from s_nation having count(*) > 0"))

# ---------------------------------------------------------------- nulls

DRAWS = 100
_SEEDS = """raw_ as (select i // {b} as draw, i % {b} as seed, ((i // {b}) * 7919 + (i % {b}) * 104729 + 15485863) % 2147483648 as z from range({b} * {draws}) t(i)),
one_ as (select draw, seed, (z * 1103515245 + 12345) % 2147483648 as z from raw_), two_ as (select draw, seed, (z * 1103515245 + 12345) % 2147483648 as z from one_), x1_ as (select draw, seed, (z * 1103515245 + 12345) % 2147483648 as z from two_), x2_ as (select draw, seed, (z * 1103515245 + 12345) % 2147483648 as z from x1_), y_ as (select draw, seed, (z * 1103515245 + 12345) % 2147483648 as z from x2_),
seed_ as (select x.draw::int as draw, x.seed::int as seed, x.z::double / 2147483648 * {nx} - 0.5 as sx, y.z::double / 2147483648 * {ny} - 0.5 as sy from x1_ x join y_ y on y.draw = x.draw and y.seed = x.seed),
vor_ as (select draw, unit_id, arg_min(seed, (round((x - sx) * (x - sx) + (y - sy) * (y - sy), 9), seed)) as label from {units} cross join seed_ group by 1, 2)"""
register("voronoi_labels", lambda s, d: nulls.voronoi(U.tracts(s), nulls.seeds(s, 5, 10, 25, 5)).select("model", "unit_id", "label"), O.compose(("u_tract",), "select 'voronoi_' || draw as model, unit_id, label from vor_", _SEEDS.format(b=5, draws=10, nx=25, ny=5, units="u_tract")))
register("voronoi_raster", lambda s, d: rounded(nulls.voronoi_raster(U.nations(s), nulls.seeds(s, 5, 5, 5, 5)).groupBy("draw", "seed").agg(F.sum("share").alias("area")), 6), O.compose(("u_nation",), "select draw, seed, round(count(*) / 16.0, 6)::double as area from (select draw, unit_id, c, arg_min(seed, ((px - sx) * (px - sx) + (py - sy) * (py - sy), seed)) as seed from (select unit_id, c, x - 0.5 + (c % 4 + 0.5) / 4 as px, y - 0.5 + (c // 4 + 0.5) / 4 as py from u_nation cross join range(16) t(c)) z cross join seed_ group by 1, 2, 3) y group by 1, 2", _SEEDS.format(b=5, draws=5, nx=5, ny=5, units="u_nation")))


def _p95(s: SparkSession, d: str) -> DataFrame:
    units = U.tracts(s)
    random = nulls.voronoi(units, nulls.seeds(s, 5, DRAWS, 25, 5))
    return rounded(nulls.percentile_test(_rule(s, "tract", "rows"), baselines.admin(units, "grand_id"), random, units).select("snmi", "p95", "above"), 6)


register("voronoi_snmi_p95", _p95, O.compose(("u_tract",), "select round(any_value(s0.v), 6) as snmi, round(quantile_cont(nmi_.v, 0.95), 6) as p95, any_value(s0.v) > quantile_cont(nmi_.v, 0.95) as above from nmi_ cross join s0", _SEEDS.format(b=5, draws=DRAWS, nx=25, ny=5, units="u_tract") + """,
rows_p as (select unit_id, y::int as label from u_tract),
n0 as (select p.label as r, u.grand_id as s, sum(u.area)::double as n from rows_p p join u_tract u on u.unit_id = p.unit_id group by 1, 2),
s0 as (select 2 * (hp + hq - h) / (hp + hq) as v from (select -(select sum(m / t * log2(m / t)) from (select sum(n) as m from n0 group by r) z) as hp, -(select sum(m / t * log2(m / t)) from (select sum(n) as m from n0 group by s) z) as hq, -(select sum(n / t * log2(n / t)) from n0) as h from (select sum(n) as t from n0) w) x),
n_ as (select v.draw, p.label as r, v.label as s, sum(u.area)::double as n from rows_p p join vor_ v on v.unit_id = p.unit_id join u_tract u on u.unit_id = p.unit_id group by 1, 2, 3),
t_ as (select draw, sum(n) as t from n_ group by 1), ha_ as (select draw, -sum(m / t * log2(m / t)) as h from (select n_.draw, r, sum(n) as m, any_value(t) as t from n_ join t_ on t_.draw = n_.draw group by 1, 2) z group by 1), hb_ as (select draw, -sum(m / t * log2(m / t)) as h from (select n_.draw, s, sum(n) as m, any_value(t) as t from n_ join t_ on t_.draw = n_.draw group by 1, 2) z group by 1), hj_ as (select n_.draw, -sum(n / t * log2(n / t)) as h from n_ join t_ on t_.draw = n_.draw group by 1),
nmi_ as (select ha_.draw, 2 * (ha_.h + hb_.h - hj_.h) / (ha_.h + hb_.h) as v from ha_ join hb_ on hb_.draw = ha_.draw join hj_ on hj_.draw = ha_.draw)"""))

# ---------------------------------------------------------------- relational surface

register("rollup_flows", lambda s, d: _rollup(s, d), O.compose(("f_tract", "u_tract"), "select u.grand_id, u.parent_id, sum(f.w)::bigint as w from f_tract f join u_tract u on u.unit_id = f.src group by rollup(u.grand_id, u.parent_id)"))


def _rollup(s: SparkSession, d: str) -> DataFrame:
    units = F.broadcast(U.tracts(s).select(F.col("unit_id").alias("src"), "parent_id", "grand_id"))
    return W.tracts(s, d).join(units, "src").rollup("grand_id", "parent_id").agg(F.sum("w").alias("w"))


register("cube_rows", lambda s, d: W.trade_rows(s, d).cube("c_mktsegment", "planted").agg(F.count("*").alias("n")), O.compose(("rows_",), "select c_mktsegment, planted, count(*)::bigint as n from rows_ group by cube(c_mktsegment, planted)"))
register("grouping_sets", lambda s, d: _grouping_sets(s, d), O.compose(("rows_",), "select o_orderpriority, c_mktsegment, count(*)::bigint as n from rows_ group by grouping sets ((o_orderpriority), (c_mktsegment))"))


def _grouping_sets(s: SparkSession, d: str) -> DataFrame:
    W.trade_rows(s, d).createOrReplaceTempView("trade_rows_view")
    return s.sql("select o_orderpriority, c_mktsegment, count(*) as n from trade_rows_view group by grouping sets ((o_orderpriority), (c_mktsegment))")


register("topk_flows", lambda s, d: W.trade(s, d).withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst"))).filter("rank <= 3").select("src", "dst", "w", "rank"), O.compose(("f_trade",), "select src, dst, w, rank::int as rank from (select *, row_number() over (partition by src order by w desc, dst) as rank from f_trade) z where rank <= 3"))
register("window_ranks", lambda s, d: rounded(W.planted(s, d).select("src", "dst", F.rank().over(Window.partitionBy("src").orderBy("w")).alias("rk"), F.dense_rank().over(Window.partitionBy("src").orderBy("w")).alias("dr"), F.ntile(4).over(Window.partitionBy("src").orderBy("w", "dst")).alias("nt"), F.percent_rank().over(Window.partitionBy("src").orderBy("w")).alias("pr"), F.cume_dist().over(Window.partitionBy("src").orderBy("w")).alias("cd")), 6), O.compose(("f_planted",), "select src, dst, (rank() over (partition by src order by w))::int as rk, (dense_rank() over (partition by src order by w))::int as dr, (ntile(4) over (partition by src order by w, dst))::int as nt, round(percent_rank() over (partition by src order by w), 6) as pr, round(cume_dist() over (partition by src order by w), 6) as cd from f_planted"))
register("window_next", lambda s, d: tables.read(s, d, "events").select("event_id", F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_id"), F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("last_id")), "select event_id, lead(event_id) over w as next_id, lag(event_id) over w as last_id from events window w as (partition by user_id order by ts, event_id)")
register("running_best", lambda s, d: rounded(greedy.run(*_net(s, d, "nation"), "mg").select("step", F.min("dl").over(Window.partitionBy("network_id").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)).alias("best"), (F.col("dl") - F.lag("dl").over(Window.partitionBy("network_id").orderBy("step"))).alias("change"))), _greedy_sql("f_planted", "a_nation", 25, "mg", "select step::int as step, round(min(dl) over (order by step rows unbounded preceding), 4) as best, round(dl - lag(dl) over (order by step), 4) as change from gd"))
register("setops_border_flow", lambda s, d: _setops(s, d), O.compose(("f_local", "a_nation"), "select 'both' as kind, count(*)::bigint as n from (select a::int, b::int from a_nation intersect select * from m) x union all select 'border only', count(*) from (select a::int, b::int from a_nation except select * from m) x union all select 'flow only', count(*) from (select * from m except select a::int, b::int from a_nation) x", "m as (select distinct least(src, dst)::int as a, greatest(src, dst)::int as b from f_local where src <> dst)"))


def _setops(s: SparkSession, d: str) -> DataFrame:
    borders = adj.from_cells(U.nations(s)).select("a", "b")
    moved = W.local(s, d).filter("src != dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    count = lambda df, kind: df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
    return count(borders.intersect(moved), "both").unionByName(count(borders.exceptAll(moved), "border only")).unionByName(count(moved.exceptAll(borders), "flow only"))


register("json_props", lambda s, d: tables.read(s, d, "events").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("n")), "select json_extract_string(props, '$.k')::int as k, count(*)::bigint as n from events group by 1")


register("join_range", lambda s, d: _near_pairs(s), O.compose(("u_tract",), "select p.unit_id as a, q.unit_id as b from u_tract p join u_tract q on p.unit_id < q.unit_id and (p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y) <= 5"))


def _near_pairs(s: SparkSession, reach: float = 5.0) -> DataFrame:
    """Units at most sqrt(5) cells apart: bands of 3 cells as an equi-key, the nine around each unit, then the exact test."""
    u = U.tracts(s).select("unit_id", "x", "y")
    band = lambda c: F.floor(F.col(c) / 3)
    left = u.select(F.col("unit_id").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay"), F.explode(F.sequence(F.lit(0), F.lit(8))).alias("k"), band("x").alias("bx"), band("y").alias("by_"))
    left = left.select("a", "ax", "ay", (F.col("bx") + F.col("k") % 3 - 1).alias("bx"), (F.col("by_") + F.floor(F.col("k") / 3) - 1).alias("by_"))
    right = u.select(F.col("unit_id").alias("b"), F.col("x").alias("qx"), F.col("y").alias("qy"), band("x").alias("bx"), band("y").alias("by_"))
    far = F.pow(F.col("ax") - F.col("qx"), 2) + F.pow(F.col("ay") - F.col("qy"), 2)
    return left.join(right, ["bx", "by_"]).filter((F.col("a") < F.col("b")) & (far <= reach)).select("a", "b")


register("pivot_days", lambda s, d: tables.read(s, d, "events").groupBy(F.to_date("ts").alias("day")).pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1))).na.fill(0), "select ts::date as day, count(*) filter (where event_type = 'click')::bigint as click, count(*) filter (where event_type = 'purchase')::bigint as purchase, count(*) filter (where event_type = 'view')::bigint as view from events group by 1")
register("moments", lambda s, d: rounded(W.planted(s, d).agg(F.avg("w").alias("mean"), F.stddev_samp("w").alias("sd"), F.median("w").alias("median"), F.percentile("w", F.lit(0.95)).alias("p95"), F.corr("src", "w").alias("corr"), F.regr_slope("w", "src").alias("slope")), 6), O.compose(("f_planted",), "select round(avg(w), 6) as mean, round(stddev_samp(w), 6) as sd, round(median(w), 6) as median, round(quantile_cont(w, 0.95), 6) as p95, round(corr(src, w), 6) as corr, round(regr_slope(w, src), 6) as slope from f_planted"))
register("page_hosts", lambda s, d: tables.read(s, d, "pages").select(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host")).groupBy("host").agg(F.count("*").alias("n")), "select regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host, count(*)::bigint as n from pages group by 1")
register("region_members", lambda s, d: baselines.admin(U.nations(s)).groupBy("label").agg(F.array_join(F.array_sort(F.collect_list("unit_id")), ",").alias("members")), O.compose(("u_nation",), "select min(unit_id)::int as label, string_agg(unit_id::varchar, ',' order by unit_id) as members from u_nation group by parent_id"))


# ---------------------------------------------------------------- streams, replayed


def _stream(s: SparkSession, d: str, make: Callable, name: str, mode: str = "complete") -> DataFrame:
    """Runs a stream over the events' file to its end, in a folder of its own below the checkpoint folder."""
    import uuid

    from flowregions.plans.checkpoints import folder
    from flowregions.streaming import flows as st

    schema = tables.read(s, d, "events").schema
    stream = s.readStream.schema(schema).parquet(f"{d}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))
    key = uuid.uuid4().hex
    out, state = f"{folder(s)}/stream-{key}", f"{folder(s)}/state-{key}"
    result = make(st, stream)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    query = result.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    rows = s.read.schema(result.schema).option("recursiveFileLookup", "true").parquet(out)
    return rows


register("stream_day_counts", lambda s, d: _stream(s, d, lambda st, x: st.counts(x), "day_counts").select(F.to_date("start").alias("day"), "event_type", "n"), "select ts::date as day, event_type, count(*)::bigint as n from events group by 1, 2")
register("stream_flows", lambda s, d: _stream(s, d, lambda st, x: st.user_pairs(x).select("src", "dst"), "flows", "append").groupBy("src", "dst").agg(F.count("*").alias("w")), O.compose(("f_clockgrid",), "select src, dst, w from f_clockgrid"))
register("stream_sliding", lambda s, d: _stream(s, d, lambda st, x: st.counts(x, "1 day", "6 hours"), "sliding").groupBy("event_type").agg(F.sum("n").alias("n"), F.count("*").alias("windows")), "select event_type, count(*)::bigint * 4 as n, (select count(distinct (floor(epoch(e.ts) / 21600) - k)::bigint) from events e cross join range(4) t(k) where e.event_type = o.event_type)::bigint as windows from events o group by event_type")
register("stream_sessions", lambda s, d: _stream(s, d, lambda st, x: st.sessions(x), "sessions").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n")), "select user_id, sum(case when last_ is null or ts - last_ >= interval 30 minutes then 1 else 0 end)::bigint as sessions, count(*)::bigint as n from (select user_id, ts, lag(ts) over (partition by user_id order by ts, event_id) as last_ from events) z group by user_id")
register("stream_once", lambda s, d: _stream(s, d, lambda st, x: st.once(x).select("event_id"), "once", "append").agg(F.count("*").alias("n")), "select count(distinct event_id)::bigint as n from events")
register("stream_blocks", lambda s, d: _stream(s, d, lambda st, x: st.user_pairs(x).select("src", "dst"), "blocks", "append").transform(lambda p: __import__("flowregions.streaming.flows", fromlist=["flows"]).block_counts(p, baselines.admin(U.clock_grid(s), "grand_id"))), O.compose(("f_clockgrid", "u_clockgrid"), "select p.low as r, q.low as s, sum(f.w)::bigint as w from f_clockgrid f join (select unit_id, min(unit_id) over (partition by grand_id) as low from u_clockgrid) p on p.unit_id = f.src join (select unit_id, min(unit_id) over (partition by grand_id) as low from u_clockgrid) q on q.unit_id = f.dst group by 1, 2"))

# ---------------------------------------------------------------- further workloads


def _vector_regions(s: SparkSession, d: str) -> DataFrame:
    """Neighbour graph of the vectors: the greedy partition against the labels, which carry no signal."""
    vectors = tables.read(s, d, "embeddings")
    near = cut(adj.knn(vectors, 8))
    flows = near.select(F.lit("vectors").alias("network_id"), "src", "dst", F.lit(1).cast("long").alias("w"))
    units = vectors.select(F.lit("vectors").alias("network_id"), F.col("vec_id").cast("int").alias("unit_id"))
    path = cut(greedy.run(flows, units, adj.from_knn(near), "mg"))
    labels = vectors.select(F.lit("vectors").alias("network_id"), F.lit("label").alias("model"), F.col("vec_id").cast("int").alias("unit_id"), "label")
    found = cut(greedy.cut_path(path, units, "ga"))
    return rounded(greedy.best_step(path).select("network_id", "b", "dl").join(similarity.ami(found, labels).select("network_id", "ami"), "network_id"), 6)


register("vectors_ami", _vector_regions)


def _unit_metadata(s: SparkSession, d: str) -> DataFrame:
    """Labels of documents as metadata of the (source, language) units."""
    docs, labels = tables.read(s, d, "documents").select("doc_id", "lang", "source"), tables.read(s, d, "labels")
    lang = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3)
    cell = (lang * 20 + F.regexp_extract("source", r"(\d+)", 1).cast("int")).alias("unit_id")
    return rounded(labels.join(docs, "doc_id").groupBy(cell).agg(F.count("*").alias("n"), F.avg("quality").alias("quality"), F.sum("toxic").alias("toxic")), 6)


register("unit_metadata", _unit_metadata, "select (case lang when 'de' then 0 when 'en' then 1 when 'es' then 2 else 3 end * 20 + regexp_extract(source, '(\\d+)', 1)::int)::int as unit_id, count(*)::bigint as n, round(avg(quality), 6) as quality, sum(toxic)::bigint as toxic from labels join documents using (doc_id) group by 1")



from flowregions import experiments, relational  # noqa: E402,F401  their queries are registered as they load
