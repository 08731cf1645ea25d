"""The experiments over panels of networks, and the networks of single states at two scales."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowregions import oracle as O  # noqa: N812
from flowregions.operators import adjacency as adj
from flowregions.operators import baselines, contiguity, dl, network, nulls, panel, scores, similarity
from flowregions.plans import greedy, mcmc
from flowregions.plans.checkpoints import cut
from flowregions.plans.store import fingerprint, kept
from flowregions.registry import register, rounded
from flowregions.sources import units as U
from flowregions.sources import workloads as W

REPS = ("mg", "w")
TABLES = ("lineitem", "orders", "customer", "supplier", "events")
#: Chains of the block models on the five regions, where every partition can be tried in SQL.
CHAINS = 4
DRAWS = 100


# ---------------------------------------------------------------- block models against all partitions


def regions(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The planted trade between the five regions, side by side in a row."""
    flows = W.planted(s, d).groupBy(F.lit("region").alias("network_id"), (F.col("src") % 5).alias("src"), (F.col("dst") % 5).alias("dst")).agg(F.sum("w").alias("w"))
    units = U.grid(s, 5, 1, "region")
    return flows, units, adj.from_cells(units)


_REGIONS = "reg_ as (select (src % 5)::int as src, (dst % 5)::int as dst, sum(w)::bigint as w from f_planted group by 1, 2)"


def _best_sql(variant: str) -> str:
    """Both forms of one variant; each is a statement of its own, put together as subqueries."""
    q = variant.partition("_")[2]
    one = lambda rep: "select '" + rep + "' as rep, b, dl from (" + O.compose(("f_planted",), "select b::int as b, round(dl, 4) as dl from best_", _REGIONS + ",\n" + O.best_model("reg_", 5, rep, "dc" in q, "r" in q, "n" in q), recursive=True) + f") {rep}_"
    return "\nunion all\n".join(one(rep) for rep in REPS)


for _v in mcmc.VARIANTS:
    register(f"anneal_{_v}", lambda s, d, v=_v: rounded(mcmc.score_rows(mcmc.best_chain(mcmc.anneal(*regions(s, d), (v,), REPS, CHAINS))).select("rep", "b", "dl")), _best_sql(_v))


def rescored(flows: DataFrame, fits: DataFrame) -> DataFrame:
    """(network_id, model, rep, dl, again): fitted lengths beside the lengths of their labels as one plan, without the kernels."""
    out = None
    for variant in mcmc.VARIANTS:
        switches = variant.partition("_")[2]
        how = {"degree_corrected": "dc" in switches, "ranked": "r" in switches}
        for rep in REPS:
            some = fits.filter((F.col("model") == variant) & (F.col("rep") == rep))
            if "n" in switches:
                again = dl.nested_total(flows, mcmc.hierarchy(some), rep, **how)
            else:
                again = dl.total(flows, some.select("network_id", "model", "unit_id", "label"), rep, **how)
            again = again.select("network_id", "model", F.lit(rep).alias("rep"), F.col("dl").alias("again"))
            out = again if out is None else out.unionByName(again)
    return mcmc.score_rows(fits).join(out, ["network_id", "model", "rep"]).select("network_id", "model", "rep", "dl", "again")


def _rescored(s: SparkSession, d: str) -> DataFrame:
    units = U.nations(s, "planted")
    flows = cut(W.planted(s, d))
    fits = cut(mcmc.anneal(flows, units, adj.from_cells(units)))
    return rescored(flows, fits).select("model", "rep", F.round(F.abs(F.col("dl") - F.col("again")), 4).alias("apart"))


register("anneal_rescored", _rescored, "select m as model, r as rep, 0.0::double as apart from (select unnest(['" + "', '".join(mcmc.VARIANTS) + "']) as m) a cross join (select unnest(['mg', 'w']) as r) b")

# ---------------------------------------------------------------- the panel


def _panel_flows(s: SparkSession, d: str) -> DataFrame:
    flows, networks = panel.trade_panel(s, d)
    return flows.groupBy("network_id").agg(F.count("*").alias("e"), F.sum("w").alias("w")).join(networks, "network_id").select("network_id", "class", "e", "w")


def _panel_flows_sql() -> str:
    return O.compose(("rows_",), """select network_id, split_part(network_id, ':', 1) as class, count(*)::bigint as e, sum(w)::bigint as w from (
select network_id, src, dst, count(*) as w from (
  select 'metro:' || o_orderpriority || '/' || floor((year(o_orderdate) - 1995) / 5.0)::int as network_id, c_nationkey as src, s_nationkey as dst from rows_ where planted
  union all select 'metro:event/' || event_type, t0 // 21600, nxt // 21600 from (select event_type, floor(epoch(ts))::bigint - 1704067200 as t0, lead(floor(epoch(ts))::bigint - 1704067200) over (partition by user_id order by ts, event_id) as nxt from events) v where nxt - t0 <= 172800
  union all select 'combined:' || c_mktsegment, c_nationkey, s_nationkey from rows_ where planted
  union all select 'combined:' || p.a || '-' || p.b, c_nationkey, s_nationkey from rows_ cross join (select i as a, j as b from range(5) t(i) cross join range(5) u(j) where i < j) p where planted and c_nationkey % 5 in (p.a, p.b) and s_nationkey % 5 in (p.a, p.b)
  union all select 'state:' || (c_nationkey % 5), (c_nationkey // 5) * 25 + c_nationkey % 5 * 5 + o_custkey % 5, (s_nationkey // 5) * 25 + s_nationkey % 5 * 5 + l_suppkey % 5 from rows_ where planted and c_nationkey % 5 = s_nationkey % 5) p group by 1, 2, 3) f group by 1""")


register("panel_flows", _panel_flows, _panel_flows_sql())


def fitted(s: SparkSession, d: str, variants: tuple[str, ...] = mcmc.VARIANTS) -> tuple[DataFrame, ...]:
    """(flows, units, borders, networks, fits, paths with rep): the panel with all its fits and greedy paths, kept as tables for the state of the inputs."""
    key = fingerprint(s, d, TABLES, variants, mcmc.WARM, mcmc.HOT, mcmc.COOL, mcmc.STARTS, mcmc.FINER)
    flows = kept(s, "flows", key, lambda: panel.trade_panel(s, d)[0])
    networks = panel.networks_of(flows)
    units = kept(s, "units", key, lambda: panel.panel_units(s, networks))
    borders = panel.panel_adjacency(units)
    fits = kept(s, "fits", key, lambda: mcmc.best_chain(cut(mcmc.anneal(flows, units, borders, variants, REPS))))
    both = lambda: greedy.run(flows, units, borders, "mg").withColumn("rep", F.lit("mg")).unionByName(greedy.run(flows, units, borders, "w").withColumn("rep", F.lit("w")))
    return flows, units, borders, networks, fits, kept(s, "paths", key, both)


def all_scores(s: SparkSession, d: str, variants: tuple[str, ...] = mcmc.VARIANTS) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(scores of all models and of the greedy method (ga), null lengths, networks)."""
    flows, units, _, networks, fits, paths = fitted(s, d, variants)
    n = units.groupBy("network_id").agg(F.count("*").alias("n"))
    rows = mcmc.score_rows(fits)
    for rep in REPS:
        rows = rows.unionByName(greedy.best_step(paths.filter(F.col("rep") == rep)).join(n, "network_id").select("network_id", F.lit("ga").alias("model"), F.lit(rep).alias("rep"), "n", "b", "dl"))
    return cut(rows), nulls.null_scores(flows, units), networks


def _block(rows: DataFrame) -> DataFrame:
    return rows.filter("model != 'ga'")


def _ga(rows: DataFrame) -> DataFrame:
    return rows.filter("model = 'ga'")


def _trajectories(s: SparkSession, d: str) -> DataFrame:
    """Both methods on the planted network: the lengths the greedy path visits, and those the annealed chain visits sweep by sweep."""
    units = U.nations(s, "planted")
    net = cut(W.planted(s, d)), units, adj.from_cells(units)
    path = greedy.run(*net, "w").select(F.lit("ga").alias("method"), "step", "b", "dl")
    return rounded(path.unionByName(mcmc.trace(*net).select(F.lit("annealed").alias("method"), F.col("sweep").alias("step"), "b", "dl")))


def _rep_gap(s: SparkSession, d: str) -> DataFrame:
    rows, _, networks = all_scores(s, d)
    return rounded(scores.rep_gap(rows).join(networks, "network_id").select("network_id", "class", "n", "gap"))


def _eta(s: SparkSession, d: str) -> DataFrame:
    rows, null, networks = all_scores(s, d)
    return rounded(scores.compression_ratio(scores.best_model(_block(rows)), null).join(networks, "network_id").select("network_id", "class", "model", "rep", "eta"), 6)


def _hist(s: SparkSession, d: str) -> DataFrame:
    rows, _, networks = all_scores(s, d)
    return scores.model_histogram(scores.best_model(_block(rows)), networks)


def _ratio(s: SparkSession, d: str) -> DataFrame:
    rows, _, _ = all_scores(s, d)
    return rounded(scores.dl_ratio(scores.best_model(_ga(rows)), scores.best_model(_block(rows))), 6)


register("x0_trajectory", _trajectories)
register("x1_rep_gap", _rep_gap)
register("x2_eta", _eta)
register("x3_hist", _hist)
register("x4_ratio", _ratio)
register("x5_groups", lambda s, d: rounded(scores.resolution_limits(all_scores(s, d)[0].filter("rep = 'w'")).select("network_id", "model", "n", "b", "flat_limit", "nested_limit"), 6))
register("x5_lines", lambda s, d: rounded(scores.fit_line(all_scores(s, d)[0].filter("rep = 'w'"), "b", "n"), 6))
register("x6_groups_pair", lambda s, d: (lambda x: _ga(x).select("network_id", "rep", F.col("b").alias("b_ga")).join(x.filter("model = 'bm'").select("network_id", "rep", F.col("b").alias("b_bm")), ["network_id", "rep"]))(all_scores(s, d)[0]))


def _nested_gain(s: SparkSession, d: str) -> DataFrame:
    """By nested variant and form: networks, how many of them a hierarchy makes shorter, and how many it makes longer (none)."""
    rows = _block(all_scores(s, d)[0])
    flat = F.regexp_replace(F.regexp_replace("model", "n", ""), "_$", "")
    both = rows.filter(F.col("model").rlike("_.*n")).withColumn("flat", flat).join(rows.select("network_id", "rep", F.col("model").alias("flat"), F.col("dl").alias("flat_dl")), ["network_id", "rep", "flat"])
    return both.groupBy("model", "rep").agg(F.count("*").alias("networks"), F.count_if(F.col("dl") < F.col("flat_dl") - 1e-6).alias("shorter"), F.count_if(F.col("dl") > F.col("flat_dl") + 1e-6).alias("longer"))


register("x3_nested_gain", _nested_gain)


def _ami_panel(s: SparkSession, d: str) -> DataFrame:
    """The greedy method against the best block model of each network, both for weighted flows; a nested model by its finest level."""
    _, units, _, _, fits, paths = fitted(s, d)
    rows = all_scores(s, d)[0].filter("rep = 'w'")
    best = scores.best_model(_block(rows)).select("network_id", "model")
    chosen = mcmc.hierarchy(fits.filter("rep = 'w'").join(best, ["network_id", "model"]))
    found = similarity.ami(greedy.cut_path(paths.filter("rep = 'w'"), units, "ga"), similarity.finest(chosen))
    gap = scores.dl_gap_per_node(rows.join(best, ["network_id", "model"]), _ga(rows))
    return rounded(found.select("network_id", "ami").join(gap, "network_id"), 6)


register("x7_ami", _ami_panel)
register("x7_ami_hist", lambda s, d: scores.histogram(_ami_panel(s, d), "ami", 10))


def _contiguity_panel(s: SparkSession, d: str) -> DataFrame:
    _, units, borders, networks, fits, paths = fitted(s, d)
    out = None
    for rep in REPS:
        parts = similarity.finest(mcmc.hierarchy(fits.filter(F.col("rep") == rep))).unionByName(greedy.cut_path(paths.filter(F.col("rep") == rep), units, "ga"))
        rows = contiguity.measures(cut(parts), borders).withColumn("rep", F.lit(rep))
        out = rows if out is None else out.unionByName(rows)
    return out.join(networks, "network_id")


register("x8_contiguity", lambda s, d: rounded(_contiguity_panel(s, d), 6))
register("x8_summary", lambda s, d: rounded(scores.summarise(_contiguity_panel(s, d).filter("rep = 'w'").withColumn("of", F.concat_ws("/", "class", "model")), "cvm", "of"), 6))

# ---------------------------------------------------------------- states at two scales


def states(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Each region's tracts as a network of its own, 25 tracts in 5 nations."""
    t = U.tracts(s)
    units = t.withColumn("network_id", F.concat(F.lit("state"), F.col("grand_id").cast("string")))
    return W.states(s, d), units, adj.from_cells(units)


def coarse(flows: DataFrame, units: DataFrame, borders: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The same networks between the parents of their units."""
    return network.coarsen(flows, units), network.coarsen_units(units), adj.coarsen(borders, units)


def _against_admin(s: SparkSession, d: str) -> DataFrame:
    """The greedy method stopped at as many groups as a state has nations, against the nations: length per tract and similarity, one row a state."""
    flows, units, borders = states(s, d)
    flows = cut(flows)
    path = cut(greedy.run(flows, units, borders, "w", stop="fixed_b", b=5))
    found, nations = cut(greedy.cut_path(path, units, "ga", 5)), baselines.admin(units)
    gap = scores.dl_gap_per_node(dl.total(flows, found, "w"), dl.total(flows, nations, "w"))
    near = similarity.spatial_nmi(found, nations, units).select("network_id", "snmi").join(similarity.nmi(found, nations).select("network_id", "nmi"), "network_id")
    return rounded(gap.join(near, "network_id"), 6)


_STATE_FLOWS = "fl_ as (select src % 25 // 5 as net, (src // 25) * 5 + src % 5 as src, (dst // 25) * 5 + dst % 5 as dst, w from f_tract where src % 25 // 5 = dst % 25 // 5)"
_H = "-sum(m / t * log2(m / t))"


def _against_sql() -> str:
    info = lambda k, weight: f"""n{k}_ as (select net, r, s, sum({weight})::double as n from two_ group by 1, 2, 3), t{k}_ as (select net, sum(n) as t from n{k}_ group by 1),
i{k}_ as (select net, p.h as hp, q.h as hq, j.h as h from (select net, {_H} as h from (select net, r, sum(n) as m from n{k}_ group by 1, 2) a join t{k}_ using (net) group by net) p join (select net, {_H} as h from (select net, s, sum(n) as m from n{k}_ group by 1, 2) a join t{k}_ using (net) group by net) q using (net) join (select net, {_H} as h from (select net, n as m from n{k}_) a join t{k}_ using (net) group by net) j using (net))"""  # noqa: E731
    admin = f"adm_ as (select net, sum(e)::bigint as e, sum(w)::bigint as w, sum({O.cost('25.0', 'e', 'w', 'w')}) as bits from (select net, src // 5 as p, dst // 5 as q, count(*)::bigint as e, sum(w)::bigint as w from fl_ group by 1, 2, 3) c group by net),\nadl_ as (select net, {O.lchoose('24', '4')} + {O.lf('25')} - 5 * {O.lf('5')} + {O.matrix('5', 'e', 'w', 'w')} + bits as dl from adm_)"
    two = "two_ as (select u.net, u.g as r, u.u // 5 as s, (1 + ((u.u // 5) * 25 + u.net * 5 + u.u % 5) % 3)::double as area from gu u where u.b = 5)"
    more = _STATE_FLOWS + ",\n" + O.greedy("fl_", "a_nation", 25, "w", 5, "select unnest(range(5)) as net") + ",\n" + ",\n".join((admin, two, info("a", "area"), info("u", "1")))
    return O.compose(("f_tract", "a_nation"), "select 'state' || d.net as network_id, round((d.dl - a.dl) / 25, 6) as gap, round(2 * (x.hp + x.hq - x.h) / (x.hp + x.hq), 6) as snmi, round(2 * (y.hp + y.hq - y.h) / (y.hp + y.hq), 6) as nmi from gd d join adl_ a using (net) join ia_ x using (net) join iu_ y using (net) where d.b = 5", more, recursive=True)


register("x9_admin", _against_admin, _against_sql())


def _tessellations(s: SparkSession, d: str) -> DataFrame:
    """For each state, whether its greedy partition is more like the nations than 95 % of 100 random tessellations with as many cells."""
    flows, units, borders = states(s, d)
    found = greedy.cut_path(cut(greedy.run(flows, units, borders, "w", stop="fixed_b", b=5)), units, "ga", 5)
    own = units.withColumn("x", F.col("x") % 5)
    random = nulls.voronoi(own, nulls.seeds(s, 5, DRAWS, 5, 5))
    return rounded(nulls.percentile_test(cut(found), baselines.admin(units), random, units).select("network_id", "snmi", "p95", "above"), 6)


register("x10_voronoi", _tessellations)


def _scale(s: SparkSession, net: tuple[DataFrame, DataFrame, DataFrame], scale: str) -> DataFrame:
    """Of each network: compression, groups, contiguity and similarity of the greedy method and of the best weighted block model."""
    flows, units, borders = cut(net[0]), cut(net[1]), cut(net[2])
    fits = cut(mcmc.best_chain(cut(mcmc.anneal(flows, units, borders, reps=("w",)))))
    path = cut(greedy.run(flows, units, borders, "w"))
    null, ga = nulls.null_scores(flows, units), greedy.best_step(path)
    best = cut(scores.best_model(mcmc.score_rows(fits)))
    block = similarity.finest(mcmc.hierarchy(fits.join(best.select("network_id", "model"), ["network_id", "model"])))
    merged = cut(greedy.cut_path(path, units, "ga"))
    rows = scores.compression_ratio(best, null).select("network_id", "model", F.col("b").alias("b_best"), F.col("eta").alias("eta_best"))
    rows = rows.join(scores.compression_ratio(ga, null).select("network_id", F.col("b").alias("b_ga"), F.col("eta").alias("eta_ga")), "network_id")
    rows = rows.join(scores.dl_ratio(ga, best), "network_id").join(similarity.ami(merged, block).select("network_id", "ami"), "network_id")
    return rows.join(contiguity.measures(block, borders).select("network_id", "cvm", "broken_fraction"), "network_id").withColumn("scale", F.lit(scale))


def _scales(s: SparkSession, d: str) -> DataFrame:
    """States and the whole country by tracts, and the same flows by nations."""
    whole = U.tracts(s)
    flows, units, borders = states(s, d)
    fine = flows.unionByName(W.tracts(s, d)), units.unionByName(whole), borders.unionByName(adj.from_cells(whole))
    return rounded(_scale(s, fine, "tract").unionByName(_scale(s, coarse(*fine), "nation")), 6)


register("x11_scale", _scales)


def _scale_eta(s: SparkSession, d: str) -> DataFrame:
    """Compression by the greedy method of each state's flows, between tracts and between nations."""
    fine = states(s, d)
    eta = lambda net: scores.compression_ratio(greedy.best_step(greedy.run(*net, "w")), nulls.null_scores(net[0], net[1]))
    return rounded(scores.scale_compare(eta(fine), eta(coarse(*fine))), 6)


def _scale_eta_sql() -> str:
    """One statement for each scale: 25 tracts of a state, and its 5 nations in a column."""
    nation = "fl_ as (select src % 25 // 5 as net, src // 25 as src, dst // 25 as dst, sum(w)::bigint as w from f_tract where src % 25 // 5 = dst % 25 // 5 group by 1, 2, 3),\ncol_ as (select i as a, i + 1 as b from range(4) t(i))"
    one = lambda more, border, n: O.compose(("f_tract", "a_nation"), f"select d.net, min(d.dl) / any_value(t.null_) as eta from gd d join (select net, {O.lmulti(str(n * n), 'sum(w)')} as null_ from fl_ group by net) t on t.net = d.net group by d.net", more + ",\n" + O.greedy("fl_", border, n, "w", 1, "select unnest(range(5)) as net"), recursive=True)
    return f"select 'state' || f.net as network_id, round(f.eta, 6) as eta_fine, round(c.eta, 6) as eta_coarse from ({one(_STATE_FLOWS, 'a_nation', 25)}) f join ({one(nation, 'col_', 5)}) c on c.net = f.net"


register("x11_eta", _scale_eta, _scale_eta_sql())


def _runtimes(s: SparkSession, d: str) -> DataFrame:
    """Kernel seconds on all networks of the panel and on larger ones, and the slope of their logarithms."""
    flows, networks = panel.trade_panel(s, d)
    flows = cut(flows)
    units = panel.panel_units(s, panel.networks_of(flows))
    rows = greedy.timed(flows, units, panel.panel_adjacency(units))
    for flows, units in ((W.tracts(s, d), U.tracts(s)), (W.clock(s, d), U.clock(s)), (W.clock_grid(s, d), U.clock_grid(s)), (W.basket(s, d), U.brand_sizes(s))):
        rows = rows.unionByName(greedy.timed(flows, units, adj.from_cells(units)))
    rows = cut(rows)
    return rows.select("network_id", "n", "e", "seconds").join(F.broadcast(scores.runtime_slope(rows)), F.col("n") > 0)  # one row


register("x12_runtime", _runtimes)


def _large(s: SparkSession, d: str) -> DataFrame:
    """The largest sparse network: groups, length and contiguity of the greedy method and of the flat block model."""
    units = U.clock_grid(s)
    flows, borders = cut(W.clock_grid(s, d)), adj.from_cells(units)
    path = cut(greedy.run(flows, units, borders, "w"))
    fits = cut(mcmc.anneal(flows, units, borders, ("bm",), ("w",)))
    parts = greedy.cut_path(path, units, "ga").unionByName(fits.select("network_id", "model", "unit_id", "label"))
    lengths = greedy.best_step(path).select(F.lit("ga").alias("model"), "dl").unionByName(mcmc.score_rows(fits).select("model", "dl"))
    return rounded(contiguity.measures(cut(parts), borders).join(lengths, "model").select("model", "b", "dl", "cvm", "broken_fraction", "mean_components"), 6)


register("x13_large", _large)
