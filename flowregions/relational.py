"""Queries of the relational surface, functions, sources, sinks and streams around the methods."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from flowregions import oracle as O  # noqa: N812
from flowregions.functions import bits
from flowregions.operators import adjacency as adj
from flowregions.operators import baselines, dl, network, sinks
from flowregions.plans import greedy
from flowregions.plans.checkpoints import cut, folder
from flowregions.registry import register, rounded
from flowregions.sources import tables
from flowregions.sources import units as U
from flowregions.sources import workloads as W
from flowregions.streaming import flows as st

# ---------------------------------------------------------------- joins


def _by_region(s: SparkSession, d: str, hint: str) -> DataFrame:
    """Weight between regions; the labels are joined the way the hint says."""
    side = baselines.admin(U.nations(s, "planted")).select("unit_id", "label").hint(hint)
    one = W.planted(s, d).join(side.select(F.col("unit_id").alias("src"), F.col("label").alias("r")).hint(hint), "src")
    return one.join(side.select(F.col("unit_id").alias("dst"), F.col("label").alias("s")).hint(hint), "dst").groupBy("r", "s").agg(F.sum("w").alias("w"))


_BY_REGION = O.compose(("f_planted",), "select (src % 5)::int as r, (dst % 5)::int as s, sum(w)::bigint as w from f_planted group by 1, 2")
register("join_merge", lambda s, d: _by_region(s, d, "merge"), _BY_REGION)
register("join_shuffle_hash", lambda s, d: _by_region(s, d, "shuffle_hash"), _BY_REGION)


def _theta(s: SparkSession, d: str) -> DataFrame:
    """For each nation, the touching ones of another region that send more than it does: equal keys first, the inequality on what is left."""
    sent = W.planted(s, d).groupBy(F.col("src").alias("u")).agg(F.sum("w").alias("w"))
    borders = adj.from_cells(U.nations(s))
    both = borders.select("a", "b").union(borders.select(F.col("b").alias("a"), F.col("a").alias("b")))
    mine, theirs = sent.select(F.col("u").alias("a"), F.col("w").alias("wa")), sent.select(F.col("u").alias("b"), F.col("w").alias("wb"))
    return both.join(mine, "a").join(theirs, (both.b == theirs.b) & (F.col("wb") > F.col("wa")) & (both.b % 5 != F.col("a") % 5)).groupBy("a").agg(F.count("*").alias("n"))


register("join_theta", _theta, O.compose(("f_planted", "a_nation"), "select x.a::int as a, count(*)::bigint as n from (select a, b from a_nation union all select b, a from a_nation) x join g_ p on p.u = x.a join g_ q on q.u = x.b and q.w > p.w where x.a % 5 <> x.b % 5 group by 1", "g_ as (select src as u, sum(w) as w from f_planted group by 1)"))


def _interval(s: SparkSession, d: str) -> DataFrame:
    """Events within administrative periods of different lengths: an equi-join on the day bands that a period covers, then the exact interval."""
    periods = s.range(6).select(F.col("id").cast("int").alias("period"), (F.lit(1704067200) + F.col("id") * 400_000).alias("begin"), (F.lit(1704067200) + F.col("id") * 400_000 + 250_000 + F.col("id") * 10_000).alias("end"))
    bands = periods.withColumn("band", F.explode(F.sequence(F.floor(F.col("begin") / 86400), F.floor(F.col("end") / 86400))))
    events = tables.read(s, d, "events").select("event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("at")).withColumn("band", F.floor(F.col("at") / 86400))
    return events.join(F.broadcast(bands), "band").filter((F.col("at") >= F.col("begin")) & (F.col("at") < F.col("end"))).groupBy("period", "event_type").agg(F.count("*").alias("n"))


register("join_interval", _interval, "select i::int as period, event_type, count(*)::bigint as n from events join range(6) t(i) on floor(epoch(ts)) >= 1704067200 + i * 400000 and floor(epoch(ts)) < 1704067200 + i * 400000 + 250000 + i * 10000 group by 1, 2")


def _lateral(s: SparkSession, d: str) -> DataFrame:
    """Each nation's strongest partner by a lateral subquery."""
    U.nations(s).createOrReplaceTempView("nation_units")
    W.trade(s, d).createOrReplaceTempView("trade_flows")
    return s.sql("select u.unit_id, t.dst, t.w from nation_units u, lateral (select dst, w from trade_flows f where f.src = u.unit_id order by w desc, dst limit 1) t")


register("join_lateral", _lateral, O.compose(("f_trade", "u_nation"), "select unit_id, dst, w from (select src as unit_id, dst, w, row_number() over (partition by src order by w desc, dst) as k from f_trade) z where k = 1"))


def _as_of(s: SparkSession, d: str) -> DataFrame:
    """For each event the user's last purchase before it, in order of time and id."""
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return tables.read(s, d, "events").select("event_id", F.last(bought, ignorenulls=True).over(before).alias("purchase"))


register("join_asof", _as_of, "select e.event_id, arg_max(p.event_id, (p.ts, p.event_id)) as purchase from events e left join events p on p.user_id = e.user_id and p.event_type = 'purchase' and (p.ts, p.event_id) < (e.ts, e.event_id) group by e.event_id")

# ---------------------------------------------------------------- shapes, samples, subqueries

register("unpivot_degrees", lambda s, d: network.degrees(W.planted(s, d)).unpivot("unit_id", ["k_out", "k_in", "s_out", "s_in"], "what", "n"), O.compose(("f_planted",), "select src as unit_id, 'k_out' as what, count(*)::bigint as n from f_planted group by 1 union all select dst, 'k_in', count(*) from f_planted group by 1 union all select src, 's_out', sum(w)::bigint from f_planted group by 1 union all select dst, 's_in', sum(w)::bigint from f_planted group by 1"))


def stratified(rows: DataFrame, key: str, by: str, shares: dict[str, float], other: float = 0.0) -> DataFrame:
    """A sample that reruns and other engines repeat: rows whose hashed key falls below their stratum's share."""
    share = F.lit(other)
    for value, part in shares.items():
        share = F.when(F.col(by) == value, F.lit(part)).otherwise(share)
    return rows.filter(F.pmod(F.col(key) * 2654435761, F.lit(1000)) < share * 1000)


register("sample_strata", lambda s, d: stratified(tables.read(s, d, "events"), "event_id", "event_type", {"purchase": 1.0, "view": 0.25}, 0.1).select("event_id", "event_type"), "select event_id, event_type from events where (event_id * 2654435761) % 1000 < case event_type when 'purchase' then 1000 when 'view' then 250 else 100 end")


def _sampled(s: SparkSession, d: str) -> DataFrame:
    """Bernoulli and stratified samples of Spark's own: each within five standard deviations of its share."""
    events = tables.read(s, d, "events")
    near = lambda got, n, p: (F.abs(got - n * p) <= 5 * F.sqrt(n * p * (1 - p)) + 1)
    all_ = events.groupBy("event_type").agg(F.count("*").alias("n"))
    plain = events.sample(0.2, seed=7).groupBy("event_type").agg(F.count("*").alias("a"))
    some = events.sampleBy("event_type", {"purchase": 0.5, "view": 0.1}, seed=7).groupBy("event_type").agg(F.count("*").alias("b"))
    share = F.when(F.col("event_type") == "purchase", 0.5).when(F.col("event_type") == "view", 0.1).otherwise(0.0)
    rows = all_.join(plain, "event_type", "left").join(some, "event_type", "left").na.fill(0)
    return rows.select("event_type", "n", near(F.col("a"), F.col("n"), F.lit(0.2)).alias("sample"), near(F.col("b"), F.col("n"), share).alias("sample_by"))


register("sample_shares", _sampled, "select event_type, count(*)::bigint as n, true as sample, true as sample_by from events group by 1")


def _correlated(s: SparkSession, d: str) -> DataFrame:
    """Customers above their nation's mean balance who ordered, by correlated subqueries."""
    for name in ("customer", "orders"):
        tables.read(s, d, name).createOrReplaceTempView(f"{name}_rows")
    return s.sql("""select c_nationkey, count(*) as n from customer_rows c
        where c_acctbal > (select avg(c_acctbal) from customer_rows o where o.c_nationkey = c.c_nationkey)
          and exists (select 1 from orders_rows o where o.o_custkey = c.c_custkey) group by c_nationkey""")


register("subquery_correlated", _correlated, "select c_nationkey, count(*)::bigint as n from customer c where c_acctbal > (select avg(c_acctbal) from customer o where o.c_nationkey = c.c_nationkey) and exists (select 1 from orders o where o.o_custkey = c.c_custkey) group by c_nationkey")


def _parts_map(s: SparkSession, d: str) -> DataFrame:
    """A length's parts as a map, and the map's entries as rows."""
    row = dl.total(W.planted(s, d), baselines.admin(U.nations(s, "planted")), "w")
    names = ["partition_bits", "matrix_bits", "placement_bits", "weight_bits"]
    parts = F.map_from_arrays(F.array(*map(F.lit, names)), F.array(*names))
    return rounded(row.select(F.explode(F.map_entries(parts)).alias("p")).select(F.col("p.key").alias("part"), F.col("p.value").alias("bits")))


register("map_parts", _parts_map, O.compose(("f_planted", "u_nation"), "unpivot (select round(partition_bits, 4) as partition_bits, round(matrix_bits, 4) as matrix_bits, round(placement_bits, 4) as placement_bits, round(weight_bits, 4) as weight_bits from d_) on columns(*) into name part value bits", "part_ as (select unit_id, parent_id as label from u_nation),\n" + O.length("f_planted", "part_", "w")))
register("variant_props", lambda s, d: tables.read(s, d, "events").select(F.variant_get(F.try_parse_json("props"), "$.k", "int").alias("k"), F.struct("event_type", "user_id").alias("who")).groupBy("k", "who.event_type").agg(F.count("*").alias("n"), F.count_distinct("who").alias("users")), "select json_extract_string(props, '$.k')::int as k, event_type, count(*)::bigint as n, count(distinct user_id)::bigint as users from events group by 1, 2")


def _pointer(s: SparkSession, d: str) -> DataFrame:
    """Ten steps along the strongest outgoing flow, from every nation, by recursion in SQL."""
    W.planted(s, d).groupBy("src").agg(F.min(F.struct((-F.col("w")).alias("k"), "dst")).alias("m")).select("src", F.col("m.dst").alias("dst")).createOrReplaceTempView("strongest")
    return s.sql("with recursive r(start, here, k) as (select src, src, 0 from strongest union all select r.start, t.dst, k + 1 from r join strongest t on t.src = r.here where k < 10) select start, here, k from r")


register("recursion", _pointer, O.compose(("f_planted",), "select start, here, k from r", "t_ as (select src, arg_min(dst, (-w, dst)) as dst from f_planted group by src), r(start, here, k) as (select src, src, 0 from t_ union all select r.start, t.dst, k + 1 from r join t_ t on t.src = r.here where k < 10)", recursive=True))
register("top_shares", lambda s, d: rounded(W.trade(s, d).withColumn("share", F.col("w") / F.sum("w").over(Window.partitionBy("src"))).orderBy(F.desc("w"), "src", "dst").offset(5).limit(10).select("src", "dst", "w", "share"), 6), O.compose(("f_trade",), "select src, dst, w, round(w / sum(w) over (partition by src), 6) as share from f_trade order by w desc, src, dst limit 10 offset 5"))
register("silent_units", lambda s, d: U.brand_sizes(s).join(W.basket(s, d), F.col("unit_id") == F.col("src"), "left_anti").select("unit_id"), O.compose(("f_basket",), "select i::int as unit_id from range(1250) t(i) where not exists (select 1 from f_basket where src = i)"))
register("keep_self", lambda s, d: network.build_flows(W.trade_rows(s, d).select(F.lit("trade").alias("network_id"), F.col("c_nationkey").alias("src"), F.col("s_nationkey").alias("dst")), keep_self=False).select("src", "dst", "w"), O.compose(("f_trade",), "select src, dst, w from f_trade where src <> dst"))

_KM = "2 * 6371.0088 * asin(sqrt(pow(sin(radians(dst // 5 - src // 5) / 2), 2) + cos(radians(src // 5)) * cos(radians(dst // 5)) * pow(sin(radians(dst % 5 - src % 5) / 2), 2)))"
register("distance_haversine", lambda s, d: network.filter_distance(W.trade(s, d), U.nations(s, "trade"), 250.0, "haversine").select("src", "dst", "w"), O.compose(("f_trade",), f"select src, dst, w from f_trade where {_KM} <= 250"))

# ---------------------------------------------------------------- code lengths as functions


def _numbers(s: SparkSession, d: str) -> DataFrame:
    """n from 1 to 60 and k from 0 to n: what the keys of all line items leave."""
    n = F.col("l_partkey") % 60 + 1
    return tables.read(s, d, "lineitem").select(n.cast("long").alias("n"), (F.col("l_suppkey") % (n + 1)).cast("long").alias("k")).distinct()


def _left(s: SparkSession, d: str, name: str, key: str, most: int, out: str) -> DataFrame:
    """Numbers from 1 to ``most``: what the keys of a table leave."""
    return tables.read(s, d, name).select((F.col(key) % most + 1).cast("long").alias(out)).distinct()


register("bits_table", lambda s, d: rounded(_numbers(s, d).select("n", "k", bits.lfact(F.col("n")).alias("fact"), bits.lchoose(F.col("n"), F.col("k")).alias("choose"), bits.lmulti(F.col("n"), F.col("k")).alias("multi"), bits.lcompositions(F.col("n"), F.greatest(F.col("k"), F.lit(1))).alias("parts"), bits.plogp(F.col("k") / F.col("n")).alias("plogp")), 8), f"select n, k, round({O.lf('n')}, 8) as fact, round({O.lchoose('n', 'k')}, 8) as choose, round({O.lmulti('n', 'k')}, 8) as multi, round({O.lcomp('n', 'greatest(k, 1)')}, 8) as parts, round(case when k > 0 then (k::double / n) * log2(k::double / n) else 0.0 end, 8) as plogp from (select distinct l_partkey % 60 + 1 as n, l_suppkey % (l_partkey % 60 + 2) as k from lineitem) z")
register("bits_lgamma", lambda s, d: rounded(_left(s, d, "orders", "o_orderkey", 2000, "i").select("i", bits.lgamma(F.col("i") / 4).alias("v")), 8), "select i, round(lgamma(i / 4.0), 8) as v from (select distinct (o_orderkey % 2000 + 1)::bigint as i from orders) t")
register("bits_huge", lambda s, d: rounded(_left(s, d, "lineitem", "l_partkey", 40, "k").select("k", bits.lchoose(F.lit(1e15), F.col("k")).alias("v")), 6), "select k, round((select sum(log2((1e15 - i) / (i + 1))) from range(40) t(i) where i < k), 6) as v from (select distinct (l_partkey % 40 + 1)::bigint as k from lineitem) u")


def _sql_bits(s: SparkSession, d: str) -> DataFrame:
    bits.register_sql(s)
    W.turns(s, d).createOrReplaceTempView("turn_flows")
    return rounded(s.sql("select src, dst, lfact_bits(w) as fact, lchoose_bits(w + 9, 9) as choose, lmulti_bits(9, w) as multi from turn_flows"))


register("sql_bits", _sql_bits, O.compose(("f_turns",), f"select src, dst, round({O.lf('w')}, 4) as fact, round({O.lchoose('w + 9', '9')}, 4) as choose, round({O.lmulti('9', 'w')}, 4) as multi from f_turns"))


def entropy_udaf():
    """Entropy in bits of a column of counts, as a grouped aggregate in pandas; ``bits.entropy`` is the native form."""
    @F.pandas_udf("double")
    def entropy_bits(counts: pd.Series) -> float:
        import numpy as np

        p = counts[counts > 0].to_numpy(dtype=float)
        p = p / p.sum() if len(p) else p
        return float(-(p * np.log2(p)).sum()) if len(p) else 0.0

    return entropy_bits


_ENTROPY = O.compose(("f_planted",), "select src, round(-sum(w / t * log2(w / t)), 6) as entropy from (select src, w::double as w, sum(w) over (partition by src) as t from f_planted) z group by src")
register("entropy_udaf", lambda s, d: rounded(W.planted(s, d).groupBy("src").agg(entropy_udaf()("w").alias("entropy")), 6), _ENTROPY)
register("entropy_native", lambda s, d: rounded(W.planted(s, d).withColumn("t", F.sum("w").over(Window.partitionBy("src"))).groupBy("src").agg(bits.entropy(F.col("w"), F.col("t")).alias("entropy")), 6), _ENTROPY)
register("dl_per_node", lambda s, d: rounded(dl.per_node(dl.total(W.planted(s, d), baselines.admin(U.nations(s, "planted")), "w")).select("n", "dl_per_node"), 6), O.compose(("f_planted", "u_nation"), "select n, round(dl / n, 6) as dl_per_node from d_", "part_ as (select unit_id, parent_id as label from u_nation),\n" + O.length("f_planted", "part_", "w")))
register("hll_units", lambda s, d: W.trade_rows(s, d).groupBy("c_mktsegment").agg(F.count_distinct("o_custkey").alias("customers"), F.approx_count_distinct("o_custkey", 0.02).alias("about"), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey", 14)).alias("sketch")).select("c_mktsegment", "customers", (F.abs(F.col("about") / F.col("customers") - 1) <= 0.1).alias("about"), (F.abs(F.col("sketch") / F.col("customers") - 1) <= 0.05).alias("sketch")), O.compose(("rows_",), "select c_mktsegment, count(distinct o_custkey)::bigint as customers, true as about, true as sketch from rows_ group by 1"))

# ---------------------------------------------------------------- sources and sinks


def _formats(s: SparkSession, d: str) -> DataFrame:
    """Flows written and read again in every format under the declared schema."""
    flows, out = cut(W.turns(s, d).select("network_id", "src", "dst", "w")), None
    for fmt in ("parquet", "orc", "json", "csv", "text"):
        path = f"{folder(s)}/flows-{uuid.uuid4().hex}"
        if fmt == "text":
            flows.select(F.concat_ws(" ", *[F.col(c).cast("string") for c in flows.columns])).write.text(path)
        else:
            flows.write.options(**({"header": True} if fmt == "csv" else {})).format(fmt).save(path)
        rows = tables.read_flows(s, path, fmt).select(F.lit(fmt).alias("fmt"), "src", "dst", "w")
        out = rows if out is None else out.unionByName(rows)
    return out


register("source_formats", _formats, O.compose(("f_turns",), "select fmt, src, dst, w from f_turns cross join (select unnest(['parquet', 'orc', 'json', 'csv', 'text']) as fmt) x"))


def _partitioned(s: SparkSession, d: str) -> DataFrame:
    """Results written by class and model, and one class read back: the reader prunes to its folders."""
    path = f"{folder(s)}/scores-{uuid.uuid4().hex}"
    units = U.nations(s, "planted")
    both = baselines.admin(units).unionByName(baselines.single(units))
    rows = dl.total(W.planted(s, d), both, "w").unionByName(dl.total(W.planted(s, d), both, "mg")).withColumn("class", F.concat(F.lit("nation_"), "rep"))
    sinks.write(rows, path)
    return rounded(s.read.parquet(path).filter("class = 'nation_w'").select("model", "b", "dl"))


register("sink_partitioned", _partitioned, O.compose(("f_planted", "u_nation"), f"select 'admin' as model, b, round(dl, 4) as dl from d_ union all select 'single', 1, round({O.lf('25')} - {O.lf('25')} + {O.matrix('1', 'e', 'w', 'w')} + {O.cost('625', 'e', 'w', 'w')}, 4) from d_", "part_ as (select unit_id, parent_id as label from u_nation),\n" + O.length("f_planted", "part_", "w")))


def _bucketed(s: SparkSession, d: str) -> DataFrame:
    """A table bucketed by network, joined to itself on the bucket key without a shuffle; the table goes when its rows are read."""
    name = f"flows_{uuid.uuid4().hex}"
    flows = W.turns(s, d).unionByName(W.local(s, d)).select("network_id", "src", "dst", "w")
    sinks.save_bucketed(flows, name, 4)
    total = s.table(name).groupBy("network_id").agg(F.sum("w").alias("all"))
    rows = cut(rounded(s.table(name).join(total, "network_id").select("network_id", "src", "dst", (F.col("w") / F.col("all")).alias("share")), 9))
    s.sql(f"drop table {name}")
    return rows


register("sink_bucketed", _bucketed, O.compose(("f_turns", "f_local"), "select network_id, src, dst, round(w / sum(w) over (partition by network_id), 9) as share from (select 'turns' as network_id, src, dst, w from f_turns union all select 'local', src, dst, w from f_local) z"))


def _udtf(s: SparkSession, d: str) -> DataFrame:
    """Regions by the SQL table function."""
    from flowregions.sqlapi import register as register_sql

    register_sql(s)
    units = U.nations(s, "planted")
    greedy.gathered(W.planted(s, d), units, adj.from_cells(units)).createOrReplaceTempView("planted_network")
    return rounded(s.sql("select unit_id, label, b, dl from regionalize(table(planted_network) partition by network_id)"))


_LABELS = "select u.u::int as unit_id, g.low as label, d.b::int as b, round(d.dl, 4) as dl from (select net, arg_min(step, (round(dl, 8), b)) as step from gd group by net) m join gd d on d.net = m.net and d.step = m.step join gu u on u.net = m.net and u.step = m.step join gs g on g.net = u.net and g.step = u.step and g.g = u.g"
register("udtf_regionalize", _udtf, O.compose(("f_planted", "a_nation"), _LABELS, "fl_ as (select 0 as net, src, dst, w from f_planted),\n" + O.greedy("fl_", "a_nation", 25, "w"), recursive=True))


def _planted_groups(s: SparkSession, d: str) -> DataFrame:
    """What each planted group sends, and whether most of it stays inside."""
    rows = tables.planted(s, 40, 4, 50, 5).withColumn("r", F.floor(F.col("src") / 10).cast("int"))
    return rows.groupBy("r").agg(F.sum("w").alias("w"), F.count_distinct("src").alias("units"), F.sum(F.when(F.floor(F.col("dst") / 10) == F.col("r"), F.col("w"))).alias("inside")).select("r", "w", "units", (F.col("inside") >= 500).alias("most_inside"))


register("planted_source", _planted_groups, "select i::int as r, 550::bigint as w, 10::bigint as units, true as most_inside from range(4) t(i)")


def _null_sample(s: SparkSession, d: str) -> DataFrame:
    """As many trips as the planted trade has, drawn at random: by origin, within six standard deviations of its share."""
    from flowregions.operators import nulls

    w = W.planted(s, d).agg(F.sum("w")).first()[0]
    rows = nulls.sample_random_flows(s, 25, w).groupBy("src").agg(F.sum("w").alias("got"))
    return rows.select("src", F.lit(w).cast("long").alias("w"), (F.abs(F.col("got") - w / 25) <= 6 * F.sqrt(F.lit(w / 25 * 24 / 25))).alias("near"))


register("null_sample", _null_sample, O.compose(("f_planted",), "select i::int as src, (select sum(w)::bigint from f_planted) as w, true as near from range(25) t(i)"))

# ---------------------------------------------------------------- streams


def _by_files(s: SparkSession, events: DataFrame, file) -> DataFrame:
    """A stream that gets ``events`` file by file, in order of the number ``file``."""
    path = f"{folder(s)}/events-{uuid.uuid4().hex}"
    rows = cut(events.withColumn("file", file))
    for (k,) in sorted(rows.select("file").distinct().collect()):  # a handful of numbers
        rows.filter(F.col("file") == k).drop("file").coalesce(1).write.mode("append").parquet(path)
    return st.events(s, path)


def _at() -> Column:
    return F.unix_timestamp(F.col("ts").cast("timestamp"))


def _late(s: SparkSession, d: str) -> DataFrame:
    """Events of which every seventh comes ten days late, counted by whether the watermark still takes them."""
    behind = F.when(F.col("event_id") % 7 == 0, 864000).otherwise(0)
    return st.late_counts(_by_files(s, tables.read(s, d, "events"), F.floor((_at() + behind) / 432000)), "2 days")


register("stream_late", _late, """with e as (select floor(epoch(ts))::bigint as moment, (floor((floor(epoch(ts)) + case when event_id % 7 = 0 then 864000 else 0 end) / 432000))::bigint as file from events),
m as (select file, max(moment) as top from e group by file), w as (select file, max(top) over (order by file rows between unbounded preceding and 1 preceding) - 172800 as mark from m)
select coalesce(moment < mark, false) as dropped, count(*)::bigint as n from e join w using (file) group by 1""")


def _drift(s: SparkSession, d: str) -> DataFrame:
    """Trips in ten-day batches: all so far, and whether regions found anew are shorter than the frozen weeks."""
    units = U.clock_grid(s)
    pairs = st.user_pairs(_by_files(s, tables.read(s, d, "events"), F.floor((_at() - 1704067200) / 864000)))
    rows = st.drift(pairs, units, adj.from_cells(units), baselines.admin(units, "grand_id"))
    return rows.select("batch", "e", "w", (F.col("dl") < F.col("dl_frozen")).alias("shorter"))


register("stream_drift", _drift, O.compose(("pairs_",), "select b.batch, (select count(*)::bigint from (select src, dst from p_ where p_.batch <= b.batch group by 1, 2) z) as e, (select count(*)::bigint from p_ where p_.batch <= b.batch) as w, true as shorter from (select distinct batch from p_) b", "p_ as (select (nxt // 864000)::int as batch, t0 // 3600 as src, nxt // 3600 as dst from pairs_ where nxt - t0 <= 86400)"))
