"""Panels: many networks of several classes, cut from the trade and event tables, and what is run on all of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowregions.operators import adjacency as adj
from flowregions.sources import units as U
from flowregions.sources import workloads as W


def slice_pairs(pairs: DataFrame, by: str, klass: str) -> DataFrame:
    """One network for each value of ``by``: counted pairs (src, dst, w) tagged with network_id and class."""
    return pairs.select(F.concat(F.lit(f"{klass}:"), F.col(by).cast("string")).alias("network_id"), F.lit(klass).alias("class"), "src", "dst", "w")


def trade_panel(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """(flows, networks): metro-like networks by order priority and five-year period, combined ones by market segment and by pair of regions,
    state-like ones by region (tracts), and metro-like ones of events by type (six-hour cells).

    Metro-like and segment networks cover all nations, pairs of regions the ten nations of both, state-like ones the
    tracts of one region, event networks the days that the events fall on. Every slice is cut from one counted table.
    """
    period = F.floor((F.year("o_orderdate") - 1995) / 5)
    rows = W.counted_trade(spark, sf, "o_orderpriority", "o_orderdate").withColumn("metro", F.concat_ws("/", "o_orderpriority", period.cast("string")))
    rows = rows.groupBy("metro", "o_orderpriority", "c_mktsegment", "c_nationkey", "s_nationkey", (F.col("o_custkey") % 5).alias("ck"), (F.col("l_suppkey") % 5).alias("sk")).agg(F.sum("w").alias("w"))
    nation = rows.select("metro", "c_mktsegment", F.col("c_nationkey").cast("int").alias("src"), F.col("s_nationkey").cast("int").alias("dst"), "w")
    a, b = F.col("c_nationkey") % 5, F.col("s_nationkey") % 5
    pair = F.explode(F.transform(F.filter(F.sequence(F.lit(0), F.lit(4)), lambda r: (r != a) & ((a == b) | (r == b))), lambda r: F.concat_ws("-", F.least(a, r).cast("string"), F.greatest(a, r).cast("string"))))
    regions = rows.select(pair.alias("regions"), F.col("c_nationkey").cast("int").alias("src"), F.col("s_nationkey").cast("int").alias("dst"), "w")
    tract = rows.filter(a == b).select(W.tract(F.col("c_nationkey"), F.col("ck")).alias("src"), W.tract(F.col("s_nationkey"), F.col("sk")).alias("dst"), "w", a.cast("string").alias("region"))
    events = W.typed_clock(spark, sf).withColumn("event", F.concat(F.lit("event/"), "event_type"))
    pairs = slice_pairs(nation, "metro", "metro").unionByName(slice_pairs(nation, "c_mktsegment", "combined")).unionByName(slice_pairs(regions, "regions", "combined")).unionByName(slice_pairs(tract, "region", "state")).unionByName(slice_pairs(events, "event", "metro"))
    flows = pairs.groupBy("network_id", "src", "dst").agg(F.sum("w").alias("w"))
    return flows, networks_of(flows)


def networks_of(flows: DataFrame) -> DataFrame:
    """(network_id, class): the class is what stands before the colon."""
    return flows.select("network_id", F.split("network_id", ":")[0].alias("class")).distinct()


def panel_units(spark: SparkSession, networks: DataFrame) -> DataFrame:
    """The units of every network: the nation grid, the nations of two regions, a region's tracts, or the days' cells. Each network meets only units of its own kind, by equi-joins on what its name says."""
    name = F.split("network_id", ":")[1]
    pair = name.rlike("^[0-4]-[0-4]$")
    event = name.startswith("event/")
    kind = F.when(F.col("class") == "state", "tract").when(pair, "pair").when(event, "clock").otherwise("nation")
    rows = networks.select("network_id", kind.alias("kind"), F.when(F.col("class") == "state", F.array(F.substring(name, 1, 1))).when(pair, F.split(name, "-")).otherwise(F.array(F.lit("all"))).alias("keys"))
    rows = rows.select("network_id", "kind", F.explode("keys").alias("key"))
    some = lambda units, kind, key: units.drop("network_id").withColumn("kind", F.lit(kind)).withColumn("key", key)
    every = F.lit("all")
    nations, tracts = U.nations(spark), U.tracts(spark)
    units = some(nations, "nation", every).unionByName(some(nations, "pair", F.col("parent_id").cast("string"))).unionByName(some(tracts, "tract", F.col("grand_id").cast("string"))).unionByName(some(U.clock(spark), "clock", every))
    return rows.join(F.broadcast(units), ["kind", "key"]).drop("kind", "key")  # 295 rows, a fixed table


def panel_adjacency(units: DataFrame) -> DataFrame:
    return adj.from_cells(units)
