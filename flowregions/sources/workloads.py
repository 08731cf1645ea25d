"""Pairs of units from the given tables: one row for each trip, and the flow networks of the experiments.

Raw rows are aggregated on their own keys before dimensions are joined wherever a unit is a function
of such keys: at 100 TB the fact table then meets only distinct key pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from flowregions.operators.network import build_flows
from flowregions.sources.tables import read

HOUR = 3600


def trade_rows(spark: SparkSession, sf: str) -> DataFrame:
    """One row for each line item: both nations and keys, and the columns that panels are cut by."""
    lines = read(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey")
    orders = read(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate")
    customers = read(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    suppliers = read(spark, sf, "supplier").select("s_suppkey", "s_nationkey")
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(customers, F.col("o_custkey") == customers.c_custkey).join(suppliers, F.col("l_suppkey") == suppliers.s_suppkey)
    planted = (F.col("c_nationkey") % 5 == F.col("s_nationkey") % 5) | ((F.col("l_orderkey") * 7 + F.col("l_linenumber")) % 20 == 0)
    return rows.withColumn("planted", planted)


def tract(nation: Column, key: Column) -> Column:
    return (F.floor(nation / 5) * 25 + nation % 5 * 5 + key % 5).cast("int")


def _named(rows: DataFrame, name: str | Column, src: Column, dst: Column, *more: Column) -> DataFrame:
    name = F.lit(name) if isinstance(name, str) else name
    return rows.select(name.alias("network_id"), src.cast("int").alias("src"), dst.cast("int").alias("dst"), *more)


def trade(spark: SparkSession, sf: str) -> DataFrame:
    """Customer nation to supplier nation: no structure.

    Line items are counted by (customer, supplier) before any nation is looked up.
    """
    lines = read(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    orders = read(spark, sf, "orders").select("o_orderkey", "o_custkey")
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("w"))
    customers = read(spark, sf, "customer").select("c_custkey", "c_nationkey")
    suppliers = read(spark, sf, "supplier").select("s_suppkey", "s_nationkey")
    rows = pairs.join(customers, F.col("o_custkey") == customers.c_custkey).join(suppliers, F.col("l_suppkey") == suppliers.s_suppkey)
    return rows.groupBy(F.lit("trade").alias("network_id"), F.col("c_nationkey").cast("int").alias("src"), F.col("s_nationkey").cast("int").alias("dst")).agg(F.sum("w").alias("w"))


def counted_trade(spark: SparkSession, sf: str, *more: str) -> DataFrame:
    """(o_custkey, c_nationkey, c_mktsegment, l_suppkey, s_nationkey, planted, w) and the order's columns ``more``: planted trade, line items counted before any nation is looked up.

    Both nations are functions of the keys, and so is the rule that they share a region; the rest of the rule depends on
    the line alone. So lines meet orders, are counted by (customer, supplier, flag), and only these counts meet the dimensions.
    """
    noise = (F.col("l_orderkey") * 7 + F.col("l_linenumber")) % 20 == 0
    lines = read(spark, sf, "lineitem").select("l_orderkey", "l_suppkey", noise.alias("noise"))
    orders = read(spark, sf, "orders").select("o_orderkey", "o_custkey", *more)
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy("o_custkey", "l_suppkey", "noise", *more).agg(F.count("*").alias("w"))
    customers = read(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    suppliers = read(spark, sf, "supplier").select("s_suppkey", "s_nationkey")
    rows = pairs.join(customers, F.col("o_custkey") == customers.c_custkey).join(suppliers, F.col("l_suppkey") == suppliers.s_suppkey)
    return rows.filter((F.col("c_nationkey") % 5 == F.col("s_nationkey") % 5) | F.col("noise"))


def summed(rows: DataFrame, name: str | Column, src: Column, dst: Column) -> DataFrame:
    """Flows from counted rows (with ``w``)."""
    return _named(rows, name, src, dst, F.col("w")).groupBy("network_id", "src", "dst").agg(F.sum("w").alias("w"))


def planted(spark: SparkSession, sf: str) -> DataFrame:
    """Trade within regions, and one line item in twenty from anywhere: the regions are the truth."""
    return summed(counted_trade(spark, sf), "planted", F.col("c_nationkey"), F.col("s_nationkey"))


def local(spark: SparkSession, sf: str) -> DataFrame:
    """Trade between nations at most two cells apart."""
    flows = trade(spark, sf)
    apart = F.abs(F.col("src") % 5 - F.col("dst") % 5) + F.abs(F.floor(F.col("src") / 5) - F.floor(F.col("dst") / 5))
    return flows.filter(apart <= 2).withColumn("network_id", F.lit("local"))


def tracts(spark: SparkSession, sf: str) -> DataFrame:
    """The planted trade between tracts."""
    return summed(counted_trade(spark, sf), "tract", tract(F.col("c_nationkey"), F.col("o_custkey")), tract(F.col("s_nationkey"), F.col("l_suppkey")))


def states(spark: SparkSession, sf: str) -> DataFrame:
    """The tract network of each region alone: five networks of 25 tracts."""
    flows = tracts(spark, sf)
    region = lambda c: F.floor(F.col(c) % 25 / 5)
    return flows.filter(region("src") == region("dst")).withColumn("network_id", F.concat(F.lit("state"), region("src").cast("string")))


def event_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Each event of a user with the next one: times in seconds, and both types."""
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    events = read(spark, sf, "events").select("user_id", "event_id", "event_type", "ts", seconds.alias("at"))
    turn = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events.withColumn("then", F.lead("at").over(turn)).filter(F.col("then").isNotNull())


def _since(c: str) -> Column:
    return F.col(c) - F.lit(1704067200)  # 2024-01-01 00:00 UTC


def clock(spark: SparkSession, sf: str) -> DataFrame:
    """From the six-hour cell of an event to that of the user's next one, at most 48 hours later."""
    cell = lambda c: F.floor(_since(c) / (6 * HOUR))
    rows = event_pairs(spark, sf).filter(F.col("then") - F.col("at") <= 48 * HOUR)
    return build_flows(_named(rows, "clock", cell("at"), cell("then")))


def typed_clock(spark: SparkSession, sf: str) -> DataFrame:
    """(event_type, src, dst, w): the same cells, by the type of the event that a step starts from."""
    cell = lambda c: F.floor(_since(c) / (6 * HOUR)).cast("int")
    rows = event_pairs(spark, sf).filter(F.col("then") - F.col("at") <= 48 * HOUR)
    return rows.groupBy("event_type", cell("at").alias("src"), cell("then").alias("dst")).agg(F.count("*").alias("w"))


def clock_grid(spark: SparkSession, sf: str) -> DataFrame:
    """From hour to hour, at most 24 hours later; a cell is the hour of the day and the day."""
    cell = lambda c: F.floor(_since(c) / HOUR)
    rows = event_pairs(spark, sf).filter(F.col("then") - F.col("at") <= 24 * HOUR)
    return build_flows(_named(rows, "clockgrid", cell("at"), cell("then")))


def basket(spark: SparkSession, sf: str) -> DataFrame:
    """From the (brand, size) cell of a line to that of the order's next line."""
    brand = F.regexp_extract("p_brand", r"(\d+)", 1).cast("int")
    parts = read(spark, sf, "part").select("p_partkey", ((brand - 1) * 50 + F.col("p_size") - 1).alias("cell"))
    lines = read(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    turn = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    rows = lines.withColumn("next", F.lead("l_partkey").over(turn)).filter(F.col("next").isNotNull()).groupBy("l_partkey", "next").agg(F.count("*").alias("w"))
    rows = rows.join(parts, F.col("l_partkey") == F.col("p_partkey")).select("next", "w", F.col("cell").alias("src"))
    rows = rows.join(parts, F.col("next") == F.col("p_partkey")).select("src", "w", F.col("cell").alias("dst"))
    return rows.groupBy(F.lit("basket").alias("network_id"), F.col("src").cast("int").alias("src"), F.col("dst").cast("int").alias("dst")).agg(F.sum("w").alias("w"))


def ship(spark: SparkSession, sf: str) -> DataFrame:
    """From the week of an order to the week a line of it is shipped, counted from 1995-01-01."""
    week = lambda c: F.floor(F.datediff(F.col(c).cast("date"), F.lit("1995-01-01").cast("date")) / 7)
    lines = read(spark, sf, "lineitem").select("l_orderkey", "l_shipdate")
    orders = read(spark, sf, "orders").select("o_orderkey", "o_orderdate")
    return build_flows(_named(lines.join(orders, lines.l_orderkey == orders.o_orderkey), "ship", week("o_orderdate"), week("l_shipdate")))


def turns(spark: SparkSession, sf: str) -> DataFrame:
    """From the role of a turn to that of the next: system, user, assistant."""
    role = lambda c: F.when(F.col(c) == "system", 0).when(F.col(c) == "user", 1).otherwise(2)
    turn = Window.partitionBy("conv_id").orderBy("turn")
    rows = read(spark, sf, "conversations").select("conv_id", "turn", "role").withColumn("next", F.lead("role").over(turn)).filter(F.col("next").isNotNull())
    return build_flows(_named(rows, "turns", role("role"), role("next")))


def docs(spark: SparkSession, sf: str) -> DataFrame:
    """From the (source, language) cell of a document to that of the next exact copy in order of id."""
    lang = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3)
    cell = lang * 20 + F.regexp_extract("source", r"(\d+)", 1).cast("int")
    rows = read(spark, sf, "documents").select("doc_id", cell.alias("cell"), F.md5(F.lower(F.trim("text"))).alias("h")).filter("h is not null")
    turn = Window.partitionBy("h").orderBy("doc_id")
    rows = rows.withColumn("next", F.lead("cell").over(turn)).filter(F.col("next").isNotNull())
    return build_flows(_named(rows, "docs", F.col("cell"), F.col("next")))


def _ordering(spark: SparkSession, sf: str) -> DataFrame:
    """The customers that have an order."""
    return read(spark, sf, "customer").join(read(spark, sf, "orders").select(F.col("o_custkey").alias("c_custkey")).distinct(), "c_custkey", "left_semi")


def nation_homes(spark: SparkSession, sf: str) -> DataFrame:
    """(unit_id): the nation of every customer with an order and of every supplier."""
    home = lambda rows, c: rows.select(F.col(c).cast("int").alias("unit_id"))
    return home(_ordering(spark, sf), "c_nationkey").unionByName(home(read(spark, sf, "supplier"), "s_nationkey"))


def tract_homes(spark: SparkSession, sf: str) -> DataFrame:
    """(unit_id): the tract of every customer with an order and of every supplier."""
    home = lambda rows, nation, key: rows.select(tract(F.col(nation), F.col(key)).alias("unit_id"))
    return home(_ordering(spark, sf), "c_nationkey", "c_custkey").unionByName(home(read(spark, sf, "supplier"), "s_nationkey", "s_suppkey"))


def hours(spark: SparkSession, sf: str) -> DataFrame:
    """(unit_id): the hour of every event."""
    at = F.unix_timestamp(F.col("ts").cast("timestamp")) - F.lit(1704067200)
    return read(spark, sf, "events").select(F.floor(at / HOUR).cast("int").alias("unit_id"))


WORKLOADS = {f.__name__: f for f in (trade, planted, local, tracts, states, clock, clock_grid, basket, ship, turns, docs)}
