"""Flow networks: building, filtering, coarsening, cutting out."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowregions.sources.units import PITCH

#: Frames whose plan promises no more bytes than this may be broadcast onto flows; beyond it joins are left to the optimizer.
BROADCAST_BYTES = 256 << 20


def small(units: DataFrame) -> DataFrame:
    """``units`` with a broadcast hint where its plan's size, which no filter or aggregate lowers, is within BROADCAST_BYTES. Nothing is run."""
    told = re.match(r"sizeInBytes=([\d.]+) (B|KiB|MiB)(?:,|$)", units._jdf.queryExecution().optimizedPlan().stats().simpleString())
    size = float(told[1]) * {"B": 1, "KiB": 1 << 10, "MiB": 1 << 20}[told[2]] if told else float("inf")  # GiB and more are not small
    return F.broadcast(units) if size <= BROADCAST_BYTES else units


def map_endpoints(rows: DataFrame, units: DataFrame, src_key: str, dst_key: str, key: str = "code") -> DataFrame:
    """Origin and destination keys looked up among the units: (network_id, src, dst). Rows with an unknown end are dropped."""
    dim = small(units.select(F.col("network_id"), F.col(key).alias("_key"), F.col("unit_id").alias("_unit")))
    first = rows.join(dim, F.col(src_key) == F.col("_key")).withColumnRenamed("_unit", "src").drop("_key")
    there = dim.select(F.col("network_id").alias("_net"), F.col("_key").alias("_to"), F.col("_unit").alias("dst"))
    return first.join(there, (F.col(dst_key) == F.col("_to")) & (F.col("network_id") == F.col("_net"))).select("network_id", "src", "dst")


def build_flows(pairs: DataFrame, keep_self: bool = True) -> DataFrame:
    """Trips counted by ordered pair: (network_id, src, dst, w). Partial sums before the one shuffle."""
    if not keep_self:
        pairs = pairs.filter("src != dst")
    return pairs.groupBy("network_id", "src", "dst").agg(F.count("*").alias("w"))


def totals(flows: DataFrame, units: DataFrame, rep: str = "w") -> DataFrame:
    """(network_id, n, e, w): for the multigraph each unit of weight is an edge."""
    n = units.groupBy("network_id").agg(F.count("*").alias("n"))
    e = F.count("*") if rep == "w" else F.sum("w")
    return flows.groupBy("network_id").agg(e.alias("e"), F.sum("w").alias("w")).join(n, "network_id").select("network_id", "n", "e", "w")


def explode_multiedges(flows: DataFrame) -> DataFrame:
    """One row for each parallel edge."""
    return flows.select("network_id", "src", "dst", F.explode(F.sequence(F.lit(1), F.col("w").cast("int"))).alias("k")).drop("k")


def haversine(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    """Kilometres between longitudes x and latitudes y in degrees."""
    a = F.pow(F.sin(F.radians(y2 - y1) / 2), 2) + F.cos(F.radians(y1)) * F.cos(F.radians(y2)) * F.pow(F.sin(F.radians(x2 - x1) / 2), 2)
    return 2 * 6371.0088 * F.asin(F.sqrt(a))


def with_distance(flows: DataFrame, units: DataFrame, metric: str = "euclid") -> DataFrame:
    """Adds ``km`` between the two units, by two joins of the (distinct) pairs to the units."""
    at = lambda end: small(units.select(F.col("network_id").alias(f"_{end}n"), F.col("unit_id").alias(f"_{end}u"), F.col("x").alias(f"_{end}x"), F.col("y").alias(f"_{end}y")))
    rows = flows.join(at("s"), (F.col("network_id") == F.col("_sn")) & (F.col("src") == F.col("_su"))).join(at("d"), (F.col("network_id") == F.col("_dn")) & (F.col("dst") == F.col("_du")))
    km = F.hypot(F.col("_sx") - F.col("_dx"), F.col("_sy") - F.col("_dy")) * PITCH if metric == "euclid" else haversine(F.col("_sx"), F.col("_sy"), F.col("_dx"), F.col("_dy"))
    return rows.select(*flows.columns, km.alias("km"))


def filter_distance(flows: DataFrame, units: DataFrame, max_km: float = 160.0, metric: str = "euclid") -> DataFrame:
    return with_distance(flows, units, metric).filter(F.col("km") <= max_km).drop("km")


def distance_share(flows: DataFrame, units: DataFrame, max_km: float = 160.0, metric: str = "euclid") -> DataFrame:
    """(network_id, kept_w, all_w, share): how much of the flow the distance cut keeps."""
    rows = with_distance(flows, units, metric)
    kept = F.coalesce(F.sum(F.when(F.col("km") <= max_km, F.col("w"))), F.lit(0))
    return rows.groupBy("network_id").agg(kept.alias("kept_w"), F.sum("w").alias("all_w")).withColumn("share", F.round(F.col("kept_w") / F.col("all_w"), 6))


def coarsen(flows: DataFrame, units: DataFrame, level: str = "parent_id") -> DataFrame:
    """Flows between parents (or grandparents) of the units; the total weight is conserved."""
    at = lambda end: small(units.select(F.col("network_id").alias(f"_{end}n"), F.col("unit_id").alias(f"_{end}u"), F.col(level).alias(f"_{end}p")))
    rows = flows.join(at("s"), (F.col("network_id") == F.col("_sn")) & (F.col("src") == F.col("_su"))).join(at("d"), (F.col("network_id") == F.col("_dn")) & (F.col("dst") == F.col("_du")))
    return rows.groupBy("network_id", F.col("_sp").alias("src"), F.col("_dp").alias("dst")).agg(F.sum("w").alias("w"))


def coarsen_units(units: DataFrame, level: str = "parent_id", up: str = "grand_id") -> DataFrame:
    """The units of the coarser network: mean position, summed area."""
    rows = units.groupBy("network_id", F.col(level).alias("unit_id")).agg(F.min(up).alias("parent_id"), F.avg("x").alias("x"), F.avg("y").alias("y"), F.sum("area").alias("area"))
    code = F.concat(F.lpad(F.col("parent_id").cast("string"), 3, "0"), F.lpad(F.col("unit_id").cast("string"), 6, "0"))
    return rows.select("network_id", "unit_id", code.alias("code"), "parent_id", F.lit(0).alias("grand_id"), "x", "y", "area")


def induce(flows: DataFrame, units: DataFrame, predicate: str) -> DataFrame:
    """Flows with both ends among the units that satisfy the predicate."""
    inside = units.filter(predicate).select("network_id", "unit_id")
    src = flows.join(inside.withColumnRenamed("unit_id", "src"), ["network_id", "src"], "left_semi")
    return src.join(inside.withColumnRenamed("unit_id", "dst"), ["network_id", "dst"], "left_semi").select(*flows.columns)


def by_period(rows: DataFrame, date_col: str, years: int = 5, first: int = 1995) -> DataFrame:
    """Adds ``period``: non-overlapping windows of whole years."""
    return rows.withColumn("period", F.floor((F.year(F.col(date_col)) - first) / years).cast("int"))


def degrees(flows: DataFrame) -> DataFrame:
    """(network_id, unit_id, k_out, k_in, s_out, s_in): edges and weight of each unit; units without any do not appear."""
    out = flows.groupBy("network_id", F.col("src").alias("unit_id")).agg(F.count("*").alias("k_out"), F.sum("w").alias("s_out"))
    into = flows.groupBy("network_id", F.col("dst").alias("unit_id")).agg(F.count("*").alias("k_in"), F.sum("w").alias("s_in"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("bigint").alias(c)
    return out.join(into, ["network_id", "unit_id"], "full_outer").select("network_id", "unit_id", zero("k_out"), zero("k_in"), zero("s_out"), zero("s_in"))
