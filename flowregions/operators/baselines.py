"""Partitions to compare with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.operators import components


def admin(units: DataFrame, level: str = "parent_id", model: str = "admin") -> DataFrame:
    """The given nesting as a partition; labels are the smallest unit of a group."""
    low = units.groupBy("network_id", level).agg(F.min("unit_id").alias("label"))
    return units.join(low, ["network_id", level]).select("network_id", F.lit(model).alias("model"), "unit_id", "label")


def single(units: DataFrame) -> DataFrame:
    low = units.groupBy("network_id").agg(F.min("unit_id").alias("label"))
    return units.join(low, "network_id").select("network_id", F.lit("single").alias("model"), "unit_id", "label")


def singletons(units: DataFrame) -> DataFrame:
    return units.select("network_id", F.lit("singletons").alias("model"), "unit_id", F.col("unit_id").alias("label"))


def by_rule(units: DataFrame, rule: str, model: str) -> DataFrame:
    """Groups by an SQL expression on the units, contiguous or not."""
    keyed = units.withColumn("_g", F.expr(rule))
    low = keyed.groupBy("network_id", "_g").agg(F.min("unit_id").alias("label"))
    return keyed.join(low, ["network_id", "_g"]).select("network_id", F.lit(model).alias("model"), "unit_id", "label")


def split_components(partition: DataFrame, adjacency: DataFrame) -> DataFrame:
    """Each connected component of a group a group of its own."""
    return components.within(partition, adjacency).select("network_id", F.concat("model", F.lit("_split")).alias("model"), "unit_id", F.col("comp").alias("label"))
