"""Connected components of each group in the border graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.plans.checkpoints import cut

KEYS = ["network_id", "model"]


def within(partition: DataFrame, adjacency: DataFrame) -> DataFrame:
    """(network_id, model, unit_id, label, comp): the smallest unit reachable within the unit's own group.

    Least label of the neighbours, then the label's own label: rounds grow with the logarithm of the
    longest chain. Each round is two joins and a checkpoint.
    """
    side = partition.select(*KEYS, "unit_id", "label")
    borders = adjacency.join(side.select("network_id", "model", F.col("unit_id").alias("a"), F.col("label").alias("la")), ["network_id", "a"]).join(side.select("network_id", "model", F.col("unit_id").alias("b"), F.col("label").alias("lb")), ["network_id", "model", "b"]).filter("la = lb")
    both = cut(borders.select(*KEYS, "a", "b").union(borders.select(*KEYS, F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    now = side.withColumn("comp", F.col("unit_id"))
    while True:
        near = both.join(now.select(*KEYS, F.col("unit_id").alias("b"), "comp"), [*KEYS, "b"]).groupBy(*KEYS, F.col("a").alias("unit_id")).agg(F.min("comp").alias("near"))
        step = now.join(near, [*KEYS, "unit_id"], "left").select(*KEYS, "unit_id", "label", F.col("comp").alias("old"), F.least("comp", F.coalesce("near", "comp")).alias("comp"))
        jump = step.select(*KEYS, F.col("unit_id").alias("comp"), F.col("comp").alias("up"))
        new = cut(step.join(jump, [*KEYS, "comp"], "left").select(*KEYS, "unit_id", "label", "old", F.coalesce("up", "comp").alias("comp")))
        if new.filter("old != comp").isEmpty():
            return new.drop("old")
        now = new.drop("old")


def sizes(found: DataFrame) -> DataFrame:
    """(network_id, model, label, comp, n_rc)."""
    return found.groupBy(*KEYS, "label", "comp").agg(F.count("*").alias("n_rc"))


def number(adjacency: DataFrame, units: DataFrame) -> DataFrame:
    """(network_id, components): connected components of the whole border graph; regions cannot be fewer."""
    one = units.select("network_id", F.lit("all").alias("model"), "unit_id", F.lit(0).alias("label"))
    return within(one, adjacency).groupBy("network_id").agg(F.count_distinct("comp").alias("components"))
