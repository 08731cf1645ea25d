"""How far groups are from being contiguous."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.operators import components

KEYS = ["network_id", "model"]


def effective_components(sizes: DataFrame) -> DataFrame:
    """(network_id, model, label, n, c, c_eff): exp of the entropy of a group's component sizes; between 1 and their number."""
    whole = sizes.groupBy(*KEYS, "label").agg(F.sum("n_rc").alias("n"), F.count("*").alias("c"), F.sum(F.col("n_rc") * F.log("n_rc")).alias("s"))
    return whole.select(*KEYS, "label", "n", "c", F.exp(F.log("n") - F.col("s") / F.col("n")).alias("c_eff"))


def measures(partition: DataFrame, adjacency: DataFrame) -> DataFrame:
    """(network_id, model, n, b, broken, broken_fraction, mean_components, mean_component_size, mean_group_component_size, cvm).

    ``mean_component_size`` is the mean over components, the other the mean over groups of their own
    means. cvm is 0 exactly when all groups are contiguous, and N / B - 1 at most.
    """
    per = effective_components(components.sizes(components.within(partition, adjacency)))
    rows = per.groupBy(*KEYS).agg(
        F.sum("n").alias("n"),
        F.count("*").alias("b"),
        F.sum(F.when(F.col("c") > 1, 1).otherwise(0)).alias("broken"),
        F.avg("c").alias("mean_components"),
        (F.sum("n") / F.sum("c")).alias("mean_component_size"),
        F.avg(F.col("n") / F.col("c")).alias("mean_group_component_size"),
        (F.avg("c_eff") - 1).alias("cvm"),
    )
    return rows.withColumn("broken_fraction", F.col("broken") / F.col("b"))
