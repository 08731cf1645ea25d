"""Comparing partitions: contingency, mutual information, its chance-adjusted and its area-weighted form."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowregions.functions.bits import LN2, lchoose

KEYS = ["network_id", "p_model", "q_model"]


def contingency(p: DataFrame, q: DataFrame, units: DataFrame | None = None) -> DataFrame:
    """(network_id, p_model, q_model, r, s, n): units in group r of p and s of q, or their area where units are given."""
    rows = p.select("network_id", "unit_id", F.col("model").alias("p_model"), F.col("label").alias("r")).join(q.select("network_id", "unit_id", F.col("model").alias("q_model"), F.col("label").alias("s")), ["network_id", "unit_id"])
    if units is None:
        return rows.groupBy(*KEYS, "r", "s").agg(F.count("*").alias("n"))
    return rows.join(units.select("network_id", "unit_id", "area"), ["network_id", "unit_id"]).groupBy(*KEYS, "r", "s").agg(F.sum("area").alias("n"))


def information(cells: DataFrame) -> DataFrame:
    """(keys, all, h_p, h_q, mi, bp, bq): entropies and mutual information in bits."""
    total = cells.groupBy(*KEYS).agg(F.sum("n").alias("all"))
    side = lambda c, h, b: cells.groupBy(*KEYS, c).agg(F.sum("n").alias("m")).join(total, KEYS).groupBy(*KEYS).agg((-F.sum(F.col("m") / F.col("all") * F.log2(F.col("m") / F.col("all")))).alias(h), F.count("*").alias(b))
    joint = cells.join(total, KEYS).groupBy(*KEYS).agg(F.first("all").alias("all"), (-F.sum(F.when(F.col("n") > 0, F.col("n") / F.col("all") * F.log2(F.col("n") / F.col("all"))).otherwise(0.0))).alias("h"))
    return joint.join(side("r", "h_p", "bp"), KEYS).join(side("s", "h_q", "bq"), KEYS).select(*KEYS, "all", "h_p", "h_q", (F.col("h_p") + F.col("h_q") - F.col("h")).alias("mi"), "bp", "bq")


def _ratio(mi: Column) -> Column:
    """Mean-normalised; 1 where both are a single group."""
    return F.when((F.col("bp") == 1) & (F.col("bq") == 1), F.lit(1.0)).otherwise(2 * mi / (F.col("h_p") + F.col("h_q")))


def nmi(p: DataFrame, q: DataFrame, units: DataFrame | None = None) -> DataFrame:
    """(network_id, p_model, q_model, nmi); with units it is weighted by area."""
    return information(contingency(p, q, units)).select(*KEYS, _ratio(F.col("mi")).alias("nmi"))


def spatial_nmi(p: DataFrame, q: DataFrame, units: DataFrame) -> DataFrame:
    """(network_id, p_model, q_model, snmi): 0 exactly for spatially independent partitions, 1 for equal ones."""
    return nmi(p, q, units).withColumnRenamed("nmi", "snmi")


def expected_information(cells: DataFrame) -> DataFrame:
    """(keys, emi): the mean mutual information of random partitions with the same group sizes.

    Group sizes are compared by their distinct values with multiplicity, so the work is bounded by
    distinct sizes and not by pairs of groups.
    """
    total = cells.groupBy(*KEYS).agg(F.sum("n").alias("all"))
    side = lambda c, m, k: cells.groupBy(*KEYS, c).agg(F.sum("n").alias(m)).groupBy(*KEYS, m).agg(F.count("*").alias(k))
    pairs = side("r", "a", "ka").join(side("s", "b", "kb"), KEYS).join(total, KEYS)
    low = F.greatest(F.lit(1), F.col("a") + F.col("b") - F.col("all"))
    rows = pairs.withColumn("k", F.explode(F.sequence(low, F.least("a", "b"))))
    chance = F.exp(LN2 * (lchoose("b", "k") + lchoose("`all` - b", "a - k") - lchoose("`all`", "a")))
    term = F.col("ka") * F.col("kb") * F.col("k") / F.col("all") * F.log2(F.col("all") * F.col("k") / (F.col("a") * F.col("b"))) * chance
    return rows.groupBy(*KEYS).agg(F.sum(term).alias("emi"))


def ami(p: DataFrame, q: DataFrame, normaliser: str = "mean") -> DataFrame:
    """(network_id, p_model, q_model, ami): 1 where both are a single group, 0 where exactly one is. normaliser: mean or max."""
    cells = contingency(p, q)
    rows = information(cells).join(expected_information(cells), KEYS)
    top = (F.col("h_p") + F.col("h_q")) / 2 if normaliser == "mean" else F.greatest("h_p", "h_q")
    value = F.when((F.col("bp") == 1) & (F.col("bq") == 1), F.lit(1.0)).when((F.col("bp") == 1) | (F.col("bq") == 1), F.lit(0.0)).when((F.col("bp") == F.col("all")) & (F.col("bq") == F.col("all")), F.lit(1.0)).otherwise((F.col("mi") - F.col("emi")) / (top - F.col("emi")))
    return rows.select(*KEYS, value.alias("ami"))


def finest(hierarchy: DataFrame) -> DataFrame:
    """The lowest level of a hierarchy as a partition."""
    return hierarchy.filter("level = 0").select("network_id", "model", F.col("node").alias("unit_id"), "label")
