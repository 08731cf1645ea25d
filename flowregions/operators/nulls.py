"""Null models: the random graph, and random tessellations of space."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from flowregions.functions.bits import lmulti
from flowregions.operators import similarity

#: The generator of seeds: whole numbers, the same in SQL.
MULTIPLIER, INCREMENT, MODULUS = 1103515245, 12345, 2147483648


def random_graph_bits(n: Column, w: Column) -> Column:
    """Bits of w edges thrown on all n^2 ordered pairs, self pairs included."""
    return lmulti(n.cast("double") * n, w)


def null_scores(flows: DataFrame, units: DataFrame) -> DataFrame:
    """(network_id, n, w, dl_null); 0 bits for a network without flows."""
    n = units.groupBy("network_id").agg(F.count("*").alias("n"))
    w = flows.groupBy("network_id").agg(F.sum("w").alias("w"))
    return n.join(w, "network_id", "left").na.fill(0, ["w"]).withColumn("dl_null", random_graph_bits(F.col("n"), F.col("w")))


def sample_random_flows(spark: SparkSession, n: int, w: int, seed: int = 1, network_id: str = "random") -> DataFrame:
    """w trips between units drawn by hash, counted by pair."""
    rows = spark.range(w).select(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(n * n)).alias("p"))
    return rows.groupBy(F.lit(network_id).alias("network_id"), F.floor(F.col("p") / n).cast("int").alias("src"), (F.col("p") % n).cast("int").alias("dst")).agg(F.count("*").alias("w"))


def _step(x: Column) -> Column:
    return (x * MULTIPLIER + INCREMENT) % MODULUS


def seeds(spark: SparkSession, b: int, draws: int, nx: int, ny: int, seed: int = 1) -> DataFrame:
    """(draw, seed, sx, sy): b points a draw, uniform over nx by ny by a linear congruential generator."""
    rows = spark.range(draws * b).select((F.floor(F.col("id") / b)).cast("int").alias("draw"), (F.col("id") % b).cast("int").alias("seed"))
    start = (F.col("draw") * 7919 + F.col("seed") * 104729 + seed * 15485863).cast("bigint") % MODULUS
    a = _step(_step(_step(start)))
    c = _step(_step(a))
    at = lambda v, size: v.cast("double") / MODULUS * size - 0.5
    return rows.select("draw", "seed", at(a, nx).alias("sx"), at(c, ny).alias("sy"))


#: Seeds in a draw's packed row at most; a table with larger draws is refused rather than sent to every task.
MOST_SEEDS = 1_000_000


def packed_seeds(points: DataFrame) -> DataFrame:
    """(draw, seeds array<struct<seed, sx, sy>>): one row for each draw, of a size that is checked."""
    rows = points.groupBy("draw").agg(F.array_sort(F.collect_list(F.struct("seed", "sx", "sy"))).alias("seeds"))
    return rows.withColumn("seeds", F.when(F.size("seeds") <= MOST_SEEDS, F.col("seeds")).otherwise(F.raise_error(F.lit(f"a draw has more than {MOST_SEEDS} seeds")).cast("array<struct<seed:int,sx:double,sy:double>>")))


def nearest_seed(px: Column, py: Column, digits: int | None = None) -> Column:
    """The nearest of the row's ``seeds`` (squared distance, then the smaller seed), one pass over the array."""
    def far(s):
        d = (px - s["sx"]) * (px - s["sx"]) + (py - s["sy"]) * (py - s["sy"])
        return F.round(d, digits) if digits is not None else d

    return F.array_min(F.transform("seeds", lambda s: F.struct(far(s).alias("d"), s["seed"].alias("seed"))))["seed"]


def per_draw(units: DataFrame, points: DataFrame) -> DataFrame:
    """Every unit once for each draw, beside that draw's packed seeds: units are exploded over draw numbers and meet the seeds by an equi-join."""
    packed = packed_seeds(points)
    draws = points.agg(F.max("draw")).first()[0]
    rows = units.select("*", F.explode(F.sequence(F.lit(0), F.lit(-1 if draws is None else draws))).alias("draw")) if draws is not None else units.withColumn("draw", F.lit(0)).limit(0)
    return rows.join(packed, "draw")


def voronoi(units: DataFrame, points: DataFrame, name: str = "voronoi") -> DataFrame:
    """PARTITION rows for each draw: a unit takes the label of the nearest seed (squared distance to its centre, then the smaller seed).

    The seeds of a draw travel as one array; pairs of units and seeds are never rows.
    """
    rows = per_draw(units.select("network_id", "unit_id", "x", "y"), points)
    return rows.select("network_id", F.concat(F.lit(f"{name}_"), F.col("draw").cast("string")).alias("model"), "unit_id", nearest_seed(F.col("x"), F.col("y"), 9).alias("label"))


def voronoi_raster(units: DataFrame, points: DataFrame, k: int = 4) -> DataFrame:
    """(network_id, draw, unit_id, seed, share): the part of each unit square nearest to each seed, by k by k sample points."""
    rows = per_draw(units.select("network_id", "unit_id", "x", "y"), points)
    cells = F.transform(F.sequence(F.lit(0), F.lit(k * k - 1)), lambda c: nearest_seed(F.col("x") - 0.5 + (c % k + 0.5) / k, F.col("y") - 0.5 + (F.floor(c / k) + 0.5) / k))
    near = rows.select("network_id", "draw", "unit_id", F.explode(cells).alias("seed"))
    return near.groupBy("network_id", "draw", "unit_id", "seed").agg((F.count("*") / (k * k)).alias("share"))


def percentile_test(found: DataFrame, admin: DataFrame, random: DataFrame, units: DataFrame, at: float = 0.95) -> DataFrame:
    """(network_id, snmi, p95, above): is the partition more like the administrative one than random tessellations are?"""
    value = similarity.spatial_nmi(found, admin, units).select("network_id", "snmi")
    null = similarity.spatial_nmi(found, random, units).groupBy("network_id").agg(F.percentile("snmi", F.lit(at)).alias("p95"))
    return value.join(null, "network_id").withColumn("above", F.col("snmi") > F.col("p95"))
