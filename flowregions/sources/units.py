"""Spatial units on grids, placed by arithmetic on keys, so that SQL can repeat it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Kilometres between neighbouring cells.
PITCH = 80.0


def _area() -> Column:
    return (1 + F.col("unit_id") % 3).cast("double")


def grid(spark: SparkSession, nx: int, ny: int, network_id: str = "grid", parent: Column | None = None, grand: Column | None = None) -> DataFrame:
    """nx by ny cells, numbered row by row. Parents default to rows of cells, grandparents to one."""
    cells = spark.range(nx * ny).select(F.col("id").cast("int").alias("unit_id")).withColumn("x", (F.col("unit_id") % nx).cast("double")).withColumn("y", F.floor(F.col("unit_id") / nx).cast("double"))
    parent = F.col("y") if parent is None else parent
    grand = F.lit(0) if grand is None else grand
    cells = cells.withColumn("parent_id", parent.cast("int")).withColumn("grand_id", grand.cast("int"))
    code = F.concat(F.lpad(F.col("grand_id").cast("string"), 2, "0"), F.lpad(F.col("parent_id").cast("string"), 3, "0"), F.lpad(F.col("unit_id").cast("string"), 6, "0"))
    return cells.select(F.lit(network_id).alias("network_id"), "unit_id", code.alias("code"), "parent_id", "grand_id", "x", "y", _area().alias("area"))


def held(units: DataFrame, cells: DataFrame) -> DataFrame:
    """Those of ``units`` that rows of a given table fall into: ``cells`` has their unit_id, once or often."""
    return units.join(cells.select("unit_id").distinct(), "unit_id", "left_semi").select(units.columns)


def nations(spark: SparkSession, network_id: str = "nation") -> DataFrame:
    """25 nations on a 5 by 5 grid; the region of a nation is its column."""
    return grid(spark, 5, 5, network_id, parent=F.col("x"), grand=F.lit(0))


def tracts(spark: SparkSession, network_id: str = "tract") -> DataFrame:
    """Each nation in five stripes side by side: 25 by 5 tracts; parent is the nation, grandparent the region."""
    column = F.floor(F.col("x") / 5)
    return grid(spark, 25, 5, network_id, parent=F.col("y") * 5 + column, grand=column)


def clock(spark: SparkSession, network_id: str = "clock") -> DataFrame:
    """120 cells of six hours in a row; parent is the day, grandparent the week."""
    return grid(spark, 120, 1, network_id, parent=F.floor(F.col("x") / 4), grand=F.floor(F.col("x") / 28))


def clock_grid(spark: SparkSession, network_id: str = "clockgrid") -> DataFrame:
    """Hour of the day by day: 24 by 30 cells."""
    return grid(spark, 24, 30, network_id, parent=F.col("y"), grand=F.floor(F.col("y") / 7))


def brand_sizes(spark: SparkSession, network_id: str = "basket") -> DataFrame:
    """Size 1..50 by brand 1..25."""
    return grid(spark, 50, 25, network_id)


def weeks(spark: SparkSession, network_id: str = "ship", n: int = 380) -> DataFrame:
    return grid(spark, n, 1, network_id, parent=F.floor(F.col("x") / 4))


def roles(spark: SparkSession, network_id: str = "turns") -> DataFrame:
    """System, user and assistant in a row."""
    return grid(spark, 3, 1, network_id)


def source_languages(spark: SparkSession, network_id: str = "docs") -> DataFrame:
    """Source 0..19 by language (de, en, es, fr)."""
    return grid(spark, 20, 4, network_id)
