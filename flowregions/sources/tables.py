"""Declared schemas, and readers that validate instead of inferring."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: The engine's own tables.
UNITS = "network_id string, unit_id int, code string, parent_id int, grand_id int, x double, y double, area double"
FLOWS = "network_id string, src int, dst int, w bigint"
ADJACENCY = "network_id string, a int, b int, shared_len double"
PARTITION = "network_id string, model string, unit_id int, label int"
HIERARCHY = "network_id string, model string, level int, node int, label int"
TRAJECTORY = "network_id string, step int, b int, kept int, absorbed int, delta double, dl double"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; Parquet carries its schema, columns are pruned and filters pushed by the optimizer."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_flows(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """Flows from Parquet, ORC, JSON, CSV (with a header) or delimited text, under the declared schema."""
    schema = StructType.fromDDL(FLOWS)
    if fmt == "text":
        mark = options.pop("sep", r"\s+")
        parts = F.split(F.trim("value"), mark)
        fields = [F.get(parts, F.lit(k)).cast(f.dataType).alias(f.name) for k, f in enumerate(schema)]
        return spark.read.text(path).filter(F.trim("value") != "").select(*fields)
    reader = spark.read.schema(schema).options(**options)
    return reader.option("header", options.get("header", True)).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def invalid_flows(flows: DataFrame) -> DataFrame:
    """Rows that are no flow: a null end or network, or a weight that is not positive."""
    return flows.filter("network_id is null or src is null or dst is null or w is null or w <= 0")


def planted(spark: SparkSession, n: int, groups: int, inside: int, outside: int, seed: int = 1, network_id: str = "planted") -> DataFrame:
    """Flows with known groups of consecutive units: ``inside`` trips from each unit within its group, ``outside`` to anywhere, ends drawn by hash."""
    size = -(-n // groups)
    trips = spark.range(n * (inside + outside)).select((F.col("id") % n).cast("int").alias("src"), F.floor(F.col("id") / n).alias("k"), F.col("id"))
    draw = F.xxhash64("id", F.lit(seed))
    first = F.floor(F.col("src") / size) * size
    width = F.least(first + size, F.lit(n)) - first
    dst = F.when(F.col("k") < inside, first + F.pmod(draw, width)).otherwise(F.pmod(draw, F.lit(n))).cast("int")
    return trips.select(F.lit(network_id).alias("network_id"), "src", dst.alias("dst")).groupBy("network_id", "src", "dst").agg(F.count("*").alias("w"))
