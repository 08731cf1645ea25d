"""Writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(frame: DataFrame, path: str, partition_by: tuple[str, ...] = ("class", "model"), mode: str = "overwrite") -> None:
    """Parquet, partitioned by the columns of ``partition_by`` that exist, so that readers prune by class and model."""
    keys = [c for c in partition_by if c in frame.columns]
    frame.write.mode(mode).partitionBy(*keys).parquet(path)


def save_bucketed(frame: DataFrame, name: str, buckets: int = 64, key: str = "network_id") -> None:
    """A table bucketed and sorted by network: joins and groupings by network then need no shuffle."""
    frame.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def upsert_batch(path: str):
    """A foreachBatch function that writes each micro-batch under its own number: replays overwrite themselves."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return put
