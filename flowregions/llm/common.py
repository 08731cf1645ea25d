"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's ``spark.checkpoint.dir``; where that is unset, a temporary one on a local master (tests), an error elsewhere."""
    context = spark.sparkContext
    set_already = context._jsc.sc().getCheckpointDir()
    if set_already.isDefined():
        return set_already.get()
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder and not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoints-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut(frame: DataFrame) -> DataFrame:
    """A reliable checkpoint of ``frame``: it is computed once, and a lost executor costs nothing."""
    shared_dir(frame.sparkSession)
    return frame.checkpoint(eager=True)


def table(frame: DataFrame) -> DataFrame:
    """``frame`` written as Parquet in the shared folder and read again; compact where a checkpoint would be large."""
    spark = frame.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: A key is hot with more than this part of all rows: there can be no more than its inverse of them, so they may be broadcast.
HOT_PART = 1e-4


def hot_join(left: DataFrame, right: DataFrame, keys: list[str], total: int, salt: list[str], count: str = "many") -> DataFrame:
    """Inner join of ``left`` with ``right``, which has each combination of ``keys`` once and in ``count`` how many rows of ``left`` have it.

    Hot keys (at most 10,000, by HOT_PART) are broadcast; their rows of ``left`` get a random first key (a hash of
    ``salt``) for the shuffle join that serves all others, so no task gets more than its share. The first key is a long.
    """
    least = max(1_000, int(total * HOT_PART))
    more = [c for c in right.columns if c not in (*keys, count)]
    value = F.struct(F.lit(1).alias("_met"), *more)
    hot = F.broadcast(right.filter(F.col(count) > least).select(*keys, value.alias("_hot")))
    cold = right.filter(F.col(count) <= least).select(*[F.col(k).alias(f"_{k}") for k in keys], value.alias("_cold"))
    rows = left.join(hot, keys, "left")
    rows = rows.withColumn("_first", F.when(F.col("_hot").isNull(), F.col(keys[0])).otherwise(F.xxhash64(*salt)))
    same = F.col("_first") == F.col(f"_{keys[0]}")
    for k in keys[1:]:
        same = same & (F.col(k) == F.col(f"_{k}"))
    rows = rows.join(cold, same, "left").withColumn("_got", F.coalesce("_hot", "_cold")).filter(F.col("_got").isNotNull())
    return rows.select(*left.columns, *[F.col("_got")[c].alias(c) for c in more])


#: Rows of an Arrow batch that holds whole texts; the session's default would send ten thousand at once.
BATCH_ROWS = 512


def text_batches(spark: SparkSession) -> None:
    """Has Spark send texts to Python in batches of BATCH_ROWS at most (a setting of the running session), so that a task's memory stays small."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def give_back() -> None:
    """At a task's end: memory that Arrow and the C library keep goes back to the system, as workers live on between tasks."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        return
