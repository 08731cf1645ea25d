"""Reliable checkpoints in the folder that the session names."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


def folder(spark) -> str:
    """The shared folder: ``spark.checkpoint.dir``; where that is unset, a temporary one on a local master, an error elsewhere."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut(frame: DataFrame) -> DataFrame:
    """``frame`` computed once and kept in the shared folder, its lineage cut and its size told by the files.

    A checkpoint on its own keeps the size that the optimizer guessed for the plan behind it. Joins multiply guesses, so
    in a loop the number of their digits grows by a factor with each round, until the driver has no memory for them.
    """
    spark = frame.sparkSession
    folder(spark)
    kept = frame.checkpoint(eager=True)
    plan = kept._jdf.queryExecution().analyzed()
    path = spark._jvm.org.apache.hadoop.fs.Path(plan.rdd().getCheckpointFile().get())
    size = path.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(path).getLength()
    # py4j hands no BigInt on, so the size comes from a plan of as many bytes: 8 to a number
    told = spark.range(max(1, -(-size // 8))).select("id")._jdf.queryExecution().analyzed().stats()
    some = spark._jvm.scala.Option
    plan = plan.copy(plan.output(), plan.rdd(), plan.outputPartitioning(), plan.outputOrdering(), False, some.empty(), spark._jsparkSession, some.apply(told), some.apply(plan.constraints()))
    return DataFrame(spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plan), spark)
