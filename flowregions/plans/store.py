"""Results kept as named tables in the shared folder: computed once for each state of their inputs."""

from __future__ import annotations

import hashlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from flowregions.plans.checkpoints import folder


def fingerprint(spark: SparkSession, sf_dir: str, tables: tuple[str, ...], *more) -> str:
    """Digest of the input files' paths, sizes and times of change, and of whatever else a result depends on."""
    parts = [repr(m) for m in more]
    for name in tables:
        for path in sorted(spark.read.parquet(f"{sf_dir}/{name}.parquet").inputFiles()):
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            status = at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at)
            parts.append(f"{path}:{status.getLen()}:{status.getModificationTime()}")
    return hashlib.blake2b("\n".join(parts).encode(), digest_size=12).hexdigest()


def kept(spark: SparkSession, name: str, key: str, make: Callable[[], DataFrame]) -> DataFrame:
    """The table ``name`` for ``key``: read where it was written to its end, else made and written."""
    path = f"{folder(spark)}/kept/{name}-{key}"
    done = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    if not done.getFileSystem(spark._jsc.hadoopConfiguration()).exists(done):
        make().write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)
