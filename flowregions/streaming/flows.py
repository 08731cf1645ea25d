"""Flow counts kept current from a stream of events."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowregions.operators.network import small

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
HOUR = 3600


def events(spark: SparkSession, path: str, schema: str | None = None, files: int = 1) -> DataFrame:
    """A stream of Parquet files of events; ``ts`` becomes a timestamp of the session's zone."""
    schema = schema or spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def counts(stream: DataFrame, width: str = "1 day", step: str | None = None, late: str = "2 hours") -> DataFrame:
    """(start, event_type, n): events by tumbling or sliding windows; later ones than ``late`` are dropped."""
    window = F.window("ts", width, step) if step else F.window("ts", width)
    return stream.withWatermark("ts", late).groupBy(window, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """(user_id, start, n): sessions of a user."""
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def once(stream: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each event once, as far as the watermark reaches back."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def user_pairs(stream: DataFrame, max_gap: int = 24 * HOUR, hours: int = 1, late: str = "2 hours") -> DataFrame:
    """(user_id, src, dst, at): cell of a user's event and of the next, where both are at most max_gap seconds apart.

    The state of a user is the last event seen. It goes once the watermark, ``late`` behind the newest event, is
    more than max_gap beyond it: no event to come can make a pair with it. Files must bring a user's events in
    order of time (within a micro-batch they are sorted).
    """
    rows = stream.withWatermark("ts", late).select("user_id", "event_id", "ts", F.unix_timestamp("ts").alias("at"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        got = pd.concat(list(batches)).sort_values(["at", "event_id"])
        times = got["at"].tolist()
        if state.exists:
            times = [state.get[0], *times]
        first = times[:-1]
        then = times[1:]
        out = pd.DataFrame({"user_id": key[0], "at": first, "then": then})
        state.update((int(times[-1]),))
        state.setTimeoutTimestamp(max((int(times[-1]) + max_gap + 1) * 1000, state.getCurrentWatermarkMs() + 1))
        yield out[out["then"] - out["at"] <= max_gap]

    pairs = rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, at long, then long", "last long", "append", "EventTimeTimeout")
    cell = lambda c: F.floor((F.col(c) - 1704067200) / (hours * HOUR)).cast("int")
    return pairs.select("user_id", cell("at").alias("src"), cell("then").alias("dst"), "at")


def flow_counts(pairs: DataFrame, network_id: str = "clockgrid") -> DataFrame:
    """Current FLOWS of a stream of pairs, for update or complete mode."""
    return pairs.groupBy(F.lit(network_id).alias("network_id"), "src", "dst").agg(F.count("*").alias("w"))


def block_counts(pairs: DataFrame, partition: DataFrame) -> DataFrame:
    """(r, s, w): current weight between the groups of a fixed partition; a stream-static join."""
    side = small(partition.select("unit_id", "label"))
    one = pairs.join(side.select(F.col("unit_id").alias("src"), F.col("label").alias("r")), "src")
    return one.join(side.select(F.col("unit_id").alias("dst"), F.col("label").alias("s")), "dst").groupBy("r", "s").agg(F.count("*").alias("w"))


def drain(stream: DataFrame, name: str, checkpoint: str, mode: str = "complete") -> DataFrame:
    """Runs all that is there into an in-memory table and returns it: replay tests and small results."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def late_counts(stream: DataFrame, late: str) -> DataFrame:
    """(dropped, n): how many rows of a stream with ``ts`` a watermark ``late`` behind the newest event refuses, and how many it takes.

    A watermark drops late rows without a word. Here each micro-batch is compared with the newest event of the
    batches before it, which is the mark that holds while it runs; marks and counts are written by batch
    number, so a replayed batch overwrites its own.
    """
    from flowregions.plans.checkpoints import folder

    spark = stream.sparkSession
    out = f"{folder(spark)}/late-{uuid.uuid4().hex}"
    seconds = int(pd.Timedelta(late).total_seconds())
    at = F.unix_timestamp(F.col("ts").cast("timestamp"))

    def put(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        mark = spark.read.parquet(f"{out}/marks").filter(F.col("batch") < number).agg(F.max("newest")).first()[0] if number else None
        dropped = F.lit(False) if mark is None else at < F.lit(mark - seconds)
        batch.agg(F.max(at).alias("newest")).write.mode("overwrite").parquet(f"{out}/marks/batch={number}")
        batch.groupBy(dropped.alias("dropped")).agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{out}/counts/batch={number}")

    stream.writeStream.option("checkpointLocation", f"{out}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.parquet(f"{out}/counts").groupBy("dropped").agg(F.sum("n").alias("n"))


def drift(pairs: DataFrame, units: DataFrame, adjacency: DataFrame, frozen: DataFrame, rep: str = "w") -> DataFrame:
    """(batch, e, w, dl_frozen, b, dl): after each micro-batch of ``pairs`` the length of a frozen partition for all trips so far, and of the regions found anew: greedy ones, settled by moves over borders.

    A frozen partition that falls behind says that the flows have changed. Trips are kept by batch number, so a
    replayed batch overwrites its own.
    """
    from flowregions.operators import dl
    from flowregions.plans import mcmc
    from flowregions.plans.checkpoints import cut, folder

    spark = pairs.sparkSession
    out = f"{folder(spark)}/drift-{uuid.uuid4().hex}"
    name = units.select("network_id").first()[0]

    def put(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        batch.groupBy("src", "dst").agg(F.count("*").alias("w")).write.mode("overwrite").parquet(f"{out}/flows/batch={number}")
        flows = cut(spark.read.parquet(f"{out}/flows").filter(F.col("batch") <= number).groupBy(F.lit(name).alias("network_id"), "src", "dst").agg(F.sum("w").alias("w")))
        best = mcmc.regions(flows, units, adjacency, rep).groupBy("network_id").agg(F.first("b").alias("b"), F.first("dl").alias("dl"))
        rows = dl.total(flows, frozen, rep).select("network_id", "e", "w", F.col("dl").alias("dl_frozen")).join(best, "network_id")
        rows.drop("network_id").write.mode("overwrite").parquet(f"{out}/scores/batch={number}")

    pairs.writeStream.option("checkpointLocation", f"{out}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.parquet(f"{out}/scores").select("batch", "e", "w", "dl_frozen", "b", "dl")
