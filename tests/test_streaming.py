from pyspark.sql import functions as F

from flowregions.sources import workloads as W
from flowregions.streaming import flows as st

SF = "/root/testdata/sf0.001"


def test_pairs_split_over_micro_batches_equal_the_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    days = events.orderBy("ts", "event_id").limit(events.count())
    for k, (low, high) in enumerate((("2024-01-01", "2024-01-10"), ("2024-01-10", "2024-01-20"), ("2024-01-20", "2024-03-01"))):
        days.filter((F.col("ts") >= F.lit(low).cast("timestamp_ntz")) & (F.col("ts") < F.lit(high).cast("timestamp_ntz"))).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = st.events(spark, str(tmp_path / "in"))
    got = st.drain(st.flow_counts(st.user_pairs(stream)), "pairs", str(tmp_path / "state"))
    want = {(r.src, r.dst): r.w for r in W.clock_grid(spark, SF).collect()}
    assert {(r.src, r.dst): r.w for r in got.collect()} == want


def test_windows_and_sessions_count_all(spark, tmp_path):
    stream = st.events(spark, f"{SF}/events.parquet*", spark.read.parquet(f"{SF}/events.parquet").schema)
    total = spark.read.parquet(f"{SF}/events.parquet").count()
    assert st.drain(st.counts(stream), "days", str(tmp_path / "a")).agg(F.sum("n")).first()[0] == total
    assert st.drain(st.counts(stream, "1 day", "6 hours"), "slides", str(tmp_path / "b")).agg(F.sum("n")).first()[0] == 4 * total
    assert st.drain(st.sessions(stream), "sessions", str(tmp_path / "c")).agg(F.sum("n")).first()[0] == total
    assert st.drain(st.once(stream).select("event_id"), "once", str(tmp_path / "d"), "append").count() == total
