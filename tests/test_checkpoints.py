"""Cut frames tell the size of their files, whatever was guessed for the plan behind them."""

from pyspark.sql import functions as F

from flowregions.operators import components
from flowregions.plans.checkpoints import cut


def told(frame):
    return int(frame._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def test_guessed_sizes_do_not_grow_with_the_rounds(spark):
    now = cut(spark.range(50).withColumn("at", F.col("id")))
    for _ in range(5):
        now = cut(now.join(now.select(F.col("id").alias("at"), F.col("at").alias("up")), "at").select("id", F.col("up").alias("at")))
    assert told(now) < 100_000
    assert {(r.id, r.at) for r in now.collect()} == {(k, k) for k in range(50)}


def test_cut_keeps_rows_types_and_partitions(spark):
    frame = spark.createDataFrame([(1, "a", [1.0, None]), (2, None, None)], "k int, s string, v array<double>").repartition(3, "k")
    kept = cut(frame)
    assert kept.schema == frame.schema and kept.rdd.getNumPartitions() == 3
    assert sorted(kept.collect()) == sorted(frame.collect())
    assert cut(frame.filter("k > 5")).count() == 0
    assert kept.join(kept.select("k"), "k").count() == 2


def test_components_of_a_winding_group_stay_cheap_to_plan(spark):
    order = [(k * 37) % 101 for k in range(101)]
    part = spark.createDataFrame([("net", "m", u, 0) for u in order], "network_id string, model string, unit_id int, label int")
    borders = spark.createDataFrame([("net", min(a, b), max(a, b)) for a, b in zip(order, order[1:]) if 50 not in (a, b)], "network_id string, a int, b int")
    found = components.within(part, borders)
    middle = order.index(50)
    want = {u: min(order[:middle]) for u in order[:middle]} | {u: min(order[middle + 1 :]) for u in order[middle + 1 :]} | {50: 50}
    assert {r.unit_id: r.comp for r in found.collect()} == want
    assert told(found) < 1_000_000
