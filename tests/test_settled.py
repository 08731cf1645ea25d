"""Greedy regions settled by moves over borders."""

import pytest
from pyspark.sql import functions as F

from flowregions.operators import adjacency as adj
from flowregions.operators import baselines, contiguity, dl
from flowregions.plans import greedy, mcmc
from flowregions.plans.checkpoints import cut
from flowregions.sources import units as U
from flowregions.sources import workloads as W


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_settled_hours_are_shorter_than_weeks_and_contiguous(spark, sf):
    """On sf0.1 the greedy regions alone are longer than the weeks."""
    units = U.clock_grid(spark)
    flows, borders = cut(W.clock_grid(spark, f"/root/testdata/{sf}")), adj.from_cells(units)
    found = cut(mcmc.regions(flows, units, borders))
    row, path = found.first(), greedy.best_step(greedy.run(flows, units, borders)).first()
    weeks = dl.total(flows, baselines.admin(units, "grand_id"), "w").first().dl
    assert row.dl < weeks and row.dl <= path.dl + 1e-6
    assert row.dl == pytest.approx(dl.total(flows, found.select("network_id", "model", "unit_id", "label"), "w").first().dl, abs=1e-3)
    shape = contiguity.measures(found, borders).first()
    assert shape.broken == 0 and shape.b == row.b and found.count() == 720


def test_units_without_borders_stay_alone(spark):
    units = spark.createDataFrame([("net", k) for k in range(4)], "network_id string, unit_id int")
    flows = spark.createDataFrame([("net", 0, 1, 5), ("net", 1, 0, 5)], "network_id string, src int, dst int, w long")
    none = spark.createDataFrame([], "network_id string, a int, b int, shared_len double")
    rows = mcmc.regions(flows, units, none).select("unit_id", F.col("label"), "b").collect()
    assert {(r.unit_id, r.label, r.b) for r in rows} == {(k, k, 4) for k in range(4)}
