"""SQL access: views of the given tables, bits functions, and regionalization as a table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from flowregions.functions import bits
from flowregions.sources.tables import read

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@udtf(returnType="network_id string, unit_id int, label int, b int, dl double")
class Regionalize:
    """``SELECT * FROM regionalize(TABLE(t) PARTITION BY network_id)``: t has network_id, kind (0 unit, 1 flow, 2 border), a, b, w."""

    def __init__(self):
        self.rows: list[tuple] = []

    def eval(self, row) -> None:
        self.rows.append((row["network_id"], row["kind"], row["a"], row["b"], row["w"]))

    def terminate(self) -> Iterator[tuple]:
        import numpy as np

        from flowregions.plans import kernel, mcmc

        if not self.rows:
            return
        self.rows.sort(key=lambda r: tuple(x or 0 for x in r[1:]))
        kind, a, b, w = (np.array([r[k] or 0 for r in self.rows]) for k in (1, 2, 3, 4))
        net = kernel.Network(a[kind == 0], a[kind == 1], b[kind == 1], w[kind == 1], a[kind == 2], b[kind == 2])
        path = kernel.greedy(net, kernel.BlockModel("w"))
        best = min(path, key=lambda p: (round(p[5], 9), p[1]))
        label = net.units[mcmc.labels_at(path, net.n, best[0])]
        for u, g in zip(net.units.tolist(), label.tolist(), strict=True):
            yield self.rows[0][0], u, g, best[1], best[5]


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    bits.register_sql(spark)
    spark.udtf.register("regionalize", Regionalize)
    for name in TABLES if sf_dir else ():
        read(spark, sf_dir, name).createOrReplaceTempView(name)
