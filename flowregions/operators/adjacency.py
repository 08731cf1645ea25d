"""Border graphs: which units touch along a line of positive length."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors of a block, and of its queries those that are scored together.
BLOCK, SOME = 4_096, 256


def from_cells(units: DataFrame) -> DataFrame:
    """Unit squares at whole x, y: neighbours to the right and above. Two equi-joins, no geometry."""
    here = units.select("network_id", "unit_id", F.col("x").cast("int").alias("x"), F.col("y").cast("int").alias("y"))
    there = here.select(F.col("network_id"), F.col("unit_id").alias("other"), "x", "y")
    step = here.withColumn("to", F.explode(F.array(F.struct((F.col("x") + 1).alias("x"), F.col("y").alias("y")), F.struct(F.col("x").alias("x"), (F.col("y") + 1).alias("y")))))
    pairs = step.select("network_id", "unit_id", F.col("to.x").alias("x"), F.col("to.y").alias("y")).join(there, ["network_id", "x", "y"])
    return pairs.select("network_id", F.least("unit_id", "other").alias("a"), F.greatest("unit_id", "other").alias("b"), F.lit(1.0).alias("shared_len"))


def cell_segments(units: DataFrame) -> DataFrame:
    """The four sides of each unit square, (network_id, unit_id, x1, y1, x2, y2) with the lesser end first."""
    x, y = F.col("x").cast("double"), F.col("y").cast("double")
    side = lambda a, b, c, d: F.struct((x + a).alias("x1"), (y + b).alias("y1"), (x + c).alias("x2"), (y + d).alias("y2"))
    sides = F.explode(F.array(side(0, 0, 1, 0), side(0, 0, 0, 1), side(1, 0, 1, 1), side(0, 1, 1, 1)))
    return units.select("network_id", "unit_id", sides.alias("s")).select("network_id", "unit_id", "s.*")


def from_segments(segments: DataFrame) -> DataFrame:
    """Polygons given by their sides: units with a side in common; corners alone do not count."""
    low, high = (F.struct(F.col(f"x{k}").alias("x"), F.col(f"y{k}").alias("y")) for k in (1, 2))
    canonical = segments.select("network_id", "unit_id", F.least(low, high).alias("p"), F.greatest(low, high).alias("q")).withColumn("len", F.hypot(F.col("q.x") - F.col("p.x"), F.col("q.y") - F.col("p.y")))
    # a side belongs to two units at most: they are found by one aggregation, without a self-join
    shared = canonical.filter("len > 0").groupBy("network_id", "p", "q").agg(F.min("unit_id").alias("a"), F.max("unit_id").alias("b"), F.first("len").alias("len")).filter("a != b")
    return shared.groupBy("network_id", "a", "b").agg(F.sum("len").alias("shared_len"))


def from_pairs(pairs: DataFrame) -> DataFrame:
    """A declared list (network_id, a, b), made canonical."""
    return pairs.filter("a != b").select("network_id", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct().withColumn("shared_len", F.lit(1.0))


def knn(vectors: DataFrame, k: int, id_col: str = "vec_id", vector_col: str = "embedding", block: int = BLOCK) -> DataFrame:
    """(src, dst, score): the k most similar (cosine, to 9 places) others of each vector, ties to the smaller id. Exact: every row is a query against all rows.

    Rows are dealt to blocks of about ``block``; each pair of blocks is one task of matrix products and sends on k
    rows a query. Null vectors, such without a direction and rows without an id take no part.
    """
    v = vectors.select(F.col(id_col).cast("int").alias("id"), F.col(vector_col).cast("array<double>").alias("v"))
    v = v.filter(F.col("id").isNotNull() & F.forall("v", lambda x: x.isNotNull() & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0))
    blocks = max(1, -(-v.count() // block))
    dealt = lambda seed: F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    queries = v.select(dealt(1).alias("i"), every.alias("j"), "id", "v")
    others = v.select(every.alias("i"), dealt(2).alias("j"), "id", "v")

    def unit(tab: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        ids = tab.column("id").to_numpy()
        x = tab.column("v").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        order = np.argsort(ids, kind="stable")
        return ids[order], x[order] / np.sqrt((x[order] * x[order]).sum(axis=1, keepdims=True))

    def nearest(left: pa.Table, right: pa.Table) -> pa.Table:
        found = [(np.zeros(0, np.int32), np.zeros(0, np.int32), np.zeros(0))]
        if left.num_rows and right.num_rows:
            (ids, x), (there, y) = unit(left), unit(right)
            for a in range(0, len(ids), SOME):
                own = ids[a : a + SOME]
                score = np.round(x[a : a + SOME] @ y.T, 9)
                score[own[:, None] == there[None, :]] = -np.inf
                kth = np.partition(score, -k, axis=1)[:, -k] if len(there) > k else np.full(len(own), -2.0)
                row, col = np.nonzero((score >= kth[:, None]) & (score > -np.inf))
                order = np.lexsort((col, -score[row, col], row))
                row, col = row[order], col[order]
                first = np.searchsorted(row, np.arange(len(own)))
                keep = np.arange(len(row)) - first[row] < k
                found.append((own[row[keep]], there[col[keep]], score[row[keep], col[keep]]))
        src, dst, score = (np.concatenate(c) for c in zip(*found, strict=True))
        return pa.table({"src": pa.array(src, pa.int32()), "dst": pa.array(dst, pa.int32()), "score": score})

    pairs = queries.groupBy("i", "j").cogroup(others.groupBy("i", "j")).applyInArrow(nearest, "src int, dst int, score double")
    order = Window.partitionBy("src").orderBy(F.desc("score"), "dst")
    return pairs.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).drop("rank")


def knn_lsh(vectors: DataFrame, k: int, id_col: str = "vec_id", vector_col: str = "embedding", bucket: float = 1.0, tables: int = 4, most: float = 1.3) -> DataFrame:
    """As knn, among pairs that share a bucket of a random projection within a distance."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = vectors.select(F.col(id_col).cast("int").alias("id"), array_to_vector(F.col(vector_col).cast("array<double>")).alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=3).fit(v)
    near = model.approxSimilarityJoin(v, v, most, "d").select(F.col("datasetA.id").alias("src"), F.col("datasetB.id").alias("dst"), "d").filter("src != dst")
    order = Window.partitionBy("src").orderBy("d", "dst")
    return near.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("src", "dst", (1 - F.col("d") * F.col("d") / 2).alias("score"))


def from_knn(neighbours: DataFrame, network_id: str = "vectors") -> DataFrame:
    """The symmetric graph of a neighbour list."""
    return from_pairs(neighbours.select(F.lit(network_id).alias("network_id"), F.col("src").alias("a"), F.col("dst").alias("b")))


def check(adjacency: DataFrame, units: DataFrame) -> DataFrame:
    """(network_id, a, b, problem) of rows that break the table's rules."""
    ends = units.select("network_id", "unit_id")
    missing = lambda end: adjacency.join(ends.withColumnRenamed("unit_id", end), ["network_id", end], "left_anti").select("network_id", "a", "b", F.lit(f"unknown {end}").alias("problem"))
    order = adjacency.filter("a >= b").select("network_id", "a", "b", F.lit("not a < b").alias("problem"))
    length = adjacency.filter("shared_len <= 0").select("network_id", "a", "b", F.lit("no common length").alias("problem"))
    twice = adjacency.groupBy("network_id", "a", "b").count().filter("count > 1").select("network_id", "a", "b", F.lit("repeated").alias("problem"))
    return missing("a").unionByName(missing("b")).unionByName(order).unionByName(length).unionByName(twice)


def coarsen(adjacency: DataFrame, units: DataFrame, level: str = "parent_id") -> DataFrame:
    """Parents touch where some of their units do; common lengths add up."""
    parent = lambda end: units.select("network_id", F.col("unit_id").alias(end), F.col(level).alias(f"p{end}"))
    rows = adjacency.join(parent("a"), ["network_id", "a"]).join(parent("b"), ["network_id", "b"]).filter("pa != pb")
    return rows.groupBy("network_id", F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).agg(F.sum("shared_len").alias("shared_len"))
